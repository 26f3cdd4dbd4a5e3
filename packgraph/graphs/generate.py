"""Generated graphs, driven by md5 digits, so that every engine and run builds the same rows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..core.model import Graph


def digit(*parts) -> Column:
    """A whole number below 2**32 from the parts joined by colons."""
    return F.conv(F.substring(F.md5(F.concat_ws(":", *(p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts))), 1, 8), 16, 10).cast("long")


def kron(spark: SparkSession, scale: int, per_vertex: int, seed: int = 7, tries: DataFrame | None = None) -> Graph:
    """2**scale vertices; each of per_vertex * n tries, or of ``tries`` (i), picks one of four quadrants a level, with chances 57, 19, 19 and 5 in a hundred."""
    n = 1 << scale
    t = spark.range(n * per_vertex).select(F.col("id").alias("i")) if tries is None else tries
    for level in range(scale):
        t = t.withColumn(f"q{level}", digit(seed, F.col("i"), level) % 100)
    src = sum((F.when(F.col(f"q{k}") >= 76, 1).otherwise(0) * (1 << k) for k in range(scale)), F.lit(0))
    dst = sum((F.when(((F.col(f"q{k}") >= 57) & (F.col(f"q{k}") < 76)) | (F.col(f"q{k}") >= 95), 1).otherwise(0) * (1 << k) for k in range(scale)), F.lit(0))
    return Graph.from_edges(f"kron_{scale}_{per_vertex}", n, t.select((src + 1).alias("src"), (dst + 1).alias("dst"), F.lit(1).alias("w")))


def er(spark: SparkSession, n: int, p: float, seed: int = 7) -> Graph:
    """Each pair with chance p: pairs are numbered by row and column, a row's pairs are one range, not a join."""
    rows = spark.range(1, n).select(F.col("id").alias("src"))
    pairs = rows.select("src", F.explode(F.sequence(F.col("src") + 1, F.lit(n).cast("long"))).alias("dst"))
    return Graph(f"er_{n}", n, pairs.where(digit(seed, F.col("src"), F.col("dst")) < int(p * 2**32)).withColumn("w", F.lit(1).cast("long")))


def powerlaw(spark: SparkSession, n: int, alpha: float, beta: float, seed: int = 7, ids: DataFrame | None = None) -> Graph:
    """alpha d**-beta vertices of degree d (at least one), stubs paired in an order by md5. The vertices are 1 to n, or ``ids`` (id)."""
    from ..core.ids import global_rank

    d = F.greatest(F.lit(1), F.floor(F.pow(alpha / F.col("id"), F.lit(1 / beta)))).cast("int")
    stubs = (spark.range(1, n + 1) if ids is None else ids).select("id", F.explode(F.sequence(F.lit(1), F.least(d, F.lit(n - 1)))).alias("k"))
    order = global_rank(stubs.withColumn("h", digit(seed, F.col("id"), F.col("k"))), [F.col("h"), F.col("id"), F.col("k")], "r", 0)
    a, b = order.where("r % 2 = 0").select((F.col("r") / 2).cast("long").alias("p"), F.col("id").alias("src")), order.where("r % 2 = 1").select(F.floor(F.col("r") / 2).alias("p"), F.col("id").alias("dst"))
    return Graph.from_edges(f"powerlaw_{n}", n, a.join(b, "p").select("src", "dst", F.lit(1).alias("w")))


def numbered_pairs(numbers: DataFrame) -> DataFrame:
    """(src, dst) of each number k from 0: the k-th pair src < dst of 1, 2, .., by dst. So N rows are the pairs of about sqrt(2 N) vertices."""
    j = F.expr("cast(floor((1 + sqrt(cast(1 + 8 * k as double))) / 2) as bigint)")
    return numbers.withColumn("j", j).select(F.expr("k - j * (j - 1) div 2 + 1").alias("src"), (F.col("j") + 1).alias("dst"))


def chosen_pairs(pairs: DataFrame, p_in: float, p_out: float, size: int, seed: int = 7) -> DataFrame:
    """(src, dst, w) of the pairs kept with chance p_in within communities of ``size`` consecutive vertices, with p_out across."""
    same = F.expr(f"(src - 1) div {size} = (dst - 1) div {size}")
    chance = F.when(same, int(p_in * 2**32)).otherwise(int(p_out * 2**32))
    return pairs.where(digit(seed, F.col("src"), F.col("dst")) < chance).select("src", "dst", F.lit(1).cast("long").alias("w"))


def table_grid(ids: DataFrame, n: int, columns: int) -> DataFrame:
    """(src, dst, w) of a grid whose n cells are the ids 0, 1, .., row after row; the last row may be short."""
    right = ids.where(f"id % {columns} < {columns - 1} AND id + 1 < {n}").select((F.col("id") + 1).alias("src"), (F.col("id") + 2).alias("dst"))
    down = ids.where(f"id + {columns} < {n}").select((F.col("id") + 1).alias("src"), (F.col("id") + 1 + columns).alias("dst"))
    return right.union(down).withColumn("w", F.lit(1).cast("long"))


def grid(spark: SparkSession, rows: int, columns: int) -> Graph:
    v = spark.range(rows * columns).select(F.col("id"), (F.col("id") % columns).alias("c"))
    right = v.where(F.col("c") < columns - 1).select((F.col("id") + 1).alias("src"), (F.col("id") + 2).alias("dst"))
    down = v.where(F.col("id") < (rows - 1) * columns).select((F.col("id") + 1).alias("src"), (F.col("id") + 1 + columns).alias("dst"))
    return Graph(f"grid_{rows}_{columns}", rows * columns, right.union(down).withColumn("w", F.lit(1).cast("long")))


def planted(spark: SparkSession, sizes: list[int], p_in: float, p_out: float, seed: int = 7) -> Graph:
    """Communities one after another; pairs within one have chance p_in, others p_out."""
    n, cuts, at = sum(sizes), [], 0
    for s in sizes:
        at += s
        cuts.append(at)

    def block(c: Column) -> Column:
        return sum((F.when(c > x, 1).otherwise(0) for x in cuts[:-1]), F.lit(0))

    pairs = spark.range(1, n).select(F.col("id").alias("src")).select("src", F.explode(F.sequence(F.col("src") + 1, F.lit(n).cast("long"))).alias("dst"))
    chance = F.when(block(F.col("src")) == block(F.col("dst")), int(p_in * 2**32)).otherwise(int(p_out * 2**32))
    return Graph(f"planted_{n}", n, pairs.where(digit(seed, F.col("src"), F.col("dst")) < chance).withColumn("w", F.lit(1).cast("long")))


def _md5(*parts: str) -> str:
    return "CAST(('0x' || substr(md5(" + " || ':' || ".join(parts) + "), 1, 8)) AS BIGINT)"


def _orders(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/orders.parquet").select(F.col("o_orderkey").cast("long").alias(name))


def _kron(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A try for each order."""
    return kron(spark, 14, 0, tries=_orders(spark, sf_dir, "i")).edges


def _er(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders number the pairs."""
    return chosen_pairs(numbered_pairs(_orders(spark, sf_dir, "k")), 0.05, 0.05, 1)


def _planted(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chosen_pairs(numbered_pairs(_orders(spark, sf_dir, "k")), 0.3, 0.02, 60)


def _grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    ids = _orders(spark, sf_dir, "id")
    return table_grid(ids, ids.count(), 30)


def _powerlaw(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders are the vertices; exponents and vertices of degree one as with 3000 of 400."""
    ids = _orders(spark, sf_dir, "id").select((F.col("id") + 1).alias("id"))
    n = ids.count()
    return powerlaw(spark, n, 7.5 * n, 2.2, ids=ids).edges


QUERIES = {"gen_kron": _kron, "gen_er": _er, "gen_grid": _grid, "gen_planted": _planted, "gen_powerlaw": _powerlaw}
_Q = [f"{_md5(repr('7'), 'i', repr(str(k)))} % 100 AS q{k}" for k in range(14)]
_NUMBERED = "(SELECT k - j * (j - 1) // 2 + 1 AS src, j + 1 AS dst FROM (SELECT k, CAST(floor((1 + sqrt(CAST(1 + 8 * k AS DOUBLE))) / 2) AS BIGINT) AS j FROM (SELECT CAST(o_orderkey AS BIGINT) AS k FROM orders) t) u) p"
ORACLES = {
    "gen_kron": "SELECT least(s, d) AS src, greatest(s, d) AS dst, CAST(1 AS BIGINT) AS w FROM (SELECT 1 + " + " + ".join(f"(CASE WHEN q{k} >= 76 THEN {1 << k} ELSE 0 END)" for k in range(14)) + " AS s, 1 + " + " + ".join(f"(CASE WHEN (q{k} >= 57 AND q{k} < 76) OR q{k} >= 95 THEN {1 << k} ELSE 0 END)" for k in range(14)) + " AS d FROM (SELECT i, " + ", ".join(_Q) + " FROM (SELECT o_orderkey AS i FROM orders) t) z) y WHERE s <> d GROUP BY 1, 2",
    "gen_er": f"SELECT src, dst, CAST(1 AS BIGINT) AS w FROM {_NUMBERED} WHERE {_md5(repr('7'), 'src', 'dst')} < {int(0.05 * 2**32)}",
    "gen_grid": "SELECT o_orderkey + 1 AS src, o_orderkey + 2 AS dst, CAST(1 AS BIGINT) AS w FROM orders, (SELECT count(*) AS n FROM orders) q WHERE o_orderkey % 30 < 29 AND o_orderkey + 1 < n UNION ALL SELECT o_orderkey + 1, o_orderkey + 31, 1 FROM orders, (SELECT count(*) AS n FROM orders) q WHERE o_orderkey + 30 < n",
    "gen_planted": f"SELECT src, dst, CAST(1 AS BIGINT) AS w FROM {_NUMBERED} WHERE {_md5(repr('7'), 'src', 'dst')} < CASE WHEN (src - 1) // 60 = (dst - 1) // 60 THEN {int(0.3 * 2**32)} ELSE {int(0.02 * 2**32)} END",
}
