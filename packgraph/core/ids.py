"""Contiguous identifiers and prefix sums without a window over one partition.

Two passes: rows are range-partitioned and written in order, each partition's total goes to the driver (a number a
partition), and the totals before a partition are added to places within it.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .store import written

SMALL_RANGES = 64


def _ordered(df: DataFrame, order: list) -> DataFrame:
    """Adds _part and _row: the range partition and the place within it. Written, since range bounds are sampled anew in each run."""
    ranged = df.repartitionByRange(*order).sortWithinPartitions(*order)
    mono = F.monotonically_increasing_id()
    return written(ranged.withColumn("_part", F.shiftright(mono, 33)).withColumn("_row", mono.bitwiseAND((1 << 33) - 1)), "ranges")


def _bases(ordered: DataFrame, total: Column) -> DataFrame:
    totals = ordered.groupBy("_part").agg(total.alias("_t")).collect()  # a row a partition
    base, at = [], 0
    for r in sorted(totals):
        base.append((r["_part"], at))
        at += r["_t"] or 0
    return F.broadcast(ordered.sparkSession.createDataFrame(base, "_part long, _base long"))


def global_rank(df: DataFrame, order: list, out: str = "rank", start: int = 1) -> DataFrame:
    """Adds the row number over all rows in the given order; a total order makes it unique."""
    ordered = _ordered(df, order)
    bases = _bases(ordered, F.count("*"))
    return ordered.join(bases, "_part").withColumn(out, F.col("_base") + F.col("_row") + start).drop("_part", "_row", "_base")


def prefix_sums(df: DataFrame, order: list, value: str, out: str = "off") -> DataFrame:
    """Adds the sum of ``value`` over all rows before."""
    ordered = _ordered(df, order)
    bases = _bases(ordered, F.sum(value))
    before = F.sum(value).over(Window.partitionBy("_part").orderBy("_row").rowsBetween(Window.unboundedPreceding, -1))
    return ordered.join(bases, "_part").withColumn(out, F.col("_base") + F.coalesce(before, F.lit(0))).drop("_part", "_row", "_base")


def place_in_group(df: DataFrame, group: str, order: str, out: str = "place") -> DataFrame:
    """Adds each row's place (from 0) within its group, by ``order``, with no group in one task.

    Rows are range-partitioned by both columns; a partition numbers its own, and only its first and last group can go on in others, so
    that a count of two groups a partition tells where they start.
    """
    ordered = _ordered(df, [F.col(group), F.col(order)])
    own = F.row_number().over(Window.partitionBy("_part", group).orderBy("_row")) - 1
    count = ordered.groupBy("_part", group).agg(F.count("*").alias("_n"))
    ends = ordered.groupBy("_part").agg(F.min(group).alias("_lo"), F.max(group).alias("_hi"))
    cut = count.join(F.broadcast(ends), "_part").where(f"`{group}` = _lo OR `{group}` = _hi").select(group, "_part", "_n").collect()  # two rows a partition
    base, before = [], {}
    for g, part, n in sorted(map(tuple, cut)):
        if before.get(g):
            base.append((part, g, before[g]))
        before[g] = before.get(g, 0) + n
    kind = dict(df.dtypes)[group]
    bases = F.broadcast(df.sparkSession.createDataFrame(base, f"_part long, `{group}` {kind}, _base long"))
    return ordered.withColumn("_own", own).join(bases, ["_part", group], "left").withColumn(out, F.col("_own") + F.coalesce("_base", F.lit(0))).drop("_part", "_row", "_own", "_base")


def assign_ids(df: DataFrame, key: str, method: str = "two_pass", out: str = "id") -> DataFrame:
    """Contiguous ids from 1 in the order of ``key``: shift (integers from 0) or two_pass (any distinct keys)."""
    if method == "shift":
        return df.withColumn(out, (F.col(key) + 1).cast("long"))
    return global_rank(df, [F.col(key)], out)
