"""Graphs as DataFrames: vertices 1..n, edges (src < dst, w) without loops or duplicates."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .ids import place_in_group

CHUNK = 65_536
HUB = 1 << 20


@dataclass
class Graph:
    """name, n and edges (src, dst, w: long, src < dst). Vertices are all of 1..n, with or without edges."""

    name: str
    n: int
    edges: DataFrame

    @classmethod
    def from_edges(cls, name: str, n: int, df: DataFrame, agg: str = "min") -> Graph:
        """Canonical edges of rows (src, dst, w): ends in order, no loops, one row a pair (weights by ``agg``)."""
        two = df.where("src != dst").select(F.least("src", "dst").cast("long").alias("src"), F.greatest("src", "dst").cast("long").alias("dst"), F.col("w").cast("long").alias("w"))
        return cls(name, n, two.groupBy("src", "dst").agg(F.expr(f"{agg}(w)").cast("long").alias("w")))

    @property
    def spark(self) -> SparkSession:
        return self.edges.sparkSession

    def vertices(self) -> DataFrame:
        return self.spark.range(1, self.n + 1)

    def cells(self) -> DataFrame:
        """(v, u, w): each edge from both ends; one scan of the edges."""
        ends = F.array(F.struct(F.col("src").alias("v"), F.col("dst").alias("u")), F.struct(F.col("dst").alias("v"), F.col("src").alias("u")))
        return self.edges.select(F.explode(ends).alias("e"), "w").select("e.v", "e.u", "w")

    def degrees(self) -> DataFrame:
        """(id, d) of all vertices, isolated ones with 0."""
        d = self.cells().groupBy("v").agg(F.count("*").alias("d"))
        return self.vertices().join(d, F.col("id") == F.col("v"), "left").select("id", F.coalesce("d", F.lit(0)).alias("d"))

    def relabel(self, perm: DataFrame) -> Graph:
        """Applies (id, new_id). Spark broadcasts ``perm`` where its size allows and merges otherwise."""
        a = perm.select(F.col("id").alias("src"), F.col("new_id").alias("_s"))
        b = perm.select(F.col("id").alias("dst"), F.col("new_id").alias("_d"))
        e = self.edges.join(a, "src").join(b, "dst")
        return Graph(self.name, self.n, e.select(F.least("_s", "_d").alias("src"), F.greatest("_s", "_d").alias("dst"), "w"))

    def with_hubs(self) -> bool:
        """Whether some list is too long to be sorted in one task."""
        return (self.cells().groupBy("v").count().agg(F.max("count")).first()[0] or 0) > HUB

    def consecutive(self) -> DataFrame:
        """(v, u, w, before): cells and the neighbour before u in v's list, null for the first."""
        if not self.with_hubs():
            return self.cells().withColumn("before", F.lag("u").over(Window.partitionBy("v").orderBy("u")))
        p = place_in_group(self.cells(), "v", "u")
        return p.join(p.select("v", (F.col("place") + 1).alias("place"), F.col("u").alias("before")), ["v", "place"], "left").select("v", "u", "w", "before")

    def places(self) -> DataFrame:
        """(v, u, w, place): cells and the place (from 0) of u among v's neighbours. Lists beyond ``HUB`` entries are numbered in ranges of
        rows, so that no hub is sorted in one task; the result is the same."""
        if self.with_hubs():
            return place_in_group(self.cells(), "v", "u")
        return self.cells().withColumn("place", F.row_number().over(Window.partitionBy("v").orderBy("u")) - 1)

    def adjacency(self, chunk: int = CHUNK) -> DataFrame:
        """(v, chunk, d, nbrs, ws): sorted neighbours; a hub's list is cut every ``chunk`` entries, so no row is unbounded."""
        cut = self.places().withColumn("chunk", F.floor(F.col("place") / chunk).cast("int"))
        lists = cut.groupBy("v", "chunk").agg(F.array_sort(F.collect_list(F.struct("u", "w"))).alias("l"))
        return lists.select("v", "chunk", F.size("l").cast("long").alias("d"), F.col("l.u").alias("nbrs"), F.col("l.w").alias("ws"))
