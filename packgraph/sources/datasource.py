"""Packed graphs as a data source of their own: ``spark.read.format("packed_graph")``.

A graph written by ``files.write_graph`` has a folder a vertex range. The reader takes conditions on ``v`` from the plan (equality, bounds, lists),
plans only ranges that they allow and decodes rows that pass; Spark checks the conditions again. Reading is one task a range.
"""

from __future__ import annotations

import os
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, GreaterThan, GreaterThanOrEqual, In, InputPartition, LessThan, LessThanOrEqual

from ..core.compressed import TRANSFORMERS, CompressedGraph
from ..core.store import kept_folder
from ..graphs import derive
from .files import write_graph

PUSH = "spark.sql.python.filterPushdown.enabled"


class RangeOfVertices(InputPartition):
    def __init__(self, path: str):
        super().__init__(path)
        self.path = path


class PackedReader(DataSourceReader):
    def __init__(self, options: dict):
        self.path, self.size = options["path"], int(options.get("range", 1 << 16))
        self.codec, self.n = options.get("codec", "gap_varint"), int(options["n"])
        self.lo, self.hi, self.some = 1, self.n, None

    def pushFilters(self, filters) -> Iterator:  # noqa: N802  (Spark's name)
        """Narrows the vertices to read; every condition is also left to Spark."""
        for f in filters:
            if getattr(f, "attribute", None) == ("v",):
                if isinstance(f, EqualTo):
                    self.some = {f.value} if self.some is None else self.some & {f.value}
                elif isinstance(f, In):
                    self.some = set(f.value) if self.some is None else self.some & set(f.value)
                elif isinstance(f, GreaterThan):
                    self.lo = max(self.lo, f.value + 1)
                elif isinstance(f, GreaterThanOrEqual):
                    self.lo = max(self.lo, f.value)
                elif isinstance(f, LessThan):
                    self.hi = min(self.hi, f.value - 1)
                elif isinstance(f, LessThanOrEqual):
                    self.hi = min(self.hi, f.value)
            yield f

    def _allowed(self, v: np.ndarray) -> np.ndarray:
        ok = (v >= self.lo) & (v <= self.hi)
        return ok & np.isin(v, list(self.some)) if self.some is not None else ok

    def partitions(self) -> list[InputPartition]:
        out = []
        for name in sorted(os.listdir(self.path)):
            if name.startswith("range_id="):
                first = int(name.split("=")[1]) * self.size + 1
                last = first + self.size - 1
                if first <= self.hi and last >= self.lo and (self.some is None or any(first <= x <= last for x in self.some)):
                    out.append(RangeOfVertices(os.path.join(self.path, name)))
        return out

    def read(self, partition: RangeOfVertices) -> Iterator[pa.RecordBatch]:
        transformer = TRANSFORMERS[self.codec]
        for name in sorted(os.listdir(partition.path)):
            if not name.endswith(".parquet"):
                continue
            for b in pq.ParquetFile(os.path.join(partition.path, name)).iter_batches(columns=["v", "d", "width", "first", "payload"]):
                b = b.filter(pa.array(self._allowed(b.column(0).to_numpy())))
                v, d = b.column(0).to_numpy(), b.column(1).to_numpy()
                u = transformer.decode(b.column(4).to_pylist(), b.column(2).to_numpy(), b.column(3).to_numpy(), d, v, self.n)
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(v, d), pa.int64()), pa.array(u, pa.int64())], names=["v", "u"])


class PackedGraphSource(DataSource):
    """Options: path, n (vertices), codec (a transformer's name), range (vertices a folder)."""

    @classmethod
    def name(cls) -> str:
        return "packed_graph"

    def schema(self) -> str:
        return "v bigint, u bigint"

    def reader(self, schema) -> DataSourceReader:
        return PackedReader(self.options)


def read_packed(spark: SparkSession, path: str, n: int, codec: str = "gap_varint", size: int = 1 << 16) -> DataFrame:
    """(v, u) of a written graph; conditions on v are pushed into the reader."""
    spark.conf.set(PUSH, "true")
    spark.dataSource.register(PackedGraphSource)
    return spark.read.format("packed_graph").option("path", path).option("n", n).option("codec", codec).option("range", size).load()


def write_bucketed(cells: DataFrame, table: str, buckets: int = 16, path: str | None = None) -> DataFrame:
    """Cells as a table of the catalog bucketed and sorted by v: joins and aggregations by v need no exchange."""
    w = cells.write.bucketBy(buckets, "v").sortBy("v", "u").mode("overwrite")
    (w.option("path", path) if path else w).saveAsTable(table)
    return cells.sparkSession.table(table)


def _pushed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Vertices 100 to 299 of a written graph, by conditions that reach the reader."""
    g, path = derive.load(spark, sf_dir, "g_page_link"), kept_folder(spark, "packed")
    write_graph(CompressedGraph.build(g, TRANSFORMERS["gap_varint"]), path, 64)
    return read_packed(spark, path, g.n, "gap_varint", 64).where("v >= 100 AND v < 300")


def _bucketed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Degrees and greatest neighbours from a bucketed table."""
    path = kept_folder(spark, "bucketed")
    table = "packgraph_" + path.rsplit("-", 1)[-1]
    cells = write_bucketed(derive.load(spark, sf_dir, "g_page_link").cells().select("v", "u"), table, 8, path)
    return cells.groupBy("v").agg(F.count("*").alias("d"), F.max("u").alias("greatest"))


QUERIES = {"source_pushed_range": _pushed, "sink_bucketed": _bucketed}
ORACLES = {
    "source_pushed_range": derive.with_graph("g_page_link") + "SELECT v, u FROM cells WHERE v BETWEEN 100 AND 299",
    "sink_bucketed": derive.with_graph("g_page_link") + "SELECT v, count(*) AS d, max(u) AS greatest FROM cells GROUP BY v",
}
