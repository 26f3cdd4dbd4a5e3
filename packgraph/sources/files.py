"""Edge lists from text files, and packed graphs as partitioned Parquet with range pruning."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..core.compressed import TRANSFORMERS, CompressedGraph
from ..core.model import Graph
from ..core.store import shared_folder
from ..graphs import derive

EDGES = "src long, dst long, w long"


def read_edges(spark: SparkSession, path: str, form: str = "csv", **options) -> DataFrame:
    """(src, dst, w) with a fixed schema; csv, json, orc or parquet."""
    return spark.read.schema(EDGES).options(**options).format(form).load(path)


def write_edges(g: Graph, path: str, form: str = "csv") -> None:
    g.edges.select("src", "dst", "w").write.format(form).save(path)


def write_graph(cg: CompressedGraph, path: str, size: int = 1 << 16) -> None:
    """Packed rows by vertex range: the range is a folder, so a reader of few vertices opens few files."""
    ranged = cg.rows.withColumn("range_id", F.floor((F.col("v") - 1) / size).cast("long"))
    ranged.repartition("range_id").sortWithinPartitions("v", "chunk").write.partitionBy("range_id").parquet(path)


def read_graph(spark: SparkSession, path: str, name: str, n: int, transformer, size: int = 1 << 16, lo: int | None = None, hi: int | None = None) -> CompressedGraph:
    """The graph's rows, or those of vertices lo..hi: ranges are pruned before files are opened."""
    rows = spark.read.parquet(path)
    if lo is not None:
        rows = rows.where(F.col("range_id").between((lo - 1) // size, (hi - 1) // size) & F.col("v").between(lo, hi))
    empty = spark.createDataFrame([], "src long, dst long, w long")
    return CompressedGraph(Graph(name, n, empty), rows, transformer)


def _round(form: str):
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        path = f"{shared_folder(spark)}/packgraph-edges-{uuid.uuid4().hex}"
        write_edges(derive.load(spark, sf_dir, "g_page_link"), path, form)
        return read_edges(spark, path, form)

    return query


def _sink(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Vertices 100 to 299 of a graph written by ranges of 64."""
    path = f"{shared_folder(spark)}/packgraph-graph-{uuid.uuid4().hex}"
    g = derive.load(spark, sf_dir, "g_page_link")
    write_graph(CompressedGraph.build(g, TRANSFORMERS["gap_varint"]), path, 64)
    return read_graph(spark, path, g.name, g.n, TRANSFORMERS["gap_varint"], 64, 100, 299).cells()


_E = derive.with_graph("g_page_link") + "SELECT src, dst, w FROM edges"
QUERIES = {"scan_edge_csv": _round("csv"), "scan_edge_json": _round("json"), "scan_edge_orc": _round("orc"), "sink_roundtrip": _sink}
ORACLES = {"scan_edge_csv": _E, "scan_edge_json": _E, "scan_edge_orc": _E, "sink_roundtrip": derive.with_graph("g_page_link") + "SELECT v, u FROM cells WHERE v BETWEEN 100 AND 299"}
