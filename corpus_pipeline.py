"""A corpus from raw documents to packed sequences: five stages, each a table.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; all but the last return the columns of ``documents``. The
data flow alone makes decisions: a stage sees only what the one before kept.

Defined results of every stage: no rows give no rows; null text stays null (and packs as its end id alone); rows with equal doc_id and text
are treated alike; extra columns go along whatever their names until packing, which drops them.
"""

from __future__ import annotations

import functools
import time

from pyspark.sql import DataFrame, SparkSession

from packgraph.llm.common import kept_folder, remove, tables
from packgraph.llm.host_rules import filter_hosts
from packgraph.llm.line_dedup import dedup_lines
from packgraph.llm.ngram_join import jaccard_components
from packgraph.llm.packing import pack_documents
from packgraph.llm.substring_dedup import remove_substrings
from packgraph.session import ship


_left: list[tuple[float, list[str]]] = []


def _stored_at(spark: SparkSession, docs: DataFrame) -> float:
    """When the rows were stored (seconds), 0 if they are no files."""
    files = docs.inputFiles()
    if not files:
        return 0.0
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(files[0])
    return path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(path).getModificationTime() / 1000


def _stage(f):
    """A stage that first removes the tables of stages whose results were stored by now: those called before ``docs`` was written.

    The last stage's tables stay until the application ends, since nobody stores its result for it.
    """

    @functools.wraps(f)
    def run(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        stored = _stored_at(spark, docs)
        for x in [x for x in _left if x[0] < stored]:
            remove(spark, x[1])
            _left.remove(x)
        before = set(tables())
        out = f(spark, docs, sf_dir)
        if f is not STAGES[-1][1].__wrapped__:
            _left.append((time.time(), [path for path in tables() if path not in before]))
        return out

    return run


@_stage
def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that fail their own or their host's rules go."""
    return filter_hosts(docs)


@_stage
def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One line of each group of similar lines stays; a document may lose all of its lines and stays, empty."""
    return dedup_lines(docs).select(*docs.columns)


@_stage
def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document with the smallest id of each group linked at 0.8 on five-word shingles stays, and every empty one."""
    groups = jaccard_components(docs.select("doc_id", "text"), k=5, percent=80)
    gone = groups.where("component_id != doc_id").select("doc_id")
    return docs.join(gone, "doc_id", "left_anti").select(*docs.columns)


@_stage
def substring_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages of 35 words or more that occur again are taken out."""
    return remove_substrings(docs)


@_stage
def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of what is left, in sequences of 2048."""
    import public_tokenizers

    return pack_documents(docs, public_tokenizers.path("word_bpe_49k.json"))


STAGES = [("quality rules", quality_rules), ("line dedup", line_dedup), ("n-gram Jaccard join", near_duplicates), ("substring dedup", substring_dedup), ("packing", packing)]

ORACLE_SQL = None  # tokenizing and packing have no SQL; tests/llm hold the stages against brute force


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages; what a stage leaves is removed as soon as the next one's result is stored."""
    docs, was = spark.read.parquet(f"{sf_dir}/documents.parquet"), None
    for name, stage in STAGES[:-1]:
        out = stage(ship(spark), docs, sf_dir)
        path = kept_folder(spark, "stage")
        out.write.parquet(path)
        docs, was = spark.read.parquet(path), remove(spark, [was] if was else []) or path
    out = STAGES[-1][1](ship(spark), docs, sf_dir)
    remove(spark, [was])  # pieces and their places are tables of their own by now
    return out
