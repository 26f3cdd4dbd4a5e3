"""Tables in the folder that all executors share; they cut lineage and survive lost executors."""

from __future__ import annotations

import atexit
import gc
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_made: list = []


def shared_folder(spark: SparkSession) -> str:
    """``spark.checkpoint.dir``; where it is unset, a temporary folder, on a local master only."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if folder is None:
        found = spark.sparkContext._jsc.sc().getCheckpointDir()
        if found.isDefined():
            return found.get()
        if not spark.sparkContext.master.startswith("local["):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        folder = tempfile.mkdtemp(prefix="packgraph-")
        spark.sparkContext.setCheckpointDir(folder)
    return folder.rstrip("/")


def _delete(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    if jvm is not None:
        where = jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


def _tidy() -> None:
    for spark, path in _made:
        try:
            _delete(spark, path)
        except Exception:  # the session has ended; its folder goes with the application
            return


atexit.register(_tidy)


def kept_folder(spark: SparkSession, name: str) -> str:
    """A new path in the shared folder, which goes with the others when the application ends."""
    path = f"{shared_folder(spark)}/packgraph-{name}-{uuid.uuid4().hex}"
    _made.append((spark, path))
    return path


def written(df: DataFrame, name: str) -> DataFrame:
    spark = df.sparkSession
    path = kept_folder(spark, name)
    df.write.option("compression", "zstd").parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._packgraph_path = path
    return out


def drop(df: DataFrame) -> None:
    """Removes a table of ``written`` that nothing reads any more."""
    path = getattr(df, "_packgraph_path", None)
    if path:
        _delete(df.sparkSession, path)
        _made[:] = [x for x in _made if x[1] != path]


def tables() -> list[str]:
    """Paths of the tables of ``written`` that are there now."""
    return [path for _, path in _made]


def remove(spark: SparkSession, paths: list[str]) -> None:
    """Removes some of them, for callers that have stored every result that reads them."""
    for path in paths:
        _delete(spark, path)
    _made[:] = [x for x in _made if x[1] not in set(paths)]
    reclaim(spark)


def reclaim(spark: SparkSession) -> None:
    """Asks both collectors to run, so that Spark removes the shuffle files of finished plans now rather than at its next half hour."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()
