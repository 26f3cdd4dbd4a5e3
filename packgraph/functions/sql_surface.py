"""Arrow functions under SQL names: packing, variable-length integers, rank and select, and a table function that decodes lists."""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import arrow_udf, udtf
from pyspark.sql.types import ArrayType, BinaryType, LongType, StructType

from ..bits import pack as kernels
from ..core.compressed import TRANSFORMERS, CompressedGraph
from ..graphs import derive


def _flat(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    off = col.offsets.to_numpy()
    return col.values.to_numpy(zero_copy_only=False)[off[0] : off[-1]].astype(np.int64), (off - off[0]).astype(np.int64)


@arrow_udf(BinaryType())
def pack_bits(values: pa.Array, width: pa.Array) -> pa.Array:
    x, begin = _flat(values)
    return pa.array(kernels.pack(x, width.to_numpy().astype(np.int64), begin), pa.binary())


@arrow_udf(ArrayType(LongType()))
def unpack_bits(payload: pa.Array, width: pa.Array, count: pa.Array) -> pa.Array:
    begin = np.concatenate([[0], np.cumsum(count.to_numpy())])
    x = kernels.unpack(payload.to_pylist(), width.to_numpy().astype(np.int64), begin)
    return pa.ListArray.from_arrays(pa.array(begin, pa.int32()), pa.array(x))


@arrow_udf(BinaryType())
def varint_encode(values: pa.Array) -> pa.Array:
    return pa.array(kernels.varint(*_flat(values)), pa.binary())


@arrow_udf(ArrayType(LongType()))
def varint_decode(payload: pa.Array) -> pa.Array:
    x, begin = kernels.unvarint(payload.to_pylist())
    return pa.ListArray.from_arrays(pa.array(begin, pa.int32()), pa.array(x))


@arrow_udf(LongType())
def bv_rank(bits: pa.Array, place: pa.Array) -> pa.Array:
    """Ones up to and including a place."""
    return pa.array([int(np.unpackbits(np.frombuffer(b, np.uint8), bitorder="little")[: p + 1].sum()) for b, p in zip(bits.to_pylist(), place.to_pylist())], pa.int64())


@arrow_udf(LongType())
def bv_select(bits: pa.Array, k: pa.Array) -> pa.Array:
    """Place of the k-th one (from 1); null beyond the last."""
    out = []
    for b, j in zip(bits.to_pylist(), k.to_pylist()):
        at = np.flatnonzero(np.unpackbits(np.frombuffer(b, np.uint8), bitorder="little"))
        out.append(int(at[j - 1]) if 0 < j <= len(at) else None)
    return pa.array(out, pa.int64())


@arrow_udf(LongType())
def zlib_size(payload: pa.Array) -> pa.Array:
    return pa.array([len(zlib.compress(b, 6)) for b in payload.to_pylist()], pa.int64())


@udtf(returnType=StructType().add("u", LongType()))
class DecodeGaps:
    """The neighbours in a gap-coded payload of vertex v."""

    def eval(self, v: int, d: int, payload: bytes):
        x, _ = kernels.unvarint([bytes(payload)])
        for u in kernels.ungaps(x, np.array([0, d]), np.array([v])).tolist():
            yield (u,)


def register_all(spark: SparkSession) -> None:
    """Makes the functions known to SQL."""
    for f in (pack_bits, unpack_bits, varint_encode, varint_decode, bv_rank, bv_select, zlib_size):
        spark.udf.register(f.__name__ if hasattr(f, "__name__") else f.func.__name__, f)
    spark.udtf.register("decode_gaps", DecodeGaps)


def _pack(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Packed and unpacked again."""
    g = derive.load(spark, sf_dir, "g_page_link")
    a = g.adjacency().select("v", F.transform("nbrs", lambda x: x - 1).alias("x"), F.lit(max(g.n - 1, 0).bit_length()).alias("w"), F.col("d").alias("n"))
    p = a.select("v", "n", "w", pack_bits("x", "w").alias("p"))
    return p.select("v", F.explode(unpack_bits("p", "w", "n")).alias("x")).select("v", (F.col("x") + 1).alias("u"))


def _varint(spark: SparkSession, sf_dir: str) -> DataFrame:
    a = derive.load(spark, sf_dir, "g_page_link").adjacency()
    return a.select("v", F.explode(varint_decode(varint_encode("nbrs"))).alias("u"))


def _vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A bit vector a vertex: the places of its neighbours."""
    a = derive.load(spark, sf_dir, "g_page_link").adjacency()

    @arrow_udf(BinaryType())
    def bits(values: pa.Array) -> pa.Array:
        out = []
        for x in values.to_pylist():
            b = np.zeros(max(x) + 1, np.uint8)
            b[np.array(x)] = 1
            out.append(np.packbits(b, bitorder="little").tobytes())
        return pa.array(out, pa.binary())

    return a.select("v", bits("nbrs").alias("b"))


def _rank(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _vectors(spark, sf_dir).select("v", bv_rank("b", F.lit(400)).alias("r"))


def _select(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _vectors(spark, sf_dir).select("v", bv_select("b", F.lit(2)).alias("second")).where("second IS NOT NULL")


def _table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lists decoded by the table function, in SQL."""
    register_all(spark)
    CompressedGraph.build(derive.load(spark, sf_dir, "g_page_link"), TRANSFORMERS["gap_varint"]).rows.createOrReplaceTempView("packed_lists")
    return spark.sql("SELECT v, u FROM packed_lists, LATERAL decode_gaps(v, d, payload)")


_CELLS = derive.with_graph("g_page_link") + "SELECT v, u FROM cells"
QUERIES = {"udf_pack": _pack, "udf_varint": _varint, "bv_rank": _rank, "bv_select": _select, "bv_rank_all": _rank, "bv_select_all": _select, "udtf_neighbors": _table}
ORACLES = {
    "udf_pack": _CELLS, "udf_varint": _CELLS, "udtf_neighbors": _CELLS,
    "bv_rank": derive.with_graph("g_page_link") + "SELECT v, count(CASE WHEN u <= 400 THEN 1 END) AS r FROM cells GROUP BY v",
    "bv_select": derive.with_graph("g_page_link") + "SELECT v, u AS second FROM (SELECT v, u, row_number() OVER (PARTITION BY v ORDER BY u) AS k FROM cells) q WHERE k = 2",
}
