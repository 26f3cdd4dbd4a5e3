"""Width arithmetic as Spark expressions and as the SQL of both engines; integers only."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def bit_length(x: str) -> str:
    """Bits of a non-negative integer; 0 for 0. SQL of Spark and of the oracle."""
    return f"(CASE WHEN ({x}) <= 0 THEN 0 ELSE length(bin(CAST(({x}) AS BIGINT))) END)"


def ceil_lg(x: str) -> str:
    """ceil(log2 x); 0 up to 1."""
    return f"(CASE WHEN ({x}) <= 1 THEN 0 ELSE length(bin(CAST(({x}) AS BIGINT) - 1)) END)"


def varint_bits(x: str) -> str:
    """Bits of a variable-length integer of seven payload bits a byte."""
    return f"(CASE WHEN ({x}) < 128 THEN 8 WHEN ({x}) < 16384 THEN 16 WHEN ({x}) < 2097152 THEN 24 WHEN ({x}) < 268435456 THEN 32 WHEN ({x}) < 34359738368 THEN 40 WHEN ({x}) < 4398046511104 THEN 48 WHEN ({x}) < 562949953421312 THEN 56 WHEN ({x}) < 72057594037927936 THEN 64 ELSE 72 END)"


def zigzag(x: str) -> str:
    return f"(CASE WHEN ({x}) >= 0 THEN 2 * ({x}) ELSE -2 * ({x}) - 1 END)"


def col(sql: str) -> Column:
    return F.expr(sql)
