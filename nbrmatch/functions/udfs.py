"""Functions that need Python, and the names under which SQL knows the engine's functions."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, IntegerType, LongType, StringType, StructType

from ..operators.pattern import parse
from .codes import decode as decode_code
from .codes import ncode


def decode_column(k: int):
    """The vector of length k of a code, as a pandas function: array<bigint>."""

    @F.pandas_udf(ArrayType(LongType()))
    def decode(c: pd.Series) -> pd.Series:
        return pd.Series([None if pd.isna(x) else decode_code(int(x), k) for x in c])

    return decode


@F.pandas_udf(LongType())
def ncode_agg(counts: pd.Series) -> int:
    """The code of a group's counts, in the order of the rows: a grouped aggregate."""
    return ncode([int(x) for x in counts])


@F.udtf(returnType=StructType().add("u", StringType()).add("vlabel", StringType()).add("pdeg", IntegerType()).add("code", LongType()))
class ExpandPattern:
    """Rows of a text pattern: expand_pattern('(a:X)-(b:Y)')."""

    def eval(self, text: str) -> Iterator[tuple]:
        q = parse(text)
        for u in sorted(q.vertices):
            yield u, q.vertices[u], q.pdeg(u), q.code(u)


@F.udtf(returnType=StructType().add("rank", IntegerType()).add("n", LongType()))
class DecodeCode:
    """Rows (rank, n) of a code's vector: decode_code(code, k)."""

    def eval(self, code: int, k: int) -> Iterator[tuple]:
        for rank, n in enumerate(decode_code(int(code), int(k)), 1):
            yield rank, n


def register(spark: SparkSession) -> None:
    """SQL names: ncode(array) and hstep(p, s) as SQL expressions on the JVM, expand_pattern and decode_code as tables."""
    spark.udtf.register("expand_pattern", ExpandPattern)
    spark.udtf.register("decode_code", DecodeCode)
    spark.sql(
        """CREATE OR REPLACE TEMPORARY FUNCTION hstep(p INT, s BIGINT) RETURNS BIGINT
        RETURN CASE WHEN s < 1 THEN 0L ELSE aggregate(sequence(1, p), 1L, (a, t) -> a * (s + t - 1) div t) END"""
    )
    spark.sql(
        """CREATE OR REPLACE TEMPORARY FUNCTION ncode(x ARRAY<BIGINT>) RETURNS BIGINT
        RETURN aggregate(x, named_struct('s', 0L, 'j', 0, 'c', 0L),
          (a, n) -> named_struct('s', a.s + n, 'j', a.j + 1, 'c', a.c + CASE WHEN a.s + n < 1 THEN 0L ELSE aggregate(sequence(1, a.j + 1), 1L, (b, t) -> b * (a.s + n + t - 1) div t) END), a -> a.c)"""
    )
