"""Functions for SQL: code lengths and weights as SQL expressions, codecs as vectorised functions, growth as a table."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from liveindex.functions import codecs
from liveindex.operators import growth


@F.pandas_udf(T.BinaryType())
def vbyte_encode(lists: pd.Series) -> pd.Series:
    return lists.map(lambda x: None if x is None else codecs.vbyte_encode(np.asarray(x, np.int64)).tobytes())


@F.pandas_udf(T.ArrayType(T.LongType()))
def vbyte_decode(data: pd.Series) -> pd.Series:
    return data.map(lambda x: None if x is None else codecs.vbyte_decode(np.frombuffer(x, np.uint8)))


_PAIRS = T.ArrayType(T.StructType([T.StructField("a", T.LongType()), T.StructField("b", T.LongType())]))


@F.pandas_udf(T.BinaryType())
def pair_encode(a: pd.Series, b: pd.Series, f: pd.Series) -> pd.Series:
    """The paired code of two arrays of one length with a threshold."""
    return pd.Series([None if x is None or y is None else codecs.pair_encode(np.asarray(x, np.int64), np.asarray(y, np.int64), int(t)).tobytes() for x, y, t in zip(a, b, f, strict=True)])


@F.pandas_udf(_PAIRS)
def pair_decode(data: pd.Series, f: pd.Series) -> pd.Series:
    def one(x: bytes | None, t: int):
        return None if x is None else [{"a": int(u), "b": int(v)} for u, v in zip(*codecs.pair_decode(np.frombuffer(x, np.uint8), int(t)), strict=True)]

    return pd.Series([one(x, t) for x, t in zip(data, f, strict=True)])


@F.udtf(returnType=T.StructType([T.StructField("d", T.LongType()), T.StructField("f", T.LongType())]))
class DecodePostings:
    """decode_postings(payload, first_d, threshold): the postings of a block of a document-level index."""

    def eval(self, payload: bytes, first: int, threshold: int):
        gap, f = codecs.pair_decode(np.frombuffer(payload or b"", np.uint8), threshold)
        if gap.size:
            yield from zip((first + np.cumsum(gap) - gap[0]).tolist(), f.tolist(), strict=True)


@F.udtf(returnType=T.StructType([T.StructField("z", T.IntegerType()), T.StructField("size", T.LongType()), T.StructField("payload", T.LongType())]))
class Growth:
    """growth(rule, B, h, blocks): sizes of the first blocks of a chain."""

    def eval(self, rule: str, unit: int, h: int, blocks: int):
        n = 0
        for z, size in enumerate(growth.sizes(rule, unit, h, blocks), 1):
            n += size - h
            yield z, size, n


def register(spark: SparkSession) -> None:
    """Puts the functions under their names into the session."""
    steps = " ".join(f"WHEN x < {1 << (7 * k)} THEN {k}" for k in range(1, 9))
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION vbyte_len(x BIGINT) RETURNS INT RETURN CASE {steps} ELSE 9 END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION pair_len(a BIGINT, b BIGINT, f BIGINT) RETURNS INT RETURN CASE WHEN b < f THEN vbyte_len((a - 1) * f + b) ELSE vbyte_len(a * f) + vbyte_len(b - f + 1) END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION tf_idf(f BIGINT, n BIGINT, ft BIGINT) RETURNS DOUBLE RETURN ln(1 + f) * ln(1 + n / ft)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION bm25(f BIGINT, n BIGINT, ft BIGINT, len BIGINT, avg_len DOUBLE) RETURNS DOUBLE RETURN ln(1 + (n - ft + 0.5D) / (ft + 0.5D)) * f * 1.9D / (f + 0.9D * (0.6D + 0.4D * len / avg_len))")
    spark.udf.register("pair_encode", pair_encode)
    spark.udf.register("pair_decode", pair_decode)
    spark.udtf.register("decode_postings", DecodePostings)
    spark.udf.register("vbyte_encode", vbyte_encode)
    spark.udf.register("vbyte_decode", vbyte_decode)
    spark.udtf.register("growth", Growth)
