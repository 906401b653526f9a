"""Lengths of codes and weights as column expressions; they stay inside code generation.

Byte code: seven bits a byte, low bits first, top bit on the last. Paired code of (a, b) with threshold F: one
number (a - 1) * F + b if b < F, else the two numbers a * F and b - F + 1. The remainder by F tells the cases apart.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Thresholds for document-level and word-level postings.
DOC_F, WORD_F = 4, 3


def vbyte_len(x: Column) -> Column:
    out = F.when(x < (1 << 7), 1)
    for k in range(2, 9):
        out = out.when(x < F.lit(1 << (7 * k)), k)
    return out.otherwise(9).cast("int")


def pair_fuse(a: Column, b: Column, f: int | Column) -> Column:
    f = F.lit(f) if isinstance(f, int) else f
    return F.when(b < f, (a - 1) * f + b).otherwise(a * f)


def pair_second(a: Column, b: Column, f: int | Column) -> Column:
    """The second number of a pair, null if one number says it all."""
    f = F.lit(f) if isinstance(f, int) else f
    return F.when(b >= f, b - f + 1)


def pair_len(a: Column, b: Column, f: int | Column) -> Column:
    f = F.lit(f) if isinstance(f, int) else f
    return (vbyte_len(pair_fuse(a, b, f)) + F.when(b >= f, vbyte_len(b - f + 1)).otherwise(0)).cast("int")


def tf_idf(f: Column, n: Column, ft: Column) -> Column:
    """log(1 + f) * log(1 + n / ft), natural logarithms."""
    return F.log(1 + f.cast("double")) * F.log(1 + n.cast("double") / ft)


def bm25(f: Column, n: Column, ft: Column, length: Column, average: Column, k1: float = 0.9, b: float = 0.4) -> Column:
    idf = F.log(1 + (n - ft + 0.5) / (ft + 0.5))
    return idf * f * (k1 + 1) / (f + k1 * (1 - b + b * length / average))
