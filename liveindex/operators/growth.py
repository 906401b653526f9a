"""Sizes of the blocks of a chain: a pure function of the block's number, computed with integers.

B: smallest block and unit of sizes; h: bytes of a link. n is the payload of the blocks so far, all bytes but links.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

RULES = ("constant", "geometric", "triangular")
CAP = 1 << 16


def _up(x_num: int, x_den: int, unit: int) -> int:
    """Smallest multiple of unit at or above x_num / x_den."""
    return -(-x_num // (x_den * unit)) * unit


def next_size(rule: str, unit: int, h: int, n: int, k: float = 1.1) -> int:
    """Size of the block that follows payload n, aligned to the unit."""
    if rule == "constant" or n == 0:
        return unit
    if rule == "geometric":
        thousandth = round((k - 1) * 1000)
        return max(unit, _up(h * 1000 + thousandth * n, 1000, unit))
    if rule == "triangular":
        root = math.isqrt(2 * h * n)
        return max(unit, _up(h + root + (root * root < 2 * h * n), 1, unit))
    raise ValueError(f"no growth rule {rule}")


def sizes(rule: str, unit: int, h: int, blocks: int, k: float = 1.1, cap: int | None = CAP) -> list[int]:
    """Sizes of the first blocks of a chain."""
    out, n = [], 0
    most = None if cap is None else cap // unit * unit
    for _ in range(blocks):
        size = next_size(rule, unit, h, n, k)
        size = size if most is None else min(size, most)
        out.append(size)
        n += size - h
    return out


def sizes_until(rule: str, unit: int, h: int, payload: int, k: float = 1.1, cap: int | None = CAP) -> list[int]:
    """Sizes of the blocks that hold some payload."""
    out, n = [], 0
    while n < payload:
        size = next_size(rule, unit, h, n, k)
        out.append(size if cap is None else min(size, cap // unit * unit))
        n += out[-1] - h
    return out


def powers_sizes(first: int, k: float, blocks: int, cap: int | None = None) -> list[int]:
    """Earlier geometric rule: each block k times the one before, rounded up, to a cap."""
    out, size = [], float(first)
    for _ in range(blocks):
        out.append(min(math.ceil(size - 1e-9), cap or 1 << 62))
        size *= k
    return out


def fibonacci_sizes(unit: int, blocks: int) -> list[int]:
    out, a, b = [], 1, 1
    for _ in range(blocks):
        out.append(a * unit)
        a, b = b, a + b
    return out


def repeated_sizes(unit: int, times: int, blocks: int) -> list[int]:
    """Each power of two times the unit, `times` times over."""
    return [unit << (z // times) for z in range(blocks)]


#: Postings of the slices of an earlier in-memory index; the last repeats.
SLICES = (2, 16, 128, 2048)


def slice_sizes(blocks: int) -> list[int]:
    return [SLICES[min(z, len(SLICES) - 1)] for z in range(blocks)]


def curve(spark: SparkSession, rule: str, unit: int, h: int, payload: int, k: float = 1.1) -> DataFrame:
    """(rule, z, lo_n, hi_n, mid_n, overhead, ratio): cost of a chain of z blocks at the middle of the payloads it holds.

    overhead: links and the unused part of the last block."""
    rows, total = [], 0
    for z, size in enumerate(sizes_until(rule, unit, h, payload, k, None), 1):
        low, total = total + 1, total + size - h
        middle = (low + total) / 2
        over = z * h + total - middle
        rows.append((rule, z, low, total, middle, over))
    return spark.createDataFrame(rows, "rule string, z long, lo_n long, hi_n long, mid_n double, overhead double").withColumn("ratio", F.round(F.col("overhead") / F.col("mid_n"), 6))


def chains(payloads: DataFrame, rule: str, unit: int, h: int, most: int, k: float = 1.1, cap: int | None = CAP) -> DataFrame:
    """(n, lists, z, lo_n, hi_n) of payloads(n, lists), none above `most`: the blocks of a chain that holds n bytes, and
    the least and largest payload of chains of so many blocks."""
    high = np.cumsum(np.array(sizes_until(rule, unit, h, most, k, cap), np.int64) - h)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = np.searchsorted(high, batch.column("n").to_numpy())
            yield pa.RecordBatch.from_arrays([batch.column("n"), batch.column("lists"), pa.array(at + 1), pa.array(np.append(0, high)[at] + 1), pa.array(high[at])], names=["n", "lists", "z", "lo_n", "hi_n"])

    return payloads.select("n", "lists").mapInArrow(run, "n long, lists long, z long, lo_n long, hi_n long")


def best_block(n: Column, h: int) -> Column:
    """Block size of least overhead for a known payload n; a block holds a byte besides its link."""
    return F.greatest(F.ceil(F.sqrt(F.lit(2 * h) * n)), F.lit(h + 1).cast("long"))


def asymptotic(rule: str, unit: int, h: int, n: float, k: float = 1.1) -> float:
    """Share of overhead for large n."""
    return {"constant": h / (unit - h), "geometric": (k - 1) / k / 2, "triangular": 2 * math.sqrt(h / 2) / math.sqrt(n)}[rule]


def array_copies(n: int, k: float) -> tuple[int, int]:
    """An array that grows by k when full: items copied until it holds n, and most cells held at a time."""
    size, copied, peak = 1, 0, 1
    while size < n:
        larger = max(size + 1, math.ceil(size * k))
        copied, peak = copied + size, max(peak, size + larger)
        size = larger
    return copied, peak
