"""Static lists: the form that a full shard takes. Postings of a list in runs of RUN, each a row of its own with the
documents it begins and ends with and its largest frequency: the rows without payloads are the skip table.

Two codes: `bp128`, document gaps and frequencies in bit-packed blocks at the width of their largest number; `interp`,
documents and running counts in interpolative code within the run's own range. The last run of a list, if it is short,
is in byte code under bp128.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from liveindex.functions import codecs
from liveindex.operators.packer import IndexConfig, _columns, _lists, _sorted

RUN = 128
CODES = ("bp128", "interp")
RUNS = "shard long, term string, block_no long, first_d long, last_d long, n long, total long, most long, payload binary"
_NAMES = [c.split()[0] for c in RUNS.split(", ")]


def _bits(codes: list[tuple[int, int]]) -> bytes:
    value = bits = 0
    for v, n in codes:
        value, bits = value << n | v, bits + n
    return (value << (-bits % 8)).to_bytes((bits + 7) // 8, "big")


def _codes(data: bytes) -> Iterator[int]:
    for byte in data:
        for k in range(7, -1, -1):
            yield byte >> k & 1


def encode_run(d: np.ndarray, f: np.ndarray, code: str) -> bytes:
    """One run. Its first document and sum of frequencies are columns of the run, and so no part of the payload."""
    if code == "bp128":
        return b"".join(codecs.bp_encode(x, RUN)[4:] for x in (np.concatenate(([0], np.diff(d))), f))
    sums = np.cumsum(f)
    return _bits(codecs.interp_encode(d[1:-1].tolist(), int(d[0]) + 1, int(d[-1]) - 1) + codecs.interp_encode(sums[:-1].tolist(), 1, int(sums[-1]) - 1))


def decode_run(payload: bytes, n: int, first: int, last: int, total: int, code: str) -> tuple[np.ndarray, np.ndarray]:
    if code == "bp128":
        if n < RUN:
            both = codecs.vbyte_decode(np.frombuffer(payload, np.uint8))
            return first + np.cumsum(both[:n]), both[n:]
        width = payload[0]
        cut = 1 + RUN * width // 8
        full = (1).to_bytes(4, "little")
        return first + np.cumsum(codecs.bp_decode(full + payload[:cut])), codecs.bp_decode(full + payload[cut:])
    bits = _codes(payload)

    def numbers(count: int, low: int, high: int) -> list[int]:
        out, walk = [0] * count, codecs._centres(low, high, count)
        try:
            index, least, most = next(walk)
            while True:
                size = most - least + 1
                width = (size - 1).bit_length()
                value = 0
                if width:
                    spare = (1 << width) - size
                    for _ in range(width - 1):
                        value = value << 1 | next(bits)
                    if value >= spare:
                        value = (value << 1 | next(bits)) - spare
                out[index] = least + value
                index, least, most = walk.send(out[index])
        except StopIteration:
            return out

    inner = numbers(max(0, n - 2), first + 1, last - 1)
    sums = [*numbers(n - 1, 1, total - 1), total]
    return np.array([first, *inner, last][:n], np.int64), np.diff(np.array([0, *sums], np.int64))


def _unpacked(data: np.ndarray, begin: np.ndarray, width: np.ndarray) -> np.ndarray:
    """RUN bit-packed numbers behind each place, a row a place; places of one width in one go."""
    out = np.zeros((begin.size, RUN), np.int64)
    for w in np.unique(width[width > 0]).tolist():
        some = np.flatnonzero(width == w)
        bits = np.unpackbits(data[begin[some][:, None] + np.arange(RUN * w // 8)], axis=1, bitorder="little").reshape(some.size, RUN, w)
        room = next(n for n in (8, 16, 32, 64) if n >= w)
        wide = np.zeros((some.size, RUN, room), np.uint8)
        wide[:, :, :w] = bits
        out[some] = np.packbits(wide, axis=2, bitorder="little").view(f"<u{room // 8}")[:, :, 0]
    return out


@cache
def _order(count: int) -> list[tuple[int, int, int, int, int]]:
    """(index, number that bounds it from below, from above, how many lie before it up to that bound, behind it) in the
    order of interpolative code, which the count alone fixes; -1 and `count` are the ends of the range."""
    out, waiting = [], [(0, count, -1, count)]
    while waiting:
        first, n, low, high = waiting.pop()
        if n:
            half = n // 2
            out.append((first + half, low, high, half, n - 1 - half))
            waiting += [(first + half + 1, n - half - 1, first + half, high), (first, half, low, first + half)]
    return out


def _interpolated(windows: np.ndarray, at: np.ndarray, count: int, low: np.ndarray, high: np.ndarray) -> np.ndarray:
    """`count` numbers of each run, a row a number, all runs side by side. windows: the 64 bits from each byte on; at: the bit
    that each run stands at, moved on."""
    out = np.empty((count + 2, low.size), np.int64)
    out[count], out[count + 1] = high + 1, low - 1  # out[-1] is the last row: the end below
    for index, below, above, before, behind in _order(count):
        least = out[below] + 1 + before
        size = out[above] - behind - least
        width = np.frexp((size - 1).astype(np.float64))[1].astype(np.int64)
        bits = windows[at >> 3] << (at & 7).astype(np.uint64)
        whole = np.where(width > 0, (bits >> (64 - np.maximum(width, 1)).astype(np.uint64)).astype(np.int64), 0)
        spare = (np.int64(1) << width) - size
        short = (whole >> 1) < spare
        out[index] = least + np.where(short, whole >> 1, whole - spare)
        at += width - short
    return out[:count]


#: So many full runs are decoded side by side; fewer one by one.
SIDE_BY_SIDE = 6


def decode_full_runs(data: np.ndarray, begin: np.ndarray, size: np.ndarray, first: np.ndarray, last: np.ndarray, total: np.ndarray, code: str) -> tuple[np.ndarray, np.ndarray]:
    """decode_run of many runs of RUN postings that lie in one array, one after the other."""
    if code == "bp128":
        width = data[begin].astype(np.int64)
        second = begin + 1 + RUN * width // 8
        gap, f = _unpacked(data, begin + 1, width), _unpacked(data, second + 1, data[second].astype(np.int64))
        return (first[:, None] + np.cumsum(gap, axis=1)).reshape(-1), f.reshape(-1)
    start = np.cumsum(size) - size
    own = np.append(data[np.repeat(begin - start, size) + np.arange(size.sum())], np.zeros(8, np.uint8)).astype(np.uint64)
    windows = np.zeros(own.size - 7, np.uint64)
    for k in range(8):
        windows |= own[k : own.size - 7 + k] << np.uint64(56 - 8 * k)
    at = start * 8
    inner = _interpolated(windows, at, RUN - 2, first + 1, last - 1)
    sums = _interpolated(windows, at, RUN - 1, np.ones_like(total), total - 1)
    return np.vstack((first, inner, last)).T.reshape(-1), np.diff(np.vstack((np.zeros_like(total), sums, total)), axis=0).T.reshape(-1)


def build_static(postings: DataFrame, cfg: IndexConfig, code: str = "bp128", shard=None) -> DataFrame:
    """RUNS of document-level postings(term, d, f): the same one shuffle as a dynamic build."""
    if code not in CODES:
        raise ValueError(f"no static code {code}")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table, first in _lists(batches):
            shard, term, d, x = _columns(table, first)
            size = np.diff(first)
            runs = -(-size // RUN)
            who = np.repeat(np.arange(size.size), runs)
            number = np.arange(who.size) - np.repeat(np.cumsum(runs) - runs, runs)
            begin = first[who] + number * RUN
            end = np.minimum(begin + RUN, first[who + 1])
            total = np.add.reduceat(x, begin)
            payload = [encode_run(d[a:b], x[a:b], code) for a, b in zip(begin.tolist(), end.tolist(), strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(shard[who]), term.take(pa.array(who)), pa.array(number + 1), pa.array(d[begin]), pa.array(d[end - 1]), pa.array(end - begin), pa.array(total), pa.array(np.maximum.reduceat(x, begin)), pa.array(payload, pa.binary())], names=_NAMES)

    return _sorted(postings, cfg, shard).mapInArrow(run, RUNS)


def build_whole(postings: DataFrame, cfg: IndexConfig, code: str = "bp128") -> DataFrame:
    """RUNS of lists that go on from shard to shard of documents, as one list of the collection would be cut. The
    postings of a list are numbered across the shards, and a shard of the result is a stretch of its numbers, whole runs
    long, so that no task holds more of a list than cfg.shard_docs postings."""
    last = postings.agg(F.max("d")).first()[0]
    if last is None or last <= cfg.shard_docs:
        return build_static(postings, cfg, code)
    by = Window.partitionBy("shard", "term")
    rows = postings.select("term", "d", "f", cfg.shard_of("d").alias("shard"))
    sizes = rows.groupBy("shard", "term").agg(F.count("*").alias("n"))
    ahead = Window.partitionBy("term").orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)
    begin = sizes.select("shard", "term", F.coalesce(F.sum("n").over(ahead), F.lit(0)).alias("begin"))
    placed = rows.withColumn("row", F.row_number().over(by.orderBy("d"))).join(begin, ["shard", "term"]).withColumn("place", F.col("begin") + F.col("row") - 1)
    stretch = -(-cfg.shard_docs // RUN) * RUN
    return build_static(placed.select("term", "d", "f", "place"), cfg, code, F.floor(F.col("place") / stretch))


def decode_static(runs: DataFrame, code: str = "bp128") -> DataFrame:
    """(shard, term, d, f) of runs; each is decoded by itself."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 2048):
                part = batch.slice(at, 2048)
                columns = [part.column(c).to_pylist() for c in ("payload", "n", "first_d", "last_d", "total")]
                found = [decode_run(*row, code) for row in zip(*columns, strict=True)]
                index = pa.array(np.repeat(np.arange(part.num_rows), [len(x[0]) for x in found]))
                yield pa.RecordBatch.from_arrays([part.column("shard").take(index), part.column("term").take(index), pa.array(np.concatenate([x[0] for x in found])), pa.array(np.concatenate([x[1] for x in found]))], names=["shard", "term", "d", "f"])

    return runs.select("shard", "term", "payload", "n", "first_d", "last_d", "total").mapInArrow(run, "shard long, term string, d long, f long")


def static_bytes(runs: DataFrame, *by: str) -> DataFrame:
    """(lists, runs, postings, payload_bytes, skip_bytes, vocabulary_bytes): what a static index takes. by: what a list is,
    (shard, term) unless said. A skip entry is a
    document, a sum and an offset of four bytes each, and stands for all runs but a list's first; a vocabulary entry is
    the term and sixteen bytes."""
    lists = runs.groupBy(*(by or ("shard", "term"))).agg(F.count("*").alias("runs"), F.sum("n").alias("n"), F.sum(F.octet_length("payload")).alias("bytes"))
    return lists.agg(F.count("*").alias("lists"), F.sum("runs").alias("runs"), F.sum("n").alias("postings"), F.sum("bytes").alias("payload_bytes"), F.sum(12 * (F.col("runs") - 1)).alias("skip_bytes"), F.sum(F.octet_length("term") + 16).cast("long").alias("vocabulary_bytes"))
