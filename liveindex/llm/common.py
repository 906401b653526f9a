"""What the operators share: scratch tables, slices of Arrow batches, words and their hashes.

Scratch tables go below spark.checkpoint.dir, the folder that the whole cluster sees; a folder of our own is
set only where the session has none and runs in one process (tests). Tables made inside `scope` go with it, others
when the interpreter ends, as a result may still be read from them.
"""

from __future__ import annotations

import atexit
import re
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: The white space of the word rule, and the rule itself for Spark's regular expressions.
SPACES = b" \t\n\v\f\r"
WORD = r"[^\x20\x09-\x0D]+"

IS_WORD = np.ones(256, bool)
IS_WORD[list(SPACES)] = False
#: A-Z to a-z, all other bytes as they are.
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32

_made: list[tuple[SparkSession, str]] = []


def scratch_dir(spark: SparkSession, name: str) -> str:
    """A new path below the cluster's shared checkpoint folder."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the whole cluster sees")
        base = tempfile.mkdtemp(prefix="liveindex-")
        spark.sparkContext.setCheckpointDir(base)
    if not _made:
        atexit.register(_sweep)
    _made.append((spark, path := f"{base.rstrip('/')}/{name}-{uuid.uuid4().hex}"))
    return path


def remove(spark: SparkSession, path: str) -> None:
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


def _sweep() -> None:
    for spark, path in _made:
        try:
            remove(spark, path)
        except Exception:  # the session has ended; its folder is the operator's to empty
            return


@contextmanager
def scope(spark: SparkSession) -> Iterator[None]:
    """Removes at its end the scratch tables made inside, but for those kept by `keep`."""
    before = {p for _, p in _made}
    try:
        yield
    finally:
        for item in [m for m in _made if m[1] not in before and m[1] not in _kept]:
            remove(*item)
            _made.remove(item)


_kept: set[str] = set()


def keep(df: DataFrame) -> DataFrame:
    """A saved table that outlives the scope it was made in."""
    _kept.add(df.scratch_path)
    return df


def drop(*tables: DataFrame) -> None:
    """Removes saved tables that nothing will read again."""
    for t in tables:
        remove(t.sparkSession, t.scratch_path)


def saved(df: DataFrame, name: str) -> DataFrame:
    """df written once to the shared folder and read back: lineage ends here and lost executors cost nothing."""
    spark = df.sparkSession
    path = scratch_dir(spark, name)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.scratch_path = path
    return out


def numbered(df: DataFrame, *order: str, into: str) -> DataFrame:
    """df with numbers from 0 in the order of some columns, without a single-task window: rows are written in range
    partitions, whose numbers are written with them, and a running sum over their counts, one row each, gives the offsets."""
    parts = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ranged = saved(df.repartitionByRange(parts, *order).withColumn("_range", F.spark_partition_id()), "ranged")
    ahead = Window.orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)
    offsets = ranged.groupBy("_range").agg(F.count("*").alias("_n")).select("_range", F.coalesce(F.sum("_n").over(ahead), F.lit(0)).alias("_offset"))
    inside = F.row_number().over(Window.partitionBy("_range").orderBy(*order)) - 1
    return ranged.withColumn("_at", inside).join(F.broadcast(offsets), "_range").withColumn(into, (F.col("_at") + F.col("_offset")).cast("long")).drop("_range", "_offset", *(["_at"] if into != "_at" else []))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def narrow(df: DataFrame, **columns: str) -> DataFrame:
    """Only the named columns, renamed; whatever else the table holds cannot clash."""
    return df.select([df[f"`{was}`"].alias(new) for new, was in columns.items()])


def pieces(batch: pa.RecordBatch, column: str, most: int = 1 << 20):
    """Slices of a batch whose texts hold about `most` bytes each; one text is never cut. What Arrow has freed goes back
    to the system after each batch, as workers live on through many stages."""
    sizes = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False)
    run = np.cumsum(sizes)
    at = 0
    while at < batch.num_rows:
        base = run[at - 1] if at else 0
        end = max(at + 1, int(np.searchsorted(run, base + most, side="right")))
        yield batch.slice(at, end - at)
        at = end
    pa.default_memory_pool().release_unused()


def flat(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of all texts in one array, and where each begins; null counts as empty."""
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    texts = pc.fill_null(texts.cast(pa.large_string() if pa.types.is_string(texts.type) else texts.type), "")
    off = np.frombuffer(texts.buffers()[1], np.int64, len(texts) + 1, texts.offset * 8) if len(texts) else np.zeros(1, np.int64)
    data = texts.buffers()[2] if len(texts) else None
    raw = np.frombuffer(data, np.uint8)[off[0] : off[-1]] if data is not None and data.size else np.zeros(0, np.uint8)
    return raw, off - off[0]


def spans(inside: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Maximal runs of `inside` that do not cross texts: starts, ends, and the first run of each text (and one more)."""
    if not inside.size:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(off), np.int64)
    cut = np.zeros(inside.size + 1, bool)
    cut[off] = True
    before = np.empty_like(inside)
    before[0], before[1:] = False, inside[:-1]
    starts = np.flatnonzero(inside & (~before | cut[:-1]))
    after = np.empty_like(inside)
    after[-1], after[:-1] = False, inside[1:]
    ends = np.flatnonzero(inside & (~after | cut[1:])) + 1
    return starts, ends, np.searchsorted(starts, off)


#: Constants of the hashes, drawn once from a fixed seed. They are odd, so that each has an inverse modulo 2^64.
_draw = np.random.default_rng(20240607)
_BYTE = _draw.integers(1, 1 << 63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_BASE = int(_draw.integers(1, 1 << 62)) * 8 + 5
_INVERSE = pow(_BASE, -1, 1 << 64)
_GRAM = _draw.integers(1, 1 << 63, 64, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_powers: dict[int, np.ndarray] = {}


def powers(base: int, n: int) -> np.ndarray:
    """base^0 .. base^(n-1) modulo 2^64."""
    have = _powers.get(base)
    if have is None or have.size < n:
        row = np.full(max(n, 1 << 16), base & ((1 << 64) - 1), np.uint64)
        row[0] = 1
        have = np.cumprod(row, dtype=np.uint64)
        if n <= 1 << 22:
            _powers[base] = have
    return have[:n]


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit words in which each output bit depends on every input bit."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def span_hashes(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit hashes of raw[starts:ends], each from two entries of one running polynomial sum."""
    if not starts.size:
        return np.zeros(0, np.uint64)
    total = np.zeros(raw.size + 1, np.uint64)
    np.cumsum(_BYTE[raw] * powers(_BASE, raw.size), out=total[1:])
    return mix((total[ends] - total[starts]) * powers(_INVERSE, raw.size + 1)[starts] + (ends - starts).astype(np.uint64))


def grams(hashes: np.ndarray, first: np.ndarray, n: int, at: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the runs of n consecutive words inside a text, and the word each begins at.

    first: index of each text's first word, and one more. at: words to begin at, all if not given."""
    if hashes.size < n:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    if at is None:
        out = np.zeros(hashes.size - n + 1, np.uint64)
        for k in range(n):
            out += hashes[k : k + out.size] * _GRAM[k]
        at = np.flatnonzero(np.arange(out.size) + n <= np.repeat(first[1:], np.diff(first))[: out.size])
        out = out[at]
    else:
        at = at[at + n <= first[np.searchsorted(first, at, side="right")]]
        out = np.zeros(at.size, np.uint64)
        for k in range(n):
            out += hashes[at + k] * _GRAM[k]
    return mix(out + np.uint64(n)), at


def owner(first: np.ndarray) -> np.ndarray:
    """The text that each item belongs to, from the first item of each text."""
    return np.repeat(np.arange(len(first) - 1), np.diff(first))


def per_text(values: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Sums of values over the items of each text."""
    run = np.zeros(values.size + 1, np.int64)
    np.cumsum(values, out=run[1:])
    return run[first[1:]] - run[first[:-1]]


def signed(x: np.ndarray) -> np.ndarray:
    return x.view(np.int64)


def words_in(column: str):
    """Number of words of a text column; null has none."""
    return F.coalesce(F.regexp_count(F.col(column), F.lit(WORD)), F.lit(0)).cast("long")


WORDS_PY = re.compile(r"[^\x20\x09-\x0D]+")
