"""Baselines: earlier list structures as cost models over list lengths, static codes, and batch construction."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from liveindex.functions import codecs
from liveindex.functions.lengths import vbyte_len


def list_lengths(postings: DataFrame) -> DataFrame:
    return postings.groupBy("term").agg(F.count("*").alias("ft"))


def linked_cost(lists: DataFrame, posting: int = 8, pointer: int = 8) -> DataFrame:
    """One node a posting."""
    return lists.agg(F.sum("ft").alias("postings"), F.sum(F.col("ft") * (posting + pointer)).alias("bytes"))


def ladder_cost(lists: DataFrame, sizes: list[int], posting: int = 8, link: int = 4) -> DataFrame:
    """Lists in blocks that hold the given numbers of postings, the last number for all further blocks.

    A list's blocks follow from running sums of the ladder, so a cost is one expression."""
    ends = np.cumsum(sizes).tolist()
    blocks, held = F.lit(None).cast("long"), F.lit(None).cast("long")
    for z in range(len(sizes) - 1, -1, -1):
        blocks = F.when(F.col("ft") <= ends[z], z + 1).otherwise(blocks)
        held = F.when(F.col("ft") <= ends[z], ends[z]).otherwise(held)
    more = F.ceil((F.col("ft") - ends[-1]) / sizes[-1])
    blocks, held = F.coalesce(blocks, len(sizes) + more), F.coalesce(held, ends[-1] + more * sizes[-1])
    return lists.agg(F.sum("ft").alias("postings"), F.sum(blocks).cast("long").alias("blocks"), F.sum(held * posting + blocks * link).cast("long").alias("bytes"))


def doubling_array_cost(lists: DataFrame, posting: int = 8) -> DataFrame:
    """Arrays that double when full: the least power of two that holds each list; copied: what doubling moved."""
    cells = F.pow(F.lit(2.0), F.ceil(F.log2(F.col("ft").cast("double")))).cast("long")
    return lists.agg(F.sum("ft").alias("postings"), F.sum(cells * posting).alias("bytes"), F.sum(cells - 1).alias("copied"))


def vocabulary_inline_cost(lists: DataFrame, inline: int, posting: int = 8, head: int = 18) -> DataFrame:
    """Lists of at most `inline` postings live in the vocabulary entry; others add a link and their postings."""
    size = F.when(F.col("ft") <= inline, inline * posting).otherwise(inline * posting + 4 + (F.col("ft") - inline) * posting)
    return lists.agg(F.sum("ft").alias("postings"), F.sum(size + F.octet_length("term") + head).cast("long").alias("bytes"))


def bit_width(x: Column) -> Column:
    return F.when(x > 0, F.length(F.bin(x))).otherwise(0).cast("long")


def bit_packed_bytes(postings: DataFrame, value: str, block: int = 128) -> DataFrame:
    """(bytes): full blocks of each list at the width of their largest number and a byte for the width; rest in byte code."""
    by = Window.partitionBy("term").orderBy("d")
    rows = postings.withColumn("block", F.floor((F.row_number().over(by) - 1) / block))
    blocks = rows.groupBy("term", "block").agg(F.count("*").alias("n"), F.max(value).alias("most"), F.sum(vbyte_len(F.col(value))).alias("plain"))
    size = F.when(F.col("n") == block, 1 + F.ceil(block * bit_width(F.col("most")) / 8)).otherwise(F.col("plain"))
    return blocks.agg(F.sum(size).cast("long").alias("bytes"))


def interpolative_bits(postings: DataFrame, last_d: int, block: int = 128) -> DataFrame:
    """(bits): documents and running counts of each list, block by block, in interpolative code.

    A block's range begins behind the block before it and ends at the collection's last document (counts: at the
    block's own last sum, which is written in byte code)."""
    parts = int(postings.sparkSession.conf.get("spark.sql.shuffle.partitions"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        term, ds, fs, low, total = None, [], [], 1, 0

        def close(ds: list[int], fs: list[int], low: int) -> int:
            sums = np.cumsum(fs).tolist()
            return codecs.interp_bits(ds, low, last_d) + codecs.interp_bits(sums[:-1], 1, sums[-1] - 1) + 8 * int(codecs.vbyte_lens(np.array([sums[-1]]))[0])

        for batch in batches:
            for t, d, f in zip(*(batch.column(c).to_pylist() for c in ("term", "d", "f")), strict=True):
                if t != term or len(ds) == block:
                    if ds:
                        total += close(ds, fs, low)
                    low = 1 if t != term else ds[-1] + 1
                    term, ds, fs = t, [], []
                ds.append(d)
                fs.append(f)
        if ds:
            total += close(ds, fs, low)
        yield pa.RecordBatch.from_pydict({"bits": [total]})

    rows = postings.select("term", "d", "f").repartition(parts, "term").sortWithinPartitions("term", "d")
    return rows.mapInArrow(run, "bits long").agg(F.sum("bits").alias("bits"))


def two_pass_offsets(postings: DataFrame) -> DataFrame:
    """(term, offset): where each list begins in one array, from counts alone. The running sum goes by first letters,
    then inside them, so that no task holds all terms."""
    lists = list_lengths(postings).withColumn("part", F.substring("term", 1, 2))
    ahead = lists.groupBy("part").agg(F.sum("ft").alias("s")).withColumn("before", F.coalesce(F.sum("s").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).select("part", "before")
    inside = Window.partitionBy("part").orderBy("term").rowsBetween(Window.unboundedPreceding, -1)
    return lists.join(ahead, "part").select("term", (F.col("before") + F.coalesce(F.sum("ft").over(inside), F.lit(0))).alias("offset"))


def merged_vocabulary(stream_counts: DataFrame, batch_docs: int) -> DataFrame:
    """(batch, new_terms): terms that each batch of documents meets first."""
    first = stream_counts.groupBy("term").agg(F.min(F.floor((F.col("d") - 1) / batch_docs)).alias("batch"))
    return first.groupBy("batch").agg(F.count("*").alias("new_terms"))


def merge_batches(stream: DataFrame, batch_docs: int) -> DataFrame:
    """Postings built batch by batch, each list of a batch as one compressed part, and the parts merged by term: equal to
    those of one build. A part's gaps begin anew; merging adds the last document of the parts before.

    Parts are short, so all those of a chunk of rows are coded, and decoded, in one go."""
    from liveindex.functions.codecs import pair_decode, pair_encode, pair_lens
    from liveindex.operators.packer import IndexConfig, _columns, _lists, _sorted
    from liveindex.operators.postings import count_terms

    def packed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table, first in _lists(batches):
            batch, term, d, f = _columns(table, first)
            begin, end = first[:-1], first[1:] - 1
            gap = np.diff(d, prepend=0)
            gap[begin] = 1
            stops = np.append(0, np.cumsum(pair_lens(gap, f, 4)))[first].astype(np.int64)
            data = pa.Array.from_buffers(pa.large_binary(), begin.size, [None, pa.py_buffer(stops.tobytes()), pa.py_buffer(pair_encode(gap, f, 4).tobytes())]).cast(pa.binary())
            yield pa.RecordBatch.from_arrays([pa.array(batch), term, pa.array(d[begin]), pa.array(d[end]), pa.array(end - begin + 1), data], names=["batch", "term", "first", "last", "n", "data"])

    def merged(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        open_term, open_last = None, 0
        for whole in batches:
            for at in range(0, whole.num_rows, 50_000):
                part = whole.slice(at, 50_000)
                term, n = part.column("term"), part.column("n").to_numpy()
                first, last = part.column("first").to_numpy(), part.column("last").to_numpy()
                gap, f = pair_decode(np.frombuffer(b"".join(part.column("data").to_pylist()), np.uint8), 4)
                begin = np.cumsum(n) - n
                codes = term.dictionary_encode().indices.to_numpy()
                same = np.append(term[0].as_py() == open_term, codes[1:] == codes[:-1])
                gap[begin] = first - np.where(same, np.append(open_last, last[:-1]), 0)
                inside = gap.copy()
                inside[begin] = 0
                total = np.cumsum(inside)
                d = total + np.repeat(first - total[begin], n)
                yield pa.RecordBatch.from_arrays([term.take(pa.array(np.repeat(np.arange(n.size), n))), pa.array(d), pa.array(f), pa.array(gap)], names=["term", "d", "f", "g"])
                open_term, open_last = term[-1].as_py(), int(last[-1])

    parts = int(stream.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    partial = _sorted(count_terms(stream), IndexConfig(shard_docs=batch_docs)).mapInArrow(packed, "batch long, term string, first long, last long, n long, data binary")
    return partial.repartition(parts, "term").sortWithinPartitions("term", "batch").mapInArrow(merged, "term string, d long, f long, g long")


def sorted_inversion(stream: DataFrame) -> DataFrame:
    """(term, d, f, g) from one sort of all occurrences, as a vocabulary tree with lists gives them in a walk."""
    from liveindex.operators.postings import occurrences, postings_doc

    runs = occurrences(stream).groupBy("term", "d").agg(F.count("*").alias("f"))
    return postings_doc(stream, runs)


def by_vocabulary_ranges(stream: DataFrame, passes: int) -> DataFrame:
    """Postings built in several passes, each over a share of the terms."""
    from liveindex.operators.postings import count_terms, postings_doc

    out = None
    for k in range(passes):
        mine = stream.withColumn("terms", F.filter("terms", lambda t: F.pmod(F.xxhash64(t), F.lit(passes)) == k))
        part = postings_doc(mine, count_terms(mine))
        out = part if out is None else out.unionAll(part)
    return out


def capacity(unit: int, bytes_per_posting: float, words_per_posting: float, pointers: int = 1 << 32) -> tuple[int, float, float]:
    """Bytes, postings and words that an array of blocks with 32-bit numbers holds."""
    total = unit * pointers
    return total, total / bytes_per_posting, total / bytes_per_posting * words_per_posting


def probe_lengths(spark: SparkSession, terms: DataFrame, load: float = 0.5) -> DataFrame:
    """(slots, mean_probes): expected probes of a successful look-up with linear steps at a load."""
    return terms.agg(F.ceil(F.count("*") / load).alias("slots"), F.lit(0.5 * (1 + 1 / (1 - load))).alias("mean_probes"))
