"""The four kinds of postings. Counting needs no shuffle, as a document is one row; gaps take one, by shard and term.

A shard is a run of SHARD documents: it bounds the rows of a term that one task sorts. The gap of a shard's first
posting goes back to the last one of the term's shard before, which a small table of such ends gives.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from liveindex.scratch import running_sum

SHARD = 1 << 20
_TOKENS = 1 << 19


def _counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        lists = batch.column("terms")
        offsets = np.concatenate(([0], np.cumsum(np.diff(lists.offsets.to_numpy()))))
        terms, d = lists.flatten(), batch.column("d")
        at = 0
        while at < len(lists):
            end = max(at + 1, int(np.searchsorted(offsets, offsets[at] + _TOKENS, side="right")) - 1)
            part = terms.slice(offsets[at], offsets[end] - offsets[at]).dictionary_encode()
            size = len(part.dictionary)
            if size:
                doc = np.repeat(np.arange(at, end), np.diff(offsets[at : end + 1]))
                known = part.indices.is_valid().to_numpy(zero_copy_only=False)
                key, f = np.unique(doc[known] * size + part.indices.fill_null(0).to_numpy()[known], return_counts=True)
                yield pa.RecordBatch.from_arrays([part.dictionary.take(pa.array(key % size)), d.take(pa.array(key // size)), pa.array(f.astype(np.int64))], names=["term", "d", "f"])
            at = end


def count_terms(stream: DataFrame) -> DataFrame:
    """(term, d, f). A document is one row with a number of its own, so its terms are counted where it lies."""
    return stream.select("d", "terms").where("terms is not null").mapInArrow(_counted, "term string, d long, f long")


def _before(rows: DataFrame, value: str, d: Column, *order: str) -> DataFrame:
    """rows with `before`: value of the row before in the term's order, 0 for its first, and `lag`: that inside the shard."""
    rows = rows.withColumn("shard", F.floor(d / SHARD))
    inside = Window.partitionBy("term", "shard").orderBy(*order)
    ends = rows.groupBy("term", "shard").agg(F.max(value).alias("last"))
    carried = ends.select("term", "shard", F.lag("last", 1, 0).over(Window.partitionBy("term").orderBy("shard")).alias("carried"))
    return rows.withColumn("lag", F.lag(value).over(inside)).join(carried, ["term", "shard"]).withColumn("before", F.coalesce("lag", "carried"))


def postings_doc(stream: DataFrame, counts: DataFrame | None = None) -> DataFrame:
    """(term, d, f, g): document-level postings with the gap from the one before."""
    counts = count_terms(stream) if counts is None else counts
    return _before(counts.select("term", "d", "f"), "d", F.col("d"), "d").select("term", "d", "f", (F.col("d") - F.col("before")).alias("g"))


def occurrences(stream: DataFrame) -> DataFrame:
    """(term, d, w), w from 1."""
    return stream.select("d", F.posexplode("terms").alias("w0", "term")).select("term", "d", (F.col("w0") + 1).cast("long").alias("w"))


def postings_word(stream: DataFrame) -> DataFrame:
    """(term, d, w, g1, wg): one posting an occurrence; g1 is the document gap plus one, wg the gap of positions
    inside a document, or the position of its first."""
    rows = _before(occurrences(stream), "d", F.col("d"), "d", "w")
    last = F.lag("w").over(Window.partitionBy("term", "shard").orderBy("d", "w"))
    return rows.select("term", "d", "w", (F.col("d") - F.col("before") + 1).alias("g1"), F.when(F.col("lag") == F.col("d"), F.col("w") - last).otherwise(F.col("w")).alias("wg"))


def postings_nested(stream: DataFrame) -> DataFrame:
    """(term, d, f, w_gaps): positions of a document as one array of gaps."""
    grouped = occurrences(stream).groupBy("term", "d").agg(F.array_sort(F.collect_list("w")).alias("ws"))
    shifted = F.concat(F.array(F.lit(0).cast("long")), F.slice("ws", 1, F.size("ws") - 1))
    return grouped.select("term", "d", F.size("ws").cast("long").alias("f"), F.zip_with("ws", shifted, lambda a, b: a - b).alias("w_gaps"))


def derive_counts(word: DataFrame) -> DataFrame:
    """Document-level counts from word-level postings."""
    return word.groupBy("term", "d").agg(F.count("*").alias("f"))


def doc_lengths(stream: DataFrame) -> DataFrame:
    return stream.select("d", F.size("terms").cast("long").alias("len"))


def doc_starts(stream: DataFrame) -> DataFrame:
    """(d, start, len): words of all documents before each, a prefix sum in three levels."""
    return running_sum(doc_lengths(stream), "len", "d", "start").select("d", "start", "len")


def postings_global(stream: DataFrame, starts: DataFrame | None = None) -> DataFrame:
    """(term, gpos, wg): positions in the whole collection, from 1, with their gaps."""
    starts = doc_starts(stream) if starts is None else starts
    at = occurrences(stream).join(starts.select("d", "start"), "d").select("term", "d", (F.col("start") + F.col("w")).alias("gpos"))
    return _before(at, "gpos", F.col("d"), "gpos").select("term", "gpos", (F.col("gpos") - F.col("before")).alias("wg"))


def resolve_positions(positions: DataFrame, starts: DataFrame, cell: int = 4096) -> DataFrame:
    """positions with d and w: a range join with the document starts, by cells of positions.

    A document goes to each cell that its words reach, so each position meets the documents of one cell."""
    last = F.col("start") + F.col("len")
    cells = starts.where("len > 0").select("d", "start", "len", F.explode(F.sequence(F.floor((F.col("start") + 1) / cell), F.floor(last / cell))).alias("_cell"))
    met = positions.withColumn("_cell", F.floor(F.col("gpos") / cell)).join(cells, "_cell").where((F.col("gpos") > F.col("start")) & (F.col("gpos") <= last))
    return met.select(*positions.columns, "d", (F.col("gpos") - F.col("start")).alias("w"))
