"""Benchmark decontamination: rare words of an item as seeds, then Smith-Waterman alignment of words.

A passage that scores at least `least` has at least that share of the item's words in place, and bounds how many
others may lie between them. So of an item's words the most frequent half of that share can be left out, and the
other half must still be met within a bounded window of a document. Such windows that hold the whole share in the
item's order, and no others, are aligned, where a local alignment of the two word sequences scores copies with words changed, added or left out. No passage that
reaches `least` is lost this way, however its changes lie.

The items are a stated set that all documents are held against, in blocks of BLOCK_WORDS words: a block's words
travel with the tasks, and their size has that bound. A document's share of the work depends on its own text.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from liveindex.llm import common as C
from liveindex.llm.licences import INSIDE

#: Fewest words of an item; words of a block of items.
LEAST_WORDS, BLOCK_WORDS = 4, 1_000_000
#: Alignment: gain of an equal word, loss of a changed one and of one too many; share of the best score an item can
#: have from which a passage counts as a copy.
MATCH, CHANGED, GAP, LEAST_SCORE = 2, -1, -1, 0.5


def word_hashes(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the words (letters and digits, A-Z lower-cased) of all texts, and each text's first word."""
    raw, off = C.flat(texts)
    raw = C.LOWER[raw]
    starts, ends, first = C.spans(INSIDE[raw], off)
    return C.span_hashes(raw, starts, ends), first


def align(item: np.ndarray, passage: np.ndarray) -> tuple[float, int, int]:
    """Best local alignment as a share of the item's own score, and the passage words it begins and ends at.

    One row of the matrix for each item word; what a gap along the row carries on is a running maximum."""
    n = passage.size
    if not n or not item.size:
        return 0.0, 0, 0
    across = -GAP * np.arange(n + 1)
    score, origin = np.zeros(n + 1, np.int64), np.arange(n + 1)
    best, where = 0, (0, 0)
    for word in item:
        slant = score[:-1] + np.where(passage == word, MATCH, CHANGED)
        down = score[1:] + GAP
        cell = np.zeros(n + 1, np.int64)
        cell[1:] = np.maximum(np.maximum(slant, down), 0)
        start = np.arange(n + 1)
        start[1:] = np.where(cell[1:] == 0, start[1:], np.where(slant >= down, origin[:-1], origin[1:]))
        lifted = cell + across
        top = np.maximum.accumulate(lifted)
        source = np.maximum.accumulate(np.where(lifted == top, np.arange(n + 1), 0))
        score, origin = top - across, start[source]
        at = int(score.argmax())
        if score[at] > best:
            best, where = int(score[at]), (int(origin[at]), at)
    return best / (MATCH * item.size), *where


LEAK = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("number", T.LongType()), T.StructField("score", T.DoubleType()), T.StructField("first_word", T.LongType()), T.StructField("end_word", T.LongType())])


def _counted(wanted: np.ndarray):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        times = np.zeros(wanted.size, np.int64)
        for batch in batches:
            for part in C.pieces(batch, "text"):
                words, _ = word_hashes(part.column("text"))
                at = np.minimum(np.searchsorted(wanted, words), wanted.size - 1)
                times += np.bincount(at[wanted[at] == words], minlength=wanted.size)
        some = np.flatnonzero(times)
        yield pa.RecordBatch.from_arrays([pa.array(C.signed(wanted[some])), pa.array(times[some])], names=["word", "times"])

    return run


def seeds(item: np.ndarray, times: dict[int, int], least: float) -> tuple[list[int], int, int]:
    """Words of an item to look for, how many places of a passage must hold one, and within how many words.

    With m words in place and e changed, added or left out, 2 m - e >= 2 least n, so that m is at least least * n and
    the passage has m + e words at most, which is at most n + 2 n (1 - least)."""
    need = max(1, int(np.ceil(least * item.size - 1e-9)))
    words, count = np.unique(item, return_counts=True)
    order = sorted(range(words.size), key=lambda k: (-times.get(int(words[k]), 0), int(words[k])))
    spare = dropped = 0
    while dropped < len(order) and spare + count[order[dropped]] <= need // 2:
        spare += int(count[order[dropped]])
        dropped += 1
    return [int(words[k]) for k in order[dropped:]], need - spare, int(np.ceil(item.size + 2 * item.size * (1 - least)))


def windows(words: np.ndarray, first: np.ndarray, vocabulary: np.ndarray, begins: np.ndarray, held: np.ndarray, need: np.ndarray, width: np.ndarray) -> Iterator[tuple[int, int, int, int]]:
    """(document, item, begin, end) of passages to align: all that hold enough seeds of the item close together.

    held[begins[v] : begins[v + 1]] are the items that the word vocabulary[v] is a seed of. The passage reaches a
    window beyond the seeds on either side; those of one document and item that meet are one."""
    at = np.minimum(np.searchsorted(vocabulary, words), vocabulary.size - 1)
    place = np.flatnonzero(vocabulary[at] == words)
    many = (begins[1:] - begins[:-1])[at[place]]
    run = np.concatenate(([0], np.cumsum(many)))
    item = held[np.repeat(begins[at[place]] - run[:-1], many) + np.arange(run[-1])]
    place = np.repeat(place, many)
    doc = np.searchsorted(first, place, side="right") - 1
    order = np.lexsort((place, item, doc))
    doc, item, place = doc[order], item[order], place[order]
    last = np.arange(place.size) + need[item] - 1
    inside = last < place.size
    end = np.minimum(last, max(0, place.size - 1))
    good = np.flatnonzero(inside & (doc[end] == doc) & (item[end] == item) & (place[end] - place < width[item]))
    low = np.maximum(place[good] - width[item[good]], first[doc[good]])
    high = np.minimum(place[end[good]] + 1 + width[item[good]], first[doc[good] + 1])
    new = np.ones(good.size, bool)
    new[1:] = (doc[good][1:] != doc[good][:-1]) | (item[good][1:] != item[good][:-1]) | (low[1:] > high[:-1])
    heads = np.flatnonzero(new)
    tails = np.append(heads[1:], good.size) - 1
    for h, t in zip(heads.tolist(), tails[: heads.size].tolist(), strict=True):
        yield int(doc[good[h]]), int(item[good[h]]), int(low[h]), int(high[t])


def places(item: np.ndarray) -> dict[int, int]:
    """Of each word of an item, a bit for each place that holds it."""
    out: dict[int, int] = {}
    for k, word in enumerate(item.tolist()):
        out[word] = out.get(word, 0) | 1 << k
    return out


def in_order(item: dict[int, int], n: int, passage: np.ndarray) -> int:
    """Most words of an item of n words that a passage has in the item's order, whatever lies between them."""
    free = every = (1 << n) - 1
    for here in filter(None, map(item.get, passage.tolist())):
        met = free & here
        free = ((free + met) | (free - met)) & every
    return n - free.bit_count()


def _aligned(numbers: list[int], items: list[np.ndarray], times: dict[int, int], least: float):
    found = [seeds(i, times, least) for i in items]
    pairs = np.array(sorted((w, k) for k, f in enumerate(found) for w in f[0]), np.uint64).reshape(-1, 2)
    vocabulary, begins = np.unique(pairs[:, 0], return_index=True)
    begins, held = np.append(begins, len(pairs)), pairs[:, 1].astype(np.int64)
    need, width = np.array([f[1] for f in found]), np.array([f[2] for f in found])
    placed, full = [places(i) for i in items], [max(1, int(np.ceil(least * i.size - 1e-9))) for i in items]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in C.pieces(batch, "text", 1 << 19):
                words, first = word_hashes(part.column("text"))
                names, out = part.column("doc_id").cast(pa.int64()).to_pylist(), []
                for doc, item, low, high in windows(words, first, vocabulary, begins, held, need, width):
                    if in_order(placed[item], items[item].size, words[low:high]) < full[item]:
                        continue
                    score, begin, end = align(items[item], words[low:high])
                    if score >= least:
                        start = low - int(first[doc])
                        out.append((names[doc], numbers[item], score, start + begin, start + end))
                if out:
                    yield pa.RecordBatch.from_arrays([pa.array(c, f) for c, f in zip(zip(*out, strict=True), (pa.int64(), pa.int64(), pa.float64(), pa.int64(), pa.int64()), strict=True)], names=LEAK.names)

    return run


def leaks(docs: DataFrame, benchmark: DataFrame, text: str = "text", doc_id: str = "doc_id", item_text: str = "text", item_id: str = "item_id", least: float = LEAST_SCORE) -> DataFrame:
    """(doc_id, item_id, score, first_word, end_word): documents that hold a copy of an item, exact or edited.

    score is the alignment's share of a perfect one, at least `least`; words count from 0 in the document. A pair
    has one row, its best. Null and empty texts and items of fewer than LEAST_WORDS words have no rows. Rows of one
    item_id are passages of one item, each looked for; items without item_id are reported with a null one.
    Repeated rows of a document give one row a pair; documents without doc_id are reported with a null one. Empty
    tables give an empty result; other columns play no part.
    """
    spark = docs.sparkSession
    rows, items = C.narrow(docs, doc_id=doc_id, text=text), C.narrow(benchmark, item_id=item_id, text=item_text)

    def hashed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            words, first = word_hashes(batch.column("text"))
            yield pa.RecordBatch.from_arrays([batch.column("number"), batch.column("item_id").cast(pa.int64()), pa.array([words[a:b].tobytes() for a, b in zip(first[:-1], first[1:], strict=True)], pa.binary())], names=["number", "item_id", "words"])

    # Each row has a number of its own: item_id may be null or name several passages.
    numbered = items.select(F.monotonically_increasing_id().alias("number"), "item_id", "text")
    bench = C.saved(numbered.mapInArrow(hashed, "number long, item_id long, words binary").where(F.length("words") >= 8 * LEAST_WORDS), "bench-items")
    size = bench.agg(F.coalesce(F.sum(F.length("words") / 8), F.lit(0)).alias("n")).first()["n"]
    blocks = max(1, int(-(-size // BLOCK_WORDS)))
    found = []
    for block in range(blocks):
        mine = bench.where(F.pmod(F.xxhash64("number"), F.lit(blocks)) == block).select("number", "words").collect()
        if not mine:
            continue
        sequences = [np.frombuffer(r["words"], np.uint64) for r in mine]
        counts = rows.mapInArrow(_counted(np.unique(np.concatenate(sequences))), "word long, times long").groupBy("word").agg(F.sum("times")).collect()
        times = {w & ((1 << 64) - 1): n for w, n in map(tuple, counts)}
        found.append(rows.mapInArrow(_aligned([r["number"] for r in mine], sequences, times, least), LEAK))
    named = T.StructType([LEAK[0], T.StructField("item_id", T.LongType()), *LEAK.fields[2:]])
    if not found:
        return spark.createDataFrame([], named)
    out = found[0]
    for more in found[1:]:
        out = out.unionAll(more)
    best = F.max_by(F.struct("score", "first_word", "end_word"), F.struct("score", -F.col("first_word"))).alias("best")
    out = C.saved(out, "leaks").join(bench.select("number", "item_id"), "number")
    return out.groupBy("doc_id", "item_id").agg(best).select("doc_id", "item_id", "best.score", "best.first_word", "best.end_word")
