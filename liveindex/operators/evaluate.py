"""Evaluation of a log of queries inside shards of documents: each shard answers every query over its own lists.

Postings of the log's terms, and no others, go to the shard of their document; what a shard sends on is its answers.
A list is never copied once for each query that names it. The log travels with the tasks in blocks of BLOCK_PAIRS
(query, term) pairs, each block a pass over the postings; equal queries of a block are answered once. Weights use
statistics of the whole collection, so that answers of shards merge by score.

Inside a shard lists are sorted arrays. A conjunction starts with the rarest list of the shard and looks its documents
up in the others; a phrase does so with positions. A ranked query adds lists up from the largest bound to the smallest
and, once what is left cannot lift a document over the k best so far, only looks candidates up (`prune`).
"""

from __future__ import annotations

import heapq
from collections.abc import Callable, Iterator
from itertools import groupby
from operator import itemgetter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: (query, term) pairs of a block; fewest and most documents of a shard of evaluation.
BLOCK_PAIRS, LEAST_DOCS, MOST_DOCS = 1_000_000, 1 << 10, 1 << 14
#: Ids of rows that are no postings: lengths of documents, and one row a document.
LENGTH, DOCUMENT = -1, -2


class Log:
    """A block of queries: distinct ones as rows of term numbers, and the queries that each stands for."""

    def __init__(self, rows: list[tuple], ordered: bool) -> None:
        self.terms: list[str] = sorted({t for _, terms, *_ in rows for t in terms})
        number = {t: k for k, t in enumerate(self.terms)}
        seen: dict[tuple, int] = {}
        self.queries: list[tuple[int, ...]] = []
        self.cuts: list[int | None] = []
        self.names: list[tuple[int, int]] = []  # (query, its number among the distinct ones)
        for qid, terms, *cut in rows:
            key = tuple(number[t] for t in terms)
            key = (key if ordered else tuple(sorted(set(key))), *cut)
            if key[0] and key not in seen:
                seen[key] = len(self.queries)
                self.queries.append(key[0])
                self.cuts.append(cut[0] if cut else None)
            if key[0]:
                self.names.append((qid, seen[key]))


def _blocks(queries: DataFrame, ordered: bool, cut: str | None) -> Iterator[Log]:
    """The log in blocks that the driver may hold, dealt by the hash of qid; a log of one block is read once."""
    some = queries.select("qid", F.coalesce("terms", F.array().cast("array<string>")).alias("terms"), *([cut] if cut else []))
    pairs = some.agg(F.coalesce(F.sum(F.size("terms")), F.lit(0))).first()[0]
    n = max(1, -(-pairs // BLOCK_PAIRS))
    for k in range(n):
        rows = [tuple(r) for r in (some if n == 1 else some.where(F.pmod(F.xxhash64("qid"), F.lit(n)) == k)).collect()]
        if rows:
            yield Log(rows, ordered)


def docs_a_shard(spark, n_docs: int | None) -> int:
    """Documents of a shard: enough shards for all cores, of a size that bounds what a task holds."""
    if n_docs is None:
        return 1 << 12
    return int(min(MOST_DOCS, max(LEAST_DOCS, n_docs // (2 * max(1, spark.sparkContext.defaultParallelism)))))


def _shards(postings: DataFrame, log: Log, value: str, cell: int, extra: DataFrame | None = None, seq: bool = False) -> DataFrame:
    """(shard, id, d, x) of the log's terms, in the order of shards and lists."""
    spark = postings.sparkSession
    vocabulary = spark.createDataFrame([(t, k) for k, t in enumerate(log.terms)], "term string, id long")  # BLOCK_PAIRS rows at most
    rows = postings.join(F.broadcast(vocabulary), "term").select("id", "d", F.col(value).cast("long").alias("x"), *(["seq"] if seq else []))
    if extra is not None:
        rows = rows.unionByName(extra)
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    rows = rows.withColumn("shard", F.floor(F.col("d") / cell))
    return rows.repartition(parts, "shard").sortWithinPartitions("shard", "id", "d", "x")


def _by_shard(answer: Callable[[np.ndarray, dict[str, np.ndarray]], dict[str, np.ndarray] | None]):
    """Gathers the rows of a shard and hands them to `answer`, with where each id's rows begin."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []

        def out(some: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            table = pa.Table.from_batches(some).combine_chunks()
            found = answer({c: table.column(c).to_numpy() for c in table.column_names})
            if found is not None and len(next(iter(found.values()))):
                yield pa.RecordBatch.from_pydict({k: pa.array(v) for k, v in found.items()})

        for batch in batches:
            while batch.num_rows:
                shard = batch.column("shard").to_numpy()
                if held and held[0].column("shard")[0].as_py() != shard[0]:
                    yield from out(held)
                    held = []
                end = int(np.searchsorted(shard, shard[0], side="right"))
                held.append(batch.slice(0, end))
                batch = batch.slice(end)
        if held:
            yield from out(held)

    return run


def _merged(parts: list[DataFrame], spark, schema: str) -> DataFrame:
    if not parts:
        return spark.createDataFrame([], schema)
    out = parts[0]
    for more in parts[1:]:
        out = out.unionAll(more)
    return out


def _named(found: DataFrame, log: Log) -> DataFrame:
    names = found.sparkSession.createDataFrame(log.names, "qid long, rep long")  # BLOCK_PAIRS rows at most
    return found.join(F.broadcast(names), "rep").drop("rep")


def _inside(sorted_: np.ndarray, wanted: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of each wanted value, whether the sorted array holds it, and where."""
    at = np.minimum(np.searchsorted(sorted_, wanted), max(0, sorted_.size - 1))
    return (sorted_[at] == wanted) if sorted_.size else np.zeros(wanted.size, bool), at


def conjunctive(postings: DataFrame, queries: DataFrame, n_docs: int | None = None, newest: int | None = None, cut: str | None = None) -> DataFrame:
    """(qid, d) of documents with all terms of a query; an unknown term or no term gives no document.

    newest: of each shard only that many matches of the largest d. cut: a column of queries with the first operation
    number that the query does not see, held against the column seq of postings."""
    spark, cell, parts = postings.sparkSession, docs_a_shard(postings.sparkSession, n_docs), []
    for log in _blocks(queries, False, cut):
        def answer(rows: dict[str, np.ndarray], log=log):
            first = np.searchsorted(rows["id"], np.arange(len(log.terms) + 1))
            size, d = np.diff(first), rows["d"]
            who, what = [], []
            for rep, (query, limit) in enumerate(zip(log.queries, log.cuts, strict=True)):
                order = sorted(query, key=size.__getitem__)
                if not size[order[0]]:
                    continue
                hit = d[first[order[0]] : first[order[0] + 1]]
                if limit is not None:
                    hit = hit[rows["seq"][first[order[0]] : first[order[0] + 1]] < limit]
                for t in order[1:]:
                    hit = hit[_inside(d[first[t] : first[t + 1]], hit)[0]]
                    if not hit.size:
                        break
                if hit.size:
                    hit = hit[-newest:] if newest else hit
                    who.append(np.full(hit.size, rep))
                    what.append(hit)
            return {"rep": np.concatenate(who), "d": np.concatenate(what)} if who else None

        found = _shards(postings, log, "d", cell, seq=cut is not None).mapInArrow(_by_shard(answer), "rep long, d long")
        parts.append(_named(found, log).select("qid", "d"))
    return _merged(parts, spark, "qid long, d long")


def disjunctive_counts(postings: DataFrame, queries: DataFrame, n_docs: int | None = None) -> DataFrame:
    """(qid, n): documents with any term of a query; queries that no document meets have no row."""
    spark, cell, parts = postings.sparkSession, docs_a_shard(postings.sparkSession, n_docs), []
    for log in _blocks(queries, False, None):
        def answer(rows: dict[str, np.ndarray], log=log):
            first = np.searchsorted(rows["id"], np.arange(len(log.terms) + 1))
            low = int(rows["d"].min())
            local = rows["d"] - low
            met = np.zeros(int(local.max()) + 1, bool)
            n = np.zeros(len(log.queries), np.int64)
            for rep, query in enumerate(log.queries):
                if len(query) == 1:
                    n[rep] = first[query[0] + 1] - first[query[0]]
                    continue
                met[:] = False
                for t in query:
                    met[local[first[t] : first[t + 1]]] = True
                n[rep] = np.count_nonzero(met)
            some = np.flatnonzero(n)
            return {"rep": some, "n": n[some]}

        found = _shards(postings, log, "d", cell).mapInArrow(_by_shard(answer), "rep long, n long").groupBy("rep").agg(F.sum("n").alias("n"))
        parts.append(_named(found, log).select("qid", "n"))
    return _merged(parts, spark, "qid long, n long")


def _best(score: np.ndarray, d: np.ndarray, k: int) -> np.ndarray:
    """Places of the k best, ties by document."""
    if score.size > k:
        least = np.partition(score, score.size - k)[score.size - k]
        some = np.flatnonzero(score >= least)
    else:
        some = np.arange(score.size)
    return some[np.lexsort((d[some], -score[some]))[:k]]


def _ranked(lists: list[tuple[np.ndarray, np.ndarray]], room: int, k: int, digits: int, prune: bool) -> tuple[np.ndarray, np.ndarray, int]:
    """Local documents of the k best sums of weights, their scores, and how many postings were added or looked up.

    lists: (local documents, weights) of each term."""
    lists = sorted(lists, key=lambda x: -float(x[1].max()))
    bound = [float(w.max()) for _, w in lists]
    left = np.append(np.cumsum(bound[::-1])[::-1][1:], 0.0)
    total, seen, touched = np.zeros(room), np.zeros(room, bool), 0
    for j, (at, w) in enumerate(lists):
        total[at] += w
        seen[at] = True
        touched += at.size
        if prune and j + 1 < len(lists) and at.size >= k:
            some = np.flatnonzero(seen)
            floor = np.partition(total[some], some.size - k)[some.size - k]
            if left[j] < floor - 10.0**-digits:  # no document outside can reach the k best any more
                some = some[total[some] + left[j] >= floor - 10.0**-digits]
                score = total[some]
                for other, weights in lists[j + 1 :]:
                    hit, where = _inside(other, some)
                    score[hit] += weights[where[hit]]
                    touched += some.size
                score = np.round(score, digits)
                pick = _best(score, some, k)
                return some[pick], score[pick], touched
    some = np.flatnonzero(seen)
    score = np.round(total[some], digits)
    pick = _best(score, some, k)
    return some[pick], score[pick], touched


def _ranked_by_heap(lists: list[tuple[np.ndarray, np.ndarray]], room: int, k: int, digits: int, prune: bool) -> tuple[np.ndarray, np.ndarray, int]:
    """The same document at a time: the lists are merged, and a heap holds the k best so far, the worst on top."""
    heap: list[tuple[float, int]] = []
    touched = 0
    merged = heapq.merge(*(zip(d.tolist(), w.tolist(), strict=True) for d, w in lists))
    for d, some in groupby(merged, key=itemgetter(0)):
        each = [w for _, w in some]
        touched += len(each)
        entry = (round(sum(each), digits), -d)
        if len(heap) < k:
            heapq.heappush(heap, entry)
        elif entry > heap[0]:
            heapq.heapreplace(heap, entry)
    best = sorted(heap, reverse=True)
    return np.array([-d for _, d in best], np.int64), np.array([s for s, _ in best]), touched


def _ranked_by_join(lists: list[tuple[np.ndarray, np.ndarray]], room: int, k: int, digits: int, prune: bool) -> tuple[np.ndarray, np.ndarray, int]:
    """The same as a join and its groups: rows of all lists of the query side by side, summed by document."""
    at, w = (np.concatenate(x) for x in zip(*lists, strict=True))
    some = np.flatnonzero(np.bincount(at, minlength=room))
    score = np.round(np.bincount(at, w, room)[some], digits)
    pick = _best(score, some, k)
    return some[pick], score[pick], at.size


def _ranked_by_bounds(lists: list[tuple[np.ndarray, np.ndarray]], room: int, k: int, digits: int, essential: list[bool]) -> tuple[np.ndarray, np.ndarray, int]:
    """The same for the documents of essential lists alone, which are looked up in the others."""
    total, seen, touched = np.zeros(room), np.zeros(room, bool), 0
    for (at, w), mine in zip(lists, essential, strict=True):
        if mine:
            total[at] += w
            seen[at] = True
            touched += at.size
    some = np.flatnonzero(seen)
    score = total[some]
    for (at, w), mine in zip(lists, essential, strict=True):
        if not mine and some.size:
            hit, where = _inside(at, some)
            score[hit] += w[where[hit]]
            touched += some.size
    score = np.round(score, digits)
    pick = _best(score, some, k)
    return some[pick], score[pick], touched


#: How a shard ranks: term at a time over accumulators, document at a time with a heap, by a join of log and lists, or
#: documents of essential lists alone.
STRATEGIES = {"terms": _ranked, "heap": _ranked_by_heap, "join": _ranked_by_join, "bounds": _ranked_by_bounds}
TFIDF = ("tfidf",)


def weights_of(kind: tuple, f: np.ndarray, ft: float, n: float, length: np.ndarray | None) -> np.ndarray:
    """Weights of a list's postings: log(1 + f) log(1 + n / ft), or BM25 as ("bm25", k1, b, average length)."""
    if kind[0] == "tfidf":
        return np.log(1 + f) * np.log(1 + n / ft)
    _, k1, b, average = kind
    return np.log(1 + (n - ft + 0.5) / (ft + 0.5)) * f * (k1 + 1) / (f + k1 * (1 - b + b * length / average))


def list_lengths(postings: DataFrame, log: Log) -> np.ndarray:
    """Postings of each of the log's terms in the whole collection."""
    vocabulary = postings.sparkSession.createDataFrame([(t, k) for k, t in enumerate(log.terms)], "term string, id long")
    out = np.zeros(len(log.terms), np.int64)
    for k, n in postings.join(F.broadcast(vocabulary), "term").groupBy("id").count().collect():
        out[k] = n
    return out


def essential_lists(postings: DataFrame, log: Log, n_docs: int, k: int) -> tuple[np.ndarray, list[list[bool]]]:
    """Postings of each term, and of each term of each query whether its list is essential. The k best by the query's rarest term alone set a floor;
    lists whose largest weights together stay below it cannot lift a document that no other list names."""
    vocabulary = postings.sparkSession.createDataFrame([(t, j) for j, t in enumerate(log.terms)], "term string, id long")
    counted = postings.join(F.broadcast(vocabulary), "term").groupBy("id", "f").agg(F.count("*").alias("n"))
    upto = counted.withColumn("upto", F.sum("n").over(Window.partitionBy("id").orderBy(F.desc("f"))))
    ft, most, kth = (np.zeros(len(log.terms), np.int64) for _ in range(3))
    for j, n, m, at in upto.groupBy("id").agg(F.sum("n"), F.max("f"), F.max(F.when(F.col("upto") >= k, F.col("f")))).collect():  # a row a term
        ft[j], most[j], kth[j] = n, m, at or 0
    length = np.maximum(ft, 1).astype(np.float64)
    bound, least = (weights_of(TFIDF, f, length, float(n_docs), None) for f in (most, kth))
    out = []
    for query in log.queries:
        known = sorted((t for t in query if ft[t]), key=lambda t: (bound[t], t))
        rarest = min(known, key=lambda t: (ft[t], t), default=None)
        floor = least[rarest] - 1e-6 if known and kth[rarest] else 0.0
        needed = {t for t, total in zip(known, np.cumsum(bound[known]).tolist() if known else [], strict=True) if total >= floor}
        out.append([t in needed for t in query])
    return ft, out


def topk(postings: DataFrame, queries: DataFrame, n_docs: int, k: int = 10, digits: int = 6, kind: tuple = TFIDF, lengths: DataFrame | None = None, prune: bool = False, stats: bool = False, strategy: str = "terms") -> DataFrame:
    """(qid, rank, d, score): the k best documents of each query, ties by document.

    lengths(d, len) serve BM25. strategy: one of STRATEGIES; score at a time is none of them, as lists are kept in the
    order of documents. stats: (qid, postings, touched) instead, sums over the shards of what a query's lists
    hold and what was added or looked up."""
    if strategy not in STRATEGIES:
        raise ValueError(f"no strategy {strategy}")
    if strategy == "bounds" and kind != TFIDF:
        raise ValueError("bounds are those of TFxIDF weights")
    ranked = STRATEGIES[strategy]
    spark, cell, parts = postings.sparkSession, docs_a_shard(postings.sparkSession, n_docs), []
    extra = None if lengths is None else lengths.select(F.lit(LENGTH).cast("long").alias("id"), "d", F.col("len").cast("long").alias("x"))
    for log in _blocks(queries, False, None):
        ft, needed = essential_lists(postings, log, n_docs, k) if strategy == "bounds" else (list_lengths(postings, log), None)

        def answer(rows: dict[str, np.ndarray], log=log, ft=ft, needed=needed):
            first = np.searchsorted(rows["id"], np.arange(len(log.terms) + 1))
            low = int(rows["d"].min())
            local = rows["d"] - low
            room = int(local.max()) + 1
            length = None
            if first[0]:
                length = np.ones(room)
                length[local[: first[0]]] = rows["x"][: first[0]]
            made: dict[int, np.ndarray] = {}
            out: list[tuple] = []
            for rep, query in enumerate(log.queries):
                lists, mine = [], []
                for j, t in enumerate(query):
                    a, b = first[t], first[t + 1]
                    if a < b:
                        if t not in made:
                            made[t] = weights_of(kind, rows["x"][a:b].astype(np.float64), float(ft[t]), float(n_docs), None if length is None else length[local[a:b]])
                        lists.append((local[a:b], made[t]))
                        mine.append(needed is None or needed[rep][j])
                if lists:
                    at, score, touched = ranked(lists, room, k, digits, prune if needed is None else mine)
                    out.append((np.full(at.size, rep), at + low, score) if not stats else (np.array([rep]), np.array([sum(x.size for x, _ in lists)]), np.array([touched])))
            if not out:
                return None
            return dict(zip(("rep", "postings", "touched") if stats else ("rep", "d", "score"), map(np.concatenate, zip(*out, strict=True)), strict=True))

        found = _shards(postings, log, "f", cell, extra).mapInArrow(_by_shard(answer), "rep long, postings long, touched long" if stats else "rep long, d long, score double")
        if stats:
            parts.append(_named(found.groupBy("rep").agg(F.sum("postings").alias("postings"), F.sum("touched").alias("touched")), log).select("qid", "postings", "touched"))
        else:
            place = F.row_number().over(Window.partitionBy("rep").orderBy(F.desc("score"), "d"))
            best = found.withColumn("rank", place.cast("long")).where(F.col("rank") <= k)
            parts.append(_named(best, log).select("qid", "rank", "d", F.round("score", digits).alias("score")))
    return _merged(parts, spark, "qid long, postings long, touched long" if stats else "qid long, rank long, d long, score double")


def topk_seen(postings: DataFrame, docs: DataFrame, ops: DataFrame, n_docs: int | None = None, k: int = 10, digits: int = 6) -> DataFrame:
    """(op_seq, qid, d, score, rank): ranked queries of an operation stream, each over the documents inserted before it
    and with the statistics of its time. postings and docs(d, seq) carry the number of the insert; ops(qid, terms,
    op_seq).

    Two passes over the shards: one counts what of each list a query sees, one scores."""
    spark, cell, parts = postings.sparkSession, docs_a_shard(postings.sparkSession, n_docs), []
    each = docs.select(F.lit(DOCUMENT).cast("long").alias("id"), "d", F.lit(1).cast("long").alias("x"), "seq")
    for log in _blocks(ops, False, "op_seq"):
        starts = np.concatenate(([0], np.cumsum([len(q) + 1 for q in log.queries])))

        def seen(rows: dict[str, np.ndarray], log=log, starts=starts):
            first = np.searchsorted(rows["id"], np.arange(len(log.terms) + 1))
            upto = np.sort(rows["seq"][: first[0]])
            made: dict[int, np.ndarray] = {}
            out = np.zeros(starts[-1], np.int64)
            for rep, (query, cut) in enumerate(zip(log.queries, log.cuts, strict=True)):
                out[starts[rep]] = np.searchsorted(upto, cut)
                for j, t in enumerate(query, 1):
                    if first[t] < first[t + 1]:
                        if t not in made:
                            made[t] = np.sort(rows["seq"][first[t] : first[t + 1]])
                        out[starts[rep] + j] = np.searchsorted(made[t], cut)
            some = np.flatnonzero(out)
            return {"place": some, "n": out[some]}

        shards = _shards(postings, log, "f", cell, each, seq=True)
        known = np.zeros(starts[-1], np.int64)
        for place, n in shards.mapInArrow(_by_shard(seen), "place long, n long").groupBy("place").agg(F.sum("n")).collect():  # a row a (query, term) pair
            known[place] = n

        def answer(rows: dict[str, np.ndarray], log=log, starts=starts, known=known):
            first = np.searchsorted(rows["id"], np.arange(len(log.terms) + 1))
            low = int(rows["d"].min())
            local = rows["d"] - low
            room = int(local.max()) + 1
            out: list[tuple] = []
            for rep, (query, cut) in enumerate(zip(log.queries, log.cuts, strict=True)):
                lists = []
                for j, t in enumerate(query, 1):
                    a, b = first[t], first[t + 1]
                    here = np.flatnonzero(rows["seq"][a:b] < cut) + a
                    if here.size:
                        lists.append((local[here], weights_of(TFIDF, rows["x"][here].astype(np.float64), float(known[starts[rep] + j]), float(known[starts[rep]]), None)))
                if lists:
                    at, score, _ = _ranked(lists, room, k, digits, True)
                    out.append((np.full(at.size, rep), at + low, score))
            return dict(zip(("rep", "d", "score"), map(np.concatenate, zip(*out, strict=True)), strict=True)) if out else None

        found = shards.mapInArrow(_by_shard(answer), "rep long, d long, score double")
        place = F.row_number().over(Window.partitionBy("rep").orderBy(F.desc("score"), "d"))
        best = found.withColumn("rank", place.cast("long")).where(F.col("rank") <= k)
        when = spark.createDataFrame([(rep, c) for rep, c in enumerate(log.cuts)], "rep long, op_seq long")
        parts.append(_named(best.join(F.broadcast(when), "rep"), log).select("op_seq", "qid", "d", F.round("score", digits).alias("score"), "rank"))
    return _merged(parts, spark, "op_seq long, qid long, d long, score double, rank long")


def phrase(occurrences: DataFrame, queries: DataFrame, n_docs: int | None = None) -> DataFrame:
    """(qid, d, hits): documents where the words of a query stand in a row, and how often. Words may repeat."""
    spark, cell, parts = occurrences.sparkSession, docs_a_shard(occurrences.sparkSession, n_docs), []
    for log in _blocks(queries, True, None):
        def answer(rows: dict[str, np.ndarray], log=log):
            first = np.searchsorted(rows["id"], np.arange(len(log.terms) + 1))
            size, low = np.diff(first), int(rows["d"].min())
            place = (rows["d"] - low) << 32 | rows["x"]
            who, what, hits = [], [], []
            for rep, query in enumerate(log.queries):
                order = sorted(range(len(query)), key=lambda j: size[query[j]])
                t = query[order[0]]
                if not size[t]:
                    continue
                at = place[first[t] : first[t + 1]]
                at = at[(at & 0xFFFFFFFF) > order[0]] - order[0]
                for j in order[1:]:
                    if not at.size:
                        break
                    at = at[_inside(place[first[query[j]] : first[query[j] + 1]], at + j)[0]]
                if at.size:
                    docs, n = np.unique(at >> 32, return_counts=True)
                    who.append(np.full(docs.size, rep))
                    what.append(docs + low)
                    hits.append(n)
            return {"rep": np.concatenate(who), "d": np.concatenate(what), "hits": np.concatenate(hits)} if who else None

        found = _shards(occurrences, log, "w", cell).mapInArrow(_by_shard(answer), "rep long, d long, hits long")
        parts.append(_named(found, log).select("qid", "d", "hits"))
    return _merged(parts, spark, "qid long, d long, hits long")


def proximity(occurrences: DataFrame, pairs: DataFrame, window: int, n_docs: int | None = None) -> DataFrame:
    """(qid, d, hits): pairs of places of a query's two words, in this order, at most `window` words apart.

    pairs(qid, terms), of two terms each. The places of the second word around each of the first are a slice of a
    sorted list, so that hits are differences of places and no pairs are formed."""
    spark, cell, parts = occurrences.sparkSession, docs_a_shard(occurrences.sparkSession, n_docs), []
    for log in _blocks(pairs, True, None):
        def answer(rows: dict[str, np.ndarray], log=log):
            first = np.searchsorted(rows["id"], np.arange(len(log.terms) + 1))
            size, low = np.diff(first), int(rows["d"].min())
            place = (rows["d"] - low) << 32 | rows["x"]
            who, what, hits = [], [], []
            for rep, (a, b) in enumerate(log.queries):
                if not size[a] or not size[b]:
                    continue
                here, there = place[first[a] : first[a + 1]], place[first[b] : first[b + 1]]
                # No document has words near 2 ** 32, so what reaches below a document's first word meets none of the one before.
                if here.size <= there.size:
                    n = np.searchsorted(there, here + window, side="right") - np.searchsorted(there, here - window)
                    at = here
                else:
                    n = np.searchsorted(here, there + window, side="right") - np.searchsorted(here, there - window)
                    at = there
                some = np.flatnonzero(n)
                if some.size:
                    docs = at[some] >> 32
                    begin = np.flatnonzero(np.append(True, docs[1:] != docs[:-1]))
                    who.append(np.full(begin.size, rep))
                    what.append(docs[begin] + low)
                    hits.append(np.add.reduceat(n[some], begin))
            return {"rep": np.concatenate(who), "d": np.concatenate(what), "hits": np.concatenate(hits)} if who else None

        found = _shards(occurrences, log, "w", cell).mapInArrow(_by_shard(answer), "rep long, d long, hits long")
        parts.append(_named(found, log).select("qid", "d", "hits"))
    return _merged(parts, spark, "qid long, d long, hits long")
