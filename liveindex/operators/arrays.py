"""A shard's index as one array of bytes, and its queries one at a time: what a query costs, counted and timed.

Blocks lie in the array by position, interleaved as they arrived or collated by list. A conjunction decodes the rarest
list and then, of each other list, only the blocks that its candidates fall in; a ranked query decodes all lists whole.
Both decode what they touch of a list in one go. A log is run shard by shard, and a query's costs are summed.
"""

from __future__ import annotations

import time
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from liveindex.functions import codecs
from liveindex.operators.evaluate import Log, _best, _blocks, _inside, _merged, _named
from liveindex.operators.packer import IndexConfig
from liveindex.operators.static import RUN, SIDE_BY_SIDE, decode_full_runs, decode_run

MODES = ("conjunctive", "topk")


class ShardIndex:
    """Lists of a shard over one array of bytes. rows: term, block_no, pos, first_d, n, payload of a document-level index."""

    def __init__(self, rows: pa.Table, cfg: IndexConfig) -> None:
        self.cfg = cfg
        order = np.argsort(rows.column("pos").to_numpy(), kind="stable")
        payload = rows.column("payload").combine_chunks().take(pa.array(order)).cast(pa.large_binary())
        self.data = np.frombuffer(payload.buffers()[2], np.uint8)
        ends = np.frombuffer(payload.buffers()[1], np.int64, len(payload) + 1)
        begin, size = np.empty(order.size, np.int64), np.empty(order.size, np.int64)
        begin[order], size[order] = ends[:-1], np.diff(ends)
        chain = pa.compute.sort_indices(pa.table({"t": rows.column("term"), "b": rows.column("block_no")}), [("t", "ascending"), ("b", "ascending")]).to_numpy()
        terms = rows.column("term").combine_chunks().take(pa.array(chain))
        codes = terms.dictionary_encode()
        cuts = np.append(np.flatnonzero(np.append(True, codes.indices.to_numpy()[1:] != codes.indices.to_numpy()[:-1])), chain.size)
        self.lists = {codes.dictionary[int(codes.indices[int(a)].as_py())].as_py(): slice(int(a), int(b)) for a, b in zip(cuts[:-1], cuts[1:], strict=True)}
        self.begin, self.size = begin[chain], size[chain]
        self.first, self.n = rows.column("first_d").to_numpy()[chain], rows.column("n").to_numpy()[chain]
        self.touched = self.decoded = 0

    def postings(self, term: str) -> int:
        at = self.lists.get(term)
        return int(self.n[at].sum()) if at else 0

    def decode(self, places: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Documents and frequencies of some blocks of a list, in order."""
        places = places[self.n[places] > 0]
        self.touched += places.size
        self.decoded += int(self.n[places].sum())
        if not places.size:
            return (np.zeros(0, np.int64),) * 2
        size = self.size[places]
        run = np.cumsum(size) - size
        data = self.data[np.repeat(self.begin[places] - run, size) + np.arange(size.sum())]
        gap, f = codecs.pair_decode(data, self.cfg.threshold)
        heads = np.cumsum(self.n[places]) - self.n[places]
        gap[heads] = 0
        total = np.cumsum(gap)
        return total - np.repeat(total[heads], self.n[places]) + np.repeat(self.first[places], self.n[places]), f

    def conjunctive(self, terms: list[str]) -> np.ndarray:
        if not terms or any(t not in self.lists for t in terms):
            return np.zeros(0, np.int64)
        order = sorted(terms, key=self.postings)
        hit, _ = self.decode(np.arange(self.lists[order[0]].start, self.lists[order[0]].stop))
        for t in order[1:]:
            at = self.lists[t]
            filled = np.arange(at.start, at.stop)[self.n[at] > 0]
            where = np.searchsorted(self.first[filled], hit, side="right") - 1
            d, _ = self.decode(filled[np.unique(where[where >= 0])])
            hit = hit[_inside(d, hit)[0]]
            if not hit.size:
                break
        return hit

    def topk(self, terms: list[str], ft: dict[str, int], n: int, k: int = 10, digits: int = 6) -> tuple[np.ndarray, np.ndarray]:
        lists = [(t, *self.decode(np.arange(self.lists[t].start, self.lists[t].stop))) for t in terms if t in self.lists]
        if not lists:
            return np.zeros(0, np.int64), np.zeros(0)
        low, high = min(int(d[0]) for _, d, _ in lists), max(int(d[-1]) for _, d, _ in lists)
        total, seen = np.zeros(high - low + 1), np.zeros(high - low + 1, bool)
        for t, d, f in lists:
            total[d - low] += np.log(1 + f) * np.log(1 + n / ft[t])
            seen[d - low] = True
        some = np.flatnonzero(seen)
        score = np.round(total[some], digits)
        pick = _best(score, some, k)
        return some[pick] + low, score[pick]


class StaticShard(ShardIndex):
    """The same over static runs of one code, whose rows without payloads are the skip table."""

    def __init__(self, rows: pa.Table, cfg: IndexConfig, code: str) -> None:
        super().__init__(rows, cfg)
        self.code = code
        order = pa.compute.sort_indices(pa.table({"t": rows.column("term"), "b": rows.column("block_no")}), [("t", "ascending"), ("b", "ascending")])
        self.last, self.total = (rows.column(c).combine_chunks().take(order).to_numpy() for c in ("last_d", "total"))

    def decode(self, places: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        self.touched += places.size
        self.decoded += int(self.n[places].sum())
        if not places.size:
            return (np.zeros(0, np.int64),) * 2
        full = self.n[places] == RUN  # all runs of a list but its last
        if np.count_nonzero(full) >= SIDE_BY_SIDE:
            some, rest = places[full], places[~full]
            d, f = decode_full_runs(self.data, self.begin[some], self.size[some], self.first[some], self.last[some], self.total[some], self.code)
            if not rest.size:
                return d, f
            more = self._each(rest)
            return np.append(d, more[0]), np.append(f, more[1])
        return self._each(places)

    def _each(self, places: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        found = [decode_run(self.data[self.begin[p] : self.begin[p] + self.size[p]].tobytes(), int(self.n[p]), int(self.first[p]), int(self.last[p]), int(self.total[p]), self.code) for p in places.tolist()]
        return np.concatenate([d for d, _ in found]), np.concatenate([f for _, f in found])


def conjunctive(blocks: DataFrame, queries: DataFrame, cfg: IndexConfig, code: str | None = None) -> DataFrame:
    """(qid, d) of documents with all terms of a query, from BLOCKS, or from static RUNS of a code: inside each shard the
    rarest list is decoded, and of the others the blocks that candidates fall in. Equal queries are answered once."""
    spark, parts = blocks.sparkSession, []
    columns = ["shard", "term", "block_no", "first_d", "n", "payload"] + (["last_d", "total"] if code else [])
    for log in _blocks(queries, False, None):
        vocabulary = spark.createDataFrame([(t,) for t in log.terms], "term string")

        def run(batches: Iterator[pa.RecordBatch], log: Log = log) -> Iterator[pa.RecordBatch]:
            held = [b for b in batches if b.num_rows]
            if not held:
                return
            table = pa.Table.from_batches(held)
            for shard in pa.compute.unique(table.column("shard")).to_pylist():
                rows = table.filter(pa.compute.equal(table.column("shard"), shard)).combine_chunks()
                rows = rows.append_column("pos", pa.array(np.arange(rows.num_rows)))
                index = StaticShard(rows, cfg, code) if code else ShardIndex(rows, cfg)
                hits = [index.conjunctive([log.terms[t] for t in query]) for query in log.queries]
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(np.arange(len(hits)), [h.size for h in hits])), pa.array(np.concatenate(hits))], names=["rep", "d"])

        count = int(spark.conf.get("spark.sql.shuffle.partitions"))
        mine = blocks.join(F.broadcast(vocabulary), "term", "left_semi").select(*columns).repartition(count, "shard")
        parts.append(_named(mine.mapInArrow(run, "rep long, d long"), log).select("qid", "d"))
    return _merged(parts, spark, "qid long, d long")


COST = "rep long, micros double, matches long, blocks long, postings long"


def run_log(placed: DataFrame, queries: DataFrame, cfg: IndexConfig, mode: str, n_docs: int, code: str | None = None) -> DataFrame:
    """(qid, n_terms, micros, matches, blocks, postings): what each query of a log costs and finds over blocks with
    their positions (`pos`): time in the shards, matches (conjunctive) or documents returned (topk, the shards' best
    together), blocks touched and postings decoded. A long log is run in blocks of queries. code: for static runs.

    The queries of a block are dealt to several tasks a shard, each of which holds the shard's lists of the log."""
    if mode not in MODES:
        raise ValueError(f"no mode {mode}")
    spark, parts = placed.sparkSession, []
    slices = max(1, spark.sparkContext.defaultParallelism)
    for log in _blocks(queries, False, None):
        vocabulary = spark.createDataFrame([(t, k) for k, t in enumerate(log.terms)], "term string, id long")
        mine = placed.join(F.broadcast(vocabulary.select("term")), "term", "left_semi")
        ft = {r["term"]: r["ft"] for r in mine.groupBy("term").agg(F.sum("n").alias("ft")).collect()} if mode == "topk" else {}

        def run(batches: Iterator[pa.RecordBatch], log: Log = log, ft: dict = ft) -> Iterator[pa.RecordBatch]:
            held = [b for b in batches if b.num_rows]
            if not held:
                return
            table = pa.Table.from_batches(held)
            for part in pa.compute.unique(table.column("part")).to_pylist():
                rows = table.filter(pa.compute.equal(table.column("part"), part)).combine_chunks()
                index = StaticShard(rows, cfg, code) if code else ShardIndex(rows, cfg)
                out = []
                for rep, query in enumerate(log.queries):
                    if rep % slices != part % slices:
                        continue
                    terms = [log.terms[t] for t in query]
                    index.touched = index.decoded = 0
                    began = time.perf_counter()
                    hit = index.conjunctive(terms) if mode == "conjunctive" else index.topk(terms, ft, n_docs)[0]
                    out.append((rep, (time.perf_counter() - began) * 1e6, hit.size, index.touched, index.decoded))
                if out:
                    yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*out, strict=True)], names=[c.split()[0] for c in COST.split(", ")])

        count = int(spark.conf.get("spark.sql.shuffle.partitions"))
        part = F.explode(F.sequence(F.col("shard") * slices, F.col("shard") * slices + slices - 1)).alias("part")
        cost = mine.select(part, "term", "block_no", "pos", "first_d", "n", "payload", *(["last_d", "total"] if code else [])).repartition(count, "part").mapInArrow(run, COST)
        cost = cost.groupBy("rep").agg(F.sum("micros").alias("micros"), F.sum("matches").alias("matches"), F.sum("blocks").alias("blocks"), F.sum("postings").alias("postings"))
        sizes = spark.createDataFrame([(k, len(q)) for k, q in enumerate(log.queries)], "rep long, n_terms long")
        parts.append(_named(cost.join(F.broadcast(sizes), "rep"), log).select("qid", "n_terms", "micros", "matches", "blocks", "postings"))
    return _merged(parts, spark, "qid long, n_terms long, micros double, matches long, blocks long, postings long")


def latency(cost: DataFrame, *by: str) -> DataFrame:
    """(by, queries, mean_us, p95_us, mean_blocks, mean_postings) of the costs of a log."""
    return cost.groupBy(*by).agg(F.count("*").alias("queries"), F.round(F.avg("micros"), 1).alias("mean_us"), F.round(F.percentile("micros", 0.95), 1).alias("p95_us"), F.round(F.avg("blocks"), 3).alias("mean_blocks"), F.round(F.avg("postings"), 3).alias("mean_postings"))
