"""The stored index as experiments use it: built by inserts, collated, half static, and timed."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import functions as F

from liveindex.operators import arrays as A
from liveindex.operators import evaluate as E
from liveindex.operators import packer as K
from liveindex.operators import postings as P
from liveindex.operators import search as X
from liveindex.operators import static as Z
from liveindex.plans.store import LiveIndex
from liveindex.registry import register
from liveindex.scratch import folder, written
from liveindex.sources import collections as S
from liveindex.sources import querylog as L
from liveindex.workloads import sqlparts as Q
from liveindex.workloads.search import _BM25, _CONJ, _QT, _SCORED, _TOP

_PACK = f"WITH RECURSIVE {Q.packed('docs')}, {Q.blocks()}"
_TABLE = "SELECT term, block_no, kind, cap, first_d, last_d, n, used FROM tab"
_COLUMNS = ("term", "block_no", "kind", "cap", "first_d", "last_d", "n", "used")


def grown(spark, sf_dir, inserts: int = 4, cfg: K.IndexConfig | None = None, **settings) -> LiveIndex:
    """A live index of `documents`, added in uneven inserts: each is about twice the one before."""
    index = LiveIndex(spark, folder(spark, "live-index"), cfg, **settings)
    stream = S.docs(spark, sf_dir)
    n = stream.agg(F.max("d")).first()[0]
    cuts = [0, *[max(1, n >> (inserts - k)) for k in range(1, inserts)], n]
    for k, (low, high) in enumerate(zip(cuts[:-1], cuts[1:], strict=True)):
        if high > low:
            index.insert(stream.where(F.col("d").between(low + 1, high)), f"insert-{k}")
    return index


@register("live_block_table", f"{_PACK} {_TABLE}")
def live_block_table(spark, sf_dir):
    """Blocks that several inserts leave are those of one build."""
    return grown(spark, sf_dir).blocks().select(*_COLUMNS)


@register("live_block_table_word", f"WITH RECURSIVE {Q.packed('docs', 'word')}, {Q.blocks()} {_TABLE}")
def live_block_table_word(spark, sf_dir):
    return grown(spark, sf_dir, 3, K.IndexConfig(level="word")).blocks().select(*_COLUMNS)


@register("collated_block_table", f"{_PACK} {_TABLE}")
def collated_block_table(spark, sf_dir):
    """Collated between inserts, and an insert said again afterwards."""
    index = LiveIndex(spark, folder(spark, "live-index"))
    stream = S.docs(spark, sf_dir)
    half = stream.agg(F.max("d")).first()[0] // 2
    index.insert(stream.where(F.col("d") <= half), "in-0")
    index.collate()
    index.insert(stream.where(F.col("d") <= half), "in-0")
    index.insert(stream.where(F.col("d") > half), "in-1")
    index.collate()
    return index.blocks().select(*_COLUMNS)


@register("fused_topk", f"WITH {_QT}, {_SCORED} {_TOP}")
def fused_topk(spark, sf_dir):
    """A dynamic shard beside static ones in both codes, answered together with statistics of the whole."""
    n = S.table(spark, sf_dir, "documents").count()
    index = grown(spark, sf_dir, 3, K.IndexConfig(shard_docs=max(1, n // 4)))
    index.to_static("bp128", [0, 2])
    index.to_static("interp", [1])
    log = L.query_log(spark, sf_dir)
    terms = sorted(r[0] for r in X.query_terms(log).select("term").distinct().collect())  # the log is broadcast anyway
    return E.topk(index.postings(terms), log, n)


def _shards(spark, sf_dir, shard_docs: int = 50):
    cfg = K.IndexConfig(shard_docs=shard_docs)
    return K.build_blocks(P.count_terms(S.docs(spark, sf_dir)), cfg), cfg


@register("conjunctive_many_shards", _CONJ)
def conjunctive_many_shards(spark, sf_dir):
    """Shards of fifty documents: blocks are sought inside their shard."""
    blocks, cfg = _shards(spark, sf_dir)
    return X.conjunctive_by_seek(blocks, L.query_log(spark, sf_dir), cfg)


@register("positions_many_shards", "SELECT count(*) AS blocks, count(*) AS places, max(pos) AS last FROM (SELECT row_number() OVER () AS pos FROM (SELECT DISTINCT term, (d - 1) // 50 AS s FROM " + Q.counts("docs") + f")) WHERE (SELECT count(*) FROM {Q.counts('docs')}) > 0")
def positions_many_shards(spark, sf_dir):
    """Lists of at most fifty documents and blocks of 2,048 bytes: one block a list and shard, a position each."""
    cfg = K.IndexConfig(B=2048, shard_docs=50, payload=False)
    placed = X.positions(K.build_blocks(P.count_terms(S.docs(spark, sf_dir)), cfg))
    return placed.agg(F.count("*").alias("blocks"), F.countDistinct("pos").alias("places"), F.max("pos").alias("last"))


@register("conjunctive_static", _CONJ)
def conjunctive_static(spark, sf_dir):
    """Static lists: candidates go through the skip table, only touched runs are decoded."""
    cfg = K.IndexConfig(shard_docs=max(1, S.table(spark, sf_dir, "documents").count() // 8))
    runs = Z.build_static(P.count_terms(S.docs(spark, sf_dir)), cfg)
    return A.conjunctive(runs, L.query_log(spark, sf_dir), cfg, "bp128")


@register("conjunctive_static_seek", _CONJ)
def conjunctive_static_seek(spark, sf_dir):
    """The same by an as-of join of candidates and the skip table."""
    cfg = K.IndexConfig()
    runs = Z.build_static(P.count_terms(S.docs(spark, sf_dir)), cfg, "interp")
    return X.conjunctive_by_seek(runs, L.query_log(spark, sf_dir), cfg, lambda some: Z.decode_static(some, "interp"))


@register("bm25_static", _BM25)
def bm25_static(spark, sf_dir):
    """BM25 over static lists, lists that cannot lift a document looked up only; lengths lie beside the index."""
    stream, log = S.docs(spark, sf_dir), L.query_log(spark, sf_dir)
    lengths = P.doc_lengths(stream)
    facts = lengths.agg(F.count("*").alias("n"), F.avg("len").alias("a")).first()
    runs = X.fetch_blocks(Z.build_static(P.count_terms(stream), K.IndexConfig()), log)
    return E.topk(Z.decode_static(runs).select("term", "d", "f"), log, facts["n"], kind=("bm25", 0.9, 0.4, facts["a"]), lengths=lengths, prune=True)


for _code in Z.CODES:

    @register(f"topk_static_{_code}", f"WITH {_QT}, {_SCORED} {_TOP}")
    def _(spark, sf_dir, code=_code):
        log = L.query_log(spark, sf_dir)
        runs = Z.build_static(P.count_terms(S.docs(spark, sf_dir)), K.IndexConfig(), code)
        return X.topk(Z.decode_static(X.fetch_blocks(runs, log), code).select("term", "d", "f"), log, S.table(spark, sf_dir, "documents").count())


def _static_sql(c: str) -> str:
    run = f"(SELECT term, (i - 1) // 128 AS b, count(*) AS n, max(f) AS mf, max(CASE WHEN (i - 1) % 128 = 0 THEN 0 ELSE g END) AS mg, sum({Q.vlen('CASE WHEN (i - 1) % 128 = 0 THEN 0 ELSE g END')} + {Q.vlen('f')}) AS plain FROM (SELECT *, row_number() OVER (PARTITION BY term ORDER BY d) AS i FROM {Q.post(c)}) GROUP BY 1, 2)"
    size = "CASE WHEN n = 128 THEN 2 + 16 * (CASE WHEN mg > 0 THEN length(bin(mg)) ELSE 0 END + length(bin(mf))) ELSE plain END"
    return f"SELECT '{c}' AS coll, count(DISTINCT term) AS lists, count(*) AS runs, sum(n)::BIGINT AS postings, sum({size})::BIGINT AS payload_bytes, (12 * (count(*) - count(DISTINCT term)))::BIGINT AS skip_bytes, (SELECT sum(strlen(term) + 16)::BIGINT FROM (SELECT DISTINCT term FROM {Q.TOK[c]})) AS vocabulary_bytes FROM {run}"


@register("static_sizes", " UNION ALL ".join(_static_sql(c) for c in S.COLLECTIONS))
def static_sizes(spark, sf_dir):
    """Each collection as one index: a list is one list, however many documents there are."""
    out = [Z.static_bytes(Z.build_whole(P.count_terms(make(spark, sf_dir)), K.IndexConfig()), "term").select(F.lit(c).alias("coll"), "*") for c, make in S.COLLECTIONS.items()]
    return reduce(lambda a, b: a.unionAll(b), out)


def asked(spark, sf_dir, coll: str = "docs"):
    """Postings of the lists that the log names, once for all engines: lists are built one by one, and no query of the
    log opens another."""
    return written(X.fetch_blocks(P.count_terms(S.COLLECTIONS[coll](spark, sf_dir)), L.query_log(spark, sf_dir)), "asked-lists")


def placed(blocks, layout: str):
    """Blocks, or static runs, with their places in the array."""
    return blocks.join(X.positions(blocks) if layout == "interleaved" else X.collated(blocks), ["shard", "term", "block_no"])


def dynamic(spark, sf_dir, growth: str, counts):
    cfg = K.IndexConfig(growth=growth, shard_docs=_quarter(spark, sf_dir))
    return written(K.build_blocks(counts, cfg), "asked-blocks"), cfg


def costs(spark, sf_dir, growth: str, layout: str, mode: str, coll: str = "docs"):
    """Costs of the log's queries over one way to grow and lay out the blocks."""
    blocks, cfg = dynamic(spark, sf_dir, growth, asked(spark, sf_dir, coll))
    return A.run_log(placed(blocks, layout), L.query_log(spark, sf_dir), cfg, mode, S.table(spark, sf_dir, "documents").count())


def _quarter(spark, sf_dir) -> int:
    """Documents of a shard of the latency experiments, which sum a query's time over its shards."""
    return max(1, -(-S.table(spark, sf_dir, "documents").count() // 4))


@register("latency_by_length")
def latency_by_length(spark, sf_dir):
    """(engine, mode, n_terms, queries, mean_us, p95_us, ..): the time of a query inside its shards, by the number of its
    terms, in the dynamic index and in two static ones."""
    counts, log, n, out = asked(spark, sf_dir), L.query_log(spark, sf_dir), S.table(spark, sf_dir, "documents").count(), []
    for engine in ("dynamic", *Z.CODES):
        if engine == "dynamic":
            blocks, cfg = dynamic(spark, sf_dir, "constant", counts)
            here, code = placed(blocks, "interleaved"), None
        else:
            cfg, code = K.IndexConfig(shard_docs=_quarter(spark, sf_dir)), engine
            here = placed(written(Z.build_static(counts, cfg, code), "asked-runs"), "collated")
        for mode in A.MODES:
            out.append(A.latency(A.run_log(here, log, cfg, mode, n, code), "n_terms").select(F.lit(engine).alias("engine"), F.lit(mode).alias("mode"), "*"))
    return reduce(lambda a, b: a.unionAll(b), out)


@register("latency_by_layout")
def latency_by_layout(spark, sf_dir):
    """(growth, layout, mode, queries, mean_us, p95_us, mean_blocks, mean_postings): growth rules and layouts side by side."""
    counts, log, n, out = asked(spark, sf_dir), L.query_log(spark, sf_dir), S.table(spark, sf_dir, "documents").count(), []
    for growth in ("constant", "triangular"):
        blocks, cfg = dynamic(spark, sf_dir, growth, counts)
        for layout in ("interleaved", "collated"):
            here = placed(blocks, layout)
            for mode in A.MODES:
                out.append(A.latency(A.run_log(here, log, cfg, mode, n)).select(F.lit(growth).alias("growth"), F.lit(layout).alias("layout"), F.lit(mode).alias("mode"), "*"))
    return reduce(lambda a, b: a.unionAll(b), out)


@register("array_conjunctive_counts", f"WITH {_QT}, c AS ({_CONJ.split(', ', 1)[1].split('c AS (', 1)[1].rsplit(') SELECT', 1)[0]}) SELECT q.qid, coalesce(c.n, 0) AS matches FROM (SELECT DISTINCT qid FROM qt) q LEFT JOIN (SELECT qid, count(*) AS n FROM c GROUP BY qid) c ON c.qid = q.qid")
def array_conjunctive_counts(spark, sf_dir):
    """Matches that the array index finds by skipping, for every logged query."""
    return costs(spark, sf_dir, "triangular", "collated", "conjunctive").select("qid", "matches")


@register("collation_cost")
def collation_cost(spark, sf_dir):
    """(step, seconds, documents): plain copy of the blocks, collated rewrite, and what a reader waits for an insert."""
    import time

    index = grown(spark, sf_dir)
    rows = []
    began = time.time()
    index.blocks().write.format("noop").mode("overwrite").save()
    rows.append(("read", time.time() - began, index.manifest()["documents"]))
    said = index.collate()
    rows.append(("collated", said["seconds"], said["documents_meanwhile"]))
    stream = S.docs(spark, sf_dir)
    last = index.manifest()["last_d"]
    began = time.time()
    index.insert(stream.where("d <= 100").withColumn("d", F.col("d") + last))
    rows.append(("insert of 100", time.time() - began, index.manifest()["documents"] - last))
    return spark.createDataFrame(rows, "step string, seconds double, documents long")
