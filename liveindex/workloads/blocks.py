"""Block chains: tables, gaps, components, sweeps over block sizes, layouts and skipping."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from liveindex.operators import packer as K
from liveindex.operators import postings as P
from liveindex.operators import search as X
from liveindex.registry import register
from liveindex.sources import collections as S
from liveindex.sources import querylog as L
from liveindex.workloads import sqlparts as Q
from liveindex.workloads.search import _QT

SIZES = (40, 48, 56, 64, 72, 80)
_PACK = f"WITH RECURSIVE {Q.packed('docs')}, {Q.blocks()}"


def build(spark, sf_dir, coll: str = "docs", **settings):
    cfg = K.IndexConfig(**settings)
    stream = S.COLLECTIONS[coll](spark, sf_dir)
    return K.build_blocks(P.count_terms(stream) if cfg.level == "doc" else P.postings_word(stream), cfg), cfg


@register("block_table", f"{_PACK} SELECT term, block_no, kind, cap, first_d, last_d, n, used FROM tab")
def block_table(spark, sf_dir):
    return build(spark, sf_dir, payload=False)[0].select("term", "block_no", "kind", "cap", "first_d", "last_d", "n", "used")


@register("block_gaps", f"{_PACK} SELECT term, block_no, first_d - lag(first_d, 1, 0) OVER (PARTITION BY term ORDER BY block_no) AS bgap FROM tab")
def block_gaps(spark, sf_dir):
    by = Window.partitionBy("term").orderBy("block_no")
    return build(spark, sf_dir, payload=False)[0].select("term", "block_no", (F.col("first_d") - F.lag("first_d", 1, 0).over(by)).alias("bgap"))


@register("trailing_nulls", f"{_PACK} SELECT kind, count(*) AS blocks, sum(cap - used)::BIGINT AS null_bytes FROM tab GROUP BY kind")
def trailing_nulls(spark, sf_dir):
    return build(spark, sf_dir, payload=False)[0].groupBy("kind").agg(F.count("*").alias("blocks"), F.sum(F.col("cap") - F.col("used")).alias("null_bytes"))


@register("term_dir", f"{_PACK} SELECT term, sum(n)::BIGINT AS ft, max(last_d) AS last_d, count(*) AS z, max_by(used, block_no) AS nx FROM tab GROUP BY term")
def term_dir(spark, sf_dir):
    return K.term_dir(build(spark, sf_dir, payload=False)[0]).select("term", F.col("postings").alias("ft"), "last_d", "z", "nx")


@register("hash_cost", f"SELECT count(DISTINCT term) AS v, 2 * count(DISTINCT term) AS slots, 8 * count(DISTINCT term) AS bytes FROM {Q.TOK['docs']}")
def hash_cost(spark, sf_dir):
    v = P.occurrences(S.docs(spark, sf_dir)).select("term").distinct().agg(F.count("*").alias("v"))
    return v.select("v", (2 * F.col("v")).alias("slots"), (8 * F.col("v")).alias("bytes"))


for _b in (48, 64):
    _parts = [("head", "links", "count(*)", "8 * count(*)", "head"), ("head", "vocabulary", "0", "sum(10 + strlen(term))", "head"), ("head", "postings", "0", "sum(used)", "head"), ("head", "unused", "0", "sum(cap - used)", "head"),
              ("full", "links", "count(*)", "4 * count(*)", "full"), ("full", "postings", "0", "sum(used)", "full"), ("full", "unused", "0", "sum(cap - used)", "full"),
              ("tail", "documents", "count(*)", "4 * count(*)", "tail"), ("tail", "postings", "0", "sum(used)", "tail"), ("tail", "unused", "0", "sum(cap - used)", "tail"), ("hash", "slots", "0", "8 * count(*)", "head")]
    _sql = " UNION ALL ".join(f"SELECT '{p}' AS part, '{e}' AS element, ({n})::BIGINT AS blocks, coalesce({b}, 0)::BIGINT AS bytes FROM tab WHERE kind = '{k}'" for p, e, n, b, k in _parts)

    @register(f"components_b{_b}", f"WITH RECURSIVE {Q.packed('docs', unit=str(_b))}, {Q.blocks(str(_b))} {_sql}")
    def _(spark, sf_dir, b=_b):
        return K.component_table(*build(spark, sf_dir, B=b, payload=False))


def b_sweep(spark, sf_dir, level: str, coll: str = "docs"):
    """All sizes in one pass over the sorted lists; only sums leave the tasks."""
    stream = S.COLLECTIONS[coll](spark, sf_dir)
    postings = P.count_terms(stream) if level == "doc" else P.postings_word(stream)
    sums = K.index_sizes(postings, [K.IndexConfig(B=b, level=level) for b in SIZES])
    size = F.element_at(F.array(*map(F.lit, SIZES)), F.col("variant") + 1).cast("long")
    return sums.select(size.alias("B"), "blocks", "total_bytes", F.round(F.col("total_bytes") / F.col("postings"), 6).alias("bytes_per_posting"))


for _level in ("doc", "word"):
    for _coll in S.COLLECTIONS:
        _sql = " UNION ALL ".join(f"(SELECT {b}::BIGINT AS B, sum(z)::BIGINT AS blocks, (sum(z) * {b} + 8 * count(*))::BIGINT AS total_bytes, round((sum(z) * {b} + 8 * count(*)) / sum(n), 6)::DOUBLE AS bytes_per_posting FROM {Q.folded(_coll, _level, b)})" for b in SIZES)

        @register(f"b_sweep_{_level}" + (f"_{_coll}" if _coll != "docs" else ""), _sql)
        def _(spark, sf_dir, level=_level, coll=_coll):
            return b_sweep(spark, sf_dir, level, coll)


@register("chains_by_fold", f"SELECT term, n AS postings, z FROM {Q.folded('docs', 'doc', 64)}")
def chains_by_fold(spark, sf_dir):
    """The packer in SQL functions alone."""
    return K.folded(P.count_terms(S.docs(spark, sf_dir)), K.IndexConfig()).select("term", "postings", "z")


for _coll in ("docs", "baskets"):
    for _level in ("doc", "word"):

        @register(f"head_only_share_{_level}_{_coll}", f"SELECT count(*) AS lists, count_if(z = 1)::BIGINT AS head_only, round(count_if(z = 1) / count(*), 6)::DOUBLE AS share FROM {Q.folded(_coll, _level, 64)}")
        def _(spark, sf_dir, level=_level, coll=_coll):
            """Lists that never leave their head block."""
            heads = build(spark, sf_dir, coll, level=level, payload=False)[0].groupBy("shard", "term").agg(F.count("*").alias("z"))
            return heads.agg(F.count("*").alias("lists"), F.count_if(F.col("z") == 1).alias("head_only")).select("lists", "head_only", F.round(F.col("head_only") / F.col("lists"), 6).alias("share"))


@register("roundtrip_diff", "SELECT l AS level, 0::BIGINT AS missing, 0::BIGINT AS extra FROM (VALUES ('doc'), ('word')) t(l)")
def roundtrip_diff(spark, sf_dir):
    """Decoded postings against those that went in."""
    out = None
    for level, x in (("doc", "f"), ("word", "w")):
        blocks, cfg = build(spark, sf_dir, level=level)
        stream = S.docs(spark, sf_dir)
        source = (P.count_terms(stream) if level == "doc" else P.occurrences(stream)).select("term", "d", x)
        back = K.decode_blocks(blocks, cfg).select("term", "d", x)
        both = source.withColumn("s", F.lit(1)).unionAll(back.withColumn("s", F.lit(-1))).groupBy("term", "d", x).agg(F.sum("s").alias("s"))
        row = both.agg(F.lit(level).alias("level"), F.count_if(F.col("s") > 0).alias("missing"), F.count_if(F.col("s") < 0).alias("extra"))
        out = row if out is None else out.unionAll(row)
    return out.select("level", "missing", "extra")


@register("query_blocks", f"WITH RECURSIVE {_QT}, {Q.packed('docs')}, {Q.blocks()} SELECT term, block_no, n FROM tab WHERE term IN (SELECT term FROM qt)")
def query_blocks(spark, sf_dir):
    return X.fetch_blocks(build(spark, sf_dir, payload=False)[0], L.query_log(spark, sf_dir)).select("term", "block_no", "n")


_LEAD = "ft AS (SELECT term, sum(n) AS ft, count_if(n > 0)::BIGINT AS blocks FROM tab GROUP BY term), kn AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY ft, term) AS r, count(*) OVER (PARTITION BY qid) AS k FROM qt JOIN ft USING (term)), kq AS MATERIALIZED (SELECT * FROM kn WHERE k = n_terms), sd AS MATERIALIZED (SELECT q.qid, p.d FROM kq q JOIN src p ON p.term = q.term WHERE q.r = 1)"
_SEEK = f"WITH RECURSIVE {_QT}, {Q.packed('docs')}, {Q.blocks()}, {_LEAD}"


@register("seek_geq", f"{_SEEK}, tg AS (SELECT DISTINCT q.term, s.d FROM kq q JOIN sd s ON s.qid = q.qid WHERE q.r > 1) SELECT t.term, t.d, b.block_no, b.first_d FROM tg t ASOF JOIN (SELECT * FROM tab WHERE n > 0) b ON t.term = b.term AND t.d >= b.first_d")
def seek_geq(spark, sf_dir):
    """The blocks that the logged queries seek: each document of a query's rarest list in its other lists."""
    blocks, cfg = build(spark, sf_dir, payload=False)
    known = X._known(blocks, L.query_log(spark, sf_dir))
    seeds = P.count_terms(S.docs(spark, sf_dir)).join(known.where("rank = 1").select("qid", "term"), "term").select("qid", "d")
    targets = seeds.join(known.where("rank > 1").select("qid", "term"), "qid").select(F.lit(0).cast("long").alias("qid"), "term", "d").distinct()
    return X.seek_geq(blocks, targets, cfg).select("term", "d", "block_no", "first_d")


_OPENED = "opened AS (SELECT term, block_no, CASE WHEN n > 0 THEN first_d ELSE lead(first_d) OVER (PARTITION BY term ORDER BY block_no) END AS o FROM tab)"
_POS = f"{_OPENED}, placed AS (SELECT term, block_no, row_number() OVER (ORDER BY o, term, block_no) AS pos FROM opened)"
_COL = "placed AS (SELECT term, block_no, row_number() OVER (ORDER BY term, block_no) AS pos FROM tab)"


@register("block_positions", f"{_PACK}, {_POS} SELECT * FROM placed")
def block_positions(spark, sf_dir):
    return X.positions(build(spark, sf_dir, payload=False)[0]).drop("shard")


@register("collated_positions", f"{_PACK}, {_COL} SELECT * FROM placed")
def collated_positions(spark, sf_dir):
    return X.collated(build(spark, sf_dir, payload=False)[0]).drop("shard")


def _jumps(layout: str, placed: str) -> str:
    return f"{_PACK}, {placed} SELECT '{layout}' AS layout, count(*) AS blocks, count_if(s <> 1)::BIGINT AS jumps, round(coalesce(avg(abs(s)), 0), 6)::DOUBLE AS mean_jump FROM (SELECT lead(pos) OVER (PARTITION BY term ORDER BY block_no) - pos AS s FROM placed)"


@register("jump_stats", f"({_jumps('interleaved', _POS)}) UNION ALL ({_jumps('collated', _COL)})")
def jump_stats(spark, sf_dir):
    blocks = build(spark, sf_dir, payload=False)[0]
    return X.jump_stats(X.positions(blocks), "interleaved").unionAll(X.jump_stats(X.collated(blocks), "collated"))


@register("skip_stats", f"{_SEEK}, pl AS (SELECT t.qid, t.term, t.d, b.block_no, b.first_d FROM (SELECT q.qid, q.term, s.d FROM kq q JOIN sd s ON s.qid = q.qid WHERE q.r > 1) t ASOF JOIN (SELECT * FROM tab WHERE n > 0) b ON t.term = b.term AND t.d >= b.first_d), pb AS (SELECT qid, term, block_no, max((d > first_d)::BIGINT) AS i FROM pl GROUP BY qid, term, block_no), pc AS (SELECT qid, term, count(*) AS t, sum(i)::BIGINT AS i FROM pb GROUP BY qid, term) SELECT k.qid, k.term, k.blocks, coalesce(c.t, 0) AS touched, coalesce(c.i, 0) AS decoded FROM kq k LEFT JOIN pc c ON c.qid = k.qid AND c.term = k.term WHERE k.r > 1")
def skip_stats(spark, sf_dir):
    blocks, cfg = build(spark, sf_dir, payload=False)
    return X.skip_stats(blocks, L.query_log(spark, sf_dir), P.count_terms(S.docs(spark, sf_dir)), cfg)


@register("shard_rollover", f"SELECT (d - 1) // 100 AS shard, count(DISTINCT d) AS docs, count(*) AS postings FROM {Q.counts('docs')} GROUP BY 1")
def shard_rollover(spark, sf_dir):
    """Shards of a hundred documents, as the packer cuts them."""
    blocks, cfg = build(spark, sf_dir, shard_docs=100)
    lists = K.decode_blocks(blocks, cfg)
    return lists.groupBy("shard").agg(F.countDistinct("d").alias("docs"), F.count("*").alias("postings"))


@register("index_by_lang", f"SELECT lang, count(DISTINCT d) AS docs, count(DISTINCT term) AS terms, count(*) AS postings, sum({Q.plen('g', 'f', 4)})::BIGINT AS bytes FROM (SELECT lang, term, d, f, d - lag(d, 1, 0) OVER (PARTITION BY lang, term ORDER BY d) AS g FROM {Q.counts('docs')} JOIN (SELECT doc_id + 1 AS d2, lang FROM documents) ON d = d2) GROUP BY lang")
def index_by_lang(spark, sf_dir):
    """Several indexes in one space, one a language."""
    from liveindex.functions.lengths import pair_len

    lang = S.table(spark, sf_dir, "documents").select((F.col("doc_id") + 1).alias("d"), "lang")
    rows = P.count_terms(S.docs(spark, sf_dir)).join(lang, "d")
    gap = F.col("d") - F.lag("d", 1, 0).over(Window.partitionBy("lang", "term").orderBy("d"))
    rows = rows.withColumn("g", gap)
    return rows.groupBy("lang").agg(F.countDistinct("d").alias("docs"), F.countDistinct("term").alias("terms"), F.count("*").alias("postings"), F.sum(pair_len(F.col("g"), F.col("f"), 4)).alias("bytes"))
