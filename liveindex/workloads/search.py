"""Query logs and the queries of the experiments over `documents`."""

from __future__ import annotations

from pyspark.sql import functions as F

from liveindex.operators import arrays as A
from liveindex.operators import evaluate as E
from liveindex.operators import packer as K
from liveindex.operators import postings as P
from liveindex.operators import search as X
from liveindex.registry import register
from liveindex.sources import collections as S
from liveindex.sources import querylog as L
from liveindex.workloads import sqlparts as Q

_WORDS = Q.CUT.format(t="text", p="[a-z]+")
LOG = f"""(SELECT (item_id * 1000 + pos) * 10 + n AS qid, list_distinct(t[pos:pos + n - 1]) AS terms, t[pos:pos + n - 1] AS phrase FROM (SELECT item_id, t, unnest(range(1, len(t) + 1, 5)) AS pos FROM (SELECT item_id, {_WORDS} AS t FROM benchmark)), range(1, 7) r(n) WHERE pos + n - 1 <= len(t))"""
_QT = f"qt AS MATERIALIZED (SELECT qid, unnest(terms) AS term, len(terms) AS n_terms FROM {LOG})"


def _all(coll: str, name: str) -> str:
    return f"{name} AS (SELECT p.d, q.qid FROM {Q.counts(coll)} p JOIN qt q ON p.term = q.term GROUP BY p.d, q.qid, q.n_terms HAVING count(*) = q.n_terms)"


_KEPT = f"{_QT}, {_all('docs', 'c1')}, {_all('pages', 'c2')}, {_all('turns', 'c3')}, kept AS MATERIALIZED (SELECT * FROM qt WHERE qid IN (SELECT qid FROM c1) AND qid IN (SELECT qid FROM c2) AND qid IN (SELECT qid FROM c3))"
_POST = f"post AS MATERIALIZED {Q.counts('docs')}, ft AS (SELECT term, count(*) AS ft FROM post GROUP BY term)"
_TFIDF = "ln(1 + p.f) * ln(1 + n.n / t.ft::DOUBLE)"
_SCORED = f"{_POST}, scored AS (SELECT q.qid, p.d, round(sum({_TFIDF}), 6) AS score FROM qt q JOIN post p ON p.term = q.term JOIN ft t ON t.term = q.term, (SELECT count(*) AS n FROM documents) n GROUP BY q.qid, p.d)"
_TOP = "SELECT qid, rank, d, score FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY score DESC, d) AS rank FROM scored) WHERE rank <= 10"


def _counts(spark, sf_dir):
    return P.count_terms(S.docs(spark, sf_dir))


def _n(spark, sf_dir):
    return S.table(spark, sf_dir, "documents").count()


def _blocks(spark, sf_dir, cfg):
    return K.build_blocks(_counts(spark, sf_dir), cfg)


@register("query_log", f"SELECT qid, len(terms) AS n_terms, array_to_string(list_sort(terms), ' ') AS terms_text FROM {LOG}")
def query_log(spark, sf_dir):
    return L.query_log(spark, sf_dir).select("qid", F.size("terms").cast("long").alias("n_terms"), F.array_join(F.array_sort("terms"), " ").alias("terms_text"))


@register("query_log_filtered", f"WITH {_KEPT} SELECT DISTINCT qid, n_terms FROM kept")
def query_log_filtered(spark, sf_dir):
    return L.filtered(spark, sf_dir).select("qid", F.size("terms").cast("long").alias("n_terms"))


@register("query_stats", "WITH " + _KEPT + ", " + ", ".join(f"a{i} AS (SELECT '{c}' AS coll, (SELECT count(DISTINCT qid) FROM kept) AS queries, (SELECT count(*) FROM c{i} WHERE qid IN (SELECT qid FROM kept)) AS conj, (SELECT count(*) FROM (SELECT DISTINCT k.qid, p.d FROM kept k JOIN {Q.counts(c)} p ON p.term = k.term)) AS disj)" for i, c in ((1, "docs"), (2, "pages"), (3, "turns"))) + " SELECT coll, queries, round(conj / queries, 6) AS avg_conj, round(disj / queries, 6) AS avg_disj FROM (SELECT * FROM a1 UNION ALL SELECT * FROM a2 UNION ALL SELECT * FROM a3)")
def query_stats(spark, sf_dir):
    log = L.filtered(spark, sf_dir)
    n = log.agg(F.count("*").alias("queries"))
    out = None
    for c in ("docs", "pages", "turns"):
        counts = P.count_terms(S.COLLECTIONS[c](spark, sf_dir))
        row = X.conjunctive(counts, log).agg(F.count("*").alias("conj")).crossJoin(E.disjunctive_counts(counts, log).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("disj"))).crossJoin(n)  # one row each
        row = row.select(F.lit(c).alias("coll"), "queries", F.round(F.col("conj") / F.col("queries"), 6).alias("avg_conj"), F.round(F.col("disj") / F.col("queries"), 6).alias("avg_disj"))
        out = row if out is None else out.unionAll(row)
    return out


_TURNS_LOG = f"(SELECT conv_id * 1000 + turn AS qid, list_distinct(({Q.CUT.format(t='text', p='[a-z]+')})[1:4]) AS terms FROM conversations WHERE role = 'user')"


@register("query_log_turns", f"SELECT qid, len(terms) AS n_terms, array_to_string(list_sort(terms), ' ') AS terms_text FROM {_TURNS_LOG} WHERE len(terms) > 0")
def query_log_turns(spark, sf_dir):
    return L.turns_log(spark, sf_dir).select("qid", F.size("terms").cast("long").alias("n_terms"), F.array_join(F.array_sort("terms"), " ").alias("terms_text"))


_VOC = f"voc AS MATERIALIZED (SELECT term, row_number() OVER (ORDER BY term) - 1 AS place, count(*) OVER () AS size FROM (SELECT DISTINCT term FROM {Q.TOK['baskets']}))"
_BASKET_QT = f"{_VOC}, asked AS (SELECT qid, unnest(CASE WHEN qid % 2 = 1 THEN [qid, 7 * qid + 3, 13 * qid + 5] ELSE [qid, 7 * qid + 3] END) % (SELECT max(size) FROM voc) AS place FROM range(2000) t(qid)), bq AS MATERIALIZED (SELECT DISTINCT qid, term FROM asked JOIN voc USING (place))"


@register("query_log_baskets", f"WITH {_BASKET_QT} SELECT qid, count(*) AS n_terms, string_agg(term, ' ' ORDER BY term) AS terms_text FROM bq GROUP BY qid")
def query_log_baskets(spark, sf_dir):
    return L.baskets_log(spark, sf_dir).select("qid", F.size("terms").cast("long").alias("n_terms"), F.array_join("terms", " ").alias("terms_text"))


@register("conjunctive_baskets", f"WITH {_BASKET_QT}, n AS (SELECT qid, count(*) AS n FROM bq GROUP BY qid) SELECT qid, count(*) AS n FROM (SELECT q.qid, p.d FROM bq q JOIN {Q.counts('baskets')} p ON p.term = q.term JOIN n ON n.qid = q.qid GROUP BY q.qid, p.d, n.n HAVING count(*) = n.n) GROUP BY qid")
def conjunctive_baskets(spark, sf_dir):
    """Long lists: matches of each query of the basket log."""
    counts = P.count_terms(S.baskets(spark, sf_dir))
    return X.conjunctive(counts, L.baskets_log(spark, sf_dir)).groupBy("qid").agg(F.count("*").alias("n"))


_CONJ = f"WITH {_QT}, {_all('docs', 'c')} SELECT qid, d FROM c"


@register("conjunctive", _CONJ)
def conjunctive(spark, sf_dir):
    return X.conjunctive(_counts(spark, sf_dir), L.query_log(spark, sf_dir), n_docs=_n(spark, sf_dir))


@register("conjunctive_count", _CONJ)
def conjunctive_count(spark, sf_dir):
    return X.conjunctive(_counts(spark, sf_dir), L.query_log(spark, sf_dir), "count")


@register("conjunctive_semijoin", _CONJ)
def conjunctive_semijoin(spark, sf_dir):
    return X.conjunctive(_counts(spark, sf_dir), L.query_log(spark, sf_dir), "semijoin")


@register("conjunctive_skip", _CONJ)
def conjunctive_skip(spark, sf_dir):
    """Blocks sought inside their shards; shards of an eighth of the documents."""
    cfg = K.IndexConfig(shard_docs=max(1, _n(spark, sf_dir) // 8))
    return A.conjunctive(_blocks(spark, sf_dir, cfg), L.query_log(spark, sf_dir), cfg)


@register("conjunctive_seek", _CONJ)
def conjunctive_seek(spark, sf_dir):
    """The same by an as-of join of candidates and blocks."""
    cfg = K.IndexConfig()
    return X.conjunctive_by_seek(_blocks(spark, sf_dir, cfg), L.query_log(spark, sf_dir), cfg)


@register("disjunctive_counts", f"WITH {_QT} SELECT q.qid, count(DISTINCT p.d) AS n FROM qt q JOIN {Q.counts('docs')} p ON p.term = q.term GROUP BY q.qid")
def disjunctive_counts(spark, sf_dir):
    return E.disjunctive_counts(_counts(spark, sf_dir), L.query_log(spark, sf_dir), _n(spark, sf_dir))


@register("topk_tfidf", f"WITH {_QT}, {_SCORED} {_TOP}")
def topk_tfidf(spark, sf_dir):
    return X.topk(_counts(spark, sf_dir), L.query_log(spark, sf_dir), _n(spark, sf_dir))


@register("topk_joined", f"WITH {_QT}, {_SCORED} {_TOP}")
def topk_joined(spark, sf_dir):
    return X.topk_joined(_counts(spark, sf_dir), L.query_log(spark, sf_dir), _n(spark, sf_dir))


@register("topk_heap", f"WITH {_QT}, {_SCORED} {_TOP}")
def topk_heap(spark, sf_dir):
    """Document at a time, with a heap of the ten best."""
    return E.topk(_counts(spark, sf_dir), L.query_log(spark, sf_dir), _n(spark, sf_dir), strategy="heap")


@register("topk_maxscore", f"WITH {_QT}, {_SCORED} {_TOP}")
def topk_maxscore(spark, sf_dir):
    return X.topk(_counts(spark, sf_dir), L.query_log(spark, sf_dir), _n(spark, sf_dir), prune=True)


@register("topk_pruned", f"WITH {_QT}, {_SCORED} {_TOP}")
def topk_pruned(spark, sf_dir):
    return X.topk_pruned(_counts(spark, sf_dir), L.query_log(spark, sf_dir), _n(spark, sf_dir))


@register("topk_from_blocks", f"WITH {_QT}, {_SCORED} {_TOP}")
def topk_from_blocks(spark, sf_dir):
    cfg = K.IndexConfig(growth="triangular")
    log = L.query_log(spark, sf_dir)
    lists = K.decode_blocks(X.fetch_blocks(_blocks(spark, sf_dir, cfg), log), cfg)
    return X.topk(lists.select("term", "d", "f"), log, _n(spark, sf_dir))


_BM = "ln(1 + (n.n - t.ft + 0.5) / (t.ft + 0.5)) * p.f * 1.9 / (p.f + 0.9 * (0.6 + 0.4 * s.len / n.a))"


_BM25 = f"WITH {_QT}, {_POST}, s AS (SELECT doc_id + 1 AS d, len({_WORDS}) AS len FROM documents), scored AS (SELECT q.qid, p.d, round(sum({_BM}), 6) AS score FROM qt q JOIN post p ON p.term = q.term JOIN ft t ON t.term = q.term JOIN s ON s.d = p.d, (SELECT count(*)::DOUBLE AS n, avg(len) AS a FROM s) n GROUP BY q.qid, p.d) {_TOP}"


@register("topk_bm25", _BM25)
def topk_bm25(spark, sf_dir):
    stream = S.docs(spark, sf_dir)
    return X.topk_bm25(P.count_terms(stream), P.doc_lengths(stream), L.query_log(spark, sf_dir))


@register("term_bounds", f"WITH {_POST} SELECT p.term, t.ft, round(ln(1 + max(p.f)) * ln(1 + (SELECT count(*) FROM documents) / t.ft::DOUBLE), 6) AS max_w FROM post p JOIN ft t ON t.term = p.term GROUP BY p.term, t.ft")
def term_bounds(spark, sf_dir):
    return X.term_bounds(_counts(spark, sf_dir), _n(spark, sf_dir))


@register("phrase", f"WITH qp AS (SELECT qid, unnest(phrase) AS term, generate_subscripts(phrase, 1) AS i, len(phrase) AS n FROM {LOG}) SELECT qid, d, count(*) AS hits FROM (SELECT q.qid, t.d, t.w - q.i AS at FROM {Q.TOK['docs']} t JOIN qp q ON q.term = t.term GROUP BY q.qid, t.d, t.w - q.i, q.n HAVING count(*) = q.n) GROUP BY qid, d")
def phrase(spark, sf_dir):
    items = S.table(spark, sf_dir, "benchmark").select("item_id", S.tokens(F.col("text")).alias("t"))
    at = items.select("item_id", "t", F.explode(F.expr("case when size(t) > 0 then sequence(1, size(t), 5) end")).alias("pos"))
    every = at.select("item_id", "t", "pos", F.explode(F.array(*map(F.lit, range(1, 7)))).alias("n")).where(F.col("pos") + F.col("n") - 1 <= F.size("t"))
    log = every.select(((F.col("item_id") * 1000 + F.col("pos")) * 10 + F.col("n")).alias("qid"), F.expr("slice(t, pos, n)").alias("terms"))
    return X.phrase(P.occurrences(S.docs(spark, sf_dir)), log, _n(spark, sf_dir))


_PAIRS = f"(SELECT qid, phrase[1] AS t1, phrase[2] AS t2 FROM {LOG} WHERE len(phrase) = 2 AND phrase[1] <> phrase[2])"


@register("proximity", f"SELECT q.qid, a.d, count(*) AS hits FROM {_PAIRS} q JOIN {Q.TOK['docs']} a ON a.term = q.t1 JOIN {Q.TOK['docs']} b ON b.term = q.t2 AND b.d = a.d AND abs(a.w - b.w) <= 5 GROUP BY q.qid, a.d")
def proximity(spark, sf_dir):
    log = L.query_log(spark, sf_dir).where("size(terms) = 2 and qid % 10 = 2").select("qid", F.col("terms")[0].alias("t1"), F.col("terms")[1].alias("t2"))
    return X.proximity(P.occurrences(S.docs(spark, sf_dir)), log, 5, _n(spark, sf_dir))


@register("recent_matches", f"WITH {_QT}, {_all('docs', 'c')} SELECT qid, d, rank FROM (SELECT qid, d, row_number() OVER (PARTITION BY qid ORDER BY d DESC) AS rank FROM c) WHERE rank <= 10")
def recent_matches(spark, sf_dir):
    return X.recent_matches(_counts(spark, sf_dir), L.query_log(spark, sf_dir), 10, _n(spark, sf_dir)).select("qid", "d", "rank")


@register("boolean_expr", f"WITH p AS MATERIALIZED {Q.counts('docs')}, x AS (SELECT d FROM p WHERE term = 'the' INTERSECT (SELECT d FROM p WHERE term = 'of' UNION SELECT d FROM p WHERE term = 'das')) SELECT d FROM x EXCEPT SELECT d FROM p WHERE term = 'from'")
def boolean_expr(spark, sf_dir):
    return X.boolean(_counts(spark, sf_dir), ("not", ("and", "the", ("or", "of", "das")), "from")).distinct()


_OPS = "ops AS (SELECT DISTINCT qid, (1 + 2 * (qid % (SELECT count(*) FROM documents)))::BIGINT AS op_seq FROM qt)"


def _ops(spark, sf_dir):
    n = _n(spark, sf_dir)
    return L.query_log(spark, sf_dir).withColumn("op_seq", 1 + 2 * (F.col("qid") % n))


@register("ops_conjunctive", f"WITH {_QT}, {_OPS} SELECT o.op_seq, q.qid, p.d FROM qt q JOIN ops o ON o.qid = q.qid JOIN {Q.counts('docs')} p ON p.term = q.term AND 2 * p.d < o.op_seq GROUP BY o.op_seq, q.qid, p.d, q.n_terms HAVING count(*) = q.n_terms")
def ops_conjunctive(spark, sf_dir):
    """Inserts have even numbers, queries odd ones; each query sees the documents before it and no others."""
    return X.ops_conjunctive(_counts(spark, sf_dir).withColumn("seq", 2 * F.col("d")), _ops(spark, sf_dir), _n(spark, sf_dir))


@register("ops_topk", f"""WITH {_QT}, {_OPS}, seen AS (SELECT o.op_seq, q.qid, q.term, p.d, p.f FROM qt q JOIN ops o ON o.qid = q.qid JOIN {Q.counts('docs')} p ON p.term = q.term AND 2 * p.d < o.op_seq),
ft AS (SELECT qid, term, count(*) AS ft FROM seen GROUP BY qid, term), sc AS (SELECT s.op_seq, s.qid, s.d, round(sum(ln(1 + s.f) * ln(1 + ((s.op_seq - 1) // 2) / t.ft::DOUBLE)), 6) AS score FROM seen s JOIN ft t ON t.qid = s.qid AND t.term = s.term GROUP BY s.op_seq, s.qid, s.d)
SELECT op_seq, qid, d, score, rank FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY score DESC, d) AS rank FROM sc) WHERE rank <= 10""")
def ops_topk(spark, sf_dir):
    docs = S.table(spark, sf_dir, "documents").select((F.col("doc_id") + 1).alias("d"), (2 * (F.col("doc_id") + 1)).alias("seq"))
    return X.ops_topk(_counts(spark, sf_dir).withColumn("seq", 2 * F.col("d")), docs, _ops(spark, sf_dir), n_docs=_n(spark, sf_dir)).select("op_seq", "qid", "d", "score", "rank")
