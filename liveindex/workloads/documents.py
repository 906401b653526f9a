"""Collections, ordinals, and the four kinds of postings."""

from __future__ import annotations

from pyspark.sql import functions as F

from liveindex.operators import postings as P
from liveindex.registry import register
from liveindex.sources import collections as S
from liveindex.workloads import sqlparts as Q

for _c in S.COLLECTIONS:

    @register(f"docstream_{_c}", f"SELECT d, count(*) AS n_terms, string_agg(term, ' ' ORDER BY w) AS terms_text FROM {Q.TOK[_c]} GROUP BY d")
    def _(spark, sf_dir, c=_c):
        return S.COLLECTIONS[c](spark, sf_dir).where(F.size("terms") > 0).select("d", F.size("terms").cast("long").alias("n_terms"), F.array_join("terms", " ").alias("terms_text"))

    @register(f"postings_doc_{_c}", f"SELECT term, d, f, g FROM {Q.post(_c)}")
    def _(spark, sf_dir, c=_c):
        return P.postings_doc(S.COLLECTIONS[c](spark, sf_dir))

    @register(f"postings_word_{_c}", f"SELECT term, d, w, g1, wg FROM {Q.word(_c)}")
    def _(spark, sf_dir, c=_c):
        return P.postings_word(S.COLLECTIONS[c](spark, sf_dir))


@register("docstream_unicode", f"SELECT d, count(*) AS n_terms, string_agg(term, ' ' ORDER BY w) AS terms_text FROM {Q.TOK_UNICODE} GROUP BY d")
def docstream_unicode(spark, sf_dir):
    return S.docs(spark, sf_dir, "unicode").where(F.size("terms") > 0).select("d", F.size("terms").cast("long").alias("n_terms"), F.array_join("terms", " ").alias("terms_text"))


@register("long_terms", "SELECT d, w, term FROM " + Q._tok("doc_id + 1", "replace(text, ' ', '')", "documents") + " WHERE length(term) = 20")
def long_terms(spark, sf_dir):
    """Words glued together, so that the cut after 20 letters has work to do."""
    rows = S.table(spark, sf_dir, "documents")
    return P.occurrences(S.docstream(rows, F.col("doc_id") + 1, F.col("doc_id"), F.replace("text", F.lit(" "), F.lit("")), "glued")).where(F.length("term") == 20).select("d", "w", "term")


@register("ordinals", "SELECT conv_id, turn, row_number() OVER (ORDER BY conv_id, turn) AS d FROM conversations")
def ordinals(spark, sf_dir):
    return S.assign_ordinals(S.table(spark, sf_dir, "conversations").select("conv_id", "turn"), "conv_id", "turn")


@register("count_terms", f"SELECT term, d, f FROM {Q.counts('docs')}")
def count_terms(spark, sf_dir):
    return P.count_terms(S.docs(spark, sf_dir))


@register("postings_nested", f"SELECT term, d, count(*) AS f, string_agg((w - pw)::VARCHAR, ',' ORDER BY w) AS w_gaps FROM (SELECT term, d, w, lag(w, 1, 0) OVER (PARTITION BY term, d ORDER BY w) AS pw FROM {Q.TOK['docs']}) GROUP BY term, d")
def postings_nested(spark, sf_dir):
    return P.postings_nested(S.docs(spark, sf_dir)).withColumn("w_gaps", F.array_join(F.col("w_gaps").cast("array<string>"), ","))


@register("derived_f", f"SELECT term, d, f FROM {Q.counts('docs')}")
def derived_f(spark, sf_dir):
    return P.derive_counts(P.postings_word(S.docs(spark, sf_dir)))


_STARTS = f"(SELECT d, sum(n) OVER (ORDER BY d) - n AS start, n AS len FROM (SELECT doc_id + 1 AS d, len({Q.CUT.format(t='text', p='[a-z]+')})::BIGINT AS n FROM documents))"


@register("doc_starts", f"SELECT d, start::BIGINT AS start, len FROM {_STARTS}")
def doc_starts(spark, sf_dir):
    return P.doc_starts(S.docs(spark, sf_dir))


_GLOBAL = f"(SELECT term, (start + w)::BIGINT AS gpos FROM {Q.TOK['docs']} t JOIN {_STARTS} s ON s.d = t.d)"


@register("postings_global", f"SELECT term, gpos, gpos - lag(gpos, 1, 0) OVER (PARTITION BY term ORDER BY gpos) AS wg FROM {_GLOBAL}")
def postings_global(spark, sf_dir):
    return P.postings_global(S.docs(spark, sf_dir))


@register("resolve_positions", f"SELECT g.term, g.gpos, s.d, (g.gpos - s.start)::BIGINT AS w FROM {_GLOBAL} g ASOF JOIN {_STARTS} s ON g.gpos > s.start WHERE g.gpos - s.start <= s.len")
def resolve_positions(spark, sf_dir):
    stream = S.docs(spark, sf_dir)
    starts = P.doc_starts(stream)
    return P.resolve_positions(P.postings_global(stream, starts).select("term", "gpos"), starts)


_MIB = {"docs": ("documents", "text"), "pages": ("pages", "html"), "turns": ("conversations", "text")}
_STATS = " UNION ALL ".join(
    f"SELECT '{c}' AS coll, (SELECT count(*) FROM {Q.TOK[c]}) AS words, (SELECT count(*) FROM {Q.counts(c)}) AS postings, (SELECT count(*) FROM {t}) AS docs, (SELECT sum(strlen({x}))::BIGINT FROM {t}) AS bytes" for c, (t, x) in _MIB.items())


@register("collection_stats", f"SELECT coll, words, postings, docs, bytes, round(words / postings, 6) AS words_per_posting, round(words / docs, 6) AS words_per_doc FROM ({_STATS})")
def collection_stats(spark, sf_dir):
    out = None
    for c, (table, text) in _MIB.items():
        raw = S.table(spark, sf_dir, table).agg(F.count("*").alias("docs"), F.sum(F.octet_length(text)).cast("long").alias("bytes"))
        one = S.COLLECTIONS[c](spark, sf_dir).select(F.size("terms").cast("long").alias("w"), F.size(F.array_distinct("terms")).cast("long").alias("p")).agg(F.sum("w").alias("words"), F.sum("p").alias("postings"))
        row = one.crossJoin(F.broadcast(raw)).select(F.lit(c).alias("coll"), "words", "postings", "docs", "bytes")  # one row each
        out = row if out is None else out.unionAll(row)
    return out.withColumns({"words_per_posting": F.round(F.col("words") / F.col("postings"), 6), "words_per_doc": F.round(F.col("words") / F.col("docs"), 6)})
