"""Baselines' sizes over the collections."""

from __future__ import annotations

from pyspark.sql import functions as F

from liveindex.operators import baselines as B
from liveindex.operators import growth as G
from liveindex.operators import postings as P
from liveindex.registry import register
from liveindex.sources import collections as S
from liveindex.workloads import sqlparts as Q

_LISTS = f"(SELECT term, count(*) AS ft FROM {Q.counts('docs')} GROUP BY term)"
_WORD_LISTS = f"(SELECT term, count(*) AS ft FROM {Q.TOK['docs']} GROUP BY term)"


def _lists(spark, sf_dir, word=False):
    stream = S.docs(spark, sf_dir)
    return B.list_lengths(P.occurrences(stream) if word else P.count_terms(stream))


@register("linked_list_cost", f"SELECT sum(ft)::BIGINT AS postings, (16 * sum(ft))::BIGINT AS bytes FROM {_LISTS}")
def linked_list_cost(spark, sf_dir):
    return B.linked_cost(_lists(spark, sf_dir))


@register("extensible_array_cost", f"SELECT sum(ft)::BIGINT AS postings, sum(8 * c)::BIGINT AS bytes, sum(c - 1)::BIGINT AS copied FROM (SELECT ft, pow(2, ceil(log2(ft)))::BIGINT AS c FROM {_LISTS})")
def extensible_array_cost(spark, sf_dir):
    return B.doubling_array_cost(_lists(spark, sf_dir))


def _ladder(lists: str, sizes: list[int], posting: int, link: int) -> str:
    ends, total = [], 0
    for s in sizes:
        total += s
        ends.append(total)
    z = " ".join(f"WHEN ft <= {e} THEN {i + 1}" for i, e in enumerate(ends)) + f" ELSE {len(sizes)} + ceil((ft - {total}) / {sizes[-1]})"
    held = " ".join(f"WHEN ft <= {e} THEN {e}" for e in ends) + f" ELSE {total} + ceil((ft - {total}) / {sizes[-1]}) * {sizes[-1]}"
    return f"SELECT sum(ft)::BIGINT AS postings, sum(z)::BIGINT AS blocks, sum(held * {posting} + z * {link})::BIGINT AS bytes FROM (SELECT ft, CASE {z} END AS z, CASE {held} END AS held FROM {lists})"


@register("slice_cost", _ladder(_LISTS, list(G.SLICES), 4, 4))
def slice_cost(spark, sf_dir):
    return B.ladder_cost(_lists(spark, sf_dir), list(G.SLICES), 4, 4)


@register("prior_live_size", _ladder(_WORD_LISTS, G.fibonacci_sizes(2, 16), 8, 4))
def prior_live_size(spark, sf_dir):
    """Word-level postings of eight bytes in blocks that grow like Fibonacci numbers."""
    return B.ladder_cost(_lists(spark, sf_dir, True), G.fibonacci_sizes(2, 16), 8, 4)


@register("prior_lists_size", _ladder(f"(SELECT term, sum({Q.vlen('wg')})::BIGINT AS ft FROM (SELECT term, gpos - lag(gpos, 1, 0) OVER (PARTITION BY term ORDER BY gpos) AS wg FROM (SELECT term, (start + w)::BIGINT AS gpos FROM {Q.TOK['docs']} t JOIN (SELECT d, sum(n) OVER (ORDER BY d) - n AS start FROM (SELECT doc_id + 1 AS d, len({Q.CUT.format(t='text', p='[a-z]+')})::BIGINT AS n FROM documents)) s ON s.d = t.d)) GROUP BY term)", G.powers_sizes(16, 1.1, 30, 256), 1, 4))
def prior_lists_size(spark, sf_dir):
    """Gaps of collection positions in byte code, in blocks that grow by a tenth from 16 to 256 bytes."""
    from liveindex.functions.lengths import vbyte_len

    lists = P.postings_global(S.docs(spark, sf_dir)).groupBy("term").agg(F.sum(vbyte_len(F.col("wg"))).alias("ft"))
    return B.ladder_cost(lists, G.powers_sizes(16, 1.1, 30, 256), 1, 4)


@register("vocab_inline_cost", f"SELECT sum(ft)::BIGINT AS postings, sum(CASE WHEN ft <= 2 THEN 16 ELSE 20 + (ft - 2) * 8 END + strlen(term) + 18)::BIGINT AS bytes FROM {_LISTS}")
def vocab_inline_cost(spark, sf_dir):
    return B.vocabulary_inline_cost(_lists(spark, sf_dir), 2)


def _bp(coll: str, value: str) -> str:
    return f"(SELECT sum(CASE WHEN n = 128 THEN 1 + ceil(128 * w / 8) ELSE plain END)::BIGINT AS b FROM (SELECT term, blk, count(*) AS n, sum({Q.vlen(value)}) AS plain, max(CASE WHEN {value} > 0 THEN length(bin({value})) ELSE 0 END) AS w FROM (SELECT *, (row_number() OVER (PARTITION BY term ORDER BY d) - 1) // 128 AS blk FROM {Q.post(coll)}) GROUP BY term, blk))"


@register("bp128_sizes", " UNION ALL ".join(f"SELECT '{c}' AS coll, {_bp(c, 'g')} + {_bp(c, 'f')} AS bytes, round(({_bp(c, 'g')} + {_bp(c, 'f')}) / (SELECT count(*) FROM {Q.counts(c)}), 6)::DOUBLE AS bytes_per_posting" for c in S.COLLECTIONS))
def bp128_sizes(spark, sf_dir):
    out = None
    for c, make in S.COLLECTIONS.items():
        postings = P.postings_doc(make(spark, sf_dir))
        both = B.bit_packed_bytes(postings, "g").unionAll(B.bit_packed_bytes(postings, "f")).agg(F.sum("bytes").alias("bytes"))
        n = postings.agg(F.count("*").alias("n"))
        row = both.crossJoin(n).select(F.lit(c).alias("coll"), "bytes", F.round(F.col("bytes") / F.col("n"), 6).alias("bytes_per_posting"))  # one row each
        out = row if out is None else out.unionAll(row)
    return out


def _interp(coll: str) -> str:
    """Bits by splitting each run at its middle, a level a step; counts likewise, and their sum in byte code."""
    code = "CASE WHEN v - lo - n // 2 < (1 << w) - size THEN w - 1 ELSE w END"
    return (f"(WITH RECURSIVE r AS (SELECT term, (i - 1) // 128 AS b, list(d ORDER BY d) AS ds, list(f ORDER BY d) AS fs FROM (SELECT *, row_number() OVER (PARTITION BY term ORDER BY d) AS i FROM {Q.counts(coll)}) GROUP BY 1, 2), "
            "s AS (SELECT ds, coalesce(lag(ds[len(ds)]) OVER (PARTITION BY term ORDER BY b), 0) + 1 AS low, list_transform(fs, lambda x, k: list_sum(fs[1:k])::BIGINT) AS sums FROM r), "
            "top AS (SELECT max(list_max(ds)) AS m FROM r), "
            "g AS (SELECT ds AS l, 0::BIGINT AS p, len(ds)::BIGINT AS n, low::BIGINT AS lo, (SELECT m FROM top)::BIGINT AS hi FROM s UNION ALL SELECT sums[1:len(sums) - 1], 0, (len(sums) - 1)::BIGINT, 1, sums[len(sums)] - 1 FROM s WHERE len(sums) > 1), "
            "t AS (SELECT l, p, n, lo, hi FROM g UNION ALL SELECT l, CASE WHEN side = 0 THEN p ELSE p + n // 2 + 1 END, CASE WHEN side = 0 THEN n // 2 ELSE n - n // 2 - 1 END, CASE WHEN side = 0 THEN lo ELSE l[p + n // 2 + 1] + 1 END, CASE WHEN side = 0 THEN l[p + n // 2 + 1] - 1 ELSE hi END "
            "FROM t, (VALUES (0), (1)) x(side) WHERE CASE WHEN side = 0 THEN n // 2 ELSE n - n // 2 - 1 END > 0), "
            f"c AS (SELECT n, lo, l[p + n // 2 + 1] AS v, hi - (n - 1 - n // 2) - lo - n // 2 + 1 AS size FROM t), w AS (SELECT *, CASE WHEN size > 1 THEN length(bin(size - 1)) ELSE 0 END AS w FROM c) "
            f"SELECT (SELECT sum({code}) FROM w) + (SELECT sum(8 * {Q.vlen('sums[len(sums)]')}) FROM s) AS bits)")


@register("interpolative_sizes", " UNION ALL ".join(f"SELECT '{c}' AS coll, ceil(bits / 8)::BIGINT AS bytes, round(bits / 8 / (SELECT count(*) FROM {Q.counts(c)}), 6)::DOUBLE AS bytes_per_posting FROM {_interp(c)}" for c in ("docs", "baskets")))
def interpolative_sizes(spark, sf_dir):
    out = None
    for c in ("docs", "baskets"):
        postings = P.count_terms(S.COLLECTIONS[c](spark, sf_dir))
        facts = postings.agg(F.max("d").alias("d"), F.count("*").alias("n")).first()
        row = B.interpolative_bits(postings, facts["d"]).select(F.lit(c).alias("coll"), F.ceil(F.col("bits") / 8).alias("bytes"), F.round(F.col("bits") / 8 / facts["n"], 6).alias("bytes_per_posting"))
        out = row if out is None else out.unionAll(row)
    return out


@register("two_pass_offsets", f"SELECT term, (sum(ft) OVER (ORDER BY term) - ft)::BIGINT AS \"offset\" FROM {_LISTS}")
def two_pass_offsets(spark, sf_dir):
    return B.two_pass_offsets(P.count_terms(S.docs(spark, sf_dir)))


@register("merged_vocab", f"SELECT batch, count(*) AS new_terms FROM (SELECT term, min((d - 1) // 50) AS batch FROM {Q.counts('docs')} GROUP BY term) GROUP BY batch")
def merged_vocab(spark, sf_dir):
    return B.merged_vocabulary(P.count_terms(S.docs(spark, sf_dir)), 50)


@register("batches_merged", f"SELECT term, d, f, g FROM {Q.post('docs')}")
def batches_merged(spark, sf_dir):
    return B.merge_batches(S.docs(spark, sf_dir), 250)


@register("tree_inversion", f"SELECT term, d, f, g FROM {Q.post('docs')}")
def tree_inversion(spark, sf_dir):
    """Inversion by one sort of all occurrences by term and document, counted in runs."""
    return B.sorted_inversion(S.docs(spark, sf_dir))


@register("vocabulary_passes", f"SELECT term, d, f, g FROM {Q.post('docs')}")
def vocabulary_passes(spark, sf_dir):
    return B.by_vocabulary_ranges(S.docs(spark, sf_dir), 3)


@register("reorder_effect", " UNION ALL ".join(f"SELECT '{name}' AS order_name, sum({Q.plen('g', 'f', 4)})::BIGINT AS bytes FROM (SELECT term, f, nd - lag(nd, 1, 0) OVER (PARTITION BY term ORDER BY nd) AS g FROM {Q.counts('docs')} JOIN (SELECT doc_id + 1 AS od, row_number() OVER (ORDER BY {o}) AS nd FROM documents) ON od = d)" for name, o in (("arrival", "doc_id"), ("lang", "lang, doc_id"), ("source", "source, doc_id"))))
def reorder_effect(spark, sf_dir):
    """Numbering documents by language or source before coding."""
    from pyspark.sql import Window

    from liveindex.functions.lengths import pair_len

    counts, out = P.count_terms(S.docs(spark, sf_dir)), None
    docs = S.table(spark, sf_dir, "documents").select("doc_id", "lang", "source")
    for name, order in (("arrival", ["doc_id"]), ("lang", ["lang", "doc_id"]), ("source", ["source", "doc_id"])):
        new = S.assign_ordinals(docs, *order, into="nd").select((F.col("doc_id") + 1).alias("d"), "nd")
        rows = counts.join(new, "d").withColumn("g", F.col("nd") - F.lag("nd", 1, 0).over(Window.partitionBy("term").orderBy("nd")))
        row = rows.agg(F.sum(pair_len(F.col("g"), F.col("f"), 4)).alias("bytes")).select(F.lit(name).alias("order_name"), "bytes")
        out = row if out is None else out.unionAll(row)
    return out
