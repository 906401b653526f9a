"""Code lengths: byte code, paired code, thresholds, and how pairing moves sizes."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from liveindex.functions import lengths as L
from liveindex.operators import postings as P
from liveindex.registry import register
from liveindex.sources import collections as S
from liveindex.workloads import sqlparts as Q

DOC_FS, WORD_FS = (1, 2, 4, 8, 16), (1, 2, 3, 4, 8)
_X = "(SELECT DISTINCT l_orderkey + 1 AS x FROM lineitem UNION SELECT (l_orderkey + 1) * 997 FROM lineitem UNION SELECT (1::BIGINT << (7 * k)) + e FROM range(1, 9) t(k), (VALUES (-1), (0), (1)) u(e))"


def _numbers(spark, sf_dir):
    keys = S.table(spark, sf_dir, "lineitem").select((F.col("l_orderkey") + 1).alias("x"))
    edges = spark.range(1, 9).select(F.explode(F.array(*[F.expr(f"shiftleft(1L, cast(7 * id as int)) + {e}") for e in (-1, 0, 1)])).alias("x"))
    return keys.union(keys.select(F.col("x") * 997)).union(edges).distinct()


@register("vbyte_lengths", f"SELECT x, {Q.vlen('x')}::BIGINT AS n_bytes FROM {_X}")
def vbyte_lengths(spark, sf_dir):
    return _numbers(spark, sf_dir).select("x", L.vbyte_len(F.col("x")).cast("long").alias("n_bytes"))


_HEX = "upper(lpad(hex({v}), 2, '0'))"
_BYTE = "CASE WHEN (x >> {s}) < 128 THEN " + _HEX.format(v="(x >> {s}) + 128") + " ELSE " + _HEX.format(v="((x >> {s}) % 128)") + " END"


@register("vbyte_hex", "SELECT x, " + " || ".join(["(" + _BYTE.format(s=7 * k) + ")" if k == 0 else f"(CASE WHEN x >= {1 << (7 * k)} THEN " + _BYTE.format(s=7 * k) + " ELSE '' END)" for k in range(9)]) + f" AS hex_text FROM {_X}")
def vbyte_hex(spark, sf_dir):
    """The bytes themselves, as expressions."""
    part = lambda k: F.lpad(F.hex(F.when(F.shiftright("x", 7 * k) < 128, F.shiftright("x", 7 * k) + 128).otherwise(F.shiftright("x", 7 * k) % 128)), 2, "0")
    return _numbers(spark, sf_dir).select("x", F.concat(*[F.when(F.col("x") >= F.lit(1 << (7 * k) if k else 0), part(k)).otherwise("") for k in range(9)]).alias("hex_text"))


@register("pair_lengths", f"SELECT term, d, {Q.plen('g', 'f', 1)}::BIGINT AS bytes_old, {Q.plen('g', 'f', 4)}::BIGINT AS bytes_new FROM {Q.post('docs')}")
def pair_lengths(spark, sf_dir):
    g, f = F.col("g"), F.col("f")
    return P.postings_doc(S.docs(spark, sf_dir)).select("term", "d", L.pair_len(g, f, 1).cast("long").alias("bytes_old"), L.pair_len(g, f, L.DOC_F).cast("long").alias("bytes_new"))


@register("pair_lengths_word", f"SELECT term, d, w, {Q.plen('wg', 'g1', 1)}::BIGINT AS bytes_old, {Q.plen('wg', 'g1', 3)}::BIGINT AS bytes_new FROM {Q.word('docs')}")
def pair_lengths_word(spark, sf_dir):
    a, b = F.col("wg"), F.col("g1")
    return P.postings_word(S.docs(spark, sf_dir)).select("term", "d", "w", L.pair_len(a, b, 1).cast("long").alias("bytes_old"), L.pair_len(a, b, L.WORD_F).cast("long").alias("bytes_new"))


@register("pair_values", f"SELECT term, d, CASE WHEN f < 4 THEN (g - 1) * 4 + f ELSE g * 4 END AS fused, CASE WHEN f >= 4 THEN f - 3 END AS second FROM {Q.post('docs')}")
def pair_values(spark, sf_dir):
    g, f = F.col("g"), F.col("f")
    return P.postings_doc(S.docs(spark, sf_dir)).select("term", "d", L.pair_fuse(g, f, 4).alias("fused"), L.pair_second(g, f, 4).alias("second"))


def _sweep_sql(c: str, level: str) -> str:
    fs, source, a, b = (DOC_FS, Q.post(c), "g", "f") if level == "doc" else (WORD_FS, Q.word(c), "wg", "g1")
    values = ", ".join(f"({f})" for f in fs)
    return f"SELECT '{c}' AS coll, '{level}' AS level, ff::BIGINT AS F, count(*) AS postings, sum({Q.plen(a, b, 'ff')})::BIGINT AS total_bytes FROM {source}, (VALUES {values}) t(ff) GROUP BY ff"


_SWEEP = " UNION ALL ".join(_sweep_sql(c, level) for c in S.COLLECTIONS for level in ("doc", "word"))


def sweep(postings, coll: str, level: str):
    """One pass for all thresholds: a sum for each, then rows."""
    fs, a, b = (DOC_FS, "g", "f") if level == "doc" else (WORD_FS, "wg", "g1")
    row = postings.agg(F.count("*").alias("postings"), *[F.sum(L.pair_len(F.col(a), F.col(b), f)).cast("long").alias(f"b{f}") for f in fs])
    return row.select("postings", F.explode(F.array(*[F.struct(F.lit(f).cast("long").alias("F"), F.col(f"b{f}").alias("total_bytes")) for f in fs])).alias("x")).select(F.lit(coll).alias("coll"), F.lit(level).alias("level"), "x.F", "postings", "x.total_bytes")


@register("pair_f_sweep", f"SELECT s.coll, s.level, s.F, s.postings, s.total_bytes, round(s.total_bytes / s.postings, 6) AS bytes_per_posting, round(s.total_bytes / o.total_bytes, 6) AS ratio FROM ({_SWEEP}) s JOIN ({_SWEEP}) o ON s.coll = o.coll AND s.level = o.level AND o.F = 1")
def pair_f_sweep(spark, sf_dir):
    """Thresholds side by side, all four collections, both levels."""
    out = None
    for c, make in S.COLLECTIONS.items():
        stream = make(spark, sf_dir)
        for level, postings in (("doc", P.postings_doc(stream)), ("word", P.postings_word(stream))):
            one = sweep(postings, c, level)
            out = one if out is None else out.unionAll(one)
    plain = F.max(F.when(F.col("F") == 1, F.col("total_bytes"))).over(Window.partitionBy("coll", "level"))
    return out.withColumns({"bytes_per_posting": F.round(F.col("total_bytes") / F.col("postings"), 6), "ratio": F.round(F.col("total_bytes") / plain, 6)})


_GAPS = "(SELECT l_suppkey, l_quantity::BIGINT AS b, l_orderkey + 1 - lag(l_orderkey + 1, 1, 0) OVER (PARTITION BY l_suppkey ORDER BY l_orderkey, l_linenumber) + 1 AS a FROM lineitem)"


@register("pair_code_lineitem", f"SELECT l_suppkey, count(*) AS n, sum({Q.plen('a', 'b', 1)})::BIGINT AS bytes_old, sum({Q.plen('a', 'b', 4)})::BIGINT AS bytes_new FROM {_GAPS} GROUP BY l_suppkey")
def pair_code_lineitem(spark, sf_dir):
    """The paired code on any two whole numbers: gaps of order keys of a supplier, and quantities."""
    key = F.col("l_orderkey") + 1
    rows = S.table(spark, sf_dir, "lineitem").select("l_suppkey", F.col("l_quantity").cast("long").alias("b"), (key - F.lag(key, 1, 0).over(Window.partitionBy("l_suppkey").orderBy("l_orderkey", "l_linenumber")) + 1).alias("a"))
    return rows.groupBy("l_suppkey").agg(F.count("*").alias("n"), F.sum(L.pair_len(F.col("a"), F.col("b"), 1)).alias("bytes_old"), F.sum(L.pair_len(F.col("a"), F.col("b"), 4)).alias("bytes_new"))


def transition_matrix(postings, a: str, b: str, f: int):
    """(old_bytes, new_bytes, n, pct): how many postings of one plain size have which paired size."""
    a, b = F.col(a), F.col(b)
    pairs = postings.groupBy(L.pair_len(a, b, 1).cast("long").alias("old_bytes"), L.pair_len(a, b, f).cast("long").alias("new_bytes")).agg(F.count("*").alias("n"))
    return pairs.withColumn("pct", F.round(100 * F.col("n") / F.sum("n").over(Window.partitionBy()), 6))  # a dozen rows


for _c in ("docs", "baskets"):
    for _level, _source, _a, _b, _f in (("doc", Q.post(_c), "g", "f", 4), ("word", Q.word(_c), "wg", "g1", 3)):

        @register(f"transitions_{_level}_{_c}", f"SELECT {Q.plen(_a, _b, 1)}::BIGINT AS old_bytes, {Q.plen(_a, _b, _f)}::BIGINT AS new_bytes, count(*) AS n, round(100 * count(*) / sum(count(*)) OVER (), 6)::DOUBLE AS pct FROM {_source} GROUP BY 1, 2")
        def _(spark, sf_dir, c=_c, level=_level, a=_a, b=_b, f=_f):
            stream = S.COLLECTIONS[c](spark, sf_dir)
            return transition_matrix(P.postings_doc(stream) if level == "doc" else P.postings_word(stream), a, b, f)


@register("codec_effectiveness", f"SELECT m AS method, round(sum(b) / count(*), 6) AS bytes_per_posting FROM (SELECT unnest(['raw', 'byte', 'paired']) AS m, unnest([8, {Q.plen('g', 'f', 1)}, {Q.plen('g', 'f', 4)}]) AS b FROM {Q.post('docs')}) GROUP BY m")
def codec_effectiveness(spark, sf_dir):
    g, f = F.col("g"), F.col("f")
    row = P.postings_doc(S.docs(spark, sf_dir)).agg(F.count("*").alias("n"), F.sum(L.pair_len(g, f, 1)).alias("byte"), F.sum(L.pair_len(g, f, 4)).alias("paired"))
    return row.select(F.explode(F.array(*[F.struct(F.lit(m).alias("method"), F.round(b / F.col("n"), 6).alias("bytes_per_posting")) for m, b in (("raw", 8 * F.col("n")), ("byte", F.col("byte")), ("paired", F.col("paired")))])).alias("x")).select("x.*")
