"""Growth rules: sizes, overhead curves, and whole indexes under each rule."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from liveindex.functions.lengths import pair_len
from liveindex.operators import growth as G
from liveindex.operators import packer as K
from liveindex.operators import postings as P
from liveindex.registry import register
from liveindex.scratch import written
from liveindex.sources import collections as S
from liveindex.workloads import sqlparts as Q

RULES = ("constant", "geometric", "triangular")


def _sizes(rule: str, unit: int, h: int, blocks: int | None, cap: int = G.CAP // 64 * 64) -> str:
    """Recursive CTE seq_<rule>(blk, size, n): n is the payload up to and with the block. Without a number of blocks, as
    many as the longest list of `pay` needs."""
    step = {"constant": f"{unit}", "geometric": f"greatest({unit}, (({h} * 1000 + 100 * n + {unit * 1000 - 1}) // {unit * 1000}) * {unit})",
            "triangular": f"greatest({unit}, (({h} + ceil(sqrt(2 * {h} * n))::BIGINT + {unit - 1}) // {unit}) * {unit})"}[rule]
    step = f"least({cap // unit * unit}, {step})"
    return f"seq_{rule} AS (SELECT 1::BIGINT AS blk, {unit}::BIGINT AS size, {unit - h}::BIGINT AS n UNION ALL SELECT blk + 1, ({step})::BIGINT, (n + {step} - {h})::BIGINT FROM seq_{rule} WHERE {'n < (SELECT max(n) FROM pay)' if blocks is None else f'blk < {blocks}'})"


_PAY = f"pay AS MATERIALIZED (SELECT n, count(*) AS lists FROM (SELECT term, sum({Q.plen('g', 'f', 4)})::BIGINT AS n FROM {Q.post('docs')} GROUP BY term) GROUP BY n)"


def _payloads(spark, sf_dir):
    """(n, lists): how many lists of `documents` have a payload of n bytes in paired code."""
    lists = P.postings_doc(S.docs(spark, sf_dir)).groupBy("term").agg(F.sum(pair_len(F.col("g"), F.col("f"), 4)).cast("long").alias("n"))
    return written(lists.groupBy("n").agg(F.count("*").alias("lists")), "payloads")


def _longest(payloads) -> int:
    return payloads.agg(F.coalesce(F.max("n"), F.lit(0))).first()[0]


@register("growth_sequence", f"WITH RECURSIVE {_PAY}, " + ", ".join(_sizes(r, 64, 4, None) for r in RULES) + ", x AS (" + " UNION ALL ".join(f"SELECT '{r}' AS rule, blk AS z, size, n AS payload FROM seq_{r}" for r in RULES) + ") SELECT rule, z, size, payload, sum(lists)::BIGINT AS lists FROM x JOIN pay ON pay.n > x.payload - x.size + 4 GROUP BY rule, z, size, payload")
def growth_sequence(spark, sf_dir):
    """The blocks of chains as far as the lists of `documents` reach, and how many lists have each."""
    payloads, out = _payloads(spark, sf_dir), None
    most = _longest(payloads)
    for rule in RULES:
        n, rows = 0, []
        for z, size in enumerate(G.sizes_until(rule, 64, 4, most), 1):
            n += size - 4
            rows.append((rule, z, size, n))
        ends = G.chains(payloads, rule, 64, 4, most).groupBy("z").agg(F.sum("lists").alias("ending"))
        one = spark.createDataFrame(rows, "rule string, z long, size long, payload long").join(ends, "z", "left")
        out = one if out is None else out.unionByName(one)
    longer = Window.partitionBy("rule").orderBy(F.desc("z")).rowsBetween(Window.unboundedPreceding, 0)  # a row a block of the longest list
    return out.select("rule", "z", "size", "payload", F.sum(F.coalesce("ending", F.lit(0))).over(longer).alias("lists"))


@register("overhead_curve", f"WITH RECURSIVE {_PAY}, " + ", ".join(_sizes(r, 16, 1, None, 1 << 40) for r in RULES) + ", x AS (" + " UNION ALL ".join(f"SELECT '{r}' AS rule, blk AS z, n - size + 1 + 1 AS lo_n, n AS hi_n FROM seq_{r}" for r in RULES) + ") SELECT rule, n, lists, z, lo_n, hi_n, z + hi_n - n AS overhead, round((z + hi_n - n) / n, 6) AS ratio FROM pay JOIN x ON n >= lo_n AND n <= hi_n")
def overhead_curve(spark, sf_dir):
    """Links and the unused part of the last block at each payload that lists of `documents` have."""
    payloads, out = _payloads(spark, sf_dir), None
    most = _longest(payloads)
    for rule in RULES:
        over = F.col("z") + F.col("hi_n") - F.col("n")
        one = G.chains(payloads, rule, 16, 1, most, cap=None).select(F.lit(rule).alias("rule"), "n", "lists", "z", "lo_n", "hi_n", over.alias("overhead"), F.round(over / F.col("n"), 6).alias("ratio"))
        out = one if out is None else out.unionAll(one)
    return out


@register("best_block", f"WITH {_PAY} SELECT n, lists, 4::BIGINT AS h, b AS best_b, ceil(n / (b - 4))::BIGINT AS z, 4 * ceil(n / (b - 4))::BIGINT AS link_bytes, (ceil(n / (b - 4)) * (b - 4) - n)::BIGINT AS unused_bytes FROM (SELECT n, lists, greatest(5, ceil(sqrt(8 * n))::BIGINT) AS b FROM pay)")
def best_block(spark, sf_dir):
    """The block size of least overhead for each payload that lists of `documents` have."""
    n = F.col("n")
    rows = _payloads(spark, sf_dir).withColumn("best_b", G.best_block(n, 4))
    z = F.ceil(n / (F.col("best_b") - 4))
    return rows.select("n", "lists", F.lit(4).cast("long").alias("h"), "best_b", z.alias("z"), (4 * z).alias("link_bytes"), (z * (F.col("best_b") - 4) - n).alias("unused_bytes"))


VARIANTS = [(rule, b) for rule in RULES for b in (48, 64)]


def compare(spark, sf_dir, coll: str):
    """All rules and sizes in one pass a level."""
    stream, out = S.COLLECTIONS[coll](spark, sf_dir), None
    for level in ("doc", "word"):
        postings = P.count_terms(stream) if level == "doc" else P.postings_word(stream)
        sums = K.index_sizes(postings, [K.IndexConfig(B=b, level=level, growth=rule) for rule, b in VARIANTS])
        of = lambda k: F.element_at(F.array(*[F.lit(v[k]) for v in VARIANTS]), F.col("variant") + 1)
        row = sums.select(F.lit(level).alias("level"), of(0).alias("rule"), of(1).cast("long").alias("B"), "total_bytes", F.round(F.col("total_bytes") / F.col("postings"), 6).alias("bytes_per_posting"))
        out = row if out is None else out.unionAll(row)
    return out


def _compare_sql(level: str, rule: str, b: int) -> str:
    head = 18 if rule == "constant" else 20
    return (f"(WITH RECURSIVE {_sizes(rule, b, 4, 1000)}, caps AS MATERIALIZED (SELECT blk, size FROM seq_{rule}), {Q.packed('docs', level, unit=str(b), head=head, caps='caps')}, "
            f"t AS (SELECT term, max(blk) AS z FROM pk GROUP BY term) SELECT '{level}' AS level, '{rule}' AS rule, {b}::BIGINT AS B, (sum(c.s) + 8 * count(*))::BIGINT AS total_bytes, round((sum(c.s) + 8 * count(*)) / (SELECT count(*) FROM pk), 6)::DOUBLE AS bytes_per_posting FROM t JOIN (SELECT blk, sum(size) OVER (ORDER BY blk) AS s FROM caps) c ON c.blk = t.z)")


@register("growth_compare", " UNION ALL ".join(_compare_sql(level, rule, b) for level in ("doc", "word") for rule in RULES for b in (48, 64)))
def growth_compare(spark, sf_dir):
    return compare(spark, sf_dir, "docs")


def _folded_sql(coll: str, level: str, rule: str, b: int) -> str:
    sizes = G.sizes(rule, b, 4, 600 if rule != "constant" else 1)
    if rule == "constant":
        return f"(SELECT '{level}' AS level, '{rule}' AS rule, {b}::BIGINT AS B, (sum(z) * {b} + 8 * count(*))::BIGINT AS total_bytes, round((sum(z) * {b} + 8 * count(*)) / sum(n), 6)::DOUBLE AS bytes_per_posting FROM {Q.folded(coll, level, b)})"
    sums = [sum(sizes[:k]) for k in range(1, 257)]
    return (f"(SELECT '{level}' AS level, '{rule}' AS rule, {b}::BIGINT AS B, sum(list_extract({sums}, z) + 8)::BIGINT AS total_bytes, round(sum(list_extract({sums}, z) + 8) / sum(n), 6)::DOUBLE AS bytes_per_posting "
            f"FROM {Q.folded(coll, level, b, sizes[:256], 20)})")


@register("growth_compare_baskets", " UNION ALL ".join(_folded_sql("baskets", level, rule, b) for level in ("doc", "word") for rule, b in VARIANTS))
def growth_compare_baskets(spark, sf_dir):
    """Long lists: here the order of the rules shows."""
    return compare(spark, sf_dir, "baskets")
