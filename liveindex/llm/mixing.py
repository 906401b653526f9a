"""Mixing sources to target weights by entropy balancing, with DataFrame functions only.

Each document of a source gets a rate r between 0 and `most`. Among all rates that give the source its target
number of words, those with the largest entropy relative to one copy each are min(most, exp(a * x)), x being the
document's size over its source's mean size: an exponential tilt, cut at the most copies allowed. The tilts a
are the optimum of a convex dual in one variable a source; Newton steps, kept inside a bracket, solve all of them
together, and each step is one aggregate over the table of (source, size, count). That table and the sources' state
stay on the cluster, whatever the number of sources.

Documents of one source and size share a rate, so how many of them get the copy more is a matter of running sums from
the longest size down; a source's words are off by less than its longest document. Which ones is decided by a hash:
large cells of equal size are dealt into buckets, and only the bucket in which the count runs out has to rank its rows.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from liveindex.llm.common import numbered, saved

WEIGHTS = (5.0, 2.0, 1.0)
#: Documents of one source and size in a bucket, about.
BUCKET_ROWS = 512
#: Columns that the result has, and those at work.
ADDED = ("source_size", "target", "rate", "copies", "_key", "_words", "_row", "_hash", "_bucket", "_part", "_buckets", "_parts", "_low", "_raised", "_before", "_n", "_left")


def source_key(column: str) -> Column:
    """Null apart from every string, and behind all of them."""
    return F.when(F.col(column).isNull(), F.lit("-")).otherwise(F.concat(F.lit("+"), F.col(column).cast("string")))


def targets(sources: DataFrame, weights=WEIGHTS, share: float = 1.5, most: float = 2.0) -> DataFrame:
    """sources(key, words, docs) with target: words wanted of each, `share` of all words by weight, none above `most`
    times what it has, the excess dealt again by weight until none is.

    Sources go by code point, null last; weights repeat in that order."""
    ordered = numbered(sources.withColumn("_last", F.col("key") == "-"), "_last", "key", into="_at").drop("_last")
    cycle = F.array(*[F.lit(float(w)) for w in weights])
    now = saved(ordered.select("key", "words", "docs", F.element_at(cycle, (F.pmod("_at", F.lit(len(weights))) + 1).cast("int")).alias("weight"), F.lit(None).cast("double").alias("target")), "targets")
    wanted = share * (now.agg(F.sum("words")).first()[0] or 0)
    while True:
        taken, weight = now.agg(F.coalesce(F.sum("target"), F.lit(0.0)), F.sum(F.when(F.col("target").isNull(), F.col("weight")))).first()
        if weight is None:
            return now.select("key", "words", "docs", "target")
        goal = F.lit((wanted - taken) / weight) * F.col("weight")
        over = F.col("target").isNull() & (goal > most * F.col("words"))
        if now.where(over).isEmpty():
            return now.select("key", "words", "docs", F.coalesce("target", goal).alias("target"))
        now = saved(now.withColumn("target", F.when(over, most * F.col("words")).otherwise(F.col("target"))), "targets")


def tilts(histogram: DataFrame, goals: DataFrame, most: float, steps: int = 100) -> DataFrame:
    """goals(key, words, docs, target) with tilt: null where each document is taken `most` times.

    histogram: (key, size, n). A Newton step that leaves the bracket, or comes from a flat place, becomes a step of
    growing length as long as the bracket is open on that side, and a halving of it afterwards."""
    free = F.when((F.col("words") > 0) & (F.col("target") < most * F.col("words") * (1 - 1e-12)), 0.0)
    state = saved(goals.select("*", free.alias("tilt"), F.lit(None).cast("double").alias("lo"), F.lit(None).cast("double").alias("hi"), (free.isNull()).alias("done")), "tilts")
    cap = math.log(most)
    for _ in range(steps):
        if state.where(~F.col("done")).isEmpty():
            break
        live = state.where(~F.col("done")).select("key", "tilt", (F.col("words") / F.col("docs")).alias("mean"))
        x = F.col("size") / F.col("mean")
        rate, inner = F.exp(F.least(F.lit(cap), F.col("tilt") * x)), F.col("tilt") * x < cap
        words = F.col("n") * F.col("size") * rate
        sums = histogram.join(live, "key").groupBy("key").agg(F.sum(words).alias("g"), F.sum(F.when(inner, words * x).otherwise(0.0)).alias("h"))
        gap = F.col("g") - F.col("target")
        met = F.abs(gap) <= 1e-9 * F.greatest(F.lit(1.0), F.col("target"))
        lo, hi = F.when(gap > 0, F.col("lo")).otherwise(F.col("tilt")), F.when(gap > 0, F.col("tilt")).otherwise(F.col("hi"))
        far = F.col("tilt") + F.when(gap > 0, -1).otherwise(1) * F.greatest(F.lit(1.0), F.abs("tilt"))
        newton = F.col("tilt") - gap / F.when(F.col("h") > 0, F.col("h"))
        inside = newton.isNotNull() & (lo.isNull() | (newton > lo)) & (hi.isNull() | (newton < hi)) & (F.abs(newton - F.col("tilt")) <= F.greatest(F.lit(4.0), 2 * F.abs("tilt")))
        step = F.when(inside, newton).when(lo.isNotNull() & hi.isNotNull(), (lo + hi) / 2).otherwise(far)
        settled = F.col("done") | F.coalesce(met, F.lit(True))
        new = {"tilt": F.when(settled, F.col("tilt")).otherwise(step), "lo": F.when(settled, F.col("lo")).otherwise(lo), "hi": F.when(settled, F.col("hi")).otherwise(hi), "done": settled}
        state = saved(state.join(sums, "key", "left").select("key", "words", "docs", "target", *[v.alias(k) for k, v in new.items()]), "tilts")
    return state.select("key", "words", "docs", "target", F.round("tilt", 10).alias("tilt"))


def mix_sources(df: DataFrame, source: str = "source", size: str = "size", doc_id: str = "doc_id", weights=WEIGHTS, share: float = 1.5, most: float = 2.0) -> DataFrame:
    """df with source_size, target, rate and copies (0 to `most`, rounded up) of each row.

    size: words of the document, null or negative counts as 0; such rows get one copy, as they weigh nothing.
    Null is a source of its own. Repeated rows are documents of their own, and rows that share doc_id, source and size
    are told apart by their place in the table alone, so df should be a stored table. An empty table gives an empty
    result. Columns of df named like one of ADDED are replaced.
    """
    df = df.drop(*[c for c in df.columns if c.lower() in ADDED and c not in (source, size, doc_id)])
    rows = df.withColumns({"_key": source_key(source), "_words": F.greatest(F.coalesce(F.col(size), F.lit(0)), F.lit(0)).cast("long"), "_row": F.monotonically_increasing_id(), "_hash": F.xxhash64(F.col(doc_id))})
    histogram = saved(rows.groupBy(F.col("_key").alias("key"), F.col("_words").alias("size")).agg(F.count("*").alias("n")), "mixing-sizes")
    sources = saved(histogram.groupBy("key").agg(F.sum(F.col("n") * F.col("size")).alias("words"), F.sum("n").alias("docs")), "mixing-sources")
    solved = tilts(histogram, targets(sources, weights, share, most), most)
    tilted = F.exp(F.least(F.lit(math.log(most)), F.col("tilt") * F.col("size") / (F.col("words") / F.col("docs"))))
    rate = F.when(F.col("size") == 0, 1.0).when(F.col("tilt").isNull(), float(most)).otherwise(tilted)
    low = F.floor(F.col("rate") + 1e-12)
    # Copies beyond the whole ones, summed from a source's longest documents to its shortest, and each size's share of
    # the rounded sum: one row a size, however many documents have it.
    so_far = F.sum(F.col("n") * F.greatest(F.col("rate") - F.col("_low"), F.lit(0.0))).over(Window.partitionBy("key").orderBy(F.desc("size")).rowsBetween(Window.unboundedPreceding, 0))
    cells = histogram.join(solved, "key").withColumn("rate", rate).withColumn("_low", low).withColumn("_sum", F.floor(so_far + 0.5))
    before = F.coalesce(F.lag("_sum").over(Window.partitionBy("key").orderBy(F.desc("size"))), F.lit(0))
    cells = saved(cells.select(F.col("key").alias("_key"), F.col("size").alias("_words"), F.col("words").alias("source_size"), "target", "rate", F.col("_low").cast("long"), F.least("n", F.greatest(F.col("_sum") - before, F.lit(0))).cast("long").alias("_raised"),
                               F.ceil(F.col("n") / BUCKET_ROWS).cast("int").alias("_buckets")), "mixing-cells")
    keys = ["_key", "_words", "_bucket"]
    at = rows.join(cells, ["_key", "_words"]).withColumn("_bucket", F.expr("pmod(_hash, _buckets)").cast("int"))
    undecided = (F.col("_raised") > 0)
    # Buckets far above their share hold repeated documents; parts by row cut those.
    some = saved(at.where(undecided).groupBy(*keys, "_raised").agg(F.count("*").alias("_n")), "mixing-buckets")
    heavy = some.where(F.col("_n") > 8 * BUCKET_ROWS).select(*keys, F.ceil(F.col("_n") / BUCKET_ROWS).cast("int").alias("_parts"))
    split = not heavy.isEmpty()
    if split:
        at = at.join(heavy, keys, "left").withColumn("_part", F.coalesce(F.expr("pmod(xxhash64(_row), _parts)"), F.lit(0)).cast("int")).drop("_parts")
        some = saved(at.where(undecided).groupBy(*keys, "_part", "_raised").agg(F.count("*").alias("_n")), "mixing-buckets")
    else:
        at, some = at.withColumn("_part", F.lit(0)), some.withColumn("_part", F.lit(0))
    keys = [*keys, "_part"]
    ahead = Window.partitionBy("_key", "_words").orderBy("_bucket", "_part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = saved(some.select(*keys, "_n", F.coalesce(F.sum("_n").over(ahead), F.lit(0)).alias("_before")), "mixing-offsets")
    at = at.join(offsets, keys, "left").withColumn("_left", F.col("_raised") - F.coalesce("_before", F.lit(0)))
    ranking = (F.col("_left") > 0) & (F.col("_left") < F.coalesce("_n", F.lit(0)))
    plain = at.where(~ranking).withColumn("copies", F.col("_low") + F.when(F.col("_left") > 0, 1).otherwise(0))
    place = F.row_number().over(Window.partitionBy(*keys).orderBy("_hash", "_row"))
    ranked = at.where(ranking).withColumn("copies", F.col("_low") + F.when(place <= F.col("_left"), 1).otherwise(0))
    names = [F.col(f"`{c}`") for c in df.columns] + ["source_size", "target", "rate", F.col("copies").cast("long").alias("copies")]
    return plain.select(*names).unionAll(ranked.select(*names))
