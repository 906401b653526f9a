"""Sharding by sampled splitters, with DataFrame functions only.

A size-weighted sample of the record keys gives quantile boundaries; records go to the key range they fall in; ranges
that turn out overfull are subdivided by a sample of their own; exact byte totals of the ranges then fix where each
shard begins, and running sums inside a range place its records. The samples decide the balance of the tasks, not
the result.

The key is (hash, tie, row): equal texts share the hash and lie together, their doc_id keeps them apart, and rows that
share both are told apart by their place in the table, so that a text or a missing doc_id held by a third of all rows
is cut by splitters like any other range.

Records above a stated share of a shard, of which there can be no more than that share allows, are dealt first,
largest to emptiest shard; the others then fill each shard to the same level. So shards differ by one small record.
"""

from __future__ import annotations

import heapq

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from liveindex.llm.common import saved

#: Sampled keys per range, and most ranges of a round: what the driver sees is bounded by their product.
SAMPLES_A_RANGE, MOST_RANGES = 24, 4096
#: A range is overfull above so many times the mean, in bytes or rows; rounds of subdividing.
OVERFULL, ROUNDS = 4, 4
#: Records of more than 1 / LARGE of a shard's bytes are dealt one by one: LARGE * shards at most.
LARGE = 64
_LEAST = -(1 << 63)
KEY = ("_hash", "_tie", "_row")
WORK = (*KEY, "size", "shard", "slot", "_range", "_bytes0", "_rows0", "_before", "_rank", "_first", "_shard", "_n", "_b")


def byte_size(text: str) -> Column:
    return (F.coalesce(F.octet_length(F.col(text)), F.lit(0)) + 1).cast("long")


def _longs(values: list[int]) -> Column:
    return F.split(F.lit(",".join(map(str, values))), ",").cast("array<bigint>")


def _draw(salt: int) -> Column:
    """A number in [0, 1) that depends on the record's key alone, so that a rerun draws the same."""
    return F.xxhash64(F.lit(salt), *KEY).bitwiseAND(F.lit((1 << 53) - 1)) / F.lit(float(1 << 53))


def splitters(df: DataFrame, ranges: int, total: int, salt: int = 77) -> list[tuple[int, int, int]]:
    """Boundaries of about equal bytes from a sample in which a record's chance is proportional to its size."""
    want = SAMPLES_A_RANGE * ranges
    chance = F.col("size") * F.lit(want / max(total, 1))
    drawn = sorted(map(tuple, df.where(_draw(salt) < chance).select(*KEY).limit(8 * want).collect()))
    return sorted({drawn[len(drawn) * k // ranges] for k in range(1, ranges)}) if drawn else []


def range_of(cuts: list[tuple[int, int, int]]) -> Column:
    """How many boundaries are at or below the key: binary search in a higher-order function."""
    if not cuts:
        return F.lit(0)
    parts = [_longs([c[k] for c in cuts]) for k in range(3)]
    steps = [1 << k for k in range(len(cuts).bit_length() - 1, -1, -1)]

    def step(p: Column, s: Column) -> Column:
        q = p + s
        a, b, c = (F.try_element_at(part, q) for part in parts)
        below = (a < F.col("_hash")) | ((a == F.col("_hash")) & ((b < F.col("_tie")) | ((b == F.col("_tie")) & (c <= F.col("_row")))))
        return F.when((q <= F.lit(len(cuts))) & below, q).otherwise(p)

    return F.aggregate(F.array(*map(F.lit, steps)), F.lit(0), step)


def keyed(df: DataFrame, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """df with the sort key and the size. Columns named like one at work here (WORK) must not be in df, but for text and
    doc_id; `shard_by_bytes` packs a table that has some."""
    return df.withColumns({"_hash": F.xxhash64(F.col(text)), "_tie": F.coalesce(F.col(doc_id).cast("long"), F.lit(_LEAST)), "_row": F.monotonically_increasing_id(), "size": byte_size(text)})


def _cut(rows: DataFrame, parts: int, shards: int, total: int) -> list[tuple[int, int, int]]:
    """Boundaries of ranges, none of which is overfull if the sample of the last round can help it."""
    ranges = min(MOST_RANGES, max(8 * shards, 4 * parts))
    cuts = splitters(rows, ranges, total)
    for k in range(ROUNDS):
        ranged = rows.withColumn("_range", range_of(cuts))
        sums = ranged.groupBy("_range").agg(F.sum("size").alias("b"), F.count("*").alias("n"))
        every = sums.agg(F.sum("b").alias("b"), F.sum("n").alias("n")).first()
        if every["n"] is None:
            return cuts
        full = sums.where((F.col("n") > 1) & ((F.col("b") > OVERFULL * every["b"] / ranges) | (F.col("n") > OVERFULL * max(1.0, every["n"] / ranges)))).limit(MOST_RANGES).collect()
        if not full:
            return cuts
        over = ranged.where(F.col("_range").isin([r["_range"] for r in full]))
        more = sorted({x for x in splitters(over.withColumn("size", F.lit(1).cast("long")), min(MOST_RANGES, 2 * OVERFULL * len(full)), sum(r["n"] for r in full), 78 + k)} - set(cuts))
        if not more:
            return cuts
        cuts = sorted({*cuts, *more})
    return cuts


def _deal(large: list[tuple], shards: int, total: int) -> tuple[list[list], list[int]]:
    """Shard and slot of each large record, largest first to the emptiest shard, and the bytes each shard lacks."""
    loads = [(0, s, 0) for s in range(shards)]
    placed = []
    for *key, size in sorted(large, key=lambda r: (-r[-1], *r[:-1])):
        held, s, n = heapq.heappop(loads)
        placed.append([*key, s, n])
        heapq.heappush(loads, (held + size, s, n + 1))
    held = [h for h, _, _ in sorted(loads, key=lambda x: x[1])]
    left = total - sum(held)
    # Level the shards up: those above the level get nothing, the others what they lack of it.
    level, open_ = 0.0, sorted(held)
    for k in range(shards):
        level = (left + sum(open_[: k + 1])) / (k + 1)
        if k + 1 == shards or level <= open_[k + 1]:
            break
    room = [max(0, int(level) - h) for h in held]
    ends, at = [], 0
    for s in range(shards):
        at += room[s]
        ends.append(at)
    return placed, ends


def shard_by_bytes(df: DataFrame, text: str = "text", doc_id: str = "doc_id", shards: int = 16, digest: DataFrame | None = None) -> DataFrame:
    """df with size, shard (0 to shards - 1) and slot (0, 1, .. inside each shard).

    A record's size is its UTF-8 bytes plus one; null text has size 1. Repeated rows count each and get a slot
    each; an empty table gives an empty result. Columns of df named size, shard or slot are replaced by the result's,
    all others are carried unchanged, whatever their names. df must be a stored table: rows that share text and
    doc_id are told apart by their place in it, which other plans may change from one use to the next.

    digest: df already reduced to the key and size by `keyed`, if the caller has it at hand.
    """
    if digest is None:
        given = [c for c in df.columns if c.lower() not in ("size", "shard", "slot")]
        packed = df.select(F.struct(*[F.col(f"`{c}`") for c in given]).alias("_given"), F.col(f"`{text}`").alias("_text"), F.col(f"`{doc_id}`").alias("_id"))
        out = shard_by_bytes(df, digest=keyed(packed, "_text", "_id"), shards=shards)
        return out.select(*[F.col(f"_given.`{c}`").alias(c) for c in given], "size", "shard", "slot")
    rows = digest
    facts = rows.agg(F.coalesce(F.sum("size"), F.lit(0)).alias("b"), F.count("*").alias("n")).first()
    total, spark = facts["b"], df.sparkSession
    is_large = F.col("size") > F.lit(total // (LARGE * shards))
    large = [tuple(r) for r in rows.where(is_large).select(*KEY, "size").collect()]  # LARGE * shards at most
    placed, ends = _deal(large, shards, total)
    given = spark.createDataFrame(placed, "_hash long, _tie long, _row long, shard int, slot long")
    dealt = spark.createDataFrame([(s, sum(1 for p in placed if p[3] == s)) for s in range(shards)], "shard int, _first long")
    small = rows.where(~is_large)
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    cuts = _cut(small, parts, shards, max(1, ends[-1]))
    ranged = small.withColumn("_range", range_of(cuts))
    sums = saved(ranged.groupBy("_range").agg(F.sum("size").alias("_b"), F.count("*").alias("_n")), "shard-ranges")
    # One row a range: a running sum over them fits one task and the result one broadcast.
    ahead = Window.orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)
    begins = sums.select("_range", F.coalesce(F.sum("_b").over(ahead), F.lit(0)).alias("_bytes0"), F.coalesce(F.sum("_n").over(ahead), F.lit(0)).alias("_rows0"))
    inside = Window.partitionBy("_range").orderBy(*KEY).rowsBetween(Window.unboundedPreceding, 0)

    def at(of: DataFrame) -> DataFrame:
        joined = of.join(F.broadcast(begins), "_range")
        joined = joined.withColumn("_before", F.col("_bytes0") + F.sum("size").over(inside) - F.col("size")).withColumn("_rank", F.col("_rows0") + F.row_number().over(inside) - 1)
        # A record lies in the shard that holds its middle byte: a border moves to the nearer side.
        full = F.size(F.filter(_longs(ends), lambda e: 2 * e <= 2 * F.col("_before") + F.col("size")))
        return joined.withColumn("shard", F.least(F.lit(shards - 1), full).cast("int"))

    heads = at(ranged.select(*KEY, "size", "_range")).groupBy("shard").agg(F.min("_rank").alias("_rank0")).join(dealt, "shard").select("shard", (F.col("_rank0") - F.col("_first")).alias("_first"))
    kept = [F.col(f"`{c}`") for c in rows.columns if c not in KEY]
    out = at(ranged).join(F.broadcast(heads), "shard").withColumn("slot", (F.col("_rank") - F.col("_first")).cast("long"))
    return out.select(*kept, "shard", "slot").unionAll(rows.where(is_large).join(F.broadcast(given), list(KEY)).select(*kept, "shard", "slot"))
