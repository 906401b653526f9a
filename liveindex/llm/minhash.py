"""Near-duplicates by SuperMinHash signatures, banding, verification on full sets, and union-find.

A signature has MINIMA places. Each shingle visits them in an order of its own, a random permutation, and offers
step + fraction at the place of each step; a place keeps the least offer. Offers grow with the step, so a text is
done once the step passes its largest minimum: a text of many shingles needs two or three steps.

Texts with equal sets collapse first. Bands of equal signature rows put the others into buckets. A bucket is never
turned into its pairs: its members are checked against one centre, and the links found give components. In buckets
that hold several components, a text that shares too few shingles with all others there is done; the rest are
checked against the member with most in common; and those still outside the largest component are held, block by
block, against all members of the buckets. So a pair of a bucket stays unchecked only if both already belong
together or no link between them is possible.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from liveindex.llm import common as C
from liveindex.llm.graphs import components

#: A pair of similarity 0.8 misses all 20 bands of 4 rows with a probability of (1 - 0.8^4)^20 < 0.00003.
BANDS, ROWS = 20, 4
MINIMA = BANDS * ROWS
_CHUNK = 1 << 17


def shingle_sets(texts: pa.Array, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingle hashes of all texts, text after text, and where each text's begin.

    Words are lower-cased (A-Z). A text of fewer words than `width` has its whole sequence as one shingle; one
    without words, or null, has none."""
    raw, off = C.flat(texts)
    raw = C.LOWER[raw]
    starts, ends, first = C.spans(C.IS_WORD[raw], off)
    words = C.span_hashes(raw, starts, ends)
    found, at = C.grams(words, first, width)
    doc = C.owner(first)[at] if at.size else np.zeros(0, np.int64)
    count = np.diff(first)
    short = np.flatnonzero((count > 0) & (count < width))
    if short.size:
        whole = np.array([C.mix(np.sum(words[a:b] * C._GRAM[: b - a], dtype=np.uint64, keepdims=True) + np.uint64(b - a))[0] for a, b in zip(first[short], first[short + 1], strict=True)], np.uint64)
        found, doc = np.concatenate((found, whole)), np.concatenate((doc, short))
    order = np.lexsort((found, doc))
    found, doc = found[order], doc[order]
    keep = np.ones(found.size, bool)
    keep[1:] = (found[1:] != found[:-1]) | (doc[1:] != doc[:-1])
    found, doc = found[keep], doc[keep]
    return found, np.searchsorted(doc, np.arange(len(texts) + 1))


def signatures(shingles: np.ndarray, first: np.ndarray, minima: int = MINIMA) -> np.ndarray:
    """SuperMinHash: one row of `minima` numbers for each text; texts without shingles keep the largest number."""
    texts = len(first) - 1
    out = np.full((texts, minima), np.uint64((1 << 64) - 1))
    at = 0
    while at < texts:
        end = max(at + 1, int(np.searchsorted(first, first[at] + _CHUNK, side="right")) - 1)
        _sign(shingles[first[at] : first[end]], first[at : end + 1] - first[at], out[at:end], minima)
        at = end
    return out


def _sign(shingles: np.ndarray, first: np.ndarray, out: np.ndarray, minima: int) -> None:
    doc = C.owner(first)
    who = np.arange(shingles.size)  # shingles of texts that are not done
    orders = np.broadcast_to(np.arange(minima, dtype=np.uint8), (shingles.size, minima)).copy()
    for step in range(minima):
        if not who.size:
            return
        drawn = C.mix(shingles[who] + np.uint64((0x9E3779B97F4A7C15 * (step + 1)) & ((1 << 64) - 1)))
        swap = step + ((drawn & np.uint64(0xFFFFFF)) * np.uint64(minima - step) >> np.uint64(24)).astype(np.int64)
        place = orders[who, swap]
        orders[who, swap] = orders[who, step]
        orders[who, step] = place
        offer = (np.uint64(step) << np.uint64(40)) | (drawn >> np.uint64(24))
        d = doc[who]
        np.minimum.at(out.reshape(-1), d * minima + place, offer)
        most = out.max(1) >> np.uint64(40)
        who = who[(most > step)[d]]


def _set_keys(shingles: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """128 bits that name a set: two sums over its members."""
    both = []
    for salt in (0x2545F4914F6CDD1D, 0x9E6C63D0876A9A47):
        run = np.zeros(shingles.size + 1, np.uint64)
        np.cumsum(C.mix(shingles ^ np.uint64(salt)), out=run[1:])
        both.append(C.signed(C.mix(run[first[1:]] - run[first[:-1]] + np.uint64(salt))))
    return both[0], both[1]


SIGNED = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("n_shingles", T.LongType()), T.StructField("set_a", T.LongType()), T.StructField("set_b", T.LongType()), T.StructField("bands", T.ArrayType(T.LongType()))])


def _signed(width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in C.pieces(batch, "text"):
                found, first = shingle_sets(part.column("text"), width)
                rows = signatures(found, first).reshape(-1, BANDS, ROWS)
                key = np.zeros(rows.shape[:2], np.uint64) + np.arange(1, BANDS + 1, dtype=np.uint64)
                for k in range(ROWS):
                    key = C.mix(key * np.uint64(0x9E3779B97F4A7C15) + rows[:, :, k])
                n = np.diff(first)
                sizes = np.where(n > 0, BANDS, 0)
                bands = pa.ListArray.from_arrays(pa.array(np.concatenate(([0], np.cumsum(sizes))), pa.int32()), pa.array(C.signed(np.ascontiguousarray(key[n > 0]).reshape(-1))))
                a, b = _set_keys(found, first)
                yield pa.RecordBatch.from_arrays([part.column("doc_id").cast(pa.int64()), pa.array(n.astype(np.int64)), pa.array(a), pa.array(b), bands], names=SIGNED.names)

    return run


def _sets(width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in C.pieces(batch, "text"):
                found, first = shingle_sets(part.column("text"), width)
                members = pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(first) - 1, [None, pa.py_buffer((first * 8).astype(np.int64).tobytes()), pa.py_buffer(found.tobytes())])
                yield pa.RecordBatch.from_arrays([part.column("doc_id").cast(pa.int64()), members.cast(pa.binary())], names=["doc_id", "members"])

    return run


def _verified(percent: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            left, right = batch.column("left"), batch.column("right")
            linked = np.zeros(batch.num_rows, bool)
            for i in range(batch.num_rows):
                x, one = (np.frombuffer(side[i].as_buffer(), np.uint64) for side in (left, right))
                if 100 * min(x.size, one.size) < percent * max(x.size, one.size):
                    continue
                both = np.sort(np.concatenate((x, one)))
                common = int(np.count_nonzero(both[1:] == both[:-1]))
                linked[i] = 100 * common >= percent * (x.size + one.size - common)
            yield pa.RecordBatch.from_arrays([batch.column("a"), batch.column("b"), pa.array(linked)], names=["a", "b", "linked"])

    return run


def _check(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """pairs(a, b) with `linked`, decided on full sets."""
    full = (pairs.join(sets.select(F.col("doc_id").alias("a"), F.col("members").alias("left")), "a")
            .join(sets.select(F.col("doc_id").alias("b"), F.col("members").alias("right")), "b").select("a", "b", "left", "right"))
    return full.mapInArrow(_verified(percent), "a long, b long, linked boolean")


def _still_split(at: DataFrame) -> DataFrame:
    """Rows of the buckets whose members are of more than one component; those buckets go to the rows if they are few."""
    parts = C.saved(at.groupBy("bucket").agg(F.min("component").alias("x"), F.max("component").alias("y")).where("x <> y").select("bucket"), "split-names")
    return at.join(F.broadcast(parts) if parts.limit(MOST_HOT + 1).count() <= MOST_HOT else parts, "bucket", "left_semi")


def _split(members: DataFrame, labels: DataFrame) -> DataFrame:
    at = members.select("bucket", "node").join(labels, "node", "left").select("bucket", "node", F.coalesce("component", "node").alias("component"))
    return C.saved(_still_split(at), "split-buckets")


def _exploded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        members = batch.column("members")
        sizes = np.array([len(m.as_buffer()) // 8 for m in members], np.int64)
        data = np.frombuffer(b"".join(m.as_buffer() for m in members), np.int64)
        for low in range(0, data.size, 1 << 18):
            high = min(low + (1 << 18), data.size)
            row = np.searchsorted(np.cumsum(sizes), np.arange(low, high), side="right")
            yield pa.RecordBatch.from_arrays([batch.column("doc_id").take(pa.array(row)), pa.array(data[low:high])], names=["node", "shingle"])


def _common(split: DataFrame, sets: DataFrame) -> DataFrame:
    """(node, n, common) of the nodes of split: size of the set, and how many of it any other of the nodes holds too."""
    some = sets.join(split.select(F.col("node").alias("doc_id")).distinct(), "doc_id", "left_semi")
    held = some.mapInArrow(_exploded, "node long, shingle long")
    alone = held.groupBy("shingle").agg(F.min("node").alias("node"), F.max("node").alias("last")).where("node = last").groupBy("node").agg(F.count("*").alias("own"))
    # Versions of one document have their sets taken together here, which can only raise what they have in common.
    sizes = some.groupBy(F.col("doc_id").alias("node")).agg(F.min(F.length("members") / 8).cast("long").alias("n"))
    return sizes.join(alone, "node", "left").select("node", "n", (F.col("n") - F.coalesce("own", F.lit(0))).alias("common"))


#: Members and bytes of a block, about.
BLOCK_MEMBERS, BLOCK_BYTES = 256, 1 << 20


def _overlaps(left: list[np.ndarray], right: list[np.ndarray]) -> np.ndarray:
    """Sizes of the intersections of all sets of one block with all of another, by products of 0-1 matrices over
    the members that both blocks have, some thousand at a time."""
    x, y = np.concatenate(left), np.concatenate(right)
    xi, yi = np.repeat(np.arange(len(left)), [s.size for s in left]), np.repeat(np.arange(len(right)), [s.size for s in right])
    both = np.intersect1d(x, y)
    out = np.zeros((len(left), len(right)), np.float32)
    for low in range(0, both.size, 4096):
        some = both[low : low + 4096]
        sides = []
        for values, rows, n in ((x, xi, len(left)), (y, yi, len(right))):
            at = np.minimum(np.searchsorted(some, values), some.size - 1)
            hit = some[at] == values
            side = np.zeros((n, some.size), np.float32)
            side[rows[hit], at[hit]] = 1
            sides.append(side)
        out += sides[0] @ sides[1].T
    return out.astype(np.int64)


def _blocks_checked(percent: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(batch.num_rows):
                sides = [batch.column(c)[k].values for c in ("minor", "member")]
                names = [s.field("node").to_numpy() for s in sides]
                sets = [[np.frombuffer(m.as_buffer(), np.uint64) for m in s.field("members")] for s in sides]
                sizes = [np.array([m.size for m in s]) for s in sets]
                common = _overlaps(*sets)
                linked = 100 * common >= percent * (sizes[0][:, None] + sizes[1][None] - common)
                i, j = np.nonzero(linked & (names[0][:, None] != names[1][None]))
                yield pa.RecordBatch.from_arrays([pa.array(np.maximum(names[0][i], names[1][j])), pa.array(np.minimum(names[0][i], names[1][j])), pa.array(np.ones(i.size, bool))], names=["a", "b", "linked"])

    return run


def _in_blocks(split: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Links between texts outside a bucket's largest component and all others of the buckets with that component.

    Both go into blocks of bounded size; a pair of blocks is one row, and only links leave it. Linked texts have sizes
    within `percent` of each other, so blocks are of one class of sizes and meet those of their own and the classes
    beside it only."""
    spark = split.sparkSession
    sizes = split.groupBy("bucket", "component").count()
    largest = sizes.groupBy("bucket").agg(F.max_by("component", F.struct("count", "component")).alias("largest"))
    step = float(np.log(100 / percent)) if percent < 100 else 1.0
    seen = split.join(largest, "bucket").groupBy("largest", "node").agg(F.max(F.col("component") != F.col("largest")).alias("minor"), F.first("n").alias("n"))
    seen = C.saved(seen.withColumn("class", F.floor(F.log("n") / step - 1e-9)), "split-members")
    group = ["largest", "class"]
    shape = seen.groupBy(*group).agg(F.ceil(F.greatest(F.count("*") / BLOCK_MEMBERS, F.sum("n") * 8 / BLOCK_BYTES)).alias("all"), F.ceil(F.greatest(F.count_if("minor") / BLOCK_MEMBERS, F.sum(F.when(F.col("minor"), F.col("n")).otherwise(0)) * 8 / BLOCK_BYTES)).alias("few"))
    full = C.saved(seen.join(sets.select(F.col("doc_id").alias("node"), "members"), "node").join(shape, group), "split-sets")
    # A row holds two blocks, so an Arrow batch takes few; a session of its own has that setting.
    other = spark.newSession()
    other.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "4")
    there = other.read.schema(full.schema).parquet(full.scratch_path)
    item = F.struct("node", "members")

    def blocks(of: DataFrame, count: str, name: str) -> DataFrame:
        return of.groupBy(*group, F.pmod(F.xxhash64("node"), F.col(count)).alias(name + "_block")).agg(F.collect_list(item).alias(name))

    minor = blocks(there.where("minor"), "few", "minor").withColumn("class", F.explode(F.array(*[F.col("class") + k for k in (-1, 0, 1)])))
    met = minor.join(blocks(there, "all", "member"), group).select("minor", "member")
    found = C.saved(met.mapInArrow(_blocks_checked(percent), "a long, b long, linked boolean"), "checked")
    out = spark.read.schema(found.schema).parquet(found.scratch_path)
    out.scratch_path = found.scratch_path
    return out


#: Members of a bucket that is spread over tasks, and most such buckets that are sent to all of them.
HOT, MOST_HOT = 512, 200_000


def _members(banded: DataFrame, shared: DataFrame) -> DataFrame:
    """banded(node, bucket) with the centre of each bucket that several nodes are in. Rows of large buckets stay where
    they are and meet a broadcast of those buckets, counted first; the others are joined by bucket."""
    hot = shared.where(F.col("members") > HOT).select("bucket", "centre")
    some = hot.limit(MOST_HOT + 1).count()
    if not 0 < some <= MOST_HOT:  # more than that means large buckets by the thousands, which the join spreads by itself
        return banded.join(shared.select("bucket", "centre"), "bucket")
    few = banded.join(F.broadcast(hot), "bucket")
    rest = banded.join(F.broadcast(hot.select("bucket")), "bucket", "left_anti").join(shared.where(F.col("members") <= HOT).select("bucket", "centre"), "bucket")
    return few.unionByName(rest)


def near_duplicates(df: DataFrame, text: str = "text", doc_id: str = "doc_id", width: int = 5, percent: int = 80) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) for each row of df.

    Documents are linked if 100 * |intersection| >= percent * |union| of their sets of distinct shingles of `width`
    lower-cased words; component_id is the smallest doc_id that links reach, and only that document is kept.
    Null, empty and blank texts have no shingles: they are linked with nothing and kept. Rows of one doc_id are
    taken as versions of one document, linked if any version is; rows without doc_id are kept and have a null
    component. An empty table gives an empty result; other columns of df play no part.
    """
    rows = C.narrow(df, doc_id=doc_id, text=text)
    signed = C.saved(rows.mapInArrow(_signed(width), SIGNED), "signatures")
    named = signed.where("doc_id is not null and n_shingles > 0")
    distinct = C.saved(named.groupBy("set_a", "set_b").agg(F.min("doc_id").alias("node"), F.first("bands").alias("bands")), "distinct-sets")
    banded = distinct.select("node", F.explode("bands").alias("bucket"))
    shared = C.saved(banded.groupBy("bucket").agg(F.min("node").alias("centre"), F.count("*").alias("members")).where("members > 1"), "shared-buckets")
    members = C.saved(_members(banded, shared), "buckets")
    wanted = members.select(F.col("node").alias("doc_id")).distinct()
    sets = C.saved(rows.join(wanted, "doc_id", "left_semi").mapInArrow(_sets(width), "doc_id long, members binary"), "shingle-sets")
    # A document that repeats its doc_id with another text has several sets, each of which counts.
    links = C.saved(_check(members.where("node > centre").select(F.col("node").alias("a"), F.col("centre").alias("b")).distinct(), sets, percent), "checked")
    versions = named.groupBy("doc_id").agg(F.min("set_a").alias("x"), F.max("set_a").alias("y")).where("x <> y").isEmpty()
    same = None if versions else distinct.join(named.select("doc_id", "set_a", "set_b"), ["set_a", "set_b"]).where("node <> doc_id").select(F.col("node").alias("a"), F.col("doc_id").alias("b")).distinct()

    def found() -> DataFrame:
        pairs = links.where("linked").select("a", "b")
        return components(pairs if same is None else pairs.union(same))

    labels = found()
    split = _split(members, labels)
    if not split.isEmpty():
        # A linked pair shares percent of either set, so a text with fewer shingles in common with all others of
        # such buckets than that has no link there.
        common = _common(split, sets)
        able = common.where(100 * F.col("common") >= percent * F.col("n"))
        split = C.saved(_still_split(split.join(able, "node")), "split-buckets")
    if not split.isEmpty():
        # The member with the least of its own is the likeliest to link with any other.
        centre = split.groupBy("bucket").agg(F.max_by(F.struct(F.col("node").alias("b"), F.col("component").alias("cb"), F.col("n").alias("nb"), F.col("common").alias("sb")), F.struct(F.col("common") / F.col("n"), -F.col("node"))).alias("x")).select("bucket", "x.*")
        enough = (100 + percent) * F.least("common", "sb") >= percent * (F.col("n") + F.col("nb"))
        pairs = split.join(centre, "bucket").where((F.col("component") != F.col("cb")) & enough).select(F.greatest("node", "b").alias("a"), F.least("node", "b").alias("b")).distinct()
        links = links.unionAll(C.saved(_check(pairs.join(links.select("a", "b"), ["a", "b"], "left_anti"), sets, percent), "checked"))
        labels = found()
        split = C.saved(_still_split(split.drop("component").join(labels, "node", "left").withColumn("component", F.coalesce("component", "node"))), "split-buckets")
    if not split.isEmpty():
        links = links.unionAll(_in_blocks(split, sets, percent))
        labels = found()
    classes = distinct.join(labels, "node", "left").select("set_a", "set_b", F.coalesce("component", "node").alias("component"))
    out = signed.join(classes, ["set_a", "set_b"], "left")
    component = F.when(F.col("n_shingles") > 0, F.when(F.col("doc_id").isNotNull(), F.col("component"))).otherwise(F.col("doc_id"))
    out = out.select("doc_id", "n_shingles", component.alias("component_id"))
    return out.withColumn("kept", F.coalesce(F.col("component_id") == F.col("doc_id"), F.lit(True)))
