"""Greedy packing of postings lists into chains of blocks, and decoding.

A block is a row: its place in the chain, its capacity, the first and last document in it, and its payload. The
head's payload is what its vocabulary entry leaves; other blocks lose a link. A posting that does not fit opens the
next block, where its gap counts from the first document of the block before, so that a search may skip from
block to block by first documents alone. An empty head counts as starting at document 0.

Lists are packed side by side: round z closes the z-th block of every list of a chunk, by binary search in the
running sum of code lengths, as only the first code of a block is unlike its plain one.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from liveindex.functions import codecs
from liveindex.functions.lengths import DOC_F, WORD_F, pair_len
from liveindex.operators import growth as rules

#: Bytes of a head apart from term and payload: links, last document, counts, offsets. Variable sizes take two more.
HEAD_BYTES, VARIABLE_BYTES = 18, 2
_CHUNK = 200_000


@dataclass(frozen=True)
class IndexConfig:
    """B, h and the growth rule of chains; F of the paired code; documents of a shard."""

    B: int = 64
    h: int = 4
    level: str = "doc"
    F: int | None = None
    growth: str = "constant"
    k: float = 1.1
    cap: int = rules.CAP
    shard_docs: int = 1 << 20
    payload: bool = True

    def __post_init__(self) -> None:
        if self.B < 40 or self.h < 1 or self.level not in ("doc", "word") or self.growth not in rules.RULES or self.threshold < 1:
            raise ValueError(f"not an index: {self}")

    @property
    def threshold(self) -> int:
        return self.F if self.F is not None else DOC_F if self.level == "doc" else WORD_F

    def shard_of(self, d: str) -> Column:
        return F.floor((F.col(d) - 1) / self.shard_docs)

    @property
    def head_bytes(self) -> int:
        return HEAD_BYTES + (0 if self.growth == "constant" else VARIABLE_BYTES)


BLOCKS = "shard long, term string, block_no long, kind string, cap long, first_d long, last_d long, n long, used long, most long, payload binary"
_NAMES = [c.split()[0] for c in BLOCKS.split(", ")]
KINDS = np.array(["head", "full", "tail"])
#: A variable chain counts its blocks in one byte: beyond this many they keep the size of the last counted one.
MOST_VARIABLE = 256


def _code(cfg: IndexConfig, gap: np.ndarray, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The pair that says a posting: rare large values second."""
    return (gap, x) if cfg.level == "doc" else (x, gap + 1)


class Chains:
    """Where lists stand before postings are added: the open block of each, block 1 and empty for a new list.

    z: its number; used, n: its bytes and postings; first: its first document, 0 if empty; last: the list's last document."""

    def __init__(self, lists: int) -> None:
        self.z = np.ones(lists, np.int64)
        self.used, self.n, self.first, self.last, self.most = (np.zeros(lists, np.int64) for _ in range(5))
        self.payload: list[bytes] | None = None


class _Sizes:
    """Sizes of a chain's blocks by number, made as far as asked for."""

    def __init__(self, cfg: IndexConfig) -> None:
        self.cfg, self.made, self.payload, self.last = cfg, np.zeros(0, np.int64), 0, cfg.B

    def of(self, z: np.ndarray) -> np.ndarray:
        cfg, more = self.cfg, int(z.max(initial=0)) - self.made.size
        if more > 0:
            out, most = [], cfg.cap // cfg.B * cfg.B
            for k in range(self.made.size + 1, self.made.size + max(more, 64) + 1):
                if cfg.growth == "constant" or k <= MOST_VARIABLE:
                    self.last = min(most, rules.next_size(cfg.growth, cfg.B, cfg.h, self.payload, cfg.k))
                out.append(self.last)
                size = self.last
                self.payload += size - cfg.h
            self.made = np.concatenate((self.made, np.array(out, np.int64)))
        return self.made[z - 1]


def pack(first: np.ndarray, letters: np.ndarray, d: np.ndarray, x: np.ndarray, cfg: IndexConfig, at_first: Chains | None = None) -> dict[str, np.ndarray]:
    """Blocks that adding postings to several lists makes or changes.

    first: where each list's postings begin, and one more; letters: bytes of its term; at_first: where the lists stand.
    A posting goes into the open block if its code fits; else it opens the next, where its gap counts from the first
    document of the block before. Returns list, block_no, cap, start, end (postings added), base (document that the
    first added gap counts from), used (bytes added), fresh (whether the block had nothing before)."""
    lists = len(first) - 1
    old = at_first or Chains(lists)
    before = np.concatenate(([0], d[:-1])) if d.size else d
    before[first[:-1]] = old.last
    gap = d - before
    lens = codecs.pair_lens(*_code(cfg, gap, x), cfg.threshold)
    run = np.concatenate(([0], np.cumsum(lens)))
    found: dict[str, list[np.ndarray]] = {k: [] for k in ("list", "block_no", "cap", "start", "end", "base", "used", "fresh")}
    sizes = _Sizes(cfg)
    who, at, base, z = np.arange(lists), first[:-1].copy(), old.last.copy(), old.z.copy()
    opening = True
    while who.size:
        cap = sizes.of(z) - np.where(z == 1, cfg.head_bytes + letters[who], cfg.h)
        room = cap - (old.used if opening else 0)
        one = codecs.pair_lens(*_code(cfg, d[at] - base, x[at]), cfg.threshold)
        end = np.minimum(np.searchsorted(run, run[at + 1] + room - one, side="right") - 1, first[who + 1])
        none = one > room
        end = np.where(none, at, end)
        used = np.where(none, 0, one + run[end] - run[np.minimum(at + 1, run.size - 1)])
        held = old.n > 0 if opening else np.zeros(who.size, bool)
        for name, value in (("list", who), ("block_no", z), ("cap", cap), ("start", at), ("end", end), ("base", base), ("used", used), ("fresh", ~held)):
            found[name].append(value)
        head = np.where(none, 0, d[at])
        base = np.where(held, old.first, head) if opening else head
        more = end < first[who + 1]
        who, at, base, z, opening = who[more], end[more], base[more], z[more] + 1, False
    out = {k: np.concatenate(v) for k, v in found.items()}
    order = np.lexsort((out["block_no"], out["list"]))
    return {k: v[order] for k, v in out.items()}


def _rows(shard: np.ndarray, term: pa.Array, d: np.ndarray, x: np.ndarray, first: np.ndarray, cfg: IndexConfig, old: Chains | None = None) -> pa.RecordBatch:
    """Blocks of whole lists, or what changes of them. shard, term: one for each list."""
    letters = np.array([len(t.encode()) for t in term.to_pylist()], np.int64)
    blocks = pack(first, letters, d, x, cfg, old)
    who, start, end = blocks["list"], blocks["start"], blocks["end"]
    last = np.append(who[1:] != who[:-1], True) if who.size else np.zeros(0, bool)
    kind = KINDS[np.where(blocks["block_no"] == 1, 0, np.where(last, 2, 1))]
    filled = end > start
    begin = np.where(filled, d[np.minimum(start, d.size - 1)], 0)
    stop = np.where(filled, d[end - 1], 0)
    most = np.zeros(who.size, np.int64)
    lengths = np.column_stack((start[filled], end[filled])).reshape(-1)
    if filled.any():
        most[filled] = np.maximum.reduceat(np.append(x, 0), lengths)[::2]
    n, used = end - start, blocks["used"]
    if old is not None:
        was = np.flatnonzero(~blocks["fresh"])
        mine = who[was]
        begin[was], stop[was] = old.first[mine], np.where(filled[was], stop[was], old.last[mine])
        most[was] = np.maximum(most[was], old.most[mine])
        n[was] += old.n[mine]
    payload: pa.Array = pa.nulls(who.size, pa.binary())
    if cfg.payload:
        before = np.concatenate(([0], d[:-1]))
        before[start[filled]] = blocks["base"][filled]
        data = codecs.pair_encode(*_code(cfg, d - before, x), cfg.threshold).tobytes()
        stops = np.cumsum(used)
        if old is None or old.payload is None or not (~blocks["fresh"]).any():
            offsets = np.concatenate(([0], stops)).astype(np.int64)
            payload = pa.Array.from_buffers(pa.large_binary(), who.size, [None, pa.py_buffer(offsets.tobytes()), pa.py_buffer(data)]).cast(pa.binary())
        else:
            payload = pa.array([(b"" if f else old.payload[w]) + data[b - u : b] for f, w, u, b in zip(blocks["fresh"].tolist(), who.tolist(), used.tolist(), stops.tolist(), strict=True)], pa.binary())
    if old is not None:
        used = used + np.where(blocks["fresh"], 0, old.used[who])
    return pa.RecordBatch.from_arrays([
        pa.array(shard[who]), term.take(pa.array(who)), pa.array(blocks["block_no"]), pa.array(kind.tolist(), pa.string()), pa.array(blocks["cap"].astype(np.int64)), pa.array(begin), pa.array(stop),
        pa.array(n), pa.array(used.astype(np.int64)), pa.array(most), payload], names=_NAMES)


def _lists(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[pa.Table, np.ndarray]]:
    """Whole lists of rows sorted by shard and term, about _CHUNK rows at a time: the rows, and where each list begins."""
    held: list[pa.RecordBatch] = []

    def cut(whole: bool):
        table = pa.Table.from_batches(held).combine_chunks()
        shard, codes = table.column("shard").to_numpy(), table.column("term").combine_chunks().dictionary_encode().indices.to_numpy()
        new = np.ones(table.num_rows, bool)
        new[1:] = (codes[1:] != codes[:-1]) | (shard[1:] != shard[:-1])
        first = np.append(np.flatnonzero(new), table.num_rows)
        if not whole:  # the last list may go on in the next batch
            first = first[:-1]
        return table, first, int(first[-1])

    for batch in batches:
        if batch.num_rows:
            held.append(batch)
        if sum(b.num_rows for b in held) >= _CHUNK:
            table, first, end = cut(False)
            if len(first) > 1:
                yield table.slice(0, end), first
            held = table.slice(end).to_batches()
    if held:
        table, first, _ = cut(True)
        yield table, first


def _columns(table: pa.Table, first: np.ndarray) -> tuple:
    heads = pa.array(first[:-1])
    one = table.combine_chunks()
    return one.column("shard").to_numpy()[first[:-1]], one.column("term").combine_chunks().take(heads), one.column("d").to_numpy(), one.column("x").to_numpy()


def _sorted(postings: DataFrame, cfg: IndexConfig, shard: Column | None = None) -> DataFrame:
    """(shard, term, d, x) dealt by shard and term and sorted: the one data shuffle of a build."""
    order = ["shard", "term", "d"] + ([] if cfg.level == "doc" else ["w"])
    x = F.col("f" if cfg.level == "doc" else "wg").cast("long").alias("x")
    parts = int(postings.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    rows = postings.withColumn("shard", cfg.shard_of("d") if shard is None else shard).select(*order, x)
    return rows.repartition(parts, "shard", "term").sortWithinPartitions(*order)


def build_blocks(postings: DataFrame, cfg: IndexConfig, shard: Column | None = None) -> DataFrame:
    """Blocks of postings(term, d, f) or (term, d, w, wg). A shard is a run of cfg.shard_docs documents unless a column
    says otherwise; it bounds each list that a task holds."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table, first in _lists(batches):
            shard, term, d, x = _columns(table, first)
            yield _rows(shard, term, d, x, first, cfg)

    return _sorted(postings, cfg, shard).mapInArrow(run, BLOCKS)


SIZED = "variant int, lists long, blocks long, postings long, total_bytes long"


def index_sizes(postings: DataFrame, cfgs: list[IndexConfig]) -> DataFrame:
    """(variant, lists, blocks, postings, total_bytes) of the indexes that several configurations of one level would
    make, in one pass: each sorted list is packed once for each, and only sums leave the task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums = np.zeros((len(cfgs), 4), np.int64)
        for table, first in _lists(batches):
            _, term, d, x = _columns(table, first)
            letters = np.array([len(t.encode()) for t in term.to_pylist()], np.int64)
            for k, cfg in enumerate(cfgs):
                blocks = pack(first, letters, d, x, cfg)
                own = np.where(blocks["block_no"] == 1, cfg.head_bytes + letters[blocks["list"]], cfg.h)
                sums[k] += (letters.size, blocks["list"].size, d.size, int((blocks["cap"] + own).sum()) + 8 * letters.size)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(cfgs)), pa.int32()), *[pa.array(sums[:, k].copy()) for k in range(4)]], names=[c.split()[0] for c in SIZED.split(", ")])

    parts = _sorted(postings, cfgs[0]).mapInArrow(run, SIZED)
    return parts.groupBy("variant").agg(*[F.sum(c.split()[0]).alias(c.split()[0]) for c in SIZED.split(", ")[1:]])


CHANGED = f"{BLOCKS}, open boolean, made boolean"


def extend_blocks(tails: DataFrame, postings: DataFrame, cfg: IndexConfig, shard: Column | None = None) -> DataFrame:
    """What adding postings changes: BLOCKS with `open` and `made`, the blocks that get postings or are made. open: the
    last of each list, which the next insert goes on with; others are final. made: blocks that were not there before.

    tails: the open blocks of the lists so far (BLOCKS), whose payloads are carried on unread. All postings are of later
    documents than any of their list. The blocks are those that one build over all postings would make."""
    order = ["shard", "term", "d"] + ([] if cfg.level == "doc" else ["w"])
    x = F.col("f" if cfg.level == "doc" else "wg").cast("long")
    state = F.struct("block_no", "used", "n", "first_d", "last_d", "most", "payload")
    new = postings.withColumn("shard", cfg.shard_of("d") if shard is None else shard)
    asked = new.select("shard", "term").distinct()
    old = tails.join(asked, ["shard", "term"], "left_semi").select("shard", "term", F.lit(0).cast("long").alias("d"), F.lit(0).cast("long").alias("w"), F.lit(0).cast("long").alias("x"), state.alias("state"))
    rows = new.select("shard", "term", "d", (F.lit(0).cast("long") if cfg.level == "doc" else F.col("w")).alias("w"), x.alias("x"), F.lit(None).cast(old.schema["state"].dataType).alias("state")).unionByName(old)
    parts = int(postings.sparkSession.conf.get("spark.sql.shuffle.partitions"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table, first in _lists(batches):
            shard, term, d, x = _columns(table, first)
            said = table.column("state").combine_chunks()
            known = said.is_valid().to_numpy(zero_copy_only=False)
            lists = np.cumsum(np.isin(np.arange(d.size), first[:-1])) - 1
            at = Chains(first.size - 1)
            at.payload = [b""] * (first.size - 1)
            where = np.flatnonzero(known)
            mine = lists[where]
            for name, field in (("z", "block_no"), ("used", "used"), ("n", "n"), ("first", "first_d"), ("last", "last_d"), ("most", "most")):
                getattr(at, name)[mine] = said.field(field).to_numpy(zero_copy_only=False)[where].astype(np.int64)
            at.first[at.n == 0] = 0
            for k, w in zip(mine.tolist(), where.tolist(), strict=True):
                at.payload[k] = said.field("payload")[w].as_py() or b""
            keep = ~known
            starts = np.concatenate(([0], np.cumsum(keep)))[first]
            out = _rows(shard, term, d[keep], x[keep], starts, cfg, at)
            last = np.append(out.column("term").dictionary_encode().indices.to_numpy()[1:] != out.column("term").dictionary_encode().indices.to_numpy()[:-1], True)
            shards = out.column("shard").to_numpy()
            last[:-1] |= shards[1:] != shards[:-1]
            heads = np.append(True, last[:-1])
            made = ~heads | (at.n == 0)[np.cumsum(heads) - 1]
            yield pa.RecordBatch.from_arrays([*out.columns, pa.array(last), pa.array(made)], names=[*_NAMES, "open", "made"])

    return rows.repartition(parts, "shard", "term").sortWithinPartitions("shard", "term", "d", "w").mapInArrow(run, CHANGED)


def fits(cfg: IndexConfig, used: Column, gap: Column, x: Column) -> Column:
    """Whether a posting's code fits into a constant chain's open block, its bytes with overhead counted: the test before
    a write."""
    return used + pair_len(gap, x, cfg.threshold) <= F.lit(cfg.B)


def folded(postings: DataFrame, cfg: IndexConfig) -> DataFrame:
    """(term, postings, z, nx): blocks of each list of document-level postings and bytes of its last, overhead included,
    by a fold over the sorted list in SQL functions alone. A list is one row, so this serves checks and short lists."""
    if cfg.growth != "constant" or cfg.level != "doc":
        raise ValueError("the fold knows constant document-level chains")
    lists = postings.groupBy("term").agg(F.array_sort(F.collect_list(F.struct("d", "f"))).alias("l"))
    long = lambda c: c.cast("long")
    empty = F.struct(long(F.lit(1)).alias("z"), long(F.lit(cfg.head_bytes) + F.octet_length("term")).alias("u"), long(F.lit(0)).alias("first"), long(F.lit(0)).alias("last"))

    def step(a: Column, p: Column) -> Column:
        gap = p["d"] - a["last"]
        good = fits(cfg, a["u"], gap, p["f"])
        opened = F.lit(cfg.h) + pair_len(p["d"] - a["first"], p["f"], cfg.threshold)
        return F.struct(F.when(good, a["z"]).otherwise(a["z"] + 1).alias("z"), long(F.when(good, a["u"] + pair_len(gap, p["f"], cfg.threshold)).otherwise(opened)).alias("u"),
                        F.when(good & (a["first"] > 0), a["first"]).otherwise(p["d"]).alias("first"), p["d"].alias("last"))

    return lists.select("term", F.size("l").cast("long").alias("postings"), F.aggregate("l", empty, step).alias("end")).select("term", "postings", F.col("end.z").alias("z"), F.col("end.u").alias("nx"))


def term_dir(blocks: DataFrame) -> DataFrame:
    """(shard, term, postings, last_d, z, nx, most): one row a list, from its blocks."""
    return blocks.groupBy("shard", "term").agg(F.sum("n").alias("postings"), F.max("last_d").alias("last_d"), F.count("*").alias("z"), F.max_by("used", "block_no").alias("nx"), F.max("most").alias("most"))


def decode_blocks(blocks: DataFrame, cfg: IndexConfig) -> DataFrame:
    """Postings of blocks: (shard, term, d, f) or (shard, term, d, w). Each block of a document-level index is decoded
    by itself, as it knows its first document; positions of a word-level index need their list's blocks in order."""
    out = "shard long, term string, d long, f long" if cfg.level == "doc" else "shard long, term string, d long, w long"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, at_d, at_w = None, 0, 0
        for batch in batches:
            rows: list[tuple] = []
            for shard, term, first, payload in zip(*(batch.column(c) for c in ("shard", "term", "first_d", "payload")), strict=True):
                a, b = codecs.pair_decode(np.frombuffer(payload.as_buffer(), np.uint8), cfg.threshold)
                if not a.size:
                    continue
                gap, x = (a, b) if cfg.level == "doc" else (b - 1, a)
                d = first.as_py() + np.cumsum(gap) - gap[0]
                if cfg.level == "word":
                    key = (shard.as_py(), term.as_py())
                    if key != last:
                        last, at_d, at_w = key, -1, 0
                    new = np.concatenate(([d[0] != at_d], d[1:] != d[:-1]))
                    total = np.cumsum(x)
                    start = np.maximum.accumulate(np.where(new, np.arange(x.size), -1))
                    offset = np.where(start >= 0, total[np.maximum(start, 0)] - x[np.maximum(start, 0)], -at_w)
                    x = total - offset
                    at_d, at_w = int(d[-1]), int(x[-1])
                rows.append((shard.as_py(), term.as_py(), d, x))
            if rows:
                n = [r[2].size for r in rows]
                index = pa.array(np.repeat(np.arange(len(rows)), n))
                yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int64()).take(index), pa.array([r[1] for r in rows]).take(index), pa.array(np.concatenate([r[2] for r in rows])), pa.array(np.concatenate([r[3] for r in rows]))], names=[c.split()[0] for c in out.split(", ")])

    if cfg.level == "word":
        parts = int(blocks.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        blocks = blocks.repartition(parts, "shard", "term").sortWithinPartitions("shard", "term", "block_no")
    return blocks.select("shard", "term", "first_d", "payload").mapInArrow(run, out)


def component_table(blocks: DataFrame, cfg: IndexConfig) -> DataFrame:
    """(part, element, blocks, bytes): where the bytes of an index go, one pass over block facts without payload."""
    letters = F.octet_length("term")
    is_ = lambda k: F.col("kind") == k
    total = lambda k, e: F.coalesce(F.sum(F.when(is_(k), e)), F.lit(0)).cast("long")
    count = lambda k: F.count_if(is_(k)).cast("long")
    h, v = cfg.h, cfg.head_bytes - 2 * cfg.h
    parts = [("head", "links", count("head"), 2 * h * count("head")), ("head", "vocabulary", F.lit(0), total("head", letters + v)), ("head", "postings", F.lit(0), total("head", F.col("used"))), ("head", "unused", F.lit(0), total("head", F.col("cap") - F.col("used"))),
             ("full", "links", count("full"), h * count("full")), ("full", "postings", F.lit(0), total("full", F.col("used"))), ("full", "unused", F.lit(0), total("full", F.col("cap") - F.col("used"))),
             ("tail", "documents", count("tail"), h * count("tail")), ("tail", "postings", F.lit(0), total("tail", F.col("used"))), ("tail", "unused", F.lit(0), total("tail", F.col("cap") - F.col("used"))),
             ("hash", "slots", F.lit(0), 8 * count("head"))]
    row = blocks.agg(*[F.struct(F.lit(p).alias("part"), F.lit(e).alias("element"), n.cast("long").alias("blocks"), b.cast("long").alias("bytes")).alias(f"c{i}") for i, (p, e, n, b) in enumerate(parts)])
    return row.select(F.explode(F.array(*[f"c{i}" for i in range(len(parts))])).alias("c")).select("c.*")


def index_bytes(blocks: DataFrame, cfg: IndexConfig) -> DataFrame:
    """(blocks, postings, total_bytes): all components, the hash slots included."""
    size = F.col("cap") + F.when(F.col("block_no") == 1, F.octet_length("term") + cfg.head_bytes).otherwise(cfg.h)
    return blocks.agg(F.count("*").alias("blocks"), F.sum("n").alias("postings"), (F.sum(size) + 8 * F.count_if(F.col("kind") == "head")).alias("total_bytes"))
