"""Token ids as length-delimited binary records with masked checksums and a separate offset index.

A record file is a run of frames: payload length (8 bytes), masked CRC-32C of those bytes (4), payload, masked
CRC-32C of the payload (4), all little-endian. A payload is the doc_id (8 bytes) and the ids, 2 bytes each if the
vocabulary allows, else 4. The index file beside it holds one (offset, length) pair of 8-byte numbers for each
frame, so that a reader can visit records in any order. Files are numbered in doc_id order, and a manifest names
those of successful tasks: what a lost task left behind is never read.
"""

from __future__ import annotations

import os
import uuid
import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from liveindex.llm import common as C

# The reflected polynomial of CRC-32C, and the rotation and offset of masked checksums.
POLYNOMIAL, MASK_SHIFT, MASK_ADD = 0x82F63B78, 15, 0xA282EAD8
_BLOCK = 64
#: Pre-tokens whose ids a worker keeps at hand; beyond that it starts anew.
CACHED = 700_000
_NO_ID = -(1 << 63)


@lru_cache(1)
def _shifts() -> list[np.ndarray]:
    """Of each k, four tables of 256 that carry a checksum over 2^k zero bytes."""
    byte = np.arange(256, dtype=np.uint32)
    for _ in range(8):
        byte = np.where(byte & 1, (byte >> 1) ^ np.uint32(POLYNOMIAL), byte >> 1)
    out = []
    for k in range(34):
        table = np.empty((4, 256), np.uint32)
        for part in range(4):
            value = np.arange(256, dtype=np.uint32) << np.uint32(8 * part)
            table[part] = _shift(out[-1], _shift(out[-1], value)) if k else byte[value & 0xFF] ^ (value >> np.uint32(8))
        out.append(table)
    return out


def _shift(table: np.ndarray, crc: np.ndarray) -> np.ndarray:
    return table[0][crc & 0xFF] ^ table[1][(crc >> 8) & 0xFF] ^ table[2][(crc >> 16) & 0xFF] ^ table[3][crc >> 24]


def _over_zeros(crc: np.ndarray, zeros: np.ndarray) -> np.ndarray:
    """Checksums carried over the given numbers of zero bytes."""
    crc = crc.copy()
    for k in range(int(zeros.max(initial=0)).bit_length()):
        here = np.flatnonzero((zeros >> k) & 1)
        crc[here] = _shift(_shifts()[k], crc[here])
    return crc


def crc32c(data: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """CRC-32C of data[start : start + size] for all records at once.

    Records are cut into blocks of equal length (zeros in front of a first block change nothing), the blocks go
    byte by byte side by side, and each block's sum is carried over what follows it in its record."""
    if not starts.size:
        return np.zeros(0, np.uint32)
    blocks = np.maximum(1, -(-sizes // _BLOCK))
    first = np.concatenate(([0], np.cumsum(blocks)))
    record = np.repeat(np.arange(starts.size), blocks)
    left = first[record + 1] - 1 - np.arange(first[-1])  # blocks behind this one
    begin = starts[record] + sizes[record] - (left + 1) * _BLOCK
    crc, step = np.zeros(record.size, np.uint32), _shifts()[0][0]
    for k in range(_BLOCK):
        at = begin + k
        byte = np.where(at >= starts[record], data[np.clip(at, 0, data.size - 1)] if data.size else 0, 0).astype(np.uint32)
        crc = step[(crc ^ byte) & 0xFF] ^ (crc >> np.uint32(8))
    whole = np.bitwise_xor.reduceat(_over_zeros(crc, left * _BLOCK), first[:-1])
    return whole ^ _over_zeros(np.full(starts.size, 0xFFFFFFFF, np.uint32), sizes) ^ np.uint32(0xFFFFFFFF)


def masked(crc: np.ndarray) -> np.ndarray:
    crc = crc.astype(np.uint64)
    turned = ((crc >> np.uint64(MASK_SHIFT)) | (crc << np.uint64(32 - MASK_SHIFT))) & np.uint64(0xFFFFFFFF)
    return ((turned + np.uint64(MASK_ADD)) & np.uint64(0xFFFFFFFF)).astype(np.uint32)


#: Classes of code points, and what stands for one that has not been asked for.
SPACE, LETTER, NUMBER, OTHER, UNKNOWN = 0, 1, 2, 3, 255


class Classes:
    """Classes of code points as a pre-tokenizer of the library has them: asked for once, when first met.

    The library's tables may be of another Unicode version than Python's."""

    def __init__(self, pre_tokenizer) -> None:
        self.library = pre_tokenizer
        self.kind = np.full(0x110000, UNKNOWN, np.uint8)
        self.kind[:128] = [SPACE if c in (9, 10, 11, 12, 13, 32) else LETTER if chr(c).isalpha() else NUMBER if chr(c).isdigit() else OTHER for c in range(128)]

    def of(self, points: np.ndarray) -> np.ndarray:
        kind = self.kind[points]
        new = np.unique(points[kind == UNKNOWN])
        for low in range(0, new.size, 1 << 14):
            some = new[low : low + (1 << 14)]
            # A letter stays with the a, a number with the 1, another sign with the !, and white space with none.
            text = "".join(f"a{c}1{c}!" for c in map(chr, some.tolist()))
            begins = np.zeros(5 * some.size, bool)
            begins[[at for _, (at, _) in self.library.pre_tokenize_str(text)]] = True
            begins = begins.reshape(-1, 5)
            self.kind[some] = np.select([~begins[:, 1], ~begins[:, 2], ~begins[:, 4]], [LETTER, NUMBER, OTHER], SPACE)
        return self.kind[points] if new.size else kind


def pretokens(points: np.ndarray, kind: np.ndarray, cut: np.ndarray) -> np.ndarray:
    """Where the pieces of byte-level pre-tokenisation begin. points: code points; kind: their classes; cut: where
    texts begin.

    Pieces are runs of letters, of numbers or of other signs, each with one blank before it if there is one;
    white space up to the last character before such a piece; and the English endings that follow an apostrophe."""
    n = points.size
    start = np.zeros(n + 1, bool)
    begins = np.zeros(n + 1, bool)
    begins[cut] = True
    start[1:n] = kind[1:] != kind[:-1]
    start |= begins
    runs = np.flatnonzero(start[:n])
    solid = runs[kind[runs] != 0]
    behind = solid[~begins[solid] & (solid > 0)]  # these follow white space or another kind in the same text
    white = behind[kind[behind - 1] == 0]
    start[white - 1] = True
    start[white[points[white - 1] == 32]] = False
    quote = np.flatnonzero((points == 39) & start[:n])
    after = lambda at, k: np.where((at + k < n) & ~begins[np.minimum(at + 1, n)] & ((k < 2) | ~begins[np.minimum(at + 2, n)]), points[np.minimum(at + k, n - 1)], 0)
    one, two = after(quote, 1), after(quote, 2)
    short = np.isin(one, [115, 116, 109, 100])
    long = ((one == 114) & (two == 101)) | ((one == 118) & (two == 101)) | ((one == 108) & (two == 108))
    for at, width in ((quote[short], 2), (quote[long], 3)):
        start[at + 1] = False
        start[at + width] = True
    return np.flatnonzero(start[:n])


@lru_cache(1)
def _alphabet() -> dict[int, str]:
    """The printable character that stands for each byte in byte-level vocabularies: itself, or one from 256 up."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    hidden = [b for b in range(256) if b not in set(shown)]
    return {b: chr(b) for b in shown} | {b: chr(256 + k) for k, b in enumerate(hidden)}


class Encoder:
    """Encodes texts with a tokenizers file, each distinct pre-token once as long as it is remembered.

    In byte-level BPE files without normaliser the ids of a text are those of its pre-tokens in turn, unless it holds
    one of the file's added tokens. Such texts, and all texts of files of other kinds, go to the library whole.
    Pre-tokens are told apart by 64 bits of hash: with the distinct ones of a slice and those remembered, under a
    million at a time, two of them share it with a probability of 3e-8."""

    def __init__(self, path: str) -> None:
        import json

        from tokenizers import Tokenizer

        tokenizer = Tokenizer.from_file(path)
        said = json.loads(tokenizer.to_str())
        before = said.get("pre_tokenizer") or {}
        self.by_pieces = said["model"]["type"] == "BPE" and not said.get("normalizer") and before.get("type") == "ByteLevel" and not before.get("add_prefix_space") and before.get("use_regex", True) and not (said.get("truncation") or said.get("padding"))
        self.library, self.model, self.size = tokenizer, tokenizer.model, tokenizer.get_vocab_size()
        self.added = sorted({t.content for t in tokenizer.get_added_tokens_decoder().values()} - {""})
        self.classes = Classes(tokenizer.pre_tokenizer) if self.by_pieces else None
        self.clear()

    def clear(self) -> None:
        self.seen: dict[int, int] = {}  # hash of a pre-token to (where its ids begin in the pool) << 32 | how many
        self.pool, self.used = np.zeros(1 << 16, np.uint32), 0

    def _learn(self, key: int, piece: str) -> int:
        ids = [t.id for t in self.model.tokenize(piece.encode().decode("latin-1").translate(_alphabet()))]
        if self.used + len(ids) > self.pool.size:
            self.pool = np.concatenate((self.pool, np.zeros(max(self.pool.size, len(ids)), np.uint32)))
        self.pool[self.used : self.used + len(ids)] = ids
        self.seen[key] = self.used << 32 | len(ids)
        self.used += len(ids)
        return self.seen[key]

    def encode(self, texts: pa.Array, end: int) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts, each followed by the end id, and where each text's begin."""
        if not self.by_pieces:
            lists = [x.ids + [end] for x in self.library.encode_batch([t or "" for t in texts.to_pylist()], add_special_tokens=False)]
            return np.array([i for x in lists for i in x], np.uint32), np.concatenate(([0], np.cumsum([len(x) for x in lists], dtype=np.int64)))
        holds = np.zeros(len(texts), bool)
        for token in self.added:
            holds |= pc.fill_null(pc.match_substring(texts, token), False).to_numpy(zero_copy_only=False)
        whole = np.flatnonzero(holds)
        by_library = [np.array(self.library.encode(texts[k].as_py(), add_special_tokens=False).ids, np.uint32) for k in whole.tolist()]
        if whole.size:
            texts = pc.if_else(pa.array(holds), pa.scalar("", texts.type), texts)
        raw, off = C.flat(texts)
        text = raw.tobytes().decode()
        points = np.frombuffer(text.encode("utf-32-le"), np.uint32)
        lead = np.zeros(raw.size + 1, np.int64)
        np.cumsum((raw & 0xC0) != 0x80, out=lead[1:])
        cut = lead[off]
        starts = pretokens(points, self.classes.of(points), cut)
        ends = np.append(starts[1:], points.size)[: starts.size]
        total = np.zeros(points.size + 1, np.uint64)
        np.cumsum(C.mix(points.astype(np.uint64) + np.uint64(1)) * C.powers(C._BASE, points.size), out=total[1:])
        keys = C.mix((total[ends] - total[starts]) * C.powers(C._INVERSE, points.size + 1)[starts] + (ends - starts).astype(np.uint64))
        distinct, first, which = np.unique(keys, return_index=True, return_inverse=True)
        if len(self.seen) > CACHED:
            self.clear()
        known = self.seen
        rows = [known.get(k, -1) for k in distinct.tolist()]
        for i in (i for i, r in enumerate(rows) if r < 0):
            a = first[i]
            rows[i] = self._learn(int(distinct[i]), text[starts[a] : ends[a]])
        place = np.array(rows, np.int64)[which]
        begin, count = place >> 32, place & 0xFFFFFFFF
        run = np.concatenate(([0], np.cumsum(count)))
        ids = self.pool[np.repeat(begin - run[:-1], count) + np.arange(run[-1])]
        stop = run[np.searchsorted(starts, cut)]
        if whole.size:
            sizes = np.zeros(len(off), np.int64)
            sizes[whole + 1] = [len(x) for x in by_library]
            ids = np.insert(ids, np.repeat(stop[whole], sizes[whole + 1]), np.concatenate(by_library))
            stop = stop + np.cumsum(sizes)
        return np.insert(ids, stop[1:], end), stop + np.arange(len(off))


@lru_cache(2)
def _encoder(path: str) -> Encoder:
    return Encoder(path)


def _opened(path: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(path)


FILES = "part int, path string, docs long, ids long, width int"


def _writer(folder: str, tokenizer: str, end: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part = TaskContext.get().partitionId()
        system, where = _opened(f"{folder}/part-{part:06d}-{uuid.uuid4().hex}")
        system.create_dir(os.path.dirname(where), recursive=True)
        encoder = _encoder(tokenizer)
        kind = np.uint16 if max(encoder.size, end + 1) <= 1 << 16 else np.uint32
        docs = count = at = 0
        with system.open_output_stream(f"{where}.rec") as data, system.open_output_stream(f"{where}.idx") as index:
            for batch in batches:
                for piece in C.pieces(batch, "text", 1 << 22):
                    ids, first = encoder.encode(piece.column("text"), end)
                    names = np.array([_NO_ID if x is None else x for x in piece.column("doc_id").to_pylist()], np.int64)
                    sizes = np.diff(first) * kind().itemsize + 8
                    frames = np.concatenate(([0], np.cumsum(sizes + 16)))
                    out = np.zeros(frames[-1], np.uint8)
                    put = lambda at, values: out.__setitem__((at[:, None] + np.arange(values.dtype.itemsize)).reshape(-1), values.view(np.uint8))
                    put(frames[:-1], sizes)
                    put(frames[:-1] + 12, names)
                    body = np.repeat(frames[:-1] + 20 - first[:-1] * kind().itemsize, np.diff(first) * kind().itemsize) + np.arange(ids.size * kind().itemsize)
                    out[body] = ids.astype(kind).view(np.uint8)
                    put(frames[:-1] + 8, masked(crc32c(out, frames[:-1], np.full(sizes.size, 8))))
                    put(frames[1:] - 4, masked(crc32c(out, frames[:-1] + 12, sizes)))
                    data.write(out)
                    index.write(np.stack((at + frames[:-1], sizes), 1).astype("<i8").tobytes())
                    docs, count, at = docs + sizes.size, count + ids.size, at + int(frames[-1])
        yield pa.RecordBatch.from_pydict({"part": pa.array([part], pa.int32()), "path": [where if "://" not in folder else f"{folder}/{os.path.basename(where)}"], "docs": [docs], "ids": [count], "width": pa.array([kind().itemsize], pa.int32())})

    return run


def write_records(df: DataFrame, tokenizer: str, text: str = "text", doc_id: str = "doc_id", end: int = 0, folder: str | None = None) -> DataFrame:
    """Writes one record for each row of df, in ascending doc_id order (null first); returns the manifest of files.

    Null and empty texts give a record of the end id alone. Repeated rows give a record each, next to each other.
    An empty table gives files without records. Other columns of df play no part.
    """
    spark = df.sparkSession
    folder = folder or C.scratch_dir(spark, "records")
    rows = C.narrow(df, doc_id=doc_id, text=text)
    rows = rows.withColumn("doc_id", F.col("doc_id").cast("long"))
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    # The place in the table parts rows that share a doc_id, or have none, over several files.
    rows = rows.withColumn("place", F.monotonically_increasing_id())
    ordered = rows.repartitionByRange(parts, "doc_id", "place").sortWithinPartitions("doc_id", "place").drop("place")
    return C.saved(ordered.mapInArrow(_writer(folder, tokenizer, end), FILES), "manifest")


class DamagedRecord(ValueError):
    """A frame whose checksum does not fit its bytes."""


def frames(path: str, width: int, most: int = 1 << 22, order: np.ndarray | None = None) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(doc_ids, ids, where each record's ids begin) of a file's records, some MB at a time, checksums verified.

    order: numbers of the records to read, in this order; all in file order if not given."""
    system, where = _opened(path)
    with system.open_input_file(f"{where}.idx") as f:
        index = np.frombuffer(f.read(), "<i8").reshape(-1, 2)
    with system.open_input_file(f"{where}.rec") as f:
        at = 0
        while at < (len(index) if order is None else len(order)):
            if order is None:
                end = max(at + 1, int(np.searchsorted(index[:, 0], index[at, 0] + most)))
                part, base = index[at:end], int(index[at, 0])
                f.seek(base)
                data = np.frombuffer(f.read(int(part[-1].sum()) + 16 - base), np.uint8)
                begin = part[:, 0] - base
            else:
                end, got = at + 1, index[order[at]]
                f.seek(int(got[0]))
                part, begin = got[None], np.zeros(1, np.int64)
                data = np.frombuffer(f.read(int(got[1]) + 16), np.uint8)
            sizes = part[:, 1]
            take = lambda at, kind: data[(at[:, None] + np.arange(kind().itemsize)).reshape(-1)].view(kind)
            good = (take(begin, np.int64) == sizes) & (take(begin + 8, np.uint32) == masked(crc32c(data, begin, np.full(sizes.size, 8)))) & (take(begin + 12 + sizes, np.uint32) == masked(crc32c(data, begin + 12, sizes)))
            if not good.all():
                raise DamagedRecord(f"{path}: record {at + int(np.flatnonzero(~good)[0])}")
            count = (sizes - 8) // width
            first = np.concatenate(([0], np.cumsum(count)))
            body = np.repeat(begin + 20 - first[:-1] * width, count * width) + np.arange(first[-1] * width)
            yield take(begin + 12, np.int64), data[body].view(np.uint16 if width == 2 else np.uint32).astype(np.uint32), first
            at = end


def read_records(manifest: DataFrame, tokens: bool = True) -> DataFrame:
    """Records of a manifest's files: doc_id, start (ids of all records before), n_tokens, ids_crc32, and tokens if wanted."""
    spark: SparkSession = manifest.sparkSession
    # One row a file: files are as many as partitions of the writing job, so the driver may order them.
    base, rows = 0, []
    for part, path, _, ids, width in sorted(map(tuple, manifest.select("part", "path", "docs", "ids", "width").collect())):
        rows.append((path, base, width))
        base += ids
    files = spark.createDataFrame(rows, "path string, base long, width int").repartition(max(1, len(rows)))
    fields = "doc_id long, start long, n_tokens long, ids_crc32 long" + ", tokens array<int>" * tokens

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                at = row["base"]
                for names, ids, first in frames(row["path"], row["width"]):
                    data = ids.astype("<u4").tobytes()
                    out = {"doc_id": pa.array(names, mask=names == _NO_ID), "start": at + first[:-1], "n_tokens": np.diff(first),
                           "ids_crc32": np.array([zlib.crc32(data[4 * a : 4 * b]) for a, b in zip(first[:-1], first[1:], strict=True)], np.int64)}
                    if tokens:
                        out["tokens"] = pa.ListArray.from_arrays(first.astype(np.int32), ids.astype(np.int32))
                    yield pa.RecordBatch.from_pydict(out)
                    at += int(first[-1])

    return files.mapInArrow(run, fields)
