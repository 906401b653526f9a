"""WARC files of pages and a Merkle audit of their replicas.

Each task writes one WARC file, a gzip member a record, and the digest and offset range of each record. Trees stand
on those rows: FANOUT neighbouring ranges of a file make a node whose hash covers their hashes and offsets, level on
level up to one root a file. Files in turn, each with its root and its length, are dealt to slots by the hash of their
name, and slots make nodes up to the root of the replica. An audit hashes the bytes a replica holds at the recorded
ranges and lists its files, compares roots, and where they differ joins only the children of differing nodes. Bytes
beyond the last record and files of no record differ like all others.
"""

from __future__ import annotations

import gzip
import hashlib
import os
import uuid
from bisect import bisect_left
from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from liveindex.llm import common as C

FANOUT = 16
#: Most bytes of records that a task holds before it hands rows on; a single record may be larger.
_HELD = 1 << 22

RECORDS = "file string, at long, offset long, length long, page_id long, url string, digest string"


def _opened(path: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(path)


def record(page_id: int | None, url: str | None, html: str | None, date: str) -> bytes:
    """One WARC/1.1 resource record. Its id follows from the page's id, address and content, so that a rerun writes equal bytes."""
    body = (html or "").encode()
    digest = hashlib.sha256(body).hexdigest()
    name = uuid.uuid5(uuid.NAMESPACE_URL, f"{page_id}\n{url}\n{digest}")
    target = (url or "urn:none").replace("\r", "%0D").replace("\n", "%0A")
    head = f"WARC/1.1\r\nWARC-Type: resource\r\nWARC-Record-ID: <urn:uuid:{name}>\r\nWARC-Date: {date}\r\nWARC-Target-URI: {target}\r\nWARC-Payload-Digest: sha256:{digest}\r\nContent-Type: text/html\r\nContent-Length: {len(body)}\r\n\r\n"
    return head.encode() + body + b"\r\n\r\n"


def parse(data: bytes) -> tuple[dict[str, str], bytes]:
    """Headers and payload of a record."""
    head, _, rest = data.partition(b"\r\n\r\n")
    fields = dict(line.split(": ", 1) for line in head.decode().split("\r\n")[1:])
    return fields, rest[: int(fields["Content-Length"])]


def write_warc(df: DataFrame, folder: str | None = None, page_id: str = "page_id", url: str = "url", html: str = "html", date: str = "2024-01-01T00:00:00Z") -> DataFrame:
    """Writes df's rows as WARC files and returns their records: file, at, offset, length, page_id, url, digest.

    Rows keep the order of their partition, by page_id. Null html is an empty payload, null url urn:none; repeated
    rows are records of their own; an empty table gives no record. The digest is SHA-256 of the stored bytes."""
    spark = df.sparkSession
    folder = folder or C.scratch_dir(spark, "warc")
    rows = C.narrow(df, page_id=page_id, url=url, html=html).sortWithinPartitions("page_id", "url")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        system, where = _opened(f"{folder}/part-{TaskContext.get().partitionId():06d}-{uuid.uuid4().hex}.warc.gz")
        system.create_dir(os.path.dirname(where), recursive=True)
        file, at, offset = os.path.basename(where), 0, 0
        with system.open_output_stream(where, compression=None) as out:
            for batch in batches:
                for part in C.pieces(batch, "html", _HELD):
                    found = []
                    for page, address, body in zip(*(part.column(c).to_pylist() for c in ("page_id", "url", "html")), strict=True):
                        data = gzip.compress(record(page, address, body, date), 1, mtime=0)
                        out.write(data)
                        found.append((file, at, offset, len(data), page, address, hashlib.sha256(data).hexdigest()))
                        at, offset = at + 1, offset + len(data)
                    if found:
                        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*found, strict=True), (pa.string(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.string()), strict=True)], names=RECORDS.replace(" long", "").replace(" string", "").split(", "))

    out = C.saved(rows.mapInArrow(run, RECORDS), "warc-records")
    out.folder = folder
    return out


def copy_replica(records: DataFrame, folder: str, to: str | None = None, damaged: Column | None = None) -> str:
    """Copies the files of records, one task a file and some MB at a time; returns the new folder.

    damaged: which records lose a bit of their middle byte in the copy, to try an audit."""
    to = to or C.scratch_dir(records.sparkSession, "replica")
    middle = F.col("offset") + F.floor(F.col("length") / 2)
    files = records.groupBy("file").agg(F.array_sort(F.collect_list(F.when(F.lit(False) if damaged is None else damaged, middle))).alias("bad"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for name, bad in zip(batch.column("file").to_pylist(), batch.column("bad").to_pylist(), strict=True):
                system, source = _opened(f"{folder}/{name}")
                other, target = _opened(f"{to}/{name}")
                other.create_dir(os.path.dirname(target), recursive=True)
                draft = f"{target}.{uuid.uuid4().hex}"
                with system.open_input_file(source) as a, other.open_output_stream(draft, compression=None) as b:
                    at = 0
                    while data := a.read(_HELD):
                        if some := bad[bisect_left(bad, at) : bisect_left(bad, at + len(data))]:
                            data = bytearray(data)
                            for k in some:
                                data[k - at] ^= 1
                        b.write(data)
                        at += len(data)
                other.move(draft, target)
            yield batch.select(["file"])

    files.mapInArrow(run, "file string").write.format("noop").mode("overwrite").save()
    return to


def hashed(records: DataFrame, folder: str) -> DataFrame:
    """records with the digests of what a replica in folder holds at their ranges; null where it holds nothing there.

    An empty table gives an empty result; repeated rows are hashed each."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        name, stream = None, None
        for batch in batches:
            found = []
            for file, offset, length in zip(*(batch.column(c).to_pylist() for c in ("file", "offset", "length")), strict=True):
                if file != name:
                    if stream:
                        stream.close()
                    name, stream = file, None
                    system, where = _opened(f"{folder}/{file}")
                    if system.get_file_info(where).is_file:
                        stream = system.open_input_file(where)
                data = b""
                if stream and offset < stream.size():
                    stream.seek(offset)
                    data = stream.read(length)
                found.append(hashlib.sha256(data).hexdigest() if len(data) == length else None)
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in ("file", "at", "offset", "length", "page_id", "url")), pa.array(found, pa.string())], names=RECORDS.replace(" long", "").replace(" string", "").split(", "))

    parts = int(records.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    near = records.repartitionByRange(parts, "file", "at").sortWithinPartitions("file", "at")
    return C.saved(near.mapInArrow(run, RECORDS), "replica-digests")


def listed(spark: SparkSession, folder: str) -> DataFrame:
    """(file, bytes) of the files that a folder holds; files are as many as the tasks that wrote them."""
    from pyarrow import fs

    system, where = _opened(folder)
    found = system.get_file_info(fs.FileSelector(where, recursive=False, allow_not_found=True))
    return spark.createDataFrame([(f.base_name, f.size) for f in found if f.is_file], "file string, bytes long")


#: Slots that files are dealt to, the leaves of the tree above them: a power of FANOUT.
SLOTS = FANOUT**3


def _joined(of: Column) -> Column:
    return F.sha2(F.concat_ws("|", F.transform(F.array_sort(F.collect_list(of)), lambda c: c["h"])), 256)


def merkle(records: DataFrame, files: DataFrame) -> list[DataFrame]:
    """Levels of a replica's tree. First those of files, leaves first: file, node, begin, end, hash, up to one root a
    file; then slots of files and their parents: node, hash, up to the one root.

    files: (file, bytes), as listed. A leaf that holds nothing hashes as the word missing, a listed file of no record
    as its length, and a file of records that is not listed as the word missing."""
    def parents(level: DataFrame) -> DataFrame:
        child = F.struct("node", F.concat_ws(":", "begin", "end", "hash").alias("h"))
        return level.groupBy("file", F.floor(F.col("node") / FANOUT).alias("node")).agg(F.min("begin").alias("begin"), F.max("end").alias("end"), _joined(child).alias("hash"))

    leaf = F.coalesce("digest", F.lit("missing"))
    level = C.saved(records.select("file", F.col("at").alias("node"), F.col("offset").alias("begin"), (F.col("offset") + F.col("length")).alias("end"), leaf.alias("hash")), "merkle")
    levels = [level]
    most = level.agg(F.max("node")).first()[0]
    while most is not None and most > 0:
        level = C.saved(parents(level), "merkle")
        levels.append(level)
        most //= FANOUT
    said = F.concat_ws(":", "file", F.coalesce(F.col("bytes").cast("string"), F.lit("missing")), F.coalesce("hash", F.lit("none")))
    slots = level.select("file", "hash").join(files, "file", "full").groupBy(F.pmod(F.xxhash64("file"), F.lit(SLOTS)).alias("node"))
    level = C.saved(slots.agg(_joined(F.struct("file", said.alias("h"))).alias("hash")), "merkle")
    levels.append(level)
    for _ in range(3):  # SLOTS is FANOUT cubed
        level = C.saved(level.groupBy(F.floor(F.col("node") / FANOUT).alias("node")).agg(_joined(F.struct("node", F.col("hash").alias("h"))).alias("hash")), "merkle")
        levels.append(level)
    return levels


def _children(level: DataFrame, differ: DataFrame, keys: list[str]) -> DataFrame:
    up = differ.select(*keys, F.col("node").alias("_up"))
    return level.withColumn("_up", F.floor(F.col("node") / FANOUT)).join(up, [*keys, "_up"], "left_semi").drop("_up")


def audit(good: list[DataFrame], other: list[DataFrame], files: DataFrame, others: DataFrame) -> DataFrame:
    """(file, at, offset, end) of what differs in the second replica, found from the root down: leaves of the first
    tree, and, with a null at, the range by which a file is longer than it should be or that a file too many holds."""
    differ = None
    inner = [k for k, level in enumerate(good) if "file" not in level.columns]
    for k in reversed(inner):
        a, b = good[k], other[k - len(good)].select("node", F.col("hash").alias("other"))
        if differ is not None:
            a, b = _children(a, differ, []), _children(b, differ, [])
        differ = C.saved(a.join(b, "node", "full").where(~F.col("hash").eqNullSafe(F.col("other"))).select("node"), "differing")
        if differ.isEmpty():
            return good[0].sparkSession.createDataFrame([], "file string, at long, offset long, end long")
    of = lambda level: level.join(differ.select("node"), F.pmod(F.xxhash64("file"), F.lit(SLOTS)) == F.col("node"), "left_semi")
    longer = of(others.select("file", F.col("bytes").alias("has"))).join(files, "file", "left").where(F.col("has") > F.coalesce("bytes", F.lit(-1)))
    extra = longer.select("file", F.lit(None).cast("long").alias("at"), F.coalesce("bytes", F.lit(0)).cast("long").alias("offset"), F.col("has").alias("end"))
    names = C.saved(of(files.select("file")), "differing")
    below = None
    for k in reversed(range(inner[0])):
        a, b = good[k], other[k].select("file", "node", F.col("hash").alias("other"))
        if below is None:
            a, b = a.join(names, "file", "left_semi"), b.join(names, "file", "left_semi")
        else:
            a, b = _children(a, below, ["file"]), _children(b, below, ["file"])
        below = C.saved(a.join(b, ["file", "node"], "left").where(~F.col("hash").eqNullSafe(F.col("other"))).select("file", "node", "begin", "end"), "differing")
    return below.select("file", F.col("node").alias("at"), F.col("begin").alias("offset"), "end").unionByName(extra)


def fixity(records: DataFrame, folder: str) -> DataFrame:
    """records with `intact`: whether the replica in folder still holds them, bytes and order alike. Null digests of
    records never match; rows of records that repeat are alike; no records give no rows. Damage beside the records, as
    `audit` gives it with a null at, is no row's."""
    bad = damage(records, folder).where("at is not null").select("file", "at", F.lit(True).alias("bad"))
    return records.join(bad, ["file", "at"], "left").withColumn("intact", F.col("bad").isNull()).drop("bad")


def damage(records: DataFrame, folder: str) -> DataFrame:
    """What `audit` finds in the replica in folder against records as they were written."""
    files = records.groupBy("file").agg(F.max(F.col("offset") + F.col("length")).alias("bytes"))
    held = listed(records.sparkSession, folder)
    return audit(merkle(records, files), merkle(hashed(records, folder), held), files, held)
