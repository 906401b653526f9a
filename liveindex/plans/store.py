"""The stored live index: chains of blocks that grow across inserts, a manifest of snapshots, and queries over one.

An insert goes on where the chains stand: it reads the open blocks of its terms, adds the new postings, and writes what
changes as a batch of its own - blocks that are final now, and the new open ones. The blocks of a snapshot are all final
ones and of each list the newest open one: byte for byte those of one build over all documents. The manifest's next
version then lists the batch, so that a reader sees all of an insert or nothing, and the next query sees every insert
that returned.

Full shards, by documents or by bytes, stay as they are or become static lists. Collation writes the blocks of a
snapshot again, unread, each list's next to each other; inserts may go on meanwhile. Blocks lie in partitions by the
checksum of their term, which prunes a search to its terms' partitions.
"""

from __future__ import annotations

import json
import re
import time
import uuid
import zlib

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from liveindex.operators import evaluate as E
from liveindex.operators import packer as K
from liveindex.operators import postings as P
from liveindex.operators import static as Z

#: Seconds after which the claim of a writer that never published is void.
CLAIM_SECONDS = 600


class Conflict(RuntimeError):
    """Another writer published the version that this one was about to."""


class LiveIndex:
    """A document-level or word-level index under one folder of any file system that Spark knows.

    cfg is that of the folder's first use; most_bytes: bytes of blocks after which the next insert opens a new shard."""

    def __init__(self, spark: SparkSession, path: str, cfg: K.IndexConfig | None = None, buckets: int = 16, most_bytes: int | None = None) -> None:
        self.spark, self.path, self.cfg, self.buckets, self.most_bytes = spark, path.rstrip("/"), cfg or K.IndexConfig(), buckets, most_bytes
        if not self.manifest():
            try:
                self._publish({"version": 0, "batches": [], "names": {}, "documents": 0, "last_d": 0, "starts": [1], "bytes": 0, "static": []})
            except Conflict:  # someone else has begun it
                pass

    # -- manifest ---------------------------------------------------------------------------------------------------

    def _hadoop(self, name: str = ""):
        path = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{self.path}/{name}" if name else self.path)
        return path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()), path

    def manifest(self, version: int | None = None) -> dict:
        """The newest version, or a given one; files of versions are never rewritten."""
        fs, path = self._hadoop()
        if not fs.exists(path):
            return {}
        names = sorted(s.getPath().getName() for s in fs.listStatus(path) if re.fullmatch(r"manifest-\d+", s.getPath().getName()))
        if version is not None:
            names = [n for n in names if n == f"manifest-{version:012d}"]
        if not names:
            return {}
        fs, path = self._hadoop(names[-1])
        stream = fs.open(path)
        try:
            data = self.spark.sparkContext._jvm.org.apache.commons.io.IOUtils.toByteArray(stream)
        finally:
            stream.close()
        return json.loads(bytes(data).decode())

    def _publish(self, manifest: dict) -> None:
        """A version is claimed, written aside and moved to its name whole: readers never see a part of it, and of two
        writers one fails. A claim whose writer has died is void after CLAIM_SECONDS."""
        name = f"manifest-{manifest['version']:012d}"
        fs, target = self._hadoop(name)
        fs.mkdirs(target.getParent())
        _, claim = self._hadoop(f"claim-{manifest['version']:012d}")
        if not self._claimed(fs, claim):
            if fs.exists(target) or time.time() - fs.getFileStatus(claim).getModificationTime() / 1000 < CLAIM_SECONDS:
                raise Conflict(name)
            fs.delete(claim, False)
            if not self._claimed(fs, claim):
                raise Conflict(name)
        if fs.exists(target):
            raise Conflict(name)
        _, aside = self._hadoop(f"aside-{uuid.uuid4().hex}")
        out = fs.create(aside, False)
        out.write(bytearray(json.dumps(manifest).encode()))
        out.close()
        if not fs.rename(aside, target):
            raise Conflict(name)

    @staticmethod
    def _claimed(fs, claim) -> bool:
        try:
            return bool(fs.createNewFile(claim))
        except Exception as why:  # some file systems say by an exception that the file is there
            if fs.exists(claim):
                return False
            raise why

    # -- inserts ----------------------------------------------------------------------------------------------------

    @staticmethod
    def _shard(starts: list[int]) -> Column:
        return (F.size(F.filter(F.split(F.lit(",".join(map(str, starts))), ",").cast("array<bigint>"), lambda s: s <= F.col("d"))) - 1).cast("long")

    def _write(self, blocks: DataFrame, batch: int) -> str:
        name = f"batch={uuid.uuid4().hex}"
        bucket = F.pmod(F.crc32(F.col("term").cast("binary")), F.lit(self.buckets)).cast("int")
        blocks.withColumns({"batch_no": F.lit(batch).cast("long"), "term_bucket": bucket}).repartition("term_bucket").sortWithinPartitions("shard", "term", "block_no").write.partitionBy("term_bucket").parquet(f"{self.path}/{name}")
        return name

    def insert(self, stream: DataFrame, batch: str | None = None, tries: int = 5) -> int:
        """Adds documents (d, terms) whose numbers are above all that the index has; returns the new version.

        batch: a name for the insert that ends with a number, as those of micro-batches do; one whose number is not
        above the last of that name is there already and is not added again, whatever has been collated since. Of
        two inserts at once one starts anew. An insert without documents changes nothing."""
        for _ in range(tries):
            now = self.manifest()
            name, number = self._named(batch)
            if name and now["names"].get(name, -1) >= number:
                return now["version"]
            facts = stream.agg(F.count("d").alias("n"), F.min("d").alias("lo"), F.max("d").alias("hi")).first()  # numbers alone are read
            if not facts["n"]:
                return now["version"]
            if facts["lo"] <= now["last_d"]:
                raise ValueError(f"document {facts['lo']} comes after document {now['last_d']}")
            starts = list(now["starts"])
            if self.most_bytes is not None and now["bytes"] >= self.most_bytes and facts["lo"] > starts[-1]:
                starts.append(facts["lo"])
            while facts["hi"] >= starts[-1] + self.cfg.shard_docs:
                starts.append(starts[-1] + self.cfg.shard_docs)
            postings = P.count_terms(stream) if self.cfg.level == "doc" else P.postings_word(stream).select("term", "d", "w", "wg")
            changed = K.extend_blocks(self._open(now).select(*K._NAMES), postings, self.cfg, self._shard(starts))
            folder = self._write(changed, now["version"] + 1)
            own = F.col("cap") + F.when(F.col("block_no") == 1, F.octet_length("term") + self.cfg.head_bytes + 8).otherwise(self.cfg.h)
            size = self._stored([folder]).where(F.col("made") & (F.col("shard") == len(starts) - 1)).agg(F.coalesce(F.sum(own), F.lit(0))).first()[0]
            new = {**now, "version": now["version"] + 1, "batches": [*now["batches"], folder], "documents": now["documents"] + facts["n"], "last_d": facts["hi"], "starts": starts,
                   "bytes": size + (now["bytes"] if len(starts) == len(now["starts"]) else 0), "names": now["names"] | ({name: number} if name else {})}
            try:
                self._publish(new)
                return new["version"]
            except Conflict:
                continue
        raise Conflict(f"{tries} other writers came first")

    @staticmethod
    def _named(batch: str | None) -> tuple[str | None, int]:
        if batch is None:
            return None, 0
        found = re.fullmatch(r"(.*?)-?(\d+)", batch)
        return (found[1] or "batch", int(found[2])) if found else (batch, 0)

    # -- snapshots --------------------------------------------------------------------------------------------------

    def _stored(self, folders: list[str], terms: list[str] | None = None) -> DataFrame:
        if not folders:
            return self.spark.createDataFrame([], f"{K.CHANGED}, batch_no long, term_bucket int")
        rows = self.spark.read.option("basePath", self.path).parquet(*[f"{self.path}/{b}" for b in folders])
        if terms is not None:
            buckets = sorted({zlib.crc32(t.encode()) % self.buckets for t in terms})
            rows = rows.where(F.col("term_bucket").isin(buckets or [-1]) & F.col("term").isin(list(terms) or [""]))
        return rows

    def _dynamic(self, now: dict, terms: list[str] | None = None) -> DataFrame:
        rows = self._stored(now["batches"], terms)
        gone = [s["shard"] for s in now["static"]]
        return rows.where(~F.col("shard").isin(gone)) if gone else rows

    def _open(self, now: dict, terms: list[str] | None = None) -> DataFrame:
        """The newest open block of each list."""
        rows = self._dynamic(now, terms).where("open")
        newest = F.max_by(F.struct(*[c for c in K._NAMES if c not in ("shard", "term")]), "batch_no").alias("b")
        return rows.groupBy("shard", "term").agg(newest).select("shard", "term", "b.*").select(*K._NAMES)

    def blocks(self, terms: list[str] | None = None, manifest: dict | None = None) -> DataFrame:
        """Blocks of a snapshot; of some terms only, from their partitions only."""
        now = manifest or self.manifest()
        done = self._dynamic(now, terms).where(~F.col("open")).select(*K._NAMES).unionByName(self._open(now, terms).withColumn("kind", F.lit("tail")))
        shaped = done.withColumn("kind", F.when(F.col("block_no") == 1, "head").when(F.col("kind") == "tail", "tail").otherwise("full"))
        return shaped.select(*K._NAMES)

    def static_runs(self, terms: list[str] | None = None, manifest: dict | None = None) -> list[tuple[DataFrame, str]]:
        """(runs, code) of the static shards."""
        now, out = manifest or self.manifest(), []
        for code in Z.CODES:
            names = sorted({s["name"] for s in now["static"] if s["code"] == code})
            if names:
                rows = self.spark.read.parquet(*[f"{self.path}/{n}" for n in names])
                if terms is not None:
                    buckets = sorted({zlib.crc32(t.encode()) % self.buckets for t in terms})
                    rows = rows.where(F.col("term_bucket").isin(buckets or [-1]) & F.col("term").isin(list(terms) or [""]))
                out.append((rows, code))
        return out

    def postings(self, terms: list[str] | None = None, manifest: dict | None = None) -> DataFrame:
        """(term, d, f), or (term, d, w) of a word-level index, of all shards, dynamic and static."""
        now = manifest or self.manifest()
        x = "f" if self.cfg.level == "doc" else "w"
        out = K.decode_blocks(self.blocks(terms, now), self.cfg).select("term", "d", x)
        for runs, code in self.static_runs(terms, now):
            out = out.unionByName(Z.decode_static(runs, code).select("term", "d", "f"))
        return out

    # -- queries ----------------------------------------------------------------------------------------------------

    def _counts(self, terms: list[str], now: dict) -> DataFrame:
        lists = self.postings(terms, now)
        return lists if self.cfg.level == "doc" else P.derive_counts(lists)

    def _log(self, texts: list[str]) -> tuple[DataFrame, list[str]]:
        asked = [(k, terms_of(t)) for k, t in enumerate(texts)]
        return self.spark.createDataFrame(asked, "qid long, terms array<string>"), sorted({t for _, ts in asked for t in ts})

    def search(self, text: str, k: int = 10) -> DataFrame:
        """(qid, rank, d, score): the k best documents for some words, over dynamic and static shards alike."""
        now, (log, terms) = self.manifest(), self._log([text])
        return E.topk(self._counts(terms, now), log, max(1, now["documents"]), k, prune=True)

    def match(self, text: str) -> DataFrame:
        """(d): all documents with all of some words."""
        now, (log, terms) = self.manifest(), self._log([text])
        return E.conjunctive(self._counts(terms, now), log, now["documents"]).select("d")

    def phrase(self, text: str) -> DataFrame:
        """(d, hits): documents where some words stand in a row. For word-level indexes."""
        if self.cfg.level != "word":
            raise ValueError("a phrase asks for positions: the index holds documents")
        now, (log, terms) = self.manifest(), self._log([text])
        return E.phrase(self.postings(terms, now), log, now["documents"]).select("d", "hits")

    # -- upkeep -----------------------------------------------------------------------------------------------------

    def _replace(self, change, tries: int = 5) -> dict:
        """Publishes change(newest manifest), again if another writer was first."""
        for _ in range(tries):
            now = self.manifest()
            new = {**change(now), "version": now["version"] + 1}
            try:
                self._publish(new)
                return new
            except Conflict:
                continue
        raise Conflict(f"{tries} other writers came first")

    def collate(self) -> dict:
        """All batches as one, each list's blocks side by side: blocks move, their payloads are not read. Batches of
        inserts that came meanwhile stay behind it.

        Returns version, seconds, and documents that arrived while it ran."""
        began, now = time.time(), self.manifest()
        final = self._dynamic(now).where(~F.col("open")).select(*K._NAMES, "open", "made")
        whole = final.unionByName(self._open(now).withColumns({"open": F.lit(True), "made": F.lit(True)}))
        name = self._write(whole, now["version"])
        new = self._replace(lambda at: {**at, "batches": [name, *[b for b in at["batches"] if b not in now["batches"]]]})
        return {"version": new["version"], "seconds": time.time() - began, "documents_meanwhile": new["documents"] - now["documents"]}

    def to_static(self, code: str = "bp128", shards: list[int] | None = None) -> int:
        """Turns shards that get no more inserts into static lists, all such or those named; returns the new version."""
        if self.cfg.level != "doc":
            raise ValueError("static lists hold document-level postings")
        now = self.manifest()
        done = {s["shard"] for s in now["static"]}
        mine = [s for s in range(len(now["starts"]) - 1) if s not in done and (shards is None or s in shards)]
        if not mine:
            return now["version"]
        lists = K.decode_blocks(self.blocks(manifest=now).where(F.col("shard").isin(mine)), self.cfg).select("shard", "term", "d", "f")
        name = f"static={uuid.uuid4().hex}"
        bucket = F.pmod(F.crc32(F.col("term").cast("binary")), F.lit(self.buckets)).cast("int")
        runs = Z.build_static(lists, self.cfg, code, F.col("shard"))
        runs.withColumn("term_bucket", bucket).repartition("term_bucket").sortWithinPartitions("shard", "term", "block_no").write.partitionBy("term_bucket").parquet(f"{self.path}/{name}")
        return self._replace(lambda at: {**at, "static": [*at["static"], *[{"shard": s, "name": name, "code": code} for s in mine]]})["version"]

    def vacuum(self, versions: int = 2) -> list[str]:
        """Removes batches that none of the newest versions names; returns their names."""
        fs, path = self._hadoop()
        newest = self.manifest()["version"]
        used: set[str] = set()
        for v in range(max(0, newest - versions + 1), newest + 1):
            at = self.manifest(v)
            used |= set(at.get("batches", [])) | {s["name"] for s in at.get("static", [])}
        names = [s.getPath().getName() for s in fs.listStatus(path)]
        gone = [n for n in names if re.match(r"(batch|static)=", n) and n not in used]
        for n in gone:
            fs.delete(self._hadoop(n)[1], True)
        return gone


def terms_of(text: str) -> list[str]:
    """The words of a query, as the ascii tokens of documents are."""
    return re.findall("[a-z]{1,20}", (text or "").lower())
