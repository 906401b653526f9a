"""Queries opN_<name>: each applies its operator to its whole table and returns the operator's rows as a digest."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from liveindex.llm import decontam, html, licences, minhash, mixing, quality, records, shards, spans, sql, warc
from liveindex.llm.common import narrow, saved, table, words_in

QUERIES: dict = {}
#: The other queries hold signatures, alignments, optima or files, which tests hold against brute force.
ORACLES: dict[str, str] = {"op2_repetition": sql.repetition(), "op5_superminhash": sql.near_duplicates(), "op8_column_bwt": sql.repeated_spans()}


def query(f):
    QUERIES[f.__name__] = f
    return f


@query
def op1_block_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = narrow(table(spark, sf_dir, "pages"), page_id="page_id", url="url", html="html")
    return html.extract_main_text(pages).withColumn("n_chars", F.length("text").cast("long"))


@query
def op2_repetition(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = narrow(table(spark, sf_dir, "documents"), doc_id="doc_id", text="text")
    return quality.repetition(docs).drop("text")


@query
def op3_sampled_splitters(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = narrow(table(spark, sf_dir, "documents"), doc_id="doc_id", text="text")
    crc = F.crc32(F.coalesce(F.col("text"), F.lit("")).cast("binary")).alias("text_crc32")
    digest = saved(shards.keyed(docs).select("doc_id", *shards.KEY, "size", crc), "shard-keys")
    out = shards.shard_by_bytes(digest, digest=digest)
    return out.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


@query
def op4_entropy_balance(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    sizes = saved(narrow(docs, doc_id="doc_id", source="source", text="text").select("doc_id", "source", words_in("text").alias("size")), "mixing-words")
    mixed = mixing.mix_sources(sizes)
    return mixed.select("doc_id", "size", "source_size", "target", (F.col("size") * F.col("copies")).alias("taken"), "rate", "copies")


@query
def op5_superminhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhash.near_duplicates(table(spark, sf_dir, "documents"), width=4)


@query
def op6_seed_and_align(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontam.leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


@query
def op7_merkle_audit(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All pages as WARC files, and the audit of a replica in which about every hundredth record is damaged: those whose
    digest begins with 00, 7f or c3."""
    found = warc.write_warc(table(spark, sf_dir, "pages"))
    replica = warc.copy_replica(found, found.folder, damaged=F.substring("digest", 1, 2).isin("00", "7f", "c3"))
    return warc.fixity(found, replica).select("page_id", "url", "file", "at", "offset", "length", "digest", "intact")


@query
def op8_column_bwt(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = spans.remove_repeats(table(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256")


def _vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


@query
def op9_token_records(spark: SparkSession, sf_dir: str) -> DataFrame:
    manifest = records.write_records(table(spark, sf_dir, "documents"), _vocabulary())
    return records.read_records(manifest, tokens=False)


@query
def op10_licences(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = narrow(table(spark, sf_dir, "documents"), doc_id="doc_id", text="text")
    return licences.scan_licences(docs).drop("text", "licence_spans")
