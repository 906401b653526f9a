"""The corpus pipeline: quality rules, near-duplicates, decontamination, mixing and sharding of `documents`.

Each stage takes the rows that the one before it kept, as a stored table, and returns the columns of documents;
the last adds size, shard and slot. Stages tell rows apart by their place in the stored table and never by doc_id, so
that rows without doc_id, or with one that others have too, are judged like all others. Columns of documents whose
names an operator uses for its own are carried through unchanged. An empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from liveindex.llm import decontam, minhash, mixing, quality, shards
from liveindex.llm.common import drop, keep, narrow, saved, scope, table, words_in

NEEDED = ("doc_id", "text", "source")


def _all(docs: DataFrame) -> list:
    return [F.col(f"`{c}`") for c in docs.columns]


def _carried(docs: DataFrame, added: set[str], work: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """work(docs) with exactly the columns of docs, though work replaces columns of the names it adds."""
    if not added & {c.lower() for c in docs.columns}:
        return work(docs).select(*_all(docs))
    packed = docs.select(F.struct(*_all(docs)).alias("_document"), *[docs[c] for c in NEEDED])
    return work(packed).select("_document.*")


def _without(docs: DataFrame, gone: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """docs but for the rows whose places gone(places, with doc_id and text) returns as `place`."""
    packed = docs.select(F.monotonically_increasing_id().alias("place"), F.struct(*_all(docs)).alias("document"))
    out = packed.join(gone(narrow(docs, doc_id="doc_id", text="text").withColumn("place", F.monotonically_increasing_id())), "place", "left_anti")
    return out.select(*[F.col(f"document.`{c}`").alias(c) for c in docs.columns])


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the repetition rules keep. Null, empty and very short texts go, as the base rule fails them;
    repeated rows are judged alike."""
    added = {n for n, _ in quality.COLUMNS}
    return _carried(docs, added, lambda d: quality.repetition(d).where("kept"))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of copies (five words, similarity 0.8): the one of the smallest doc_id, those without
    one last, the first in the table of several. Texts without words are copies of nothing and stay."""

    def gone(rows: DataFrame) -> DataFrame:
        groups = minhash.near_duplicates(rows, doc_id="place", width=5, percent=80).select(F.col("doc_id").alias("place"), F.col("component_id").alias("component"))
        groups = saved(groups.join(rows.select("place", "doc_id"), "place"), "copies")
        best = groups.groupBy("component").agg(F.min(F.struct(F.col("doc_id").isNull().alias("unnamed"), "doc_id", "place")).alias("best"))
        # Rows meet the best places by their own, which no two share, and never by the component, which thousands may.
        return groups.select("place").join(best.select(F.col("best.place").alias("place")), "place", "left_anti")

    return _without(docs, gone)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no copy of a benchmark item. Null and empty texts hold none; repeated rows go or stay alike."""
    return _without(docs, lambda rows: decontam.leaks(rows, table(spark, sf_dir, "benchmark"), doc_id="place").select(F.col("doc_id").alias("place")).distinct())


def mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents repeated, kept once or left out so that the sources' words meet their targets. A null source is one of
    its own; texts without words weigh nothing and stay once."""

    def work(d: DataFrame) -> DataFrame:
        mixed = mixing.mix_sources(d.withColumn("_size", words_in("text")), size="_size")
        return mixed.where("copies > 0").withColumn("_copy", F.explode(F.sequence(F.lit(1), F.col("copies").cast("int"))))

    return _carried(docs, {*mixing.ADDED, "_size", "_copy"}, work)


def sharding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All rows with size, shard and slot, sixteen shards of nearly equal bytes. Null texts have size 1; rows that
    repeat have a slot each; columns of documents named size, shard or slot give way to the result's."""
    return shards.shard_by_bytes(docs)


STAGES = [("quality rules", quality_rules), ("near-duplicates", near_duplicates), ("decontamination", decontamination), ("mixture", mixture), ("sharding", sharding)]
#: SQL cannot express signatures, alignment and the balance of the sources; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The rows of the last stage. Scratch tables of a stage go once its rows are stored, and those rows once the next
    stage's are."""
    docs, last = table(spark, sf_dir, "documents"), None
    for name, stage in STAGES:
        with scope(spark):
            docs = keep(saved(stage(spark, docs, sf_dir), f"stage-{name.replace(' ', '-')}"))
        if last is not None:
            drop(last)
        last = docs
    return docs
