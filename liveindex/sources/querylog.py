"""Query logs from the benchmark passages: windows of consecutive words, kept if every collection has a match."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from liveindex.operators.postings import count_terms
from liveindex.operators.search import conjunctive
from liveindex.scratch import numbered, written
from liveindex.sources import collections as S

LONGEST, STRIDE = 6, 5


def query_log(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(qid, terms): windows of 1 to LONGEST words at every STRIDE-th word; qid = (item * 1000 + position) * 10 + length."""
    items = S.table(spark, sf_dir, "benchmark").select("item_id", S.tokens(F.col("text")).alias("t"))
    at = items.select("item_id", "t", F.explode(F.expr(f"case when size(t) > 0 then sequence(1, size(t), {STRIDE}) end")).alias("pos"))
    every = at.select("item_id", "t", "pos", F.explode(F.array(*map(F.lit, range(1, LONGEST + 1)))).alias("n")).where(F.col("pos") + F.col("n") - 1 <= F.size("t"))
    return every.select(((F.col("item_id") * 1000 + F.col("pos")) * 10 + F.col("n")).alias("qid"), F.expr("array_distinct(slice(t, pos, n))").alias("terms"))


def filtered(spark: SparkSession, sf_dir: str, log: DataFrame | None = None) -> DataFrame:
    """The log's queries that have a conjunctive match in docs, pages and turns."""
    log = query_log(spark, sf_dir) if log is None else log
    for make in (S.docs, S.pages, S.turns):
        log = written(log.join(conjunctive(count_terms(make(spark, sf_dir)), log).select("qid").distinct(), "qid", "left_semi"), "query-log")
    return log


def turns_log(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(qid, terms): the first four words of each turn of a user; qid = conversation * 1000 + turn."""
    rows = S.table(spark, sf_dir, "conversations").where("role = 'user'")
    words = F.slice(S.tokens(F.col("text")), 1, 4)
    return rows.select((F.col("conv_id") * 1000 + F.col("turn")).alias("qid"), F.array_distinct(words).alias("terms")).where(F.size("terms") > 0)


def baskets_log(spark: SparkSession, sf_dir: str, queries: int = 2000) -> DataFrame:
    """(qid, terms): pairs and triples of terms of the order baskets, picked by a rule: the k-th query takes places
    k, 7 k + 3 and, if k is odd, 13 k + 5 of the sorted vocabulary, round its end."""
    terms = S.baskets(spark, sf_dir).select(F.explode("terms").alias("term")).distinct()
    vocabulary = numbered(terms, "term", into="at").select("term", (F.col("at") - 1).alias("at"))
    size = vocabulary.count()
    steps = F.when(F.col("qid") % 2 == 1, F.array(F.col("qid"), 7 * F.col("qid") + 3, 13 * F.col("qid") + 5)).otherwise(F.array(F.col("qid"), 7 * F.col("qid") + 3))
    asked = spark.range(queries).withColumnRenamed("id", "qid").select("qid", F.explode(F.transform(steps, lambda x: F.pmod(x, F.lit(size)))).alias("at"))
    return asked.join(vocabulary, "at").groupBy("qid").agg(F.array_sort(F.collect_set("term")).alias("terms"))
