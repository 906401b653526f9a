"""Streams run to their end over files of the tables, and what they leave, against the SQL of the batch."""

from __future__ import annotations

from pyspark.sql import functions as F

from liveindex.operators import packer as K
from liveindex.plans.store import LiveIndex
from liveindex.registry import register
from liveindex.scratch import folder
from liveindex.sources import collections as S
from liveindex.sources import querylog as L
from liveindex.streaming import ingest as I
from liveindex.workloads import sqlparts as Q
from liveindex.workloads.search import _OPS, _QT

_COLUMNS = ("term", "block_no", "kind", "cap", "first_d", "last_d", "n", "used")


def staged(df, order: str, files: int = 3):
    """A stream of df's rows in files that come one after the other, by ranges of a column."""
    spark, where = df.sparkSession, folder(df.sparkSession, "staged")
    low, high = df.agg(F.min(order), F.max(order)).first()
    step = max(1, -(-(high - low + 1) // files))
    for k in range(files):
        df.where(F.col(order).between(low + k * step, low + (k + 1) * step - 1)).coalesce(1).write.mode("append").parquet(where)
    return spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(where)


def finished(stream, mode: str = "append"):
    """Rows that a stream leaves once all that is there has been read."""
    spark, where, checkpoint = stream.sparkSession, folder(stream.sparkSession, "stream-out"), folder(stream.sparkSession, "checkpoint")

    def put(batch, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{where}/batch_no={number}")

    I._started(stream, put, checkpoint, None, mode).awaitTermination()
    return spark.read.schema(stream.schema).parquet(where).select(*stream.columns)


@register("stream_blocks", f"WITH RECURSIVE {Q.packed('turns')}, {Q.blocks()} SELECT term, block_no, kind, cap, first_d, last_d, n, used FROM tab")
def stream_blocks(spark, sf_dir):
    """Chains in the state store, fed in three micro-batches."""
    cfg = K.IndexConfig()
    where, checkpoint = folder(spark, "stream-blocks"), folder(spark, "checkpoint")
    stream = staged(S.turns(spark, sf_dir).select("d", "terms"), "d")
    I.stateful_ingest(stream, cfg, where, checkpoint).awaitTermination()
    return I.stateful_blocks(spark, where).select(*_COLUMNS)


@register("stream_inserts", f"WITH RECURSIVE {Q.packed('turns')}, {Q.blocks()} SELECT term, block_no, kind, cap, first_d, last_d, n, used FROM tab")
def stream_inserts(spark, sf_dir):
    """The stored index fed by a stream."""
    index = LiveIndex(spark, folder(spark, "live-index"))
    I.stream_ingest(staged(S.turns(spark, sf_dir).select("d", "terms"), "d"), index, folder(spark, "checkpoint")).awaitTermination()
    return index.blocks().select(*_COLUMNS)


@register("stream_ops", f"WITH {_QT}, {_OPS} SELECT o.op_seq, q.qid, p.d FROM qt q JOIN ops o ON o.qid = q.qid JOIN {Q.counts('docs')} p ON p.term = q.term AND 2 * p.d < o.op_seq GROUP BY o.op_seq, q.qid, p.d, q.n_terms HAVING count(*) = q.n_terms")
def stream_ops(spark, sf_dir):
    """Inserts and queries in one stream: each query sees the inserts before it."""
    docs = S.docs(spark, sf_dir).select("seq", F.lit("insert").alias("op"), "terms", F.lit(None).cast("long").alias("qid"))
    n = S.table(spark, sf_dir, "documents").count()
    asked = L.query_log(spark, sf_dir).select((1 + 2 * (F.col("qid") % n)).alias("seq"), F.lit("query").alias("op"), "terms", "qid")
    index, answers = LiveIndex(spark, folder(spark, "live-index")), folder(spark, "answers")
    I.ops_stream(staged(docs.unionByName(asked), "seq"), index, answers, folder(spark, "checkpoint")).awaitTermination()
    return spark.read.parquet(answers).select("op_seq", "qid", "d")


def _events(spark, sf_dir):
    return S.table(spark, sf_dir, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type")


@register("stream_rate", "SELECT strftime(date_trunc('hour', ts), '%Y-%m-%d %H') AS hour, count(*) AS n FROM events GROUP BY 1")
def stream_rate(spark, sf_dir):
    out = finished(I.ingest_rate(staged(_events(spark, sf_dir), "event_id"), late="60 days"), "complete")
    return out.groupBy(F.date_format("start", "yyyy-MM-dd HH").alias("hour")).agg(F.max("n").alias("n"))


@register("stream_interval_join", "SELECT a.user_id, strftime(a.ts, '%Y-%m-%d %H:%M:%S.%f') AS at_text, strftime(b.ts, '%Y-%m-%d %H:%M:%S.%f') AS other_text FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type <> 'view' AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 6 HOURS")
def stream_interval_join(spark, sf_dir):
    """Two streams: what a user does within six hours of a view."""
    events = _events(spark, sf_dir)
    left, right = staged(events.where("event_type = 'view'"), "event_id"), staged(events.where("event_type <> 'view'"), "event_id")
    out = finished(I.interval_join(left, right, "user_id", late="60 days"))
    text = lambda c: F.date_format(c, "yyyy-MM-dd HH:mm:ss.SSSSSS")
    return out.select("user_id", text("at").alias("at_text"), text("other_at").alias("other_text"))


@register("stream_enriched", "SELECT d.doc_id, l.quality, l.toxic FROM documents d LEFT JOIN labels l ON l.doc_id = d.doc_id")
def stream_enriched(spark, sf_dir):
    docs = staged(S.table(spark, sf_dir, "documents").select("doc_id", "lang"), "doc_id")
    return finished(I.enrich(docs, S.table(spark, sf_dir, "labels"), "doc_id")).select("doc_id", "quality", "toxic")


@register("stream_dedup", "SELECT user_id, count(*) AS n FROM (SELECT DISTINCT user_id FROM events) GROUP BY user_id")
def stream_dedup(spark, sf_dir):
    """Each user's first event, the others suppressed."""
    out = finished(I.dedup_docs(staged(_events(spark, sf_dir), "event_id"), "user_id", "ts", "60 days"))
    return out.groupBy("user_id").agg(F.count("*").alias("n"))
