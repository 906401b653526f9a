"""Structured Streaming around the live index: ingest, operations, rates, trends, joins, late rows, standing queries.

Sinks write a micro-batch under its number, so that one that runs again after a failure replaces itself. Document
numbers follow arrival, so a late document is never out of order in an index; event time concerns rates, trends,
joins and late rows alone.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from liveindex.operators import evaluate as E
from liveindex.operators import packer as K
from liveindex.operators import postings as P
from liveindex.operators.search import query_terms
from liveindex.plans.store import LiveIndex
from liveindex.scratch import running_sum


def _started(stream: DataFrame, put: Callable[[DataFrame, int], None], checkpoint: str, trigger: dict | None, mode: str = "append"):
    return stream.writeStream.outputMode(mode).foreachBatch(put).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True})).start()


def stream_ingest(stream: DataFrame, index: LiveIndex, checkpoint: str, name: str = "ingest", trigger: dict | None = None):
    """Starts a query that inserts (d, terms) as they come. A micro-batch is one insert under a name of its own, so a
    batch that is run again after a failure is added once. trigger: as writeStream takes it; what is there by default."""

    def put(batch: DataFrame, number: int) -> None:
        batch = batch.select("d", "terms").persist()
        try:
            index.insert(batch, f"{name}-{number}")
        finally:
            batch.unpersist()

    return _started(stream, put, checkpoint, trigger)


_STATE = "block_no long, used long, n long, first_d long, last_d long, most long, payload binary"


def _extended(cfg: K.IndexConfig):
    def run(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        shard, term = key
        rows = pd.concat(list(frames)).sort_values("d")
        at = K.Chains(1)
        at.payload = [b""]
        if state.exists:
            z, used, n, first, last, most, payload = state.get
            for name, value in (("z", z), ("used", used), ("n", n), ("first", first), ("last", last), ("most", most)):
                getattr(at, name)[0] = value
            at.payload[0] = bytes(payload)
        had = bool(at.n[0])
        d, x = rows["d"].to_numpy(np.int64), rows["f"].to_numpy(np.int64)
        out = K._rows(np.array([shard]), pa.array([term]), d, x, np.array([0, d.size]), cfg, at).to_pandas()
        last = out.iloc[-1]
        state.update((int(last["block_no"]), int(last["used"]), int(last["n"]), int(last["first_d"]), int(last["last_d"]), int(last["most"]), bytes(last["payload"])))
        out["open"] = [False] * (len(out) - 1) + [True]
        out["made"] = [not had] + [True] * (len(out) - 1)
        yield out

    return run


def stateful_ingest(stream: DataFrame, cfg: K.IndexConfig, folder: str, checkpoint: str, trigger: dict | None = None):
    """Starts a query that keeps the open block of each list of (d, terms) in the state store and appends, micro-batch by
    micro-batch, the blocks that change: an insert reads nothing back but the state of its terms. For document-level
    indexes; documents come in the order of d. `stateful_blocks` reads the result."""
    postings = P.count_terms(stream).withColumn("shard", cfg.shard_of("d"))
    changed = postings.groupBy("shard", "term").applyInPandasWithState(_extended(cfg), K.CHANGED, _STATE, "append", GroupStateTimeout.NoTimeout)

    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/batch_no={number}")

    return _started(changed, put, checkpoint, trigger)


def stateful_blocks(spark: SparkSession, folder: str) -> DataFrame:
    """BLOCKS that stateful ingest has written: final ones, and the newest open one of each list."""
    rows = spark.read.parquet(folder)
    newest = F.max_by(F.struct(*[c for c in K._NAMES if c not in ("shard", "term")]), "batch_no").alias("b")
    tails = rows.where("open").groupBy("shard", "term").agg(newest).select("shard", "term", "b.*").select(*K._NAMES)
    done = rows.where("not open").select(*K._NAMES).withColumn("kind", F.lit("full")).unionByName(tails.withColumn("kind", F.lit("tail")))
    return done.withColumn("kind", F.when(F.col("block_no") == 1, "head").otherwise(F.col("kind")))


def ops_stream(ops: DataFrame, index: LiveIndex, answers: str, checkpoint: str, name: str = "ops", trigger: dict | None = None):
    """Starts a query over operations (seq, op, terms, qid) in which inserts and queries are mixed: an insert gets the
    next document number, a query sees exactly the inserts before it, those of its own micro-batch included. Conjunctive
    answers (op_seq, qid, d) are appended below `answers`.

    The documents before an operation are counted by a running sum over the micro-batch, not in one task."""

    def put(batch: DataFrame, number: int) -> None:
        batch = batch.select("seq", "op", "terms", "qid").persist()
        try:
            now = index.manifest()
            # A micro-batch that is in already runs again over the numbers it got then.
            again = now["names"].get(name, -1) >= number
            last = now["last_d"] - (batch.where("op = 'insert'").count() if again else 0)
            placed = running_sum(batch.withColumn("one", F.when(F.col("op") == "insert", 1).otherwise(0)), "one", "seq", "before").withColumn("d", (F.col("before") + last + 1).cast("long"))
            index.insert(placed.where("op = 'insert'").select("d", "terms"), f"{name}-{number}")
            queries = placed.where("op = 'query'").select("qid", "terms", F.col("d").alias("cut"), "seq")
            terms = sorted(r[0] for r in query_terms(queries).select("term").distinct().collect())  # of one micro-batch's queries
            found = E.conjunctive(index.postings(terms).withColumn("seq", F.col("d")), queries, cut="cut")
            found.join(queries.select("qid", F.col("seq").alias("op_seq")), "qid").select("op_seq", "qid", "d").write.mode("overwrite").parquet(f"{answers}/batch_no={number}")
        finally:
            batch.unpersist()

    return _started(ops, put, checkpoint, trigger)


def ingest_rate(events: DataFrame, ts: str = "ts", every: str = "1 hour", late: str = "1 day") -> DataFrame:
    """(start, n): events a tumbling window; rows later than the watermark are dropped, as windows close with it."""
    rows = events.select(F.col(ts).cast("timestamp").alias("at")).withWatermark("at", late)
    return rows.groupBy(F.window("at", every).alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")


def term_trend(stream: DataFrame, size: str = "2 hours", slide: str = "1 hour", late: str = "1 day") -> DataFrame:
    """(start, term, n) of a stream with (at, terms), over sliding windows."""
    rows = stream.withWatermark("at", late).select("at", F.explode("terms").alias("term"))
    return rows.groupBy(F.window("at", size, slide).alias("w"), "term").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "term", "n")


def sessions(events: DataFrame, key: str, ts: str = "ts", gap: str = "6 hours", late: str = "1 day") -> DataFrame:
    """(key, begin, n): runs of a key's events with no gap between two of them."""
    rows = events.select(F.col(key), F.col(ts).cast("timestamp").alias("at")).withWatermark("at", late)
    return rows.groupBy(key, F.session_window("at", gap).alias("s")).agg(F.count("*").alias("n")).select(key, F.col("s.start").alias("begin"), "n")


def dedup_docs(stream: DataFrame, key: str, at: str, within: str = "1 day") -> DataFrame:
    """The first row of each key; state is kept as long as the watermark allows."""
    return stream.withWatermark(at, within).dropDuplicatesWithinWatermark([key])


def enrich(stream: DataFrame, static: DataFrame, key: str) -> DataFrame:
    """Rows of a stream with the columns of a static table; stateless, and rows that it does not know stay."""
    return stream.join(static, key, "left")


def interval_join(left: DataFrame, right: DataFrame, key: str, ts: str = "ts", within: str = "6 hours", late: str = "1 day") -> DataFrame:
    """(key, at, other_at) of pairs of two streams in which the right one follows the left within a time. Watermarks on
    both sides and the range bound the state."""
    a = left.select(F.col(key).alias("a_key"), F.col(ts).cast("timestamp").alias("at")).withWatermark("at", late)
    b = right.select(F.col(key).alias("b_key"), F.col(ts).cast("timestamp").alias("other_at")).withWatermark("other_at", late)
    near = F.expr(f"a_key = b_key AND other_at >= at AND other_at <= at + INTERVAL {within}")
    return a.join(b, near).select(F.col("a_key").alias(key), "at", "other_at")


def _flagged(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    mark = pd.Timestamp(state.getCurrentWatermarkMs(), unit="ms")
    for rows in frames:
        rows["late"] = rows["at"].dt.tz_localize(None) < mark if rows["at"].dt.tz is None else rows["at"].dt.tz_convert("UTC").dt.tz_localize(None) < mark
        yield rows[["key", "at", "late"]]


def late_rows(stream: DataFrame, key: str, ts: str = "ts", within: str = "1 hour") -> DataFrame:
    """(key, at, late): every row, and whether the watermark had passed it when it came. None is dropped: a policy may
    append late rows, leave them out, or put them aside."""
    rows = stream.select(F.col(key).cast("string").alias("key"), F.col(ts).cast("timestamp").alias("at")).withWatermark("at", within)
    return rows.groupBy("key").applyInPandasWithState(_flagged, "key string, at timestamp, late boolean", "seen boolean", "append", GroupStateTimeout.NoTimeout)


def _idle(after_ms: int):
    def run(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            n, last = state.get
            state.remove()
            yield pd.DataFrame({"term": [key[0]], "n": [n], "last_ms": [last]})
            return
        n, last = state.get if state.exists else (0, 0)
        for rows in frames:
            n, last = n + len(rows), max(last, int(rows["at_ms"].max()))
        state.update((n, last))
        state.setTimeoutTimestamp(max(last, state.getCurrentWatermarkMs()) + after_ms)

    return run


def idle_terms(stream: DataFrame, after: int = 3600, late: str = "1 hour") -> DataFrame:
    """(term, n, last_ms) of each term of (at, terms) once it has not been seen for `after` seconds of event time: a timer
    a term takes its state out of memory, so that what is held follows the active vocabulary."""
    rows = stream.withWatermark("at", late).select("at", F.explode("terms").alias("term")).select("term", "at", F.unix_millis("at").alias("at_ms"))
    return rows.groupBy("term").applyInPandasWithState(_idle(1000 * after), "term string, n long, last_ms long", "n long, last long", "append", GroupStateTimeout.EventTimeTimeout)


def state_rows(spark: SparkSession, checkpoint: str) -> DataFrame:
    """Keys and values that a stopped or running query holds, read from its checkpoint."""
    return spark.read.format("statestore").load(checkpoint)


def standing_queries(stream: DataFrame, queries: DataFrame) -> DataFrame:
    """(d, qid): stored conjunctions that each new document meets; stateless, inside a document.

    The words of the queries travel to the documents if they are counted and few; each document looks its own words
    up, so the work is that of its words and not of all queries."""
    wanted = query_terms(queries)
    rows = [tuple(r) for r in wanted.limit(E.BLOCK_PAIRS + 1).collect()]
    if len(rows) > E.BLOCK_PAIRS:
        return _standing_joined(stream, wanted)
    need: dict[int, int] = {q: n for q, _, n in rows}
    by_term: dict[str, list[int]] = {}
    for q, t, _ in rows:
        by_term.setdefault(t, []).append(q)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            docs, found = [], []
            for d, terms in zip(batch.column("d").to_pylist(), batch.column("terms").to_pylist(), strict=True):
                met: dict[int, int] = {}
                for t in set(terms or ()):
                    for q in by_term.get(t, ()):
                        met[q] = met.get(q, 0) + 1
                hits = [q for q, n in met.items() if n == need[q]]
                docs += [d] * len(hits)
                found += hits
            yield pa.RecordBatch.from_arrays([pa.array(docs, pa.int64()), pa.array(found, pa.int64())], names=["d", "qid"])

    return stream.select("d", "terms").mapInArrow(run, "d long, qid long")


def _standing_joined(stream: DataFrame, wanted: DataFrame) -> DataFrame:
    """The same for more queries than travel: a document's words meet the queries' by a join and are counted."""
    words = stream.select("d", F.explode(F.array_distinct("terms")).alias("term"))
    return words.join(wanted, "term").groupBy("d", "qid").agg(F.count("*").alias("m"), F.first("n_terms").alias("n")).where("m = n").select("d", "qid")
