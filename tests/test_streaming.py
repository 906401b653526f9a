import datetime as dt

import pytest
from pyspark.sql import functions as F

from liveindex.streaming import ingest as I
from liveindex.workloads.streams import finished

DAY = dt.datetime(2024, 1, 1)


def fed(spark, folder, batches, schema):
    """A stream of batches, one file after the other."""
    for rows in batches:
        spark.createDataFrame(rows, schema).coalesce(1).write.mode("append").parquet(str(folder))
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(str(folder))


def test_late_rows_are_told_and_kept(spark, tmp_path):
    at = lambda h: DAY + dt.timedelta(hours=h)
    stream = fed(spark, tmp_path / "in", [[("a", at(10)), ("b", at(11))], [("a", at(12))], [("a", at(2)), ("b", at(12))]], "k string, ts timestamp")
    got = sorted((r["key"], r["at"].hour, r["late"]) for r in finished(I.late_rows(stream, "k")).collect())
    assert got == [("a", 2, True), ("a", 10, False), ("a", 12, False), ("b", 11, False), ("b", 12, False)]


def test_idle_terms_leave_the_state(spark, tmp_path):
    at = lambda h: DAY + dt.timedelta(hours=h)
    stream = fed(spark, tmp_path / "in", [[(at(1), ["x", "y"])], [(at(2), ["y"])], [(at(9), ["z"])], [(at(10), ["z"])]], "at timestamp, terms array<string>")
    got = sorted((r["term"], r["n"]) for r in finished(I.idle_terms(stream, 3600)).collect())
    assert got == [("x", 1), ("y", 2)]


def test_windows_of_streams(spark, tmp_path):
    at = lambda h: DAY + dt.timedelta(hours=h)
    rows = [[(1, at(1), ["x"]), (1, at(2), ["x", "y"])], [(2, at(20), ["x"])]]
    schema = "k long, ts timestamp, terms array<string>"
    got = finished(I.sessions(fed(spark, tmp_path / "a", rows, schema), "k", late="0 seconds", gap="3 hours")).collect()
    assert sorted((r["k"], r["begin"].hour, r["n"]) for r in got) == [(1, 1, 2)]  # the other session is still open
    trend = I.term_trend(fed(spark, tmp_path / "b", rows, schema).withColumnRenamed("ts", "at"))
    assert finished(trend, "complete").where("term = 'x'").agg(F.max("n")).first()[0] == 2
    unique = finished(I.dedup_docs(fed(spark, tmp_path / "c", [[(1, at(1), ["x"])], [(1, at(2), ["x"]), (3, at(2), [])]], schema), "k", "ts", "5 hours"))
    assert sorted(r["k"] for r in unique.collect()) == [1, 3]


def test_restart_goes_on_with_the_state(spark, tmp_path):
    from liveindex.operators import packer as K
    from liveindex.operators import postings as P

    cfg, schema = K.IndexConfig(B=40), "d long, terms array<string>"
    docs = [(d, ["a", "b" if d % 2 else "c"] * (d % 5)) for d in range(1, 120)]
    for part in (docs[:50], docs[50:]):
        stream = fed(spark, tmp_path / "in", [part], schema)
        I.stateful_ingest(stream, cfg, str(tmp_path / "out"), str(tmp_path / "ck")).awaitTermination()
    want = K.build_blocks(P.count_terms(spark.createDataFrame(docs, schema)), cfg)
    assert sorted(map(tuple, I.stateful_blocks(spark, str(tmp_path / "out")).collect())) == sorted(map(tuple, want.collect()))
    assert I.state_rows(spark, str(tmp_path / "ck")).count() == 3


@pytest.mark.parametrize("trigger", [{"availableNow": True}, {"once": True}])
def test_triggers(spark, tmp_path, trigger):
    from liveindex.plans.store import LiveIndex

    index = LiveIndex(spark, str(tmp_path / "index"))
    stream = fed(spark, tmp_path / "in", [[(1, ["a"])]], "d long, terms array<string>")
    I.stream_ingest(stream, index, str(tmp_path / "ck"), trigger=trigger).awaitTermination()
    assert index.match("a").count() == 1


def test_standing_queries_by_both_ways(spark):
    docs = spark.createDataFrame([(1, ["a", "b"]), (2, ["b", "c"]), (3, []), (4, None)], "d long, terms array<string>")
    queries = spark.createDataFrame([(1, ["a", "b"]), (2, ["b"]), (3, ["x"]), (4, [])], "qid long, terms array<string>")
    want = [(1, 1), (1, 2), (2, 2)]
    assert sorted(map(tuple, I.standing_queries(docs, queries).collect())) == want
    assert sorted(map(tuple, I._standing_joined(docs, I.query_terms(queries)).collect())) == want
