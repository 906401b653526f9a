import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from pyspark.sql import functions as F

from liveindex.functions import codecs
from liveindex.operators import arrays as A
from liveindex.operators import baselines as B
from liveindex.operators import evaluate as E
from liveindex.operators import growth as G
from liveindex.operators import packer as K
from liveindex.operators import postings as P
from liveindex.operators import search as X
from liveindex.operators import static as Z

numbers = st.lists(st.integers(1, 1 << 40), max_size=60)


@given(numbers)
@settings(max_examples=60, deadline=None)
def test_byte_code_round_trip(x):
    data = codecs.vbyte_encode(np.array(x, np.int64))
    assert codecs.vbyte_decode(data).tolist() == x
    assert codecs.vbyte_decode(np.append(data, np.zeros(5, np.uint8))).tolist() == x and len(data) == codecs.vbyte_lens(np.array(x, np.int64)).sum()


@given(st.lists(st.tuples(st.integers(1, 1 << 30), st.integers(1, 300)), max_size=60), st.integers(1, 16))
@settings(max_examples=80, deadline=None)
def test_paired_code_round_trip(pairs, f):
    a, b = (np.array([p[k] for p in pairs], np.int64) for k in (0, 1))
    data = codecs.pair_encode(a, b, f)
    x, y = codecs.pair_decode(data, f)
    assert x.tolist() == a.tolist() and y.tolist() == b.tolist()
    assert len(data) == codecs.pair_lens(a, b, f).sum()


@given(st.sets(st.integers(1, 5000), max_size=150))
@settings(max_examples=40, deadline=None)
def test_interpolative_round_trip(x):
    x = sorted(x)
    assert codecs.interp_decode(codecs.interp_encode(x, 1, 5000), len(x), 1, 5000) == x


@given(st.lists(st.integers(0, 1 << 20), max_size=400))
@settings(max_examples=40, deadline=None)
def test_bit_packing_round_trip(x):
    x = [v + 1 for v in x]
    assert codecs.bp_decode(codecs.bp_encode(np.array(x, np.int64))).tolist() == x


def test_worked_codes():
    assert codecs.vbyte_encode(np.array([12345])).tolist() == [0x39, 0xE0]
    assert codecs.pair_numbers([10], [3], 4)[0].tolist() == [39]
    assert codecs.pair_numbers([40], [3], 4)[0].tolist() == [159]
    assert codecs.pair_numbers([40], [5], 4)[0].tolist() == [160, 2]
    assert [int(codecs.pair_lens(np.array([a]), np.array([b]), 4)[0]) for a, b in ((10, 3), (40, 3), (40, 5))] == [1, 2, 3]


def test_growth_rules():
    assert G.sizes("geometric", 16, 4, 9, 1.5) == [16, 16, 16, 32, 48, 64, 96, 144, 208]
    assert G.sizes("triangular", 16, 4, 9) == [16, 16, 32, 32, 32, 48, 48, 48, 48]
    n = 20_000
    b = math.ceil(math.sqrt(2 * 4 * n))
    z = -(-n // (b - 4))
    assert (b, z, 4 * z, z * (b - 4) - n) == (400, 51, 204, 196)
    copied, peak = G.array_copies(10_000, 2)
    assert copied <= 10_000 * 2 / (2 - 1) and peak >= 10_000
    ratios = [(sum(G.sizes_until("triangular", 16, 1, n, cap=None)) - n) / n * math.sqrt(n) for n in (10**4, 10**5, 10**6)]
    assert max(ratios) < 3.5


def test_triangular_cycle(spark):
    row = G.curve(spark, "triangular", 16, 1, 50_000).where("lo_n <= 49840 and hi_n >= 49840").first()
    assert (row["lo_n"], row["hi_n"]) == (49_681, 49_999) and round(row["overhead"] / 49_840 * 100, 2) == 0.9


def test_config_is_checked():
    for bad in ({"B": 32}, {"level": "page"}, {"growth": "none"}, {"F": 0}):
        with pytest.raises(ValueError):
            K.IndexConfig(**bad)
    assert B.capacity(64, 2.0, 2.0)[0] == 256 << 30


def plain(lists, cfg):
    """Packs one posting at a time: (term, block, first_d, used) and total bytes."""
    blocks, total = [], 0
    for term, postings in lists.items():
        sizes = G.sizes(cfg.growth, cfg.B, cfg.h, len(postings) + 2, cfg.k)
        z, used, cap, first, last, n = 1, 0, sizes[0] - cfg.head_bytes - len(term), 0, 0, 0
        for d, f in postings:
            one = int(codecs.pair_lens(np.array([d - last]), np.array([f]), cfg.threshold)[0])
            if used + one > cap:
                blocks.append((term, z, first if n else 0, used))
                one = int(codecs.pair_lens(np.array([d - first]), np.array([f]), cfg.threshold)[0])
                z, used, cap, first, n = z + 1, 0, sizes[z] - cfg.h, d, 0
            elif not n:
                first = d
            used, last, n = used + one, d, n + 1
        blocks.append((term, z, first, used))
        total += sum(sizes[:z]) + 8
    return sorted(blocks), total


@pytest.mark.parametrize("rule,unit", [("constant", 40), ("geometric", 48), ("triangular", 64)])
def test_packer_against_plain_one(spark, rule, unit):
    rng = np.random.default_rng(unit)
    lists = {}
    for t in ["a", "letters" * 2, "x" * 20, "long"]:
        d = np.unique(rng.integers(1, 60_000 if t != "long" else 4000, 600 if t != "x" * 20 else 1)).tolist()
        lists[t] = [(x, int(f)) for x, f in zip(d, rng.integers(1, 9, len(d)), strict=True)]
    rows = [(t, d, f) for t, p in lists.items() for d, f in p]
    cfg = K.IndexConfig(B=unit, growth=rule)
    postings = spark.createDataFrame(rows, "term string, d long, f long")
    blocks = K.build_blocks(postings, cfg)
    want, total = plain(lists, cfg)
    assert sorted(map(tuple, blocks.select("term", "block_no", "first_d", "used").collect())) == want
    assert K.index_bytes(blocks, cfg).first()["total_bytes"] == total
    assert K.component_table(blocks, cfg).groupBy().sum("bytes").first()[0] == total
    assert sorted(map(tuple, K.decode_blocks(blocks, cfg).select("term", "d", "f").collect())) == sorted(rows)


def some_docs(n=200, seed=3, kinds=40):
    rng = np.random.default_rng(seed)
    return [(d, [f"t{int(x)}" for x in np.minimum(rng.zipf(1.4, rng.integers(0, 30)), kinds)]) for d in range(1, n)]


def test_queries_against_brute_force(spark):
    rng = np.random.default_rng(3)
    docs = some_docs()
    stream = spark.createDataFrame(docs, "d long, terms array<string>")
    log = [(q, [f"t{int(x)}" for x in rng.integers(1, 12, rng.integers(1, 4))]) for q in range(30)] + [(99, ["t1", "nowhere"]), (100, []), (101, None)]
    queries = spark.createDataFrame(log, "qid long, terms array<string>")
    counts = P.count_terms(stream)
    want = sorted((q, d) for q, ts in log if ts for d, terms in docs if set(ts) <= set(terms))
    cfg = K.IndexConfig(B=40)
    for shard_docs in (1 << 20, 37):
        cut = K.IndexConfig(B=40, shard_docs=shard_docs)
        blocks = K.build_blocks(counts, cut)
        runs = Z.build_static(counts, cut, "interp")
        for got in (X.conjunctive_by_seek(blocks, queries, cut), A.conjunctive(blocks, queries, cut), A.conjunctive(runs, queries, cut, "interp"), X.conjunctive_by_seek(runs, queries, cut, lambda some: Z.decode_static(some, "interp"))):
            assert sorted(map(tuple, got.collect())) == want
    for got in (X.conjunctive(counts, queries), X.conjunctive(counts, queries, "count"), X.conjunctive(counts, queries, "semijoin")):
        assert sorted(map(tuple, got.collect())) == want
    ft = {t: sum(t in set(terms) for _, terms in docs) for t in {t for _, terms in docs for t in terms}}
    best = []
    for q, ts in log:
        scores = sorted((-round(sum(math.log(1 + terms.count(t)) * math.log(1 + 199 / ft[t]) for t in set(ts or ()) if t in terms), 6), d) for d, terms in docs if set(ts or ()) & set(terms))
        best += [(q, k, d, -s) for k, (s, d) in enumerate(scores[:5], 1)]
    for got in (X.topk(counts, queries, 199, 5), X.topk(counts, queries, 199, 5, prune=True), X.topk_pruned(counts, queries, 199, 5), X.topk_joined(counts, queries, 199, 5)):
        assert sorted(map(tuple, got.collect())) == sorted(best)
    stats = E.topk(counts, queries, 199, 5, prune=True, stats=True).agg({"postings": "sum", "touched": "sum"}).first()
    assert 0 < stats[1] and 0 < stats[0]


def test_joined_ranking_copies_no_list_across_tasks(spark):
    docs = some_docs()
    counts = P.count_terms(spark.createDataFrame(docs, "d long, terms array<string>"))
    queries = spark.createDataFrame([(q, ["t1", f"t{q % 9 + 1}"]) for q in range(300)], "qid long, terms array<string>")
    found = X.topk_joined(counts, queries, 199)
    assert sorted(map(tuple, found.collect())) == sorted(map(tuple, X.topk(counts, queries, 199).collect()))
    plan = found._jdf.queryExecution().executedPlan().toString()
    assert "hashpartitioning(qid" not in plan and "hashpartitioning(shard" in plan


def test_pruned_ranking_skips_lists_and_copies_none(spark):
    docs = [(d, ["common"] * (d % 3 + 1) + (["rare"] * (d % 5 + 9) if d % 20 == 0 else []) + ([f"t{d % 7}"] if d % 2 else [])) for d in range(1, 3000)]
    counts = P.count_terms(spark.createDataFrame(docs, "d long, terms array<string>"))
    queries = spark.createDataFrame([(1, ["rare", "common"]), (2, ["t1", "t2", "common"]), (3, ["rare", "nowhere"]), (4, ["nowhere"]), (5, None)], "qid long, terms array<string>")
    found = X.topk_pruned(counts, queries, 2999)
    assert sorted(map(tuple, found.collect())) == sorted(map(tuple, X.topk(counts, queries, 2999).collect()))
    plan = found._jdf.queryExecution().executedPlan().toString()
    assert "hashpartitioning(qid" not in plan and "hashpartitioning(shard" in plan
    stats = {r["qid"]: r for r in E.topk(counts, queries, 2999, strategy="bounds", stats=True).collect()}
    assert stats[1]["touched"] < stats[1]["postings"]  # the common list is looked up only


def test_blocks_of_queries_and_empty_inputs(spark, monkeypatch):
    docs = some_docs(60)
    counts = P.count_terms(spark.createDataFrame(docs, "d long, terms array<string>"))
    queries = spark.createDataFrame([(q, [f"t{q % 5 + 1}", f"t{q % 3 + 1}"]) for q in range(40)], "qid long, terms array<string>")
    whole = sorted(map(tuple, X.conjunctive(counts, queries).collect()))
    monkeypatch.setattr(E, "BLOCK_PAIRS", 9)
    assert sorted(map(tuple, X.conjunctive(counts, queries).collect())) == whole
    for call in (lambda c, q: X.conjunctive(c, q), lambda c, q: X.topk(c, q, 60), lambda c, q: E.disjunctive_counts(c, q)):
        assert call(counts.limit(0), queries).count() == 0 and call(counts, queries.limit(0)).count() == 0


def test_phrases_with_repeated_words(spark):
    docs = [(1, ["a", "a", "b", "a"]), (2, ["a", "b", "a", "b"]), (3, []), (5000, ["b", "a", "a"])]
    at = P.occurrences(spark.createDataFrame(docs, "d long, terms array<string>"))
    queries = spark.createDataFrame([(1, ["a", "a"]), (2, ["a", "b"]), (3, ["b", "a", "a"]), (4, ["c"]), (5, ["a"])], "qid long, terms array<string>")
    assert sorted(map(tuple, X.phrase(at, queries).collect())) == [(1, 1, 1), (1, 5000, 1), (2, 1, 1), (2, 2, 2), (3, 5000, 1), (5, 1, 3), (5, 2, 2), (5, 5000, 2)]


def test_proximity_deals_each_place_once(spark):
    rng = np.random.default_rng(4)
    docs = [(d, [f"t{x}" for x in rng.integers(0, 6, rng.integers(0, 40)).tolist()]) for d in (1, 2, 3, 1023, 1024, 1025, 5000)]
    at = P.occurrences(spark.createDataFrame(docs, "d long, terms array<string>"))
    pairs = [(q, f"t{q % 6}", f"t{q // 6 % 7}") for q in range(42)]
    got = X.proximity(at, spark.createDataFrame(pairs, "qid long, t1 string, t2 string"), 5, 5000)
    want = [(q, d, sum(abs(i - j) <= 5 for i, a in enumerate(ts) if a == x for j, b in enumerate(ts) if b == y)) for q, x, y in pairs for d, ts in docs]
    assert sorted(map(tuple, got.collect())) == sorted(r for r in want if r[2])
    # One shuffle, by the shard of the document: no place is copied for each query that asks for its word.
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "hashpartitioning(shard" in plan and "hashpartitioning(qid" not in plan


def test_operations_see_what_came_before(spark):
    docs = some_docs(80, 5, 6)
    counts = P.count_terms(spark.createDataFrame(docs, "d long, terms array<string>")).withColumn("seq", F.col("d") * 2)
    ops = spark.createDataFrame([(q, ["t1", f"t{q % 4 + 1}"], 1 + 2 * (q * 7 % 80)) for q in range(30)], "qid long, terms array<string>, op_seq long")
    want = sorted((s, q, d) for q, ts, s in map(tuple, ops.collect()) for d, terms in docs if 2 * d < s and set(ts) <= set(terms))
    assert sorted(map(tuple, X.ops_conjunctive(counts, ops).collect())) == want


def test_batches_are_coded_a_chunk_at_a_time(spark):
    stream = spark.createDataFrame(some_docs(400, 6), "d long, terms array<string>").repartition(3)
    got = B.merge_batches(stream, 3)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, P.postings_doc(stream).collect()))
    # Parts come from sorted rows, many at a time; before, each was an array of its own, coded by calls of its own.
    assert "collect_list" not in got._jdf.queryExecution().optimizedPlan().toString()


def test_gaps_and_numbers_across_shards(spark, monkeypatch):
    from liveindex.scratch import numbered, running_sum

    docs = some_docs(150, 8)
    stream = spark.createDataFrame(docs, "d long, terms array<string>").repartition(5)
    doc, word = sorted(map(tuple, P.postings_doc(stream).collect())), sorted(map(tuple, P.postings_word(stream).collect()))
    place = sorted(map(tuple, P.postings_global(stream).collect()))
    monkeypatch.setattr(P, "SHARD", 7)
    assert sorted(map(tuple, P.postings_doc(stream).collect())) == doc and sorted(map(tuple, P.postings_word(stream).collect())) == word and sorted(map(tuple, P.postings_global(stream).collect())) == place
    skewed = spark.createDataFrame([(k % 3 if k < 900 else k,) for k in range(1000)], "k long").repartition(6)
    got = sorted(map(tuple, numbered(skewed, "k", into="d").collect()), key=lambda r: r[1])
    assert [d for _, d in got] == list(range(1, 1001)) and [k for k, _ in got] == sorted(k for k, _ in got)
    rows = spark.createDataFrame([(k, k % 5) for k in range(0, 900, 3)], "k long, v long")
    assert all(s == sum(j % 5 for j in range(0, k, 3)) for k, _, s in running_sum(rows, "v", "k", "s", 4).collect())


@pytest.mark.parametrize("settings", [{"B": 40}, {"B": 48, "growth": "triangular", "shard_docs": 90}, {"level": "word"}, {"B": 40, "level": "word", "growth": "geometric"}])
def test_inserts_leave_the_blocks_of_one_build(spark, tmp_path, settings):
    from liveindex.plans.store import LiveIndex

    cfg = K.IndexConfig(**settings)
    stream = spark.createDataFrame(some_docs(260, 11), "d long, terms array<string>")
    index = LiveIndex(spark, str(tmp_path / "index"), cfg, buckets=3)
    for k, (low, high) in enumerate(((1, 90), (91, 91), (92, 259))):
        index.insert(stream.where(F.col("d").between(low, high)), f"in-{k}")
    whole = P.count_terms(stream) if cfg.level == "doc" else P.postings_word(stream)
    want = sorted(map(tuple, K.build_blocks(whole, cfg).collect()))
    assert sorted(map(tuple, index.blocks().collect())) == want
    assert index.collate()["documents_meanwhile"] == 0
    index.insert(stream.where("d >= 92"), "in-2")  # said again after the collation
    assert sorted(map(tuple, index.blocks().collect())) == want and index.manifest()["documents"] == 259
    with pytest.raises(ValueError):
        index.insert(stream.where("d = 5"))
    x = "f" if cfg.level == "doc" else "w"
    assert sorted(map(tuple, index.postings().collect())) == sorted(map(tuple, whole.select("term", "d", x).collect()))
    if cfg.level == "word":
        assert sorted(map(tuple, index.phrase("tA t").collect())) == [] and index.match("t").count() == 0


def test_full_shards_become_static(spark, tmp_path):
    from liveindex.plans.store import LiveIndex

    stream = spark.createDataFrame([(d, [f"x{chr(97 + len(t) % 7)}" for t in terms] + [f"y{chr(97 + d % 3)}"]) for d, terms in some_docs(300, 12)], "d long, terms array<string>")
    index = LiveIndex(spark, str(tmp_path / "index"), K.IndexConfig(B=40), most_bytes=100)
    for low, high in ((1, 100), (101, 200), (201, 299)):
        index.insert(stream.where(F.col("d").between(low, high)))
    assert len(index.manifest()["starts"]) == 3
    before = [sorted(map(tuple, f().collect())) for f in (index.postings, lambda: index.search("xb ya"), lambda: index.match("xb ya"))]
    index.to_static("interp", [0])
    index.to_static()
    assert {s["code"] for s in index.manifest()["static"]} == set(Z.CODES) and index.blocks().select("shard").distinct().count() == 1
    assert [sorted(map(tuple, f().collect())) for f in (index.postings, lambda: index.search("xb ya"), lambda: index.match("xb ya"))] == before
    index.collate()
    assert index.vacuum(1) and sorted(map(tuple, index.postings().collect())) == before[0]


def test_writers_that_meet(spark, tmp_path):
    from liveindex.plans.store import Conflict, LiveIndex

    one, two = (LiveIndex(spark, str(tmp_path / "index")) for _ in range(2))
    now = one.manifest()
    two.insert(spark.createDataFrame([(1, ["a"])], "d long, terms array<string>"))
    with pytest.raises(Conflict):
        one._publish({**now, "version": now["version"] + 1})
    (tmp_path / "index" / f"claim-{2:012d}").write_text("")  # a writer that never publishes
    with pytest.raises(Conflict):
        one.insert(spark.createDataFrame([(2, ["a"])], "d long, terms array<string>"), tries=1)
    assert one.manifest()["version"] == 1 and one.match("a").count() == 1


@given(st.lists(st.tuples(st.integers(1, 400), st.integers(1, 90)), min_size=1, max_size=128), st.sampled_from(["bp128", "interp"]))
@settings(max_examples=60, deadline=None)
def test_static_runs_round_trip(pairs, code):
    d, f = np.cumsum([p[0] for p in pairs]), np.array([p[1] for p in pairs], np.int64)
    data = Z.encode_run(d, f, code)
    x, y = Z.decode_run(data, d.size, int(d[0]), int(d[-1]), int(f.sum()), code)
    assert x.tolist() == d.tolist() and y.tolist() == f.tolist()


def test_lines_of_documents(spark, tmp_path):
    from liveindex.sources import collections as S

    rows = spark.createDataFrame([(0, "One two TWO"), (1, ""), (7, None)], "doc_id long, text string")
    stream = S.docstream(rows, F.col("doc_id") + 1, F.col("doc_id"), F.col("text"), "x")
    S.write_docstream(stream, str(tmp_path / "lines"))
    back = S.read_docstream(spark, str(tmp_path / "lines"), "x")
    assert sorted(map(tuple, back.collect()), key=str) == sorted(map(tuple, stream.collect()), key=str)


def test_live_index_sees_inserts_and_streams(spark, tmp_path):
    from liveindex.plans.store import LiveIndex
    from liveindex.streaming.ingest import stream_ingest

    index = LiveIndex(spark, str(tmp_path / "index"))
    assert index.search("alpha").count() == 0
    index.insert(spark.createDataFrame([(1, ["alpha", "beta"]), (2, ["beta"])], "d long, terms array<string>"), "one")
    index.insert(spark.createDataFrame([(1, ["alpha", "beta"]), (2, ["beta"])], "d long, terms array<string>"), "one")
    assert [r["d"] for r in index.match("Alpha beta").collect()] == [1]
    for k in range(3):
        spark.createDataFrame([(10 + k, ["beta", "gamma"])], "d long, terms array<string>").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    source = spark.readStream.schema("d long, terms array<string>").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    stream_ingest(source, index, str(tmp_path / "ck")).awaitTermination()
    assert sorted(r["d"] for r in index.match("beta").collect()) == [1, 2, 10, 11, 12]
    before = sorted(map(tuple, index.search("beta gamma").collect()))
    index.collate()
    assert sorted(map(tuple, index.search("beta gamma").collect())) == before and len(index.manifest()["batches"]) == 1


def test_build_has_one_exchange(spark):
    stream = spark.createDataFrame([(1, ["a"])], "d long, terms array<string>")
    plan = K.build_blocks(P.count_terms(stream), K.IndexConfig())._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 1 and "MapInArrow" in plan


@pytest.mark.parametrize("shard_docs", [1 << 20, 300])
def test_whole_static_lists_whatever_the_shards(spark, shard_docs):
    docs = [(d, ["each"] + (["some"] if d % 3 else []) + ([f"t{d}"] if d % 40 == 0 else []) + ["late"] * (d > 500)) for d in range(1, 1200)]
    counts = P.count_terms(spark.createDataFrame(docs, "d long, terms array<string>").repartition(3))
    runs = Z.build_whole(counts, K.IndexConfig(shard_docs=shard_docs))
    want = Z.static_bytes(Z.build_static(counts, K.IndexConfig())).first()
    assert Z.static_bytes(runs, "term").first() == want
    assert sorted(map(tuple, Z.decode_static(runs).select("term", "d", "f").collect())) == sorted(map(tuple, counts.collect()))
    assert runs.agg(F.max("block_no")).first()[0] <= -(-shard_docs // Z.RUN)


@pytest.mark.parametrize("code", Z.CODES)
def test_full_runs_side_by_side(code):
    rng = np.random.default_rng(8)
    runs, data = [], []
    for width in (1, 3, 40, 5000, 1 << 20, 1, 1 << 33):
        d = 5 + np.cumsum(rng.integers(1, width + 1, Z.RUN))
        f = rng.integers(1, rng.integers(2, 300), Z.RUN)
        data.append(Z.encode_run(d, f, code))
        runs.append((d, f))
    size = np.array([len(x) for x in data])
    columns = [np.array(c, np.int64) for c in zip(*((d[0], d[-1], f.sum()) for d, f in runs), strict=True)]
    d, f = Z.decode_full_runs(np.frombuffer(b"".join(data), np.uint8), np.cumsum(size) - size, size, *columns, code)
    assert d.tolist() == np.concatenate([d for d, _ in runs]).tolist() and f.tolist() == np.concatenate([f for _, f in runs]).tolist()
