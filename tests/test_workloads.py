import os

import pytest

from liveindex import registry

SF = "/root/testdata/sf0.001"
SOME = ("count_terms", "postings_word_turns", "resolve_positions", "vbyte_hex", "pair_values", "block_table", "seek_geq", "conjunctive", "conjunctive_skip", "topk_pruned", "ops_topk", "proximity", "two_pass_offsets", "agg_cube", "session")


def plain(rows, names):
    order = sorted(range(len(names)), key=lambda i: names[i])
    return sorted((tuple(round(float(r[i]), 6) if isinstance(r[i], float) else r[i] for i in order) for r in rows), key=str)


@pytest.fixture(scope="module")
def oracle():
    duckdb = pytest.importorskip("duckdb")
    if not os.path.isdir(SF):
        pytest.skip("no test tables")
    con = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents pages benchmark labels conversations".split():
        con.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", SOME)
def test_query_equals_its_oracle(spark, oracle, name):
    registry.load()
    got = registry.QUERIES[name](spark, SF)
    want = oracle.execute(registry.ORACLES[name])
    columns = [d[0] for d in want.description]
    assert sorted(got.columns) == sorted(columns)
    assert plain(map(tuple, got.collect()), got.columns) == plain(want.fetchall(), columns)


def test_every_oracle_has_a_query():
    registry.load()
    assert set(registry.ORACLES) <= set(registry.QUERIES) and len(registry.QUERIES) > 120


def test_nothing_imports_the_corpus_subpackage():
    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    for folder, _, names in os.walk(os.path.join(root, "liveindex")):
        if os.sep + "llm" in folder:
            continue
        for n in (n for n in names if n.endswith(".py")):
            assert "liveindex.llm" not in open(os.path.join(folder, n)).read()


def test_last_order_before_an_event(spark):
    import random
    from datetime import datetime, timedelta

    from liveindex.workloads.operators import last_before

    draw, start = random.Random(3), datetime(1999, 12, 1)
    day = lambda: start + timedelta(hours=12 * draw.randrange(400))
    orders = [(k, draw.randrange(3), day()) for k in range(120)] + [(200, None, start), (201, 0, None)]
    events = [(k, draw.randrange(4), day()) for k in range(300)] + [(7, 1, day()), (400, None, start), (401, 1, None), (402, 1, start - timedelta(days=90))]
    best = {}
    for e, c, at in events:
        for o, k, when in orders:
            if c is not None and c == k and at is not None and when is not None and when <= at:
                best[e] = max(best.get(e, (when, o)), (when, o))
    got = last_before(spark.createDataFrame(events, "event_id long, class long, at timestamp"), spark.createDataFrame(orders, "o_orderkey long, class long, at timestamp"))
    assert sorted(map(tuple, got.collect())) == sorted((e, o) for e, (_, o) in best.items())


@pytest.mark.parametrize("name", ["growth_sequence", "overhead_curve", "best_block"])
def test_growth_rules_over_the_lists_of_documents(spark, oracle, name):
    test_query_equals_its_oracle(spark, oracle, name)
    assert "documents" in registry.ORACLES[name] and "lists" in registry.QUERIES[name](spark, SF).columns


def test_layouts_and_modes_share_the_blocks_of_a_growth_rule(spark, monkeypatch):
    from liveindex.operators import packer

    made, build = [], packer.build_blocks
    monkeypatch.setattr(packer, "build_blocks", lambda *a, **k: made.append(1) or build(*a, **k))
    rows = registry.QUERIES["latency_by_layout"](spark, SF).collect()
    assert len(made) == 2 and len(rows) == 8
    counts = {(r["growth"], r["mode"]): set() for r in rows}
    for r in rows:
        counts[r["growth"], r["mode"]].add((r["queries"], r["mean_blocks"], r["mean_postings"]))
    assert all(len(c) == 1 for c in counts.values())  # layouts move bytes and change no counts
