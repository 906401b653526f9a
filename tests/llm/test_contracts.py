"""The registered queries on the smallest tables, against plain Python versions of what they promise."""

import collections
import os
import re
import time
import zlib
from html import unescape

import numpy as np
import pyarrow as pa
import pytest

from liveindex.llm import decontam, html, licences, queries
from liveindex.llm import common as C

SF = "/root/testdata/sf0.001"
pytestmark = pytest.mark.skipif(not os.path.isdir(SF), reason="no test tables")


@pytest.fixture(scope="module")
def texts(spark):
    return {r["doc_id"]: (r["text"], r["source"]) for r in spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text", "source").collect()}


def rows(spark, name):
    return {r["doc_id"]: r for r in queries.QUERIES[name](spark, SF).collect()}


def words(t):
    return C.WORDS_PY.findall(t or "")


def test_main_text_is_the_article(spark):
    pages = {r["page_id"]: r["html"] for r in spark.read.parquet(f"{SF}/pages.parquet").collect()}
    for r in queries.QUERIES["op1_block_tree"](spark, SF).collect():
        inside = re.search(r"<article>(.*)</article>", pages[r["page_id"]], re.S)[1]
        plain = [" ".join(unescape(re.sub(r"<[^>]*>", " ", b)).split()) for b in re.split(r"</?(?:p|h1)>", re.sub(r"</?b>", "", inside))]
        assert r["text"] == "\n".join(b for b in plain if b) and r["n_chars"] == len(r["text"])


def test_tree_on_pages_it_has_not_seen():
    node = html.tree()
    x, y = html.labelled(html.labelled_pages(300, seed=5))
    got = np.array([html.is_main(node, f) for f in x])
    assert (got & y).sum() / got.sum() > 0.97 and (got & y).sum() / y.sum() > 0.97
    prose = lambda n: " ".join(f"k{i}" for i in range(n))
    for page, count in (
        (f"<div class='page no-sidebar'><p>{prose(60)}</p><p>{prose(50)}</p></div>", 110),
        (f"<div class='post has-header'><p>{prose(60)}</p><p>{prose(50)}</p></div>", 110),
        (f"<form action=x><div><h1>{prose(5)}</h1><p>{prose(60)}</p></div></form>", 65),
        ("<p>one two three</p><p>four five six</p><p>seven eight</p>", 8),
        (f"<html><head><title>t</title><header><h1>Site</h1></header><article>{prose(30)}</article>", 30),
        (f"<p>{prose(30)}<button>go<p>{prose(20)}", 51),
        (f"<p>{prose(30)} <math><mi>x</mi></math> İ<script>a</script>{prose(20)}</p>", 52),
        (f"<section id=search><h2 id=related-work>Related work</h2><p>{prose(60)}</p></section><footer>foot note</footer>", 62),
        (f"<nav><a>x</a></nav><article><p>{prose(40)}</p></article><div class=comments><article><p>{prose(50)}</p></article></div>", 40),
    ):
        assert len(html.main_text(page, node).split()) == count, page[:60]


def test_labels_of_a_table_grow_the_tree(spark):
    page = "<div data-y=1>short one</div><div data-y=0>w w w w w w w w w w w w</div>"
    labels = spark.createDataFrame([(page.replace("w", f"w{k}"),) for k in range(20)], "html string")
    df = spark.createDataFrame([(1, "<div>a b</div><div>c c c c c c c c c c c c</div>")], "page_id long, html string")
    assert html.extract_main_text(df, labels=labels).first()["text"] == "a b"


@pytest.mark.parametrize("piece", ["<a ", '<a b="', "<!--", "<", "<script>", "<div>", "<button>", "</div>", "<p   ", "<a x = ", "<div class=comments><p>"])
def test_odd_pages_take_linear_time(piece):
    node, times = html.tree(), []
    for n in (20_000, 80_000):
        began = time.perf_counter()
        html.main_text(piece * n, node)
        times.append(time.perf_counter() - began)
    assert times[1] < 10 * times[0] + 0.5 and times[1] < 5


def test_repetition_base(spark, texts):
    for d, r in rows(spark, "op2_repetition").items():
        t, w = texts[d][0] or "", words(texts[d][0])
        seen = collections.Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4))
        inside = {j for i in range(len(w) - 4) if seen[tuple(w[i : i + 5])] > 1 for j in range(i, i + 5)}
        lines = [x for x in t.split("\n") if words(x)]
        want = (len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in t), len(lines) - len(set(lines)), len(inside))
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == want
        assert r["base_failed"] == (len(w) < 10 or 100 * len(inside) > 20 * len(w)) and not (r["base_failed"] and r["kept"])


def test_shards_are_near_equal(spark, texts):
    got = queries.QUERIES["op3_sampled_splitters"](spark, SF).collect()
    load, slots = collections.Counter(), collections.defaultdict(list)
    for r in got:
        data = (texts[r["doc_id"]][0] or "").encode()
        assert (r["size"], r["text_crc32"], r["law"], r["grown_shard"]) == (len(data) + 1, zlib.crc32(data), "bytes", None)
        load[r["shard"]] += r["size"]
        slots[r["shard"]].append(r["slot"])
    assert len(got) == len(texts) and all(sorted(s) == list(range(len(s))) for s in slots.values())
    mean, most = sum(load.values()) / 16, max(r["size"] for r in got)
    assert set(load) == set(range(16)) and max(load.values()) - min(load.values()) <= max(0.05 * mean, most)


def test_mixture_meets_targets(spark, texts):
    got = rows(spark, "op4_entropy_balance")
    sizes = {d: len(words(t)) for d, (t, _) in texts.items()}
    source = collections.Counter()
    for d, (_, s) in texts.items():
        source[s] += sizes[d]
    order = sorted(source, key=lambda s: (s is None, s))
    weight = {s: (5, 2, 1)[k % 3] for k, s in enumerate(order)}
    goal, left, free = {}, 1.5 * sum(source.values()), set(order)
    while True:
        unit = left / sum(weight[s] for s in free)
        over = [s for s in free if unit * weight[s] > 2 * source[s]]
        if not over:
            goal |= {s: unit * weight[s] for s in free}
            break
        for s in over:
            goal[s] = 2 * source[s]
            left -= goal[s]
            free.discard(s)
    taken = collections.Counter()
    for d, r in got.items():
        s = texts[d][1]
        assert r["size"] == sizes[d] and r["source_size"] == source[s] and abs(r["target"] - goal[s]) < 1e-6 * max(1, goal[s]) and 0 <= r["taken"] <= 2 * r["size"]
        taken[s] += r["taken"]
    assert all(abs(taken[s] - goal[s]) <= max(sizes[d] for d in sizes if texts[d][1] == s) for s in order)


def test_records_hold_the_library_ids(spark, texts):
    P = pytest.importorskip("public_tokenizers")
    from tokenizers import Tokenizer

    tokenizer, at = Tokenizer.from_file(P.path("byte_bpe_50k.json")), 0
    got = rows(spark, "op9_token_records")
    for d in sorted(texts):
        ids = [*tokenizer.encode(texts[d][0] or "", add_special_tokens=False).ids, 0]
        assert (got[d]["start"], got[d]["n_tokens"], got[d]["ids_crc32"]) == (at, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
        at += len(ids)


def test_licence_base(spark, texts):
    for d, r in rows(spark, "op10_licences").items():
        t = (texts[d][0] or "").translate({c: c + 32 for c in range(65, 91)})
        w = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", t)
        places, labels = [], set()
        for phrase, label in licences.PHRASES.items():
            p = phrase.split()
            here = [i for i in range(len(w) - len(p) + 1) if w[i : i + len(p)] == p]
            places += here
            labels |= {label} if here else set()
        assert (r["n_words"], r["n_base"], r["first_word"], r["last_word"]) == (len(w), len(places), min(places, default=None), max(places, default=None))
        assert r["base_labels"] == ",".join(sorted(labels)) and labels <= set(filter(None, r["labels"].split(","))) and 0 <= r["score"] <= 1


def test_leaks_against_all_pairs(spark):
    """Edited copies of every kind, among documents that hold the items' words by the hundred: none is lost."""
    rng = np.random.default_rng(17)
    common = [f"c{k}" for k in range(30)]
    items = [[common[int(x)] if rng.random() < 0.6 else f"r{n}x{k}" for k, x in enumerate(rng.integers(0, 30, int(rng.integers(8, 40))))] for n in range(12)]
    docs = [list(map(common.__getitem__, rng.integers(0, 30, 60))) for _ in range(80)]
    for item in items:
        for every in (0, 3, 4, 6):
            edited = [w if not every or k % every else f"new{k}" for k, w in enumerate(item)]
            if rng.random() < 0.5:
                del edited[int(rng.integers(0, len(edited)))]
            if rng.random() < 0.5:
                edited.insert(int(rng.integers(0, len(edited))), "gap")
            docs.append([*rng.choice(common, 20).tolist(), *edited, *rng.choice(common, 20).tolist()])
        docs.append([item[int(k)] for k in rng.permutation(len(item))])
    hashed = lambda ws: decontam.word_hashes(pa.array([" ".join(ws)]))[0]
    want = {}
    for d, doc in enumerate(docs):
        for i, item in enumerate(items):
            score = decontam.align(hashed(item), hashed(doc))[0]
            if score >= decontam.LEAST_SCORE:
                want[d, i] = score
    df = spark.createDataFrame([(d, " ".join(w)) for d, w in enumerate(docs)], "doc_id long, text string")
    bench = spark.createDataFrame([(i, " ".join(w)) for i, w in enumerate(items)], "item_id long, text string")
    got = {(r["doc_id"], r["item_id"]): r["score"] for r in decontam.leaks(df, bench).collect()}
    assert len(want) >= 40 and got == want


def test_audit_of_the_query_finds_what_it_planted(spark):
    for r in queries.QUERIES["op7_merkle_audit"](spark, SF).collect():
        assert r["intact"] == (r["digest"][:2] not in ("00", "7f", "c3"))
