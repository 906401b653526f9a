import collections
import hashlib
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from liveindex.llm import common as C
from liveindex.llm import decontam, graphs, html, licences, minhash, mixing, quality, records, shards, spans, warc

A = " ".join(f"alpha{k} beta{k % 7} gamma{k % 5}" for k in range(60))
DOCS = [(1, A, "s"), (2, A, "s"), (3, A + " tail", None), (4, None, "s"), (5, "", "t"), (6, " \n\t ", "t"), (7, "one", "t"), (8, "ONE", None), (9, "é ü 日本 " * 30, "u"),
        (10, "x" * 3000, "u"), (11, A[:400] + " other words here " + A[400:], "u"), (None, A, "s"), (12, "spam spam " * 200, "s")]
SCHEMA = "doc_id long, text string, source string, size int, kept string, labels double, target int, shard string"


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame([(*d, 5, "k", 1.0, 2, "x") for d in DOCS], SCHEMA)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def test_words_and_grams():
    texts = pa.array([t for _, t, _ in DOCS])
    raw, off = C.flat(texts)
    starts, ends, first = C.spans(C.IS_WORD[raw], off)
    want = [C.WORDS_PY.findall(t or "") for _, t, _ in DOCS]
    got = [[raw[a:b].tobytes().decode() for a, b in zip(starts[i:j], ends[i:j], strict=True)] for i, j in zip(first[:-1], first[1:], strict=True)]
    assert got == want
    grams, at = C.grams(C.span_hashes(raw, starts, ends), first, 3)
    flat = [tuple(w[i : i + 3]) for w in want for i in range(len(w) - 2)]
    assert len(set(flat)) == len(set(grams.tolist())) and len(flat) == len(grams)


def test_main_text_of_odd_pages(spark, empty):
    page = "<body><nav><a href=/>Menu</a></nav><article><h1>T &amp; t</h1><p>One<p>Two <b>bold</b>&nbsp;x<br>y<script>bad('</p>')</script><!-- no --><div class=ad>Buy this now</div></article><footer>&copy; f</footer>"
    df = spark.createDataFrame([(1, page, "was"), (2, None, "was"), (3, "", "was"), (4, "<p title=it's>kept words " + "w " * 50, "was")], "page_id long, html string, text string")
    got = {r["page_id"]: r["text"] for r in html.extract_main_text(df).collect()}
    assert got[1] == "T & t\nOne\nTwo bold x y" and got[2] == "" and got[3] == "" and got[4].startswith("kept words w w")
    assert html.extract_main_text(df.limit(0)).count() == 0


def test_tree_fits_unseen_sizes():
    node, right, total = html.tree(), 0, 0
    import re

    for n, page in enumerate(html.labelled_pages(240, seed=6)):
        sized = re.sub(r"w\d+(?: w\d+)*", lambda m: " ".join((m[0].split() * 2)[: max(1, len(m[0].split()) * (3 + 2 * (n % 2)) // 4)]), page)
        for _, features, label in html.blocks(sized):
            if label is not None:
                total, right = total + 1, right + (html.is_main(node, features) == (label == "1"))
    assert total > 2000 and right / total > 0.9, (total, right / total)


def test_repetition(docs, empty):
    got = {r["doc_id"]: r for r in quality.repetition(docs).collect()}
    for d, t, _ in DOCS:
        if d is None:
            continue
        w = C.WORDS_PY.findall(t or "")
        seen = collections.defaultdict(list)
        for i in range(len(w) - 4):
            seen[tuple(w[i : i + 5])].append(i)
        inside = {j for v in seen.values() if len(v) > 1 for i in v for j in range(i, i + 5)}
        assert (got[d]["n_words"], got[d]["word_chars"], got[d]["n_repeat_words"]) == (len(w), sum(map(len, w)), len(inside))
    assert not got[12]["kept"] and got[1]["kept"] and not got[4]["kept"]
    assert quality.repetition(empty).count() == 0


def laws_of_shards(out, n, shards=16):
    by = collections.defaultdict(list)
    for r in out:
        by[r["shard"]].append(r)
    assert len(out) == n and set(by) <= set(range(shards))
    assert all(sorted(r["slot"] for r in v) == list(range(len(v))) for v in by.values())
    sizes = [sum(r["size"] for r in by[s]) for s in range(shards)]
    return max(sizes) - min(sizes), sum(sizes) / shards


def test_shards_cut_by_bytes(spark, docs, empty, tmp_path):
    rows = [(i % 50, f"text {i % 3}" * (i % 40), i, i) for i in range(3000)] + [(None, None, 1, 1)] * 2000 + [(5, "long " * 900, 1, 1)]
    df = spark.createDataFrame(rows, "doc_id long, text string, Shard int, _hash int").repartition(4)
    df.write.parquet(str(tmp_path / "t"))
    out = shards.shard_by_bytes(spark.read.parquet(str(tmp_path / "t")))
    assert out.columns == ["doc_id", "text", "_hash", "size", "shard", "slot"]
    out = out.collect()
    assert all(r["size"] == len((r["text"] or "").encode()) + 1 for r in out)
    gap, mean = laws_of_shards(out, len(rows))
    assert gap <= 0.05 * mean + 10
    assert sorted((r["doc_id"] is None, r["doc_id"] or 0, r["text"] or "", r["_hash"]) for r in out) == sorted((d is None, d or 0, t or "", h) for d, t, _, h in rows)
    assert shards.shard_by_bytes(empty).count() == 0 and shards.shard_by_bytes(docs).count() == len(DOCS)


def test_overfull_ranges_are_subdivided(spark, monkeypatch):
    df = shards.keyed(spark.createDataFrame([(i, f"t{i}") for i in range(4000)], "doc_id long, text string"))
    few = sorted(map(tuple, df.select(*shards.KEY).collect()))[:1]
    was = shards.splitters
    monkeypatch.setattr(shards, "splitters", lambda rows, ranges, total, salt=77: few if salt == 77 else was(rows, ranges, total, salt))
    cuts = shards._cut(df, 4, 16, df.agg(F.sum("size")).first()[0])
    sizes = [r["count"] for r in df.withColumn("r", shards.range_of(cuts)).groupBy("r").count().collect()]
    assert max(sizes) < 1000 and sum(sizes) == 4000


def balanced_by_bisection(sizes, goal, most=2.0):
    """Rates of largest entropy that sum to the goal, found apart from the operator: bisection on the tilt."""
    x = np.array(sizes, float)
    mean, lo, hi = x.mean(), -60.0, 60.0
    rate = lambda a: np.minimum(most, np.exp(np.minimum(a * x / mean, np.log(most))))
    for _ in range(200):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if (rate(mid) * x).sum() < goal else (lo, mid)
    return rate((lo + hi) / 2)


def test_mixing_meets_targets(spark, empty):
    rng = np.random.default_rng(5)
    rows = [(i, "abc"[min(2, i % 7)] if i % 11 else None, int(x)) for i, x in enumerate(rng.pareto(1.5, 4000) * 50)]
    df = spark.createDataFrame(rows, "doc_id long, source string, size long")
    out = mixing.mix_sources(df).collect()
    by = collections.defaultdict(list)
    for r in out:
        assert r["copies"] in (int(np.floor(r["rate"] + 1e-9)), int(np.ceil(r["rate"] - 1e-9))) and 0 <= r["copies"] <= 2
        by[r["source"]].append(r)
    assert len(out) == len(rows)
    for some in by.values():
        sizes, goal = [r["size"] for r in some], some[0]["target"]
        assert abs(sum(r["copies"] * r["size"] for r in some) - goal) <= 0.5 * max(sizes) + 1 and goal <= 2 * sum(sizes) + 1e-6
        if goal < 2 * sum(sizes) - 1:
            want = balanced_by_bisection(sizes, goal)
            assert all(abs(r["rate"] - w) < 1e-6 for r, w in zip(some, want, strict=True) if r["size"])
    assert sorted(map(tuple, mixing.mix_sources(df.repartition(3)).select("doc_id", "copies").collect())) == sorted((r["doc_id"], r["copies"]) for r in out)
    assert mixing.mix_sources(empty).count() == 0


def test_targets_by_weight(spark):
    def wanted(sizes):
        rows = spark.createDataFrame([(k, s, 1) for k, s in sizes.items()], "key string, words long, docs long")
        return {r["key"]: round(r["target"], 9) for r in mixing.targets(rows).collect()}

    assert wanted({"+a": 100, "+b": 100, "-": 1000}) == {"+a": 200, "+b": 200, "-": 1400}
    assert wanted({"+a": 0, "-": 0}) == {"+a": 0, "-": 0}
    many = wanted({f"+{k:06d}": 10 + k % 7 for k in range(5000)})
    assert len(many) == 5000 and abs(sum(many.values()) - 1.5 * sum(10 + k % 7 for k in range(5000))) < 1e-3


def test_mixing_of_a_hot_repeated_document(spark):
    rows = [(None, "a", 5)] * 30000 + [(7, "a", 5)] * 9000 + [(i, "b", 9) for i in range(200)]
    df = spark.createDataFrame(rows, "doc_id long, source string, size long").repartition(5)
    out = mixing.mix_sources(df).groupBy("source").agg(F.count("*").alias("n"), F.sum(F.col("copies") * F.col("size")).alias("w"), F.first("target").alias("t")).collect()
    assert {r["source"]: r["n"] for r in out} == {"a": 39000, "b": 200} and all(abs(r["w"] - r["t"]) <= 5 for r in out)


def jaccard_components(texts, width, percent):
    sets = {}
    for d, t in texts:
        w = [x.translate(str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)})) for x in C.WORDS_PY.findall(t or "")]
        sets[d] = {tuple(w[i : i + width]) for i in range(len(w) - width + 1)} if len(w) >= width else ({tuple(w)} if w else set())
    label = {d: d for d in sets}
    for a in sets:
        for b in sets:
            both = len(sets[a] & sets[b])
            if a < b and both and 100 * both >= percent * (len(sets[a]) + len(sets[b]) - both):
                x, y = label[a], label[b]
                label = {d: min(x, y) if v in (x, y) else v for d, v in label.items()}
    return label, sets


def test_near_duplicates_against_all_pairs(spark, docs, empty):
    rng = np.random.default_rng(9)
    base, rows = [f"w{int(x)}" for x in rng.integers(0, 400, 80)], list((d, t) for d, t, _ in DOCS if d is not None)
    for k in range(150):  # a group of copies with edits of their own: many links just above and below the limit
        words = list(base)
        for _ in range(int(rng.integers(0, 6))):
            words[int(rng.integers(0, 80))] = f"edit{int(rng.integers(0, 60))}"
        rows.append((100 + k, " ".join(words)))
    label, sets = jaccard_components(rows, 4, 80)
    got = {r["doc_id"]: r for r in minhash.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), width=4).collect()}
    assert {d: r["component_id"] for d, r in got.items()} == label
    assert {d: r["n_shingles"] for d, r in got.items()} == {d: len(s) for d, s in sets.items()}
    assert minhash.near_duplicates(empty).count() == 0
    lone = minhash.near_duplicates(docs).where("doc_id is null").collect()
    assert len(lone) == 1 and lone[0]["kept"] and lone[0]["component_id"] is None


def test_superminhash_estimates():
    rng = np.random.default_rng(2)
    pool = rng.integers(0, 1 << 62, 3000).astype(np.uint64)
    a, b = pool[:2000], pool[1000:3000]
    rows = minhash.signatures(np.concatenate((a, b)), np.array([0, 2000, 4000]), 200)
    assert abs((rows[0] == rows[1]).mean() - 1 / 3) < 0.1


def test_components(spark):
    links = spark.createDataFrame([(i + 1, i) for i in range(30) if i != 12] + [(40, 41), (41, 42), (50, 50)], "a long, b long")
    got = dict(map(tuple, graphs.components(links).collect()))
    assert {got[i] for i in range(13)} == {0} and {got[i] for i in range(13, 31)} == {13} and got[42] == 40 and 50 not in got


def test_components_of_long_paths(spark):
    n = 3000
    order = np.random.default_rng(1).permutation(n).tolist()
    links = [(i, i + 1) for i in range(n - 1)] + [(n + a, n + b) for a, b in zip(order[:-1], order[1:], strict=True)] + [(9000, 9001 + i) for i in range(50)] + [(9999, 9500 + i) for i in range(50)]
    got = dict(map(tuple, graphs.components(spark.createDataFrame(links, "a long, b long")).collect()))
    assert got == {i: 0 for i in range(n)} | {n + i: n for i in range(n)} | {9000 + i: 9000 for i in range(51)} | {9500 + i: 9500 for i in range(50)} | {9999: 9500}


def test_leaks_exact_and_edited(spark, docs, empty):
    item = [f"q{k}" for k in range(40)]
    edited = list(item)
    for k in (7, 15, 22, 30):
        edited[k] = "changed"
    del edited[35]
    rows = [(1, "noise " * 50 + " ".join(item) + " noise" * 10), (2, " ".join(edited)), (3, " ".join(item[:8])), (4, "noise only"), (5, None)]
    bench = spark.createDataFrame([(9, " ".join(item)), (10, None), (11, "two words")], "item_id long, text string")
    got = {(r["doc_id"], r["item_id"]): r["score"] for r in decontam.leaks(spark.createDataFrame(rows, "doc_id long, text string"), bench).collect()}
    assert set(got) == {(1, 9), (2, 9)} and got[1, 9] == 1.0 and 0.6 < got[2, 9] < 1
    assert decontam.leaks(docs, bench).count() == 0 and decontam.leaks(empty, bench).count() == 0 and decontam.leaks(docs, bench.limit(0)).count() == 0


def test_leaks_of_shared_and_missing_ids_and_dense_edits(spark):
    texts = {k: [f"{k}{i}" for i in range(16)] for k in "abcde"}
    bench = [(1, " ".join(texts["a"])), (1, " ".join(texts["b"])), (None, " ".join(texts["c"])), (2, " ".join(texts["d"])), (3, " ".join(texts["e"]))]
    fourth = [w if i % 4 != 3 else f"new{i}" for i, w in enumerate(texts["d"])]  # no run of four words is left
    spaced = [x for w in texts["e"] for x in (w, "and")]  # every word apart from the next: just enough
    docs = [(k, "noise " * 9 + " ".join(t) + " tail" * 9) for k, t in enumerate([texts["a"], texts["b"], texts["c"], fourth, spaced, texts["d"][:7]])]
    got = {(r["doc_id"], r["item_id"]): r["score"] for r in decontam.leaks(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(bench, "item_id long, text string")).collect()}
    assert set(got) == {(0, 1), (1, 1), (2, None), (3, 2), (4, 3)} and got[3, 2] >= 0.625 and got[4, 3] == 17 / 32


def test_windows_lose_no_passage():
    rng = np.random.default_rng(12)
    for least in (0.5, 0.7):
        for _ in range(150):
            item, doc = rng.integers(0, 12, rng.integers(4, 14)).astype(np.uint64), rng.integers(0, 20, rng.integers(5, 90)).astype(np.uint64)
            words, need, width = decontam.seeds(item, {k: 20 - k for k in range(12)}, least)
            vocabulary = np.unique(np.array(words, np.uint64))
            k = np.arange(vocabulary.size + 1)
            passages = list(decontam.windows(doc, np.array([0, doc.size]), vocabulary, k, np.zeros(vocabulary.size, np.int64), np.array([need]), np.array([width])))
            whole = decontam.align(item, doc)[0]
            full = int(np.ceil(least * item.size - 1e-9))
            best = max((decontam.align(item, doc[a:b])[0] for _, _, a, b in passages if decontam.in_order(decontam.places(item), item.size, doc[a:b]) >= full), default=0.0)
            assert best == whole or (whole < least and best < least)


def test_alignment_against_full_matrix():
    rng = np.random.default_rng(4)
    for _ in range(30):
        a, b = rng.integers(0, 4, rng.integers(1, 12)).astype(np.uint64), rng.integers(0, 4, rng.integers(1, 15)).astype(np.uint64)
        h = np.zeros((len(a) + 1, len(b) + 1), int)
        for i in range(len(a)):
            for j in range(len(b)):
                h[i + 1, j + 1] = max(0, h[i, j] + (2 if a[i] == b[j] else -1), h[i, j + 1] - 1, h[i + 1, j] - 1)
        assert decontam.align(a, b)[0] == h.max() / (2 * len(a))


def test_audit_finds_planted_damage(spark, tmp_path):
    df = spark.createDataFrame([(i, f"http://x/{i}" if i % 5 else None, f"<p>page {i}</p>\r\n\r\n" * (i % 9) if i % 4 else None) for i in range(400)], "page_id long, url string, html string").repartition(3)
    found = warc.write_warc(df, str(tmp_path / "a"))
    other = warc.copy_replica(found, str(tmp_path / "a"), str(tmp_path / "b"))
    assert warc.damage(found, other).count() == 0
    planted = warc.copy_replica(found, str(tmp_path / "a"), damaged=F.col("page_id").isin(7, 123, 300))
    assert sorted(r["page_id"] for r in warc.fixity(found, planted).where("not intact").collect()) == [7, 123, 300]
    names = sorted(r["file"] for r in found.select("file").distinct().collect())
    size = (tmp_path / "b" / names[0]).stat().st_size
    with open(tmp_path / "b" / names[0], "ab") as f:
        f.write(b"more")
    (tmp_path / "b" / "stray").write_bytes(b"123")
    (tmp_path / "b" / names[1]).unlink()
    got = sorted((r["file"], r["at"], r["offset"], r["end"]) for r in warc.damage(found, other).collect() if r["at"] is None)
    assert got == sorted([(names[0], None, size, size + 4), ("stray", None, 0, 3)])
    lost = {r["page_id"] for r in warc.fixity(found, other).where("not intact").collect()}
    assert lost == {r["page_id"] for r in found.where(F.col("file") == names[1]).collect()}
    import gzip

    for row in found.where("page_id in (9, 10, 12)").collect():
        with open(tmp_path / "a" / row["file"], "rb") as f:
            f.seek(row["offset"])
            fields, body = warc.parse(gzip.decompress(f.read(row["length"])))
        n = row["page_id"]
        assert body.decode() == (f"<p>page {n}</p>\r\n\r\n" * (n % 9) if n % 4 else "") and int(fields["Content-Length"]) == len(body)
    assert warc.fixity(warc.write_warc(df.limit(0), str(tmp_path / "c")), str(tmp_path / "c")).count() == 0


def removed_by_hand(rows):
    seen, out = set(), {}
    for d, t in sorted(rows, key=lambda r: r[0]):
        data = (t or "").encode()
        gone = bytearray(len(data))
        for i in range(len(data) - spans.WIDTH + 1):
            w = data[i : i + spans.WIDTH]
            if w in seen:
                gone[i : i + spans.WIDTH] = b"\1" * spans.WIDTH
            seen.add(w)
        rest = bytes(b for b, g in zip(data, gone, strict=True) if not g)
        out[d] = (len(data), sum(gone), hashlib.sha256(rest).hexdigest())
    return out


def test_repeats_against_brute_force(spark, docs, empty):
    rng = np.random.default_rng(8)
    rows = [(d, t) for d, t, _ in DOCS if d is not None]
    passage = "".join(chr(97 + int(x)) for x in rng.integers(0, 26, 260))
    for k in range(40):
        own = "".join(chr(97 + int(x)) for x in rng.integers(0, 26, 120))
        cut = int(rng.integers(0, 150))
        rows.append((100 + k, own + passage[cut : cut + int(rng.integers(90, 200))] + own[:60]))
    got = {r["doc_id"]: (r["n_bytes"], r["n_removed"], r["kept_sha256"]) for r in spans.remove_repeats(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == removed_by_hand(rows)
    assert spans.remove_repeats(empty).count() == 0 and spans.remove_repeats(docs).count() == len(DOCS)


def test_transform_orders_suffixes_and_keeps_their_prefixes():
    rng = np.random.default_rng(5)
    base = bytes(rng.integers(97, 99, 260).astype(np.uint8))
    cuts = [base[a : a + n] for a, n in zip(rng.integers(0, 80, 30).tolist(), rng.integers(1, 170, 30).tolist(), strict=True)]
    noise = [bytes(rng.integers(97, 110, 150).astype(np.uint8)) for _ in range(20)]
    for texts in ([b"banana", b"ananas", b"nab", b"a"], [b"a" * 300, b"a" * 120, b"b"], cuts, cuts + noise, noise):
        data, sizes = np.frombuffer(b"".join(texts), np.uint8), np.array([len(t) for t in texts])
        symbols, _, m, prefixes = spans.transform(data, np.cumsum(sizes) - sizes, sizes)
        rank = spans.order(symbols, m, sizes)
        suffixes = sorted(((t[len(t) - k :], i, k) for i, t in enumerate(texts) for k in range(len(t) + 1)), key=lambda s: rank[s[1], s[2]])
        assert [s[:2] for s in suffixes] == sorted(s[:2] for s in suffixes)
        common = [next((k for k, (x, y) in enumerate(zip(a[0], b[0], strict=False)) if x != y), min(len(a[0]), len(b[0]))) for a, b in zip(suffixes[:-1], suffixes[1:], strict=True)]
        assert prefixes.tolist() == [0] + [min(n, spans.WIDTH) for n in common]


def test_token_records_round_trip(spark, docs, empty, tmp_path):
    P = pytest.importorskip("public_tokenizers")
    from tokenizers import Tokenizer

    path = P.path("byte_bpe_50k.json")
    tokenizer = Tokenizer.from_file(path)
    manifest = records.write_records(docs, path, folder=str(tmp_path / "r"))
    got = records.read_records(manifest).orderBy("start").collect()
    rows = sorted(DOCS, key=lambda d: (d[0] is not None, d[0] or 0))
    at = 0
    for r, (d, t, _) in zip(got, rows, strict=True):
        ids = tokenizer.encode(t or "", add_special_tokens=False).ids + [0]
        assert (r["doc_id"], r["start"], r["tokens"]) == (d, at, ids) and r["ids_crc32"] == zlib.crc32(np.array(ids, "<u4").tobytes())
        at += len(ids)
    assert records.read_records(records.write_records(empty, path)).count() == 0
    file = max(manifest.collect(), key=lambda r: r["docs"])
    order = np.arange(file["docs"])[::-1]
    assert [x[0][0] for x in records.frames(file["path"], file["width"], order=order)] == [n for x in records.frames(file["path"], file["width"]) for n in x[0]][::-1]
    with open(f"{file['path']}.rec", "r+b") as f:
        f.seek(25)
        f.write(b"\xff\xfe")
    with pytest.raises(records.DamagedRecord):
        list(records.frames(file["path"], file["width"]))


def test_encoder_equals_the_library():
    P = pytest.importorskip("public_tokenizers")
    from tokenizers import Tokenizer

    path = P.path("byte_bpe_50k.json")
    tokenizer, encoder = Tokenizer.from_file(path), records.Encoder(path)
    rng = np.random.default_rng(3)
    every = [chr(c) for c in range(0x80, 0x20000) if not 0xD800 <= c < 0xE000]
    texts = ["a<|endoftext|>b", "<|endoftext|>", "", None, " x  <|endoftext|> <|endoftext|>y's", "plain", "<|endoftext|", "\u1c89a \ua7cb1 \U000105c0!"]
    texts += ["".join(f"a{c}1{c}! {c}" for c in every[k : k + 512]) for k in range(0, len(every), 512)]
    signs = ["a", "'", "s", "1", " ", "\n", "!", "\u00a0", "\u0085", "\u180e", "\u200b", "\u3000", "\u1c89", "\u00b2", "\U0001e5f0", "<|endoftext|>"]
    texts += ["".join(rng.choice(signs, 30)) for _ in range(500)]
    ids, first = encoder.encode(pa.array(texts), 7)
    for t, a, b in zip(texts, first[:-1], first[1:], strict=True):
        assert ids[a:b].tolist() == tokenizer.encode(t or "", add_special_tokens=False).ids + [7]


def test_checksum():
    data = np.frombuffer(b"123456789" + bytes(200), np.uint8)
    assert records.crc32c(data, np.array([0, 0]), np.array([9, 0])).tolist() == [0xE3069283, 0]


def test_licences(docs, empty):
    texts = ["Released under the MIT License.", "x " * 500 + "Permission is hereby granted, free of charge, to any person obtaining a copy of this Software and associated documentation files, the software, to deal in the software without restriction including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense and or sell copies of the software",
             "under the and to of the mit of license", None, "", "Apache License, Version 2.0; CC BY-NC cc by nc"]
    got = licences.scan(pa.array(texts), tuple(licences.TEMPLATES))
    assert [g["labels"] for g in got] == ["mit", "mit", "", "", "", "apache-2,cc-by-nc"]
    assert got[5]["n_base"] == 3 and got[0]["first_word"] == 1 and got[1]["n_base"] == 0 and got[1]["score"] > 0.9
    assert licences.scan_licences(docs).count() == len(DOCS) and licences.scan_licences(empty).count() == 0


def test_chains_against_all_subsets():
    rng = np.random.default_rng(31)
    for _ in range(200):
        found = []
        for _ in range(int(rng.integers(1, 6))):
            f0, t0, n = int(rng.integers(0, 40)), int(rng.integers(0, 15)), int(rng.integers(4, 9))
            found.append((f0, f0 + n, t0, t0 + n))
        best = 0
        for mask in range(1, 1 << len(found)):
            chain = sorted((m for k, m in enumerate(found) if mask >> k & 1), key=lambda m: (m[1], m[3]))
            total, good = chain[0][3] - chain[0][2], True
            for x, y in zip(chain[:-1], chain[1:], strict=True):
                both = max(0, x[1] - y[0], x[3] - y[2])
                good &= x[1] < y[1] and x[3] < y[3] and x[1] >= y[0] - licences.MOST_SKIPPED and both < y[3] - y[2]
                total += y[3] - y[2] - both
            best = max(best, total if good else 0)
        chains = list(licences._chains(found))
        assert chains[0][2] == best and all(b <= c or d <= a for k, (a, b, _) in enumerate(chains) for c, d, _ in chains[:k])


def test_automaton_matching_statistics():
    rng = np.random.default_rng(6)
    templates = [rng.integers(0, 4, 20).tolist() for _ in range(3)]
    automaton = licences.SuffixAutomaton(templates)
    pieces = {tuple(t[i:j]) for t in templates for i in range(20) for j in range(i + 1, 21)}
    text = rng.integers(0, 5, 200).tolist()
    for end, length, state in automaton.matches(text, 1):
        assert tuple(text[end - length : end]) in pieces and tuple(text[max(0, end - length - 1) : end]) not in pieces or end == length
        assert all(templates[w][e - length : e] == text[end - length : end] for w, e in automaton.ends[state])


def stored(spark, folder, rows, schema, item):
    spark.createDataFrame(rows, schema).write.parquet(str(folder / "documents.parquet"))
    spark.createDataFrame([(1, item)], "item_id long, text string").write.parquet(str(folder / "benchmark.parquet"))
    return str(folder)


def prose(seed, n):
    return " ".join(f"v{int(x)}" for x in np.random.default_rng(seed).integers(0, 5000, n))


def test_pipeline(spark, tmp_path):
    import corpus_pipeline

    item = prose(999, 40)
    rows = [(i, prose(i, 120), "en", "ab"[i % 2], 0) for i in range(60)] + [(60, prose(3, 120), "en", "a", 0), (61, item + " " + prose(61, 60), "en", "b", 0), (62, "bad " * 300, "en", None, 0), (63, None, None, None, None)]
    out = corpus_pipeline.run(spark, stored(spark, tmp_path, rows, "doc_id long, text string, lang string, source string, kept long", item))
    got = {r["doc_id"] for r in out.collect()}
    assert not got & {60, 61, 62, 63} and {r["shard"] for r in out.collect()} <= set(range(16))
    assert out.columns == ["doc_id", "text", "lang", "source", "kept", "size", "shard", "slot"]
    taken = dict(map(tuple, out.groupBy("source").agg(F.sum(F.size(F.split("text", " ")))).collect()))
    assert abs(taken["a"] + taken["b"] - 1.5 * 60 * 120) < 400


def test_pipeline_stages_lose_no_row(spark, tmp_path):
    """Rows without doc_id, of one doc_id with different texts, and columns named like those at work."""
    import corpus_pipeline

    item = prose(999, 40)
    texts = [(None, prose(1, 90)), (None, prose(2, 90)), (None, prose(2, 90)), (5, prose(3, 90)), (5, prose(4, 90)), (5, prose(3, 90)), (None, item + " " + prose(8, 50)), (9, prose(2, 90)), (4, prose(3, 90) + " end")]
    schema = "doc_id long, text string, lang string, source string, _hash long, Slot string, copies long, place string, kept string, document string, _row long"
    sf_dir = stored(spark, tmp_path, [(d, t, "en", "s", k, "was", k, "p", "k", "d", k) for k, (d, t) in enumerate(texts)], schema, item)
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    stages = dict(corpus_pipeline.STAGES)
    key = lambda df: sorted((str(r["doc_id"]), r["text"], r["_hash"], r["copies"], r["place"], r["document"]) for r in df.collect())
    row = lambda *ks: sorted((str(texts[k][0]), texts[k][1], k, k, "p", "d") for k in ks)
    assert key(stages["quality rules"](spark, docs, sf_dir)) == row(*range(9))
    assert key(stages["near-duplicates"](spark, docs, sf_dir)) == row(0, 4, 6, 7, 8)
    assert key(stages["decontamination"](spark, docs, sf_dir)) == row(0, 1, 2, 3, 4, 5, 7, 8)
    assert set(key(stages["mixture"](spark, docs, sf_dir))) <= set(row(*range(9)))
    out = stages["sharding"](spark, docs, sf_dir)
    assert out.columns == [c for c in docs.columns if c != "Slot"] + ["size", "shard", "slot"] and key(out) == row(*range(9))
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, docs.limit(0), sf_dir).count() == 0
