"""Times the headline queries and experiments: python bench.py prints one JSON line, and a line a query to stderr.

BENCH_SF_DIR: tables (default /root/testdata/sf0.1); BENCH_CPUS: cores (default all); BENCH_LIMIT: seconds for all
(default 900), after which what is left is not begun; BENCH_EACH: seconds after which one query is cancelled (default
180). Each query runs once into the noop sink after a small warm-up. A query that fails or is cancelled counts as null.
"""

from __future__ import annotations

import json
import os
import signal
import sys
import threading
import time

HERE = os.path.dirname(os.path.abspath(__file__))
sys.path.insert(0, HERE)
os.environ["PYTHONPATH"] = f"{HERE}:{os.environ.get('PYTHONPATH', '')}"

HEADLINE = ("count_terms", "postings_doc_docs", "block_table", "term_dir", "components_b64", "conjunctive", "conjunctive_skip", "conjunctive_static", "topk_tfidf", "topk_maxscore", "topk_bm25", "phrase", "ops_conjunctive", "ops_topk", "b_sweep_doc", "b_sweep_word", "growth_compare", "pair_f_sweep", "bp128_sizes",
            "interpolative_sizes", "jump_stats", "skip_stats", "disjunctive_counts", "standing", "batches_merged")
REPORTS = {"latency_by_length": ("engine", "mode", "n_terms"), "latency_by_layout": ("growth", "layout", "mode"), "collation_cost": ("step",)}


def codec_seconds(spark, sf: str) -> dict[str, float]:
    """Encoding and decoding of all postings of `docs` and `baskets` in memory, and three copies of the pairs."""
    import numpy as np

    from liveindex.functions import codecs
    from liveindex.operators import postings as P
    from liveindex.sources import collections as S

    both = [P.postings_doc(make(spark, sf)).select("g", "f").toPandas() for make in (S.docs, S.baskets)]
    gap, f = (np.concatenate([b[c].to_numpy(np.int64) for b in both]) for c in ("g", "f"))
    out = {"codec_postings": int(gap.size)}
    for name, threshold in (("byte", 1), ("paired", 4)):
        began = time.perf_counter()
        data = codecs.pair_encode(gap, f, threshold)
        middle = time.perf_counter()
        x, y = codecs.pair_decode(data, threshold)
        end = time.perf_counter()
        assert (x == gap).all() and (y == f).all()
        out |= {f"codec_{name}_encode": round(middle - began, 3), f"codec_{name}_decode": round(end - middle, 3), f"codec_{name}_bytes": round(data.size / gap.size, 3)}
    pairs = np.stack((gap, f)).astype(np.uint32)
    flat, copy = pairs.reshape(-1), np.empty(pairs.size, np.uint32)

    def timed(name: str, work) -> None:
        began = time.perf_counter()
        work()
        out[name] = round(time.perf_counter() - began, 4)

    def by_byte() -> None:
        for k in range(4):
            copy.view(np.uint8)[k::4] = flat.view(np.uint8)[k::4]

    def by_integer() -> None:
        for k in range(0, flat.size, 1 << 12):
            copy[k : k + (1 << 12)] = flat[k : k + (1 << 12)]

    timed("copy_byte_lanes", by_byte)
    timed("copy_integer_loop", by_integer)
    timed("copy_slab", lambda: np.copyto(copy, flat))
    return out


def ingest_seconds(spark, sf: str) -> dict[str, float]:
    """Microseconds a document of counting alone, of counting and indexing, and seconds of a word-level build."""
    from pyspark.sql import functions as F

    from liveindex.operators import packer as K
    from liveindex.operators import postings as P
    from liveindex.sources import collections as S

    stream = S.docs(spark, sf)
    n = stream.count()
    size = spark.read.parquet(f"{sf}/documents.parquet").agg(F.sum(F.octet_length("text"))).first()[0]

    def timed(df) -> float:
        began = time.time()
        df.write.format("noop").mode("overwrite").save()
        return time.time() - began

    word = K.IndexConfig(level="word")
    count, index, words = timed(P.count_terms(stream)), timed(K.build_blocks(P.count_terms(stream), K.IndexConfig())), timed(K.build_blocks(P.postings_word(stream), word))
    total = K.index_sizes(P.postings_word(stream), [word]).first()["total_bytes"]
    return {"count_only_us_a_document": round(count / n * 1e6, 1), "count_and_index_us_a_document": round(index / n * 1e6, 1), "ingest_mb_a_second": round(size / index / 1e6, 2), "word_level_build_seconds": round(words, 2), "word_level_mib": round(total / (1 << 20), 2)}


def main() -> None:
    from pyspark.sql import SparkSession

    from liveindex import registry

    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "*")
    until, each = time.time() + float(os.environ.get("BENCH_LIMIT", "900")), float(os.environ.get("BENCH_EACH", "180"))
    spark = (SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", "16").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false")
             .config("spark.driver.memory", "12g").config("spark.sql.session.timeZone", "UTC").getOrCreate())
    spark.sparkContext.setLogLevel("ERROR")
    registry.load()
    seconds: dict[str, float | None] = {}
    extra: dict = {}

    def tell(*_) -> None:
        done = [s for s in seconds.values() if s is not None]
        print(json.dumps({"metric": "headline_queries_total", "value": round(sum(done), 3), "unit": "sec", "queries": seconds, "sf": float(os.path.basename(sf.rstrip("/")).removeprefix("sf") or 0), **extra}), flush=True)

    def stopped(*_) -> None:
        tell()
        os._exit(0)

    signal.signal(signal.SIGTERM, stopped)

    def run(name: str, work):
        """work(), within the time of one query; None if there is none left or it fails."""
        left = min(each, until - time.time())
        if left <= 0:
            return None
        stop = threading.Timer(left, spark.sparkContext.cancelAllJobs)
        stop.start()
        began = time.time()
        try:
            return work()
        except Exception as why:
            print(f"{name}: {str(why)[:200]}", file=sys.stderr)
            return None
        finally:
            stop.cancel()
            print(f"{name} {time.time() - began:.2f} s", file=sys.stderr, flush=True)

    def query(name: str) -> float:
        began = time.time()
        registry.QUERIES[name](spark, sf).write.format("noop").mode("overwrite").save()
        return round(time.time() - began, 3)

    run("warm-up", lambda: (query("count_terms"), registry.QUERIES["conjunctive"](spark, sf).count()))
    for name in HEADLINE:
        seconds[name] = run(name, lambda: query(name))  # noqa: B023
    extra["ingest"] = run("ingest", lambda: ingest_seconds(spark, sf))
    extra["codecs"] = run("codecs", lambda: codec_seconds(spark, sf))
    for name, keys in REPORTS.items():
        rows = run(name, lambda: registry.QUERIES[name](spark, sf).collect())  # noqa: B023
        extra[name] = rows and {"/".join(str(r[k]) for k in keys): {c: r[c] for c in r.__fields__ if c not in keys} for r in sorted(rows, key=lambda r: [r[k] for k in keys])}
    tell()


if __name__ == "__main__":
    main()
