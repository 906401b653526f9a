"""Queries over postings and blocks. A log of queries is one plan: qid is a column like any other.

queries: (qid, terms). A query is the set of its terms. Whole logs are answered shard by shard (see `evaluate`); the
forms by joins stay as variants, with the log as the small side, which is broadcast only if its rows are counted and
fewer than SMALL_LOG.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from liveindex.functions.lengths import tf_idf
from liveindex.operators import evaluate as E
from liveindex.operators.packer import IndexConfig, decode_blocks
from liveindex.scratch import numbered

SMALL_LOG = 200_000


def query_terms(queries: DataFrame) -> DataFrame:
    """(qid, term, n_terms), each term once."""
    return queries.select("qid", F.array_distinct("terms").alias("t")).select("qid", F.explode("t").alias("term"), F.size("t").cast("long").alias("n_terms"))


def _small(df: DataFrame) -> DataFrame:
    """df marked for broadcast if it is small, counted up to the bound."""
    return F.broadcast(df) if df.limit(SMALL_LOG + 1).count() <= SMALL_LOG else df


def fetch(postings: DataFrame, queries: DataFrame) -> DataFrame:
    """Postings of the queries' terms, with qid and n_terms."""
    return postings.join(_small(query_terms(queries)), "term")


def fetch_blocks(blocks: DataFrame, queries: DataFrame) -> DataFrame:
    """Blocks of the lists that some query names; payloads of others are never read."""
    return blocks.join(_small(query_terms(queries).select("term").distinct()), "term", "left_semi")


def conjunctive(postings: DataFrame, queries: DataFrame, method: str = "shards", n_docs: int | None = None) -> DataFrame:
    """(qid, d) of documents with all terms of a query; an unknown term or no term gives no document.

    shards: each shard of documents intersects its own lists, rarest first; semijoin: documents of the rarest term,
    held against the others' lists by joins; count: matches of each (qid, d) counted, which copies a list once for
    each query that names it."""
    if method == "shards":
        return E.conjunctive(postings, queries, n_docs)
    if method == "count":
        return fetch(postings, queries).groupBy("qid", "d").agg(F.count("*").alias("m"), F.first("n_terms").alias("n_terms")).where("m = n_terms").select("qid", "d")
    if method != "semijoin":
        raise ValueError(f"no method {method}")
    lists = fetch(postings.groupBy("term").agg(F.count("*").alias("ft")), queries)
    by = Window.partitionBy("qid").orderBy("ft", "term")
    ranked = lists.withColumn("rank", F.row_number().over(by)).withColumn("known", F.count("*").over(Window.partitionBy("qid"))).where("known = n_terms")
    first = postings.join(ranked.where("rank = 1").select("term", "qid"), "term").select("qid", "d")
    # What to look up follows from the rarest lists; the others' postings join it by (term, d) and are never copied.
    wanted = first.join(ranked.where("rank > 1").select("qid", "term", "n_terms"), "qid")
    left = wanted.join(postings.select("term", "d"), ["term", "d"], "left_semi").groupBy("qid", "d").agg(F.count("*").alias("m"), F.first("n_terms").alias("n")).where("m = n - 1").select("qid", "d")
    alone = first.join(ranked.where("n_terms = 1").select("qid"), "qid", "left_semi")
    return left.unionAll(alone)


def disjunctive(postings: DataFrame, queries: DataFrame) -> DataFrame:
    """(qid, d) of documents with any term of a query."""
    return fetch(postings, queries).select("qid", "d").distinct()


def zone_map(blocks: DataFrame) -> DataFrame:
    """Blocks with the first document of the one after, without payloads. Empty heads hold nothing to seek."""
    return blocks.where("n > 0").select("shard", "term", "block_no", "first_d", F.lead("first_d").over(Window.partitionBy("shard", "term").orderBy("block_no")).alias("next_d"))


def seek_geq(blocks: DataFrame, targets: DataFrame, cfg: IndexConfig) -> DataFrame:
    """targets(qid, term, d) with shard, block_no and first_d of the one block of the term's list that may hold d.

    As-of join by a union of blocks and targets and a running last value: one shuffle by shard and term, no range join."""
    marks = blocks.where("n > 0").select("shard", "term", F.col("first_d").alias("at"), F.lit(0).alias("kind"), F.struct("block_no", "first_d").alias("block"), F.lit(None).cast("long").alias("qid"))
    asks = targets.select(cfg.shard_of("d").alias("shard"), "term", F.col("d").alias("at"), F.lit(1).alias("kind"), F.lit(None).cast(marks.schema["block"].dataType).alias("block"), "qid")
    found = marks.unionAll(asks).withColumn("block", F.last("block", ignorenulls=True).over(Window.partitionBy("shard", "term").orderBy("at", "kind").rowsBetween(Window.unboundedPreceding, 0)))
    return found.where((F.col("kind") == 1) & F.col("block").isNotNull()).select("qid", "shard", "term", F.col("at").alias("d"), "block.block_no", "block.first_d")


def _known(blocks: DataFrame, queries: DataFrame) -> DataFrame:
    """(qid, term, n_terms, ft, blocks, rank): terms of the queries that the index knows all terms of, rarest first."""
    lists = blocks.groupBy("term").agg(F.sum("n").alias("ft"), F.count_if(F.col("n") > 0).alias("blocks"))
    by = Window.partitionBy("qid")
    return fetch(lists, queries).withColumn("rank", F.row_number().over(by.orderBy("ft", "term"))).withColumn("known", F.count("*").over(by)).where("known = n_terms").drop("known")


def conjunctive_by_seek(blocks: DataFrame, queries: DataFrame, cfg: IndexConfig, decode: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
    """Conjunction that decodes the rarest list of each query, and of the others only the blocks that candidates fall in.

    decode: for blocks of another form, such as the runs of a static index, whose rows without payloads are its skip table."""
    decode = decode or (lambda some: decode_blocks(some, cfg))
    known = _known(blocks, queries)
    lead = known.where("rank = 1").select("qid", "term", "n_terms")
    seeds = decode(blocks.join(lead.select("term").distinct(), "term", "left_semi")).select("term", "d").join(lead, "term").select("qid", "d", "n_terms")
    targets = seeds.join(known.where("rank > 1").select("qid", "term"), "qid").select("qid", "term", "d")
    # Queries that ask a list for the same document seek it once.
    places = seek_geq(blocks.drop("payload"), targets.select(F.lit(0).cast("long").alias("qid"), "term", "d").distinct(), cfg)
    touched = blocks.join(places.select("shard", "term", "block_no").distinct(), ["shard", "term", "block_no"], "left_semi")
    met = targets.join(decode(touched).select("term", "d"), ["term", "d"], "left_semi").groupBy("qid", "d").agg(F.count("*").alias("m"))
    return seeds.join(met, ["qid", "d"], "left").where(F.coalesce("m", F.lit(0)) == F.col("n_terms") - 1).select("qid", "d")


def skip_stats(blocks: DataFrame, queries: DataFrame, postings: DataFrame, cfg: IndexConfig) -> DataFrame:
    """(qid, term, blocks, touched, decoded): of the lists after the rarest of a query, how many blocks candidates fall
    in, and how many of those must be decoded, as a candidate is not the block's own first document."""
    known = _known(blocks, queries)
    seeds = postings.join(known.where("rank = 1").select("qid", "term"), "term").select("qid", "d")
    rest = known.where("rank > 1").select("qid", "term", "blocks")
    places = seek_geq(blocks, seeds.join(rest.select("qid", "term"), "qid"), cfg)
    block = places.groupBy("qid", "term", "shard", "block_no").agg(F.max(F.when(F.col("d") > F.col("first_d"), 1).otherwise(0)).alias("inside"))
    counts = block.groupBy("qid", "term").agg(F.count("*").alias("touched"), F.sum("inside").alias("decoded"))
    return rest.join(counts, ["qid", "term"], "left").select("qid", "term", "blocks", F.coalesce("touched", F.lit(0)).alias("touched"), F.coalesce("decoded", F.lit(0)).alias("decoded"))


def _best(scored: DataFrame, k: int) -> DataFrame:
    """(qid, rank, d, score): the k best of each query, ties by document. Filtering row_number lets each task of the
    shuffle keep k rows a query before it sends any."""
    rank = F.row_number().over(Window.partitionBy("qid").orderBy(F.desc("score"), "d"))
    return scored.withColumn("rank", rank).where(F.col("rank") <= k).select("qid", F.col("rank").cast("long").alias("rank"), "d", "score")


def topk(postings: DataFrame, queries: DataFrame, n_docs: int, k: int = 10, digits: int = 6, prune: bool = False) -> DataFrame:
    """(qid, rank, d, score): the k documents of each query with the largest sums of log(1 + f) * log(1 + N / ft).

    prune: lists that cannot lift a document any more are looked up instead of added; answers are the same."""
    return E.topk(postings, queries, n_docs, k, digits, prune=prune)


def topk_joined(postings: DataFrame, queries: DataFrame, n_docs: int, k: int = 10, digits: int = 6) -> DataFrame:
    """The same by a join of the log and the lists, grouped by query and document. Each list is copied once for each
    query that names it, but inside its shard and for one query at a time: the copies never leave a task."""
    return E.topk(postings, queries, n_docs, k, digits, strategy="join")


def topk_bm25(postings: DataFrame, lengths: DataFrame, queries: DataFrame, k: int = 10, k1: float = 0.9, b: float = 0.4, digits: int = 6) -> DataFrame:
    """The same by BM25, with document lengths kept apart from the index."""
    facts = lengths.agg(F.count("*").alias("N"), F.avg("len").alias("avg")).first()
    return E.topk(postings, queries, facts["N"], k, digits, ("bm25", k1, b, facts["avg"]), lengths)


def term_bounds(postings: DataFrame, n_docs: int, digits: int = 6) -> DataFrame:
    """(term, ft, max_w): the largest weight that each list can add."""
    lists = postings.groupBy("term").agg(F.count("*").alias("ft"), F.max("f").alias("most"))
    return lists.select("term", "ft", F.round(tf_idf(F.col("most"), F.lit(n_docs), F.col("ft")), digits).alias("max_w"))


def topk_pruned(postings: DataFrame, queries: DataFrame, n_docs: int, k: int = 10, digits: int = 6) -> DataFrame:
    """The answers of topk, scoring fewer documents: exact, by bounds on lists.

    The k best by each query's rarest term alone set a floor. Lists whose bounds together stay below the floor
    cannot lift a document that no other list names, so only documents of the other lists are scored. Floors and bounds
    are of the whole collection; documents are scored inside their shards."""
    return E.topk(postings, queries, n_docs, k, digits, strategy="bounds")


def fuse_topk(answers: list[DataFrame], k: int = 10) -> DataFrame:
    """Best k over the shards' answers, whose weights share global statistics."""
    out = answers[0].select("qid", "d", "score")
    for more in answers[1:]:
        out = out.unionByName(more.select("qid", "d", "score"))
    return _best(out, k)


def phrase(occurrences: DataFrame, queries: DataFrame, n_docs: int | None = None) -> DataFrame:
    """(qid, d, hits): documents where the words of a query stand in a row, and how often; from each shard's rarest word."""
    return E.phrase(occurrences, queries, n_docs)


def proximity(occurrences: DataFrame, pairs: DataFrame, window: int, n_docs: int | None = None) -> DataFrame:
    """pairs(qid, t1, t2): (qid, d, hits) of places where the two stand at most `window` words apart; no pairs are formed."""
    return E.proximity(occurrences, pairs.select("qid", F.array("t1", "t2").alias("terms")), window, n_docs)


def recent_matches(postings: DataFrame, queries: DataFrame, k: int, n_docs: int | None = None) -> DataFrame:
    """(qid, rank, d): the newest k conjunctive matches; a shard sends its newest k."""
    rank = F.row_number().over(Window.partitionBy("qid").orderBy(F.desc("d")))
    return E.conjunctive(postings, queries, n_docs, newest=k).withColumn("rank", rank.cast("long")).where(F.col("rank") <= k).select("qid", "rank", "d")


def boolean(postings: DataFrame, expression: tuple) -> DataFrame:
    """(d) of documents for an expression: a term, ("and" | "or", a, b, ..) or ("not", a, b) for a without b."""
    if isinstance(expression, str):
        return postings.where(F.col("term") == expression).select("d")
    kind, first, *rest = expression
    out = boolean(postings, first)
    for e in rest:
        other = boolean(postings, e)
        out = out.join(other, "d", "left_semi") if kind == "and" else out.join(other, "d", "left_anti") if kind == "not" else out.union(other).distinct()
    return out


def ops_conjunctive(postings: DataFrame, ops: DataFrame, n_docs: int | None = None) -> DataFrame:
    """(op_seq, qid, d): what each query of an operation stream finds among the documents inserted before it.

    postings carry seq of their document; ops(op_seq, qid, terms)."""
    return E.conjunctive(postings, ops, n_docs, cut="op_seq").join(_small(ops.select("qid", "op_seq")), "qid").select("op_seq", "qid", "d")


def ops_topk(postings: DataFrame, docs: DataFrame, ops: DataFrame, k: int = 10, digits: int = 6, n_docs: int | None = None) -> DataFrame:
    """The same ranked, by statistics of the time of each query; docs(d, seq) are all inserts."""
    return E.topk_seen(postings, docs, ops, n_docs, k, digits)


def positions(blocks: DataFrame) -> DataFrame:
    """(shard, term, block_no, pos): arrival order of blocks - by the document that opens each, then by term.

    Ranks come from the range partitioning of the sort, not from one task."""
    chain = Window.partitionBy("shard", "term").orderBy("block_no")
    opened = blocks.select("shard", "term", "block_no", F.when(F.col("n") > 0, F.col("first_d")).otherwise(F.lead("first_d").over(chain)).alias("opened"))
    return numbered(opened, "opened", "term", "block_no", into="pos").select("shard", "term", "block_no", "pos")


def collated(blocks: DataFrame) -> DataFrame:
    """(shard, term, block_no, pos) once each term's blocks lie together."""
    return numbered(blocks.select("shard", "term", "block_no"), "shard", "term", "block_no", into="pos").select("shard", "term", "block_no", "pos")


def jump_stats(placed: DataFrame, layout: str) -> DataFrame:
    """(layout, blocks, jumps, mean_jump): successors of a chain that are not the next block in the array."""
    step = F.lead("pos").over(Window.partitionBy("shard", "term").orderBy("block_no")) - F.col("pos")
    return placed.withColumn("step", step).agg(F.count("*").alias("blocks"), F.count_if(F.col("step") != 1).alias("jumps"), F.round(F.coalesce(F.avg(F.abs("step")), F.lit(0.0)), 6).alias("mean_jump")).select(F.lit(layout).alias("layout"), "blocks", "jumps", "mean_jump")
