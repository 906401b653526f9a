"""Collections of documents as streams of (coll, d, seq, doc_key, terms).

A term is a run of letters after lower-casing, cut after every MAX_TERM letters; nothing is stemmed or stopped, and
the words of markup count like others. d counts documents from 1 in arrival order.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from liveindex.scratch import numbered

MAX_TERM = 20
LETTERS = {"ascii": "[a-z]", "unicode": r"\p{L}"}


def tokens(text: Column, mode: str = "ascii", most: int = MAX_TERM) -> Column:
    """Runs of letters, cut after every `most` of them: one greedy pattern does both."""
    return F.regexp_extract_all(F.lower(F.coalesce(text, F.lit(""))), F.lit(f"({LETTERS[mode]}{{1,{most}}})"), 1)


def docstream(df: DataFrame, d: Column, key: Column, text: Column, coll: str, mode: str = "ascii", most: int = MAX_TERM) -> DataFrame:
    """One projection, no shuffle."""
    return df.select(F.lit(coll).alias("coll"), d.cast("long").alias("d"), (2 * d.cast("long")).alias("seq"), key.cast("string").alias("doc_key"), tokens(text, mode, most).alias("terms"))


def assign_ordinals(df: DataFrame, *order: str, into: str = "d", start: int = 0) -> DataFrame:
    """Dense numbers from start + 1 in the order of some columns. The ranged rows are written, see `numbered`."""
    return numbered(df, *order, into=into, start=start)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def docs(spark: SparkSession, sf_dir: str, mode: str = "ascii", most: int = MAX_TERM) -> DataFrame:
    return docstream(table(spark, sf_dir, "documents"), F.col("doc_id") + 1, F.col("doc_id"), F.col("text"), "docs", mode, most)


def pages(spark: SparkSession, sf_dir: str, mode: str = "ascii") -> DataFrame:
    return docstream(table(spark, sf_dir, "pages"), F.col("page_id") + 1, F.col("page_id"), F.col("html"), "pages", mode)


def turns(spark: SparkSession, sf_dir: str, mode: str = "ascii") -> DataFrame:
    rows = assign_ordinals(table(spark, sf_dir, "conversations").select("conv_id", "turn", "text"), "conv_id", "turn")
    return docstream(rows, F.col("d"), F.concat_ws("-", "conv_id", "turn"), F.col("text"), "turns", mode)


def basket_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(o, line, words) of each order line, words already lower-case and split on blanks."""
    line, part = table(spark, sf_dir, "lineitem"), table(spark, sf_dir, "part")
    joined = line.join(part, line.l_partkey == part.p_partkey)
    text = F.concat_ws(" ", "p_name", "p_brand", "p_type", "l_returnflag", "l_linestatus", F.concat(F.lit("q"), F.col("l_quantity").cast("int").cast("string")), F.concat(F.lit("s"), F.col("p_size").cast("string")))
    return joined.select(F.col("l_orderkey").alias("o"), F.struct("l_linenumber", F.lower(text).alias("text")).alias("line"))


def baskets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One document an order: the words of its lines in order. Few terms, long lists."""
    grouped = basket_words(spark, sf_dir).groupBy("o").agg(F.array_sort(F.collect_list("line")).alias("lines"))
    words = F.flatten(F.transform("lines", lambda x: F.split(x["text"], " ")))
    return grouped.select(F.lit("baskets").alias("coll"), (F.col("o") + 1).alias("d"), (2 * (F.col("o") + 1)).alias("seq"), F.col("o").cast("string").alias("doc_key"), words.alias("terms"))


def zipf(spark: SparkSession, n: int, vocabulary: int, words: int = 100, exponent: float = 1.1, seed: int = 7) -> DataFrame:
    """n documents of `words` terms with ranks of about the given exponent, drawn from hashes: any size, no input."""
    draw = lambda i: (F.pmod(F.xxhash64("id", i, F.lit(seed)), F.lit(1 << 40)) + 1) / F.lit(float(1 << 40))
    top = F.lit(float(vocabulary) ** (1 - exponent))
    rank = lambda i: F.floor(F.pow(1 - draw(i) * (1 - top), F.lit(1 / (1 - exponent))))
    terms = F.transform(F.sequence(F.lit(1), F.lit(words)), lambda i: F.concat(F.lit("t"), F.lpad(rank(i).cast("string"), 9, "0")))
    return spark.range(n).select(F.lit("zipf").alias("coll"), (F.col("id") + 1).alias("d"), (2 * F.col("id") + 2).alias("seq"), F.col("id").cast("string").alias("doc_key"), terms.alias("terms"))


COLLECTIONS = {"docs": docs, "pages": pages, "turns": turns, "baskets": baskets}


def write_docstream(df: DataFrame, path: str) -> None:
    """One line a document: its key, then its terms."""
    df.select(F.concat_ws(" ", F.array(F.col("doc_key")), "terms")).write.mode("overwrite").text(path)


def read_docstream(spark: SparkSession, path: str, coll: str = "file") -> DataFrame:
    """Lines written by write_docstream; d follows the file order of the keys only if they are numbers."""
    parts = F.split(F.col("value"), " ")
    rows = spark.read.schema("value string").text(path).select(parts[0].alias("doc_key"), F.slice(parts, 2, F.greatest(F.size(parts) - 1, F.lit(0))).alias("terms"))
    return rows.select(F.lit(coll).alias("coll"), (F.col("doc_key").cast("long") + 1).alias("d"), (2 * F.col("doc_key").cast("long") + 2).alias("seq"), "doc_key", "terms")
