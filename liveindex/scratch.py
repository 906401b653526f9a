"""Tables written once to the folder that the cluster shares, and numbers that rest on them.

The folder is spark.checkpoint.dir; one of our own is set only where the session has none and runs in one process."""

from __future__ import annotations

import atexit
import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

_made: list[tuple[SparkSession, str]] = []


def folder(spark: SparkSession, name: str) -> str:
    """A new path below the shared folder, removed when the interpreter ends."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the whole cluster sees")
        base = tempfile.mkdtemp(prefix="liveindex-")
        spark.sparkContext.setCheckpointDir(base)
    if not _made:
        atexit.register(_sweep)
    _made.append((spark, path := f"{base.rstrip('/')}/{name}-{uuid.uuid4().hex}"))
    return path


def _sweep() -> None:
    for spark, path in _made:
        try:
            where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
            where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
        except Exception:  # the session has ended; its folder is the operator's to empty
            return


def written(df: DataFrame, name: str) -> DataFrame:
    """df written once and read back: lineage ends here and lost executors cost nothing."""
    path = folder(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def running_sum(df: DataFrame, value: str, order: str, into: str, cell: int = 4096) -> DataFrame:
    """df, one row for each number of `order`, with the sum of value over all rows of smaller numbers.

    Three levels: cells of rows, cells of cells, and the sums of these, so that the one task that sums them sees a row
    for cell * cell numbers."""
    rows = df.withColumn("_c", F.floor(F.col(order) / cell))
    first = rows.groupBy("_c").agg(F.sum(value).alias("_s")).withColumn("_cc", F.floor(F.col("_c") / cell))
    second = first.groupBy("_cc").agg(F.sum("_s").alias("_ss"))
    before = lambda what, *by: F.coalesce(F.sum(what).over(by[0].rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    second = second.select("_cc", before("_ss", Window.orderBy("_cc")).alias("_b2"))
    first = first.join(second, "_cc").select("_c", (before("_s", Window.partitionBy("_cc").orderBy("_c")) + F.col("_b2")).alias("_b1"))
    return rows.join(first, "_c").withColumn(into, before(value, Window.partitionBy("_c").orderBy(order)) + F.col("_b1")).drop("_c", "_b1")


def numbered(df: DataFrame, *order: str, into: str, start: int = 0) -> DataFrame:
    """df with dense numbers from start + 1 in the order of some columns, without a single-task window.

    Rows are written in range partitions, each with its partition's number, so that counts and rows come from the same
    ranges however often they are read; the counts, one row a partition, give the offsets."""
    parts = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ranged = written(df.repartitionByRange(parts, *order).withColumn("_part", F.spark_partition_id()), "ranged")
    ahead = Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = ranged.groupBy("_part").agg(F.count("*").alias("_n")).select("_part", F.coalesce(F.sum("_n").over(ahead), F.lit(0)).alias("_offset"))
    inside = F.row_number().over(Window.partitionBy("_part").orderBy(*order))
    return ranged.withColumn("_row", inside).join(F.broadcast(offsets), "_part").withColumn(into, (F.col("_offset") + F.col("_row") + start).cast("long")).drop("_part", "_row", "_offset")
