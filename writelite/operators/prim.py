"""Subroutines: prefix sums, merging, transposes, global positions, and lineage cuts."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from writelite.operators import bucketing


def shared_folder(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir; in local mode one of its own where that is unset."""
    sc = spark.sparkContext
    if not sc.getCheckpointDir():
        folder = spark.conf.get("spark.checkpoint.dir", None)
        if not folder and not (sc.master.startswith("local[") or sc.master == "local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors see")
        sc.setCheckpointDir(folder or tempfile.mkdtemp(prefix="writelite_"))
    return sc.getCheckpointDir()


def cut_lineage(df: DataFrame) -> DataFrame:
    """checkpoint() in the shared folder."""
    shared_folder(df.sparkSession)
    return df.checkpoint()


def prefix_sum(df: DataFrame, order: str, value: str, width: int, out: str = "running") -> DataFrame:
    """Running totals in the order of a unique integer column, without ordering the table in one task.

    Ranges of `width` consecutive order values are summed; the table of range sums is scanned in two levels; rows are ordered inside their range.
    """
    cell = df.withColumn("cell", F.floor(F.col(order) / width))
    sums = cell.groupBy("cell").agg(F.sum(value).alias("s"))
    before = bucketing.running(sums, "cell", "s").select("cell", "before")
    inner = F.sum(value).over(W.partitionBy("cell").orderBy(order).rowsBetween(W.unboundedPreceding, 0))
    return cell.withColumn("inner", inner).join(before, "cell").withColumn(out, (F.col("inner") + F.col("before")).cast("long")).drop("cell", "inner", "before")


def merge_two(a: DataFrame, b: DataFrame, key: str, width: float) -> DataFrame:
    """Two sorted tables (key, pos) as one: a row's place is its own plus the number of rows of the other before it.

    Rows of a go before equal rows of b. Rows before are counted by cells of the key of the given width, then inside the cell.
    """
    both = a.select(key, "pos", F.lit(0).alias("side")).unionByName(b.select(key, "pos", F.lit(1).alias("side"))).withColumn("cell", F.floor(F.col(key) / width))
    sizes = both.groupBy("cell").agg(F.count(F.lit(1)).alias("n"))
    before = bucketing.running(sizes, "cell", "n").select("cell", "before")
    rank = F.row_number().over(W.partitionBy("cell").orderBy(key, "side", "pos"))
    return both.withColumn("nth", rank).join(before, "cell").select(key, "side", "pos", (F.col("before") + F.col("nth")).cast("long").alias("merged_pos"))


def transpose(matrix: DataFrame) -> DataFrame:
    """(i, j, v) with rows and columns swapped: a projection, nothing moves."""
    return matrix.select(F.col("j").alias("i"), F.col("i").alias("j"), "v")


def transpose_index(idx, rows: int, cols: int):
    """Place in the transpose of a rows x cols row-major array."""
    return (idx % cols) * rows + F.floor(idx / cols)
