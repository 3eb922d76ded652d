"""Measures over ledgers: bound checks, depth, processors, amortised cost, footprints, and Spark's own bytes."""

from __future__ import annotations

import functools
import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from writelite.functions import bounds, metrics, model
from writelite.functions.model import STD, MachineParams
from writelite.operators import sort
from writelite.workloads.sorting import HEAP, REAL, TIE, _ok_sql, _ops, processor_times, table


def _lineitem(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "lineitem").select(*REAL)


def _bounds_check(spark: SparkSession, d: str) -> DataFrame:
    """Each sort's ledger over lineitem against its bound; the constants of Big-O bounds are 2 for reads and writes."""
    df = _lineitem(spark, d)
    n, lev = df.count(), 0
    lev, nb = bounds.levels(n, STD), bounds.blocks(n, STD.B)
    r, w = bounds.oblivious_sort(n, MachineParams(STD.M, STD.B, 4, 1))
    parts = [
        metrics.check(sort.em_sample(df, REAL, TIE, STD).ledger, 2 * (STD.k + 1) * nb * lev, 2 * nb * lev),
        metrics.check(sort.em_merge(df, REAL, TIE, STD).ledger, 1.1 * (STD.k + 1) * nb * lev, 1.1 * nb * lev),
        metrics.check(sort.co_sort(df, REAL, TIE, 4, 256).ledger, 8 * r, 8 * w),
    ]
    return functools.reduce(DataFrame.unionByName, parts).select("method", "ok_r", "ok_w")


def _depth(spark: SparkSession, d: str) -> DataFrame:
    """Depth of the parallel sample sort's ledger is below its total cost by about the number of processors."""
    led = sort.em_sample_parallel(_lineitem(spark, d), REAL, TIE, STD).ledger
    deep, total = model.depth(led, STD.omega), model.ledger_cost(led, STD.omega).first()["cost"]
    return spark.createDataFrame([("depth", bool(0 < deep < total))], "measure string, ok boolean")


def _private(spark: SparkSession, d: str) -> DataFrame:
    """The dearest processor of the parallel sample sort costs at most 4 times the mean one."""
    led = sort.em_sample_parallel(_lineitem(spark, d), REAL, TIE, STD).ledger.where("phase = 'distribute'")
    most, total = model.private_cache_time(led, STD.omega), model.ledger_cost(led, STD.omega).first()["cost"]
    return spark.createDataFrame([("private_cache", bool(most * led.select("node").distinct().count() <= 4 * total))], "measure string, ok boolean")


def _amortised(spark: SparkSession, d: str) -> DataFrame:
    """Reads and writes counted so far over operations so far, after each delete-min of a mixed stream."""
    from writelite.operators import pq

    done = pq.run(_ops(spark, d), HEAP)
    nth = _ops(spark, d).withColumn("i", F.row_number().over(W.partitionBy("shard").orderBy("seq"))).select("shard", "seq", "i")
    return done.join(nth, ["shard", "seq"]).select("shard", "seq", (F.col("reads") / F.col("i")).alias("reads_per_op"), (F.col("writes") / F.col("i")).alias("writes_per_op"))


def _speedup(spark: SparkSession, d: str) -> DataFrame:
    """Whether T(1) over p T(p), counted from the parallel sample sort's ledger, is at least a half for p up to n / 8M."""
    led = sort.em_sample_parallel(_lineitem(spark, d), REAL, TIE, STD).ledger
    t = processor_times(led, STD.omega, (1, 2, 3))
    return spark.createDataFrame([(p, t[1] >= 0.5 * p * t[p]) for p in (1, 2, 3)], "p long, linear boolean")


def _memory(spark: SparkSession, d: str) -> DataFrame:
    """Fast memory of each method in records, for lineitem: a pointer has the bits that tell its rows apart, a record 512."""
    n = table(spark, d, "lineitem").agg(F.count("l_extendedprice").alias("n")).first()["n"]
    return spark.createDataFrame([(m, float(round(bounds.memory(m, STD, n=n), 4))) for m in ("merge", "base", "sample")], "method string, records double")


def _levels(spark: SparkSession, d: str) -> DataFrame:
    """Levels of the sample sort's ledger are at most one more than the mergesort's bound."""
    df = _lineitem(spark, d)
    led = sort.em_sample(df, REAL, TIE, MachineParams(64, 8, 8, 2)).ledger.where("phase = 'distribute'")
    found = led.select("level").distinct().count()
    return spark.createDataFrame([("levels", found <= bounds.levels(df.count(), MachineParams(64, 8, 8, 2)) + 1)], "measure string, ok boolean")


def _ratio(spark: SparkSession, d: str) -> DataFrame:
    """The cache-oblivious sort's reads over writes grow with omega."""
    df = _lineitem(spark, d)
    ratios = [(t := model.ledger_cost(sort.co_sort(df, REAL, TIE, o, 256).ledger, o).first())["reads"] / t["writes"] for o in (1, 4, 8)]
    return spark.createDataFrame([("read_write_ratio", ratios == sorted(ratios) and ratios[2] > ratios[0])], "measure string, ok boolean")


def io_bytes(spark: SparkSession, df: DataFrame) -> dict[str, dict[str, int]]:
    """What Spark reads, shuffles and spills for the sample sort in one scan, in k filtered scans, and for its own order by."""
    actions = {
        "fused": lambda: sort.em_sample(df, REAL, TIE, STD).rows.write.format("noop").mode("overwrite").save(),
        "rounds": lambda: sort.em_sample(df, REAL, TIE, STD, how="rounds").rows.write.format("noop").mode("overwrite").save(),
        "order_by": lambda: df.orderBy(*REAL).write.format("noop").mode("overwrite").save(),
    }
    return {name: metrics.io_of(spark, act) for name, act in actions.items()}


def _io(spark: SparkSession, d: str) -> DataFrame:
    """Whether the sample sort, which also gives positions, writes at most 1.1 times the shuffle bytes of Spark's own order
    by. Its sample and its counts are a lower-order term: 100 bytes for each of the keys that fan-out and log n ask for.
    """
    df = _lineitem(spark, d)
    found = io_bytes(spark, df)
    least = 100 * sort.OVER * 64 * math.log2(max(df.count(), 2))
    return spark.createDataFrame([(m, found[m]["shuffle_write"] <= 1.1 * found["order_by"]["shuffle_write"] + least) for m in ("fused", "rounds")], "method string, ok boolean")


def _nulls(spark: SparkSession, d: str) -> DataFrame:
    """Nulls first, NaN last, one zero: orders by a derived key."""
    k = F.col("o_orderkey")
    key = F.when(k % 7 == 0, None).when(k % 11 == 0, F.lit(float("nan"))).when(k % 13 == 0, F.lit(-0.0)).when(k % 17 == 0, F.lit(0.0)).otherwise(F.col("o_totalprice"))
    df = table(spark, d, "orders").select("o_orderkey", key.alias("key"))
    return sort.em_sample(df, ["key", "o_orderkey"], ["o_orderkey"], MachineParams(64, 8, 8, 4)).rows.select("o_orderkey", "pos")


def _turns(spark: SparkSession, d: str) -> DataFrame:
    c = table(spark, d, "conversations").select("conv_id", "turn")
    return sort.em_sample(c, ["conv_id", "-turn"], ["conv_id", "turn"], MachineParams(64, 8, 8, 4)).rows


QUERIES = {
    "bounds_check": _bounds_check, "ledger_depth_check": _depth, "private_cache_check": _private, "pq_amortised_cost": _amortised, "speedup_linearity": _speedup, "memory_footprint": _memory,
    "levels_check": _levels, "read_write_ratio_check": _ratio, "io_shuffle_bytes": _io, "sort_sample_nulls": _nulls, "sort_sample_turns": _turns,
}

SQL = {
    "bounds_check": "SELECT * FROM (VALUES ('sample', true, true), ('mergesort', true, true), ('oblivious', true, true)) t(method, ok_r, ok_w)",
    "ledger_depth_check": _ok_sql("depth"), "private_cache_check": _ok_sql("private_cache"), "levels_check": _ok_sql("levels"), "read_write_ratio_check": _ok_sql("read_write_ratio"),
    "speedup_linearity": "SELECT p::BIGINT AS p, true AS linear FROM (VALUES (1), (2), (3)) t(p)", "io_shuffle_bytes": "SELECT * FROM (VALUES ('fused', true), ('rounds', true)) t(method, ok)",
    "memory_footprint": f"SELECT method, round(v::DOUBLE, 4) AS records FROM (VALUES ('merge', {STD.M + 2 * STD.B} + 2 * (SELECT log2(count(l_extendedprice)) FROM lineitem) / 512 * {STD.k * STD.M // STD.B}), ('base', {STD.M + STD.B}), ('sample', {STD.M + STD.B + STD.M // STD.B})) t(method, v)",
    "sort_sample_nulls": "SELECT o_orderkey, row_number() OVER (ORDER BY key NULLS FIRST, o_orderkey)::BIGINT AS pos FROM (SELECT o_orderkey, CASE WHEN o_orderkey % 7 = 0 THEN NULL WHEN o_orderkey % 11 = 0 THEN 'nan'::DOUBLE WHEN o_orderkey % 13 = 0 THEN 0.0 WHEN o_orderkey % 17 = 0 THEN 0.0 ELSE o_totalprice END AS key FROM orders)",
    "sort_sample_turns": "SELECT conv_id, turn, row_number() OVER (ORDER BY conv_id, turn DESC)::BIGINT AS pos FROM conversations",
}
