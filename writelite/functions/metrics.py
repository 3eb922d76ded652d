"""What Spark itself read, shuffled and spilled for an action, and ledgers held against bounds."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from writelite.functions import model


def io_of(spark: SparkSession, action: Callable[[], object]) -> dict[str, int]:
    """Bytes of the stages that an action runs, from the session's own status store."""
    group, sc = f"io-{uuid.uuid4().hex}", spark.sparkContext
    sc.setJobGroup(group, "measured")
    try:
        action()
    finally:
        sc.setLocalProperty("spark.jobGroup.id", None)
    sc._jsc.sc().listenerBus().waitUntilEmpty(30_000)
    tracker, store = sc.statusTracker(), sc._jsc.sc().statusStore()
    stages = {s for j in tracker.getJobIdsForGroup(group) if (info := tracker.getJobInfo(j)) for s in info.stageIds}
    out = dict.fromkeys(("input", "shuffle_write", "shuffle_read", "spill", "records"), 0)
    for s in stages:
        try:
            d = store.lastStageAttempt(s)
        except Exception:  # noqa: BLE001  a stage that was skipped has no attempt
            continue
        out["input"] += d.inputBytes()
        out["shuffle_write"] += d.shuffleWriteBytes()
        out["shuffle_read"] += d.shuffleReadBytes()
        out["spill"] += d.diskBytesSpilled()
        out["records"] += d.shuffleWriteRecords()
    return out


def event_log_io(spark: SparkSession, path: str) -> DataFrame:
    """(stage, input, shuffle_write, spill) of a finished application, from its event log, read as JSON."""
    schema = "Event string, `Stage ID` long, `Task Metrics` struct<`Disk Bytes Spilled`: long, `Input Metrics`: struct<`Bytes Read`: long>, `Shuffle Write Metrics`: struct<`Shuffle Bytes Written`: long>>"
    m = F.col("Task Metrics")
    ends = spark.read.schema(schema).json(path).where("Event = 'SparkListenerTaskEnd'")
    return ends.groupBy(F.col("Stage ID").alias("stage")).agg(F.sum(m["Input Metrics"]["Bytes Read"]).alias("input"), F.sum(m["Shuffle Write Metrics"]["Shuffle Bytes Written"]).alias("shuffle_write"), F.sum(m["Disk Bytes Spilled"]).alias("spill"))


def check(ledger: DataFrame, bound_reads: float, bound_writes: float) -> DataFrame:
    """(method, reads, writes, bound_r, bound_w, ratio_r, ratio_w, ok_r, ok_w) of a ledger."""
    total = model.ledger_cost(ledger, 1, "method")
    return total.select(
        "method", "reads", "writes", F.lit(float(bound_reads)).alias("bound_r"), F.lit(float(bound_writes)).alias("bound_w"),
        (F.col("reads") / bound_reads).alias("ratio_r"), (F.col("writes") / bound_writes).alias("ratio_w"),
        (F.col("reads") <= bound_reads).alias("ok_r"), (F.col("writes") <= bound_writes).alias("ok_w"),
    )
