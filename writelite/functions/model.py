"""Machine parameters, ledgers and costs of a memory whose writes cost omega reads."""

from __future__ import annotations

from dataclasses import dataclass, replace

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: A ledger has one row for each method, phase, level of recursion, node and round; reads and writes count blocks.
LEDGER = T.StructType(
    [
        T.StructField("method", T.StringType()), T.StructField("phase", T.StringType()), T.StructField("level", T.IntegerType()),
        T.StructField("node", T.LongType()), T.StructField("rnd", T.LongType()), T.StructField("reads", T.LongType()), T.StructField("writes", T.LongType()),
    ]
)
ARROW_LEDGER = pa.schema([("method", pa.string()), ("phase", pa.string()), ("level", pa.int32()), ("node", pa.int64()), ("rnd", pa.int64()), ("reads", pa.int64()), ("writes", pa.int64())])


def ledger_table(rows: list[tuple]) -> pa.Table:
    """Ledger rows as what a group function returns."""
    return pa.table([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True) if rows else [[]] * 7, ARROW_LEDGER, strict=True)], schema=ARROW_LEDGER)


@dataclass(frozen=True)
class MachineParams:
    """M and B in records, omega the cost of a write, k the extra branching, p processors, depth D."""

    M: int = 256
    B: int = 16
    omega: int = 8
    k: int = 1
    p: int = 1
    D: int = 1

    def __post_init__(self) -> None:
        if self.M < 1 or self.B < 1 or self.B > self.M:
            raise ValueError("a block has at least one record and fits in memory")
        if self.omega < 1 or not 1 <= self.k <= self.omega:
            raise ValueError("omega is at least 1 and k lies between 1 and omega")

    @property
    def fan_out(self) -> int:
        return max(2, self.k * self.M // self.B)

    def with_k(self, k: int) -> MachineParams:
        return replace(self, k=k)


TINY, STD, WIDE = MachineParams(64, 8, 8, 4), MachineParams(256, 16, 8, 4), MachineParams(1024, 32, 16, 2)

#: Quoted device figures as (device, read, write, unit, kind).
DEVICES = [
    ("spin_torque_cell_time", 0.14, 10.0, "ns", "time"),
    ("spin_torque_cell_energy", 1e-15, 1e-12, "J", "energy"),
    ("resistive_8mb_chip_time", 1.7, 200.0, "ns", "time"),
    ("resistive_8mb_chip_energy", 0.2, 25.0, "nJ", "energy"),
    ("phase_change_4kb_time", 6.7, 128.0, "us", "time"),
    ("phase_change_sector_time", 1.0, 15.0, "relative", "time"),
    ("phase_change_byte_time", 16.0, 416.0, "ns", "time"),
    ("phase_change_cache_time", 1.0, 40.0, "relative", "time"),
    ("phase_change_cache_energy", 1.0, 17.0, "relative", "energy"),
]


def device_presets(spark: SparkSession) -> DataFrame:
    """Devices with omega, the whole ratio of a write to a read."""
    table = spark.createDataFrame(DEVICES, "device string, read double, write double, unit string, kind string")
    return table.withColumn("omega", F.round(F.col("write") / F.col("read")).cast("long"))


def cost(omega: int | Column) -> Column:
    return (F.col("reads") + F.col("writes") * omega).cast("long")


def ledger_cost(ledger: DataFrame, omega: int, *by: str) -> DataFrame:
    """Reads, writes and cost of a ledger, by any of its columns."""
    total = ledger.groupBy(*by).agg(F.sum("reads").cast("long").alias("reads"), F.sum("writes").cast("long").alias("writes"))
    return total.withColumn("cost", cost(omega))


def depth(ledger: DataFrame, omega: int) -> int:
    """Longest chain of a level-synchronous run: the dearest node of every (level, phase), one after another."""
    per = ledger.groupBy("level", "phase", "node").agg(F.sum(cost(omega)).alias("c")).groupBy("level", "phase").agg(F.max("c").alias("c"))
    return int(per.agg(F.coalesce(F.sum("c"), F.lit(0))).first()[0])


def private_cache_time(ledger: DataFrame, omega: int, processor: str = "node") -> int:
    """The dearest processor's cost where each has a cache of its own."""
    return int(ledger.groupBy(processor).agg(F.sum(cost(omega)).alias("c")).agg(F.coalesce(F.max("c"), F.lit(0))).first()[0])
