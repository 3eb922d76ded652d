"""Choice of the extra branching k, and the same as Spark expressions over a table of settings."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from writelite.functions import bounds
from writelite.functions.model import MachineParams


def choose_k(n: int, mp: MachineParams) -> int:
    """The cheapest k for a mergesort of n records: for each number of levels the least k that needs no more of them.

    >>> choose_k(60_000, MachineParams(64, 8, 8)), choose_k(60_000, MachineParams(256, 16, 4))
    (3, 1)
    """
    nb, best = bounds.blocks(n, mp.B), (bounds.classic_cost(n, mp), 1)
    for t in range(1, bounds.levels(n, mp.with_k(1)) + 1):
        low, high = 1, mp.omega
        while low < high:
            mid = (low + high) // 2
            low, high = (low, mid) if max(2, mid * mp.M // mp.B) ** t >= nb else (mid + 1, high)
        if low > 1:
            best = min(best, (bounds.mergesort_cost(n, mp.with_k(low)), low))
    return best[1]


def fan_out(n: int, mp: MachineParams) -> int:
    """Buckets of a distribution step: kM/B, or just enough for small inputs."""
    if n * mp.B <= (mp.k * mp.M) ** 2:
        return min(mp.fan_out, max(2, -(-n // (mp.k * mp.M))))
    return mp.fan_out


def k_condition(k: int, mp: MachineParams) -> bool:
    """Whether k / log k < (omega + 1) / log(M/B), ceilings ignored; false at k = 1."""
    import math

    return k > 1 and k / math.log(k) < (mp.omega + 1) / math.log(mp.M / mp.B)


def level_column(nb: Column, fan: Column) -> Column:
    """lev as an expression: the least of 1..63 whose power of the fan-out reaches the blocks."""
    return F.filter(F.sequence(F.lit(1), F.lit(63)), lambda t: F.pow(fan.cast("double"), t.cast("double")) >= nb.cast("double"))[0].cast("long")


def k_table(spark: SparkSession, sizes: DataFrame, settings: list[tuple[int, int, int]]) -> DataFrame:
    """One row for each n of `sizes`, (M, B, omega) of `settings` and k of 1..omega: levels, cost, and whether it is best."""
    from pyspark.sql import Window as W

    grid = spark.createDataFrame(settings, "M long, B long, omega long").select("*", F.explode(F.sequence(F.lit(1).cast("long"), "omega")).alias("k"))
    rows = sizes.crossJoin(F.broadcast(grid))
    nb = F.ceil(F.col("n") / F.col("B"))
    lev = level_column(nb, F.greatest(F.lit(2), F.floor(F.col("k") * F.col("M") / F.col("B"))))
    rows = rows.withColumn("levels", lev).withColumn("cost", (F.when(F.col("k") == 1, F.col("omega") + 1).otherwise(F.col("omega") + F.col("k") + 1) * nb * F.col("levels")).cast("long"))
    best = F.row_number().over(W.partitionBy("n", "M", "B", "omega").orderBy("cost", "k")) == 1
    return rows.withColumn("best", best).select("n", "M", "B", "omega", "k", "levels", "cost", "best")
