"""Splitters, bucket location, counts, offsets and placement: the parts that distribution sorts are made of."""

from __future__ import annotations

import math
from collections.abc import Callable, Sequence

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from writelite.operators.keys import SortKey, array_literal, coin_limit, coin_of, fields, order_by

#: Sampled keys that go to the driver at once, and so splitters in a plan.
MOST_SPLITTERS = 100_000
#: Rows of a table of running totals that one task orders at most.
CELL = 4096


def _ends(splitters: Sequence[tuple], upto: int) -> list[int]:
    """For each splitter, the end of the run of splitters that are like it in their first `upto` fields; NaN is like NaN."""
    alike = [tuple("NaN" if x != x else x for x in s[:upto]) for s in splitters]
    out, end = [0] * len(alike), len(alike)
    for i in reversed(range(len(alike))):
        if i + 1 < len(alike) and alike[i] != alike[i + 1]:
            end = i + 1
        out[i] = end
    return out


def locate(df: DataFrame, keys: list[str | SortKey], splitters: Sequence[tuple], out: str = "node") -> DataFrame:
    """df with its bucket: how many splitters are at most the row's key.

    splitters are tuples of the fields of `keys`, in order. They are searched field by field: the range of splitters that
    are like the row so far is halved by looking into one constant array, then cut to those that are like it in this
    field too. A field is halved as often as its longest run needs, once where the fields before it tell splitters apart.
    Each step is one small projection and all stay inside one compiled stage, short enough for the JVM to compile: it
    interprets methods of more than 8000 bytes of code for ever.

    The last step is tied to the partition's number, else a filter on the bucket would be pushed down through all steps
    and multiply at each of them. For the same reason (the optimiser looks for a join key's origin) the bucket is for
    windows, groups and exchanges; cut the lineage before a join on it.
    """
    n = len(splitters)
    if not n:
        return df.withColumn(out, F.lit(0))
    more, steps, low, high, ends = [], [], "0", str(n), [n] * n
    for i, (c, kind, flag) in enumerate(fields(df, keys)):
        values, own, array = [s[i] for s in splitters], f"__f{i}", f"__a{i}"
        more.append(c.alias(own))
        if flag and len(set(values)) == 1:  # a row of the other flag is before or after the whole range
            moved = f"CASE WHEN {own} THEN {high} ELSE {low} END AS __x{i}"
            steps.append(moved)
            low, high = (low, f"__x{i}") if values[0] else (f"__x{i}", high)
            continue
        longest = max(end - at for at, end in enumerate(ends))
        more.append(array_literal(values, kind).alias(array))
        for b in reversed(range(longest.bit_length())):
            ahead, new = f"{low} + {(1 << b) - 1}", f"__l{i}_{b}"
            steps.append(f"CASE WHEN {ahead} < {high} AND get({array}, {ahead}) < {own} THEN {low} + {1 << b} ELSE {low} END AS {new}")
            low = new
        ends = _ends(splitters, i + 1)
        after = f"{low} + 1"
        if any(end != at + 1 for at, end in enumerate(ends)):
            more.append(array_literal(ends, "int").alias(f"__e{i}"))
            after = f"get(__e{i}, {low})"
        steps.append(f"CASE WHEN {low} < {high} AND get({array}, {low}) = {own} THEN {after} ELSE {low} END AS __h{i}")
        high = f"__h{i}"
    found = df.select("*", *more).selectExpr("*", *steps)
    return found.select(*[F.col(f"`{c}`") for c in df.columns if c != out], (F.col(high) + F.spark_partition_id() * 0).alias(out))


def locate_join(df: DataFrame, key: str, splitters: DataFrame) -> DataFrame:
    """Bucket by a join with ranges: splitters has the columns (lo, hi, bucket), lo null for the first and hi for the last.

    The table of ranges is small (at most MOST_SPLITTERS) and is broadcast; more ranges than that are for `locate`.
    """
    if (n := splitters.count()) > MOST_SPLITTERS:
        raise ValueError(f"{n} ranges are more than a range join takes")
    s = F.broadcast(splitters)
    return df.join(s, (s["lo"].isNull() | (df[key] >= s["lo"])) & (s["hi"].isNull() | (df[key] < s["hi"]))).drop("lo", "hi")


def locate_arrow(column: str, splitters: Sequence[float]) -> Column:
    """Bucket of one numeric column by binary search over Arrow batches, for splitter counts that no expression holds."""
    import numpy as np

    cut = np.asarray(splitters)

    @F.pandas_udf("long")
    def find(values: pd.Series) -> pd.Series:
        return pd.Series(np.searchsorted(cut, values.to_numpy(), side="right"))

    return find(F.col(column))


def sample_rate(n: int, wanted: int) -> float:
    return 1.0 if n <= wanted else wanted / n


def evenly(sample: list, count: int) -> list:
    """`count` evenly spaced members of a sorted list, without repeats.

    >>> evenly(list(range(10)), 3)
    [2, 5, 7]
    """
    picked = [sample[(i + 1) * len(sample) // (count + 1)] for i in range(count)] if sample else []
    return [x for i, x in enumerate(picked) if i == 0 or x != picked[i - 1]]


def collected(sample: DataFrame, keys: list[str | SortKey], *more: str) -> list[tuple]:
    """The fields of a bounded sample, in order, on the driver: (more..., fields...)."""
    few = sample.repartition(1).sortWithinPartitions(*order_by(sample, keys))
    got = few.select(*more, *[c.alias(f"__f{i}") for i, (c, _, _) in enumerate(fields(sample, keys))]).toArrow()
    return list(zip(*[c.to_pylist() for c in got.columns], strict=True))


def picked(sample: DataFrame, keys: list[str | SortKey], by: str, count: Callable[[Column], Column]) -> dict[int, list[tuple]]:
    """`evenly` of every group of a bounded sample, of whose m rows count(m) are picked: ranked where the sample is put in
    order, so no more than the picks go to the driver."""
    whole = W.partitionBy(by)
    rank = F.row_number().over(whole.orderBy(*order_by(sample, keys))) - 1
    ranked = sample.repartition(1).withColumn("__m", F.count(F.lit(1)).over(whole)).withColumn("__rank", rank.cast("long"))
    # The least i of those whose pick i * m / (count + 1) can be this row.
    ith = ranked.withColumn("__few", count(F.col("__m")).cast("long")).withColumn("__i", F.expr("greatest(1L, (__rank * (__few + 1) + __m - 1) DIV __m)"))
    out: dict[int, list[tuple]] = {}
    for r in collected(ith.where("__i <= __few AND (__i * __m) DIV (__few + 1) = __rank"), keys, by):
        own = out.setdefault(r[0], [])
        if not own or own[-1] != r[1:]:
            own.append(r[1:])
    return out


def splitters(df: DataFrame, keys: list[str | SortKey], coin: list[str], n: int, fan: int, over: float = 4.0, seed: int = 42) -> list[tuple]:
    """At most fan - 1 splitters from a sample of about over * fan * log n keys, or of MOST_SPLITTERS if that is less."""
    wanted = min(math.ceil(over * fan * max(math.log2(max(n, 2)), 1)), int(0.9 * MOST_SPLITTERS))
    if fan > wanted:
        raise ValueError(f"{fan} buckets are more than one sample of {wanted} keys cuts evenly; use more levels of less fan-out")
    return evenly(collected(df.where(coin_of(coin, coin_limit(sample_rate(n, wanted)), seed)), keys), fan - 1)


def node_splitters(df: DataFrame, keys: list[str | SortKey], coin: list[str], cuts: list[tuple], fans: dict[int, tuple[int, int]], over: float, seed: int) -> dict[int, list[tuple]]:
    """Splitters of several nodes of a level, from one pass of samples: fans has (rows, wanted buckets) of each node.

    Every node is sampled at a rate of its own. Where all samples together are more than the driver takes, the nodes go
    in several passes.
    """
    out: dict[int, list[tuple]] = {}
    left = list(fans.items())
    while left:
        now, total = {}, 0
        while left:
            v, (n, fan) = left[0]
            wanted = min(math.ceil(over * fan * max(math.log2(max(n, 2)), 1)), int(0.9 * MOST_SPLITTERS))
            if now and total + wanted > MOST_SPLITTERS:
                break
            now[v], total = (sample_rate(n, wanted), fan), total + wanted
            left.pop(0)
        limits = array_literal([coin_limit(now[v][0]) if v in now else 0 for v in range(len(cuts) + 1)], "bigint")
        drawn = locate(df, keys, cuts, "__node").where(coin_of(coin, F.get(limits, F.col("__node")), seed))
        few = array_literal([now[v][1] - 1 if v in now else 0 for v in range(len(cuts) + 1)], "bigint")
        found = picked(drawn, keys, "__node", lambda m, few=few: F.get(few, F.col("__node")))
        out |= {v: found.get(v, []) for v in now}
    return out


def merged(cuts: list[tuple], inner: dict[int, list[tuple]]) -> tuple[list[tuple], list[int]]:
    """(all cuts in order, first new bucket of every old one) when the buckets `inner` are cut further."""
    out, first = [], []
    for v in range(len(cuts) + 1):
        first.append(len(out))
        out += inner.get(v, [])
        if v < len(cuts):
            out.append(cuts[v])
    return out, first


def sizes_of(df: DataFrame, keys: list[str | SortKey], cuts: list[tuple]) -> list[int]:
    """Rows of every bucket between cuts: one scan of the key columns and counts before anything is exchanged."""
    found = {r["__node"]: r["cnt"] for r in counts(locate(df, keys, cuts, "__node"), "__node").collect()}
    return [found.get(v, 0) for v in range(len(cuts) + 1)]


def packed(sizes: Sequence[int], parts: int) -> tuple[list[int], list[int]]:
    """Consecutive buckets as at most `parts` partitions of about equal rows: (first bucket, rows before) of each.

    >>> packed([5, 1, 1, 1, 4], 3)
    ([0, 1, 4], [0, 5, 8])
    """
    total, first, before, at = sum(sizes), [0], [0], 0
    for v, n in enumerate(sizes):
        if at > before[-1] and len(first) < parts and at * parts >= len(first) * total:
            first.append(v)
            before.append(at)
        at += n
    return first, before


def positioned(df: DataFrame, keys: list[str | SortKey], cuts: list[tuple], sizes: Sequence[int], parts: int, more: Sequence[Column] = ()) -> DataFrame:
    """Rows in order with pos, by one exchange: whole buckets go to numbered partitions and are sorted there.

    The partition of a row is known beforehand, so its position is the rows of the partitions before it plus its place
    in its own: nothing is ranked by a window, joined or collected. `more` sorts before the keys inside a partition.
    """
    first, before = packed(sizes, parts)
    dealt = locate(df, keys, [cuts[b - 1] for b in first[1:]], "__part").repartitionById(len(first), F.col("__part"))
    ordered = dealt.sortWithinPartitions(*more, *order_by(df, keys))
    place = F.get(array_literal(before, "bigint"), F.spark_partition_id()) + F.monotonically_increasing_id().bitwiseAND(F.lit(2**33 - 1)) + 1
    return ordered.withColumn("pos", place.cast("long")).drop("__part")


def placed(df: DataFrame, keys: list[str | SortKey], cuts: list[tuple], parts: int) -> DataFrame:
    """`positioned` by as many of the cuts as the partitions need to come out even; their buckets are counted first."""
    few = evenly(cuts, 4 * parts - 1) if len(cuts) >= 4 * parts else cuts
    names = [k.lstrip("-") if isinstance(k, str) else k.name for k in keys]
    return positioned(df, keys, few, sizes_of(df.select(*dict.fromkeys(names)), keys, few), parts)


def ranked_splitters(thin: DataFrame, keys: list[str | SortKey], coin: list[str], count: int) -> list[tuple]:
    """`count` evenly spaced keys of a sample of any size: ranked where it lies when it is too large for the driver."""
    n = thin.count()
    if n <= MOST_SPLITTERS:
        return evenly(collected(thin, keys), count)
    parts = int(thin.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    cuts = splitters(thin, keys, coin, n, 4 * parts)
    wanted = sorted({(i + 1) * n // (count + 1) + 1 for i in range(count)})
    at = placed(thin, keys, cuts, parts)
    return collected(at.where(F.array_contains(array_literal(wanted, "bigint"), F.col("pos"))), keys)


def thinned(df: DataFrame, keys: list[str | SortKey], group: Column, step: Column | int, *by: str) -> DataFrame:
    """Every step-th row of each ordered group: what a deterministic sample takes."""
    w = W.partitionBy(*by, "__group").orderBy(*order_by(df, keys))
    return df.withColumn("__group", group).withColumn("__i", F.row_number().over(w)).where(F.col("__i") % step == 0).drop("__group", "__i")


def deterministic_split(df: DataFrame, keys: list[str | SortKey], m: int | None = None) -> tuple[DataFrame, int]:
    """(rows with bucket, number of buckets): about m^(1/3) buckets without chance.

    Rows are cut into groups of m^(1/3), each group is ordered, every log m-th row of it is sampled, and m^(1/3) - 1
    evenly spaced sampled keys split the rows. No bucket has more than m^(2/3) (log m + 1) rows.
    """
    m = m if m is not None else df.count()
    third, log = max(2, round(m ** (1 / 3))), max(1, int(math.log2(max(m, 2))))
    coin = [k.lstrip("-") if isinstance(k, str) else k.name for k in keys]
    thin = thinned(df, keys, F.pmod(F.xxhash64(*coin), F.lit(max(1, m // third))), log)
    cut = ranked_splitters(thin, keys, coin, third - 1)
    return locate(df, keys, cut, "bucket").withColumn("bucket", F.col("bucket").cast("long")), len(cut) + 1


def split_nodes(df: DataFrame, keys: list[str | SortKey], top: str, node: str = "node", base: int = 4096) -> DataFrame:
    """The same split of every node at once, where the nodes lie: node becomes node * base + its part.

    df is dealt out by `top`, of which each node is a part, so every window works inside its partition and nothing is
    exchanged. A sampled row is a splitter if its rank in its node's sample is evenly spaced; parts are running counts
    of splitters in key order, so no list of them is ever built.
    """
    whole = W.partitionBy(top, node)
    ordered = whole.orderBy(*order_by(df, keys)).rowsBetween(W.unboundedPreceding, 0)
    names = [k.lstrip("-") if isinstance(k, str) else k.name for k in keys]
    m = F.col("__m").cast("double")
    frame = df.withColumn("__m", F.count(F.lit(1)).over(whole)).withColumn("__third", F.greatest(F.lit(1), F.round(F.pow(m, F.lit(1 / 3)))).cast("long"))
    frame = frame.withColumn("__group", F.pmod(F.xxhash64(*names), F.greatest(F.lit(1), F.floor(F.col("__m") / F.col("__third")))))
    nth = F.row_number().over(W.partitionBy(top, node, "__group").orderBy(*order_by(df, keys)))
    frame = frame.withColumn("__drawn", (nth % F.greatest(F.lit(1), F.floor(F.log2(m))) == 0).cast("int"))
    frame = frame.withColumn("__rank", F.sum("__drawn").over(ordered) - 1).withColumn("__s", F.sum("__drawn").over(whole))
    j = F.ceil(F.col("__rank") * F.col("__third") / F.greatest(F.col("__s"), F.lit(1)))
    even = (F.col("__drawn") == 1) & j.between(1, F.col("__third") - 1) & (F.floor(j * F.col("__s") / F.col("__third")) == F.col("__rank"))
    frame = frame.withColumn("__cut", F.coalesce(even, F.lit(False)).cast("int"))
    part = F.least(F.sum("__cut").over(ordered), F.lit(base - 1))
    return frame.withColumn(node, (F.col(node) * base + part).cast("long")).select(*df.columns)


def counts(df: DataFrame, *by: str) -> DataFrame:
    return df.groupBy(*by).agg(F.count(F.lit(1)).alias("cnt"))


def running(sizes: DataFrame, cell: str, size: str, out: str = "before") -> DataFrame:
    """Totals before each row of a table with one row for each whole number `cell`, in its order.

    In two levels: blocks of CELL cells are summed, their totals run through one task, and each block runs by itself.
    """
    blocks = sizes.withColumn("__block", F.floor(F.col(cell) / CELL))
    tops = blocks.groupBy("__block").agg(F.sum(size).alias("__s"))
    tops = tops.select("__block", F.coalesce(F.sum("__s").over(W.orderBy("__block").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("__top"))
    inner = F.coalesce(F.sum(size).over(W.partitionBy("__block").orderBy(cell).rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    return blocks.withColumn("__in", inner).join(tops, "__block").withColumn(out, (F.col("__in") + F.col("__top")).cast("long")).drop("__block", "__in", "__top")


def offsets(sizes: DataFrame, outer: str, inner: str, size: str = "cnt") -> DataFrame:
    """Totals before each row of a table of (outer, inner) sizes in that order: running totals of the outer sums, then
    of the inner sizes of each outer value. outer is a whole number.
    """
    tops = running(sizes.groupBy(outer).agg(F.sum(size).alias("__n")), outer, "__n", "__start").select(outer, "__start")
    before = F.coalesce(F.sum(size).over(W.partitionBy(outer).orderBy(inner).rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    return sizes.withColumn("before", before).join(tops, outer).withColumn("before", (F.col("before") + F.col("__start")).cast("long")).drop("__start")


def integer_sort(df: DataFrame, column: str, within: list[str], partitions: int) -> DataFrame:
    """Stable grouping by a small integer: rows with pos, from counts, their prefix sums, and ranks inside each value."""
    place = running(counts(df, column), column, "cnt").select(column, "before")
    dealt = df.repartition(partitions, column)
    ranked = dealt.withColumn("nth", F.row_number().over(W.partitionBy(column).orderBy(*within)))
    return ranked.join(place, column).withColumn("pos", (F.col("before") + F.col("nth")).cast("long")).drop("before", "nth")


def place_random(df: DataFrame, cap: Column, ident: str, bucket: str = "bucket", seed: int = 42, most: int = 64, told: bool = False) -> tuple[DataFrame, list[int]]:
    """(rows with slot, rows left after each try): every row tries a random free slot of its bucket until it has one.

    One winner a slot and try, the least id; losers and rows whose slot was taken try again. `told` adds each row's tries.
    """
    spark = df.sparkSession
    from writelite.operators.prim import cut_lineage

    left = cut_lineage(df.select(bucket, ident, cap.cast("long").alias("cap")))
    taken, tries = None, []
    for t in range(most):
        left_n = left.count()
        if not left_n:
            break
        tries.append(left_n)
        drawn = left.withColumn("slot", F.pmod(F.xxhash64(ident, F.lit(seed), F.lit(t)), F.col("cap")))
        free = drawn if taken is None else drawn.join(taken.select(bucket, "slot"), [bucket, "slot"], "left_anti")
        won = free.groupBy(bucket, "slot").agg(F.min(ident).alias(ident)).withColumn("tries", F.lit(t + 1))
        taken = cut_lineage(won if taken is None else taken.unionByName(won))
        left = cut_lineage(left.join(taken.select(ident), ident, "left_anti"))
    else:
        raise RuntimeError("arrays are too full for random placement")
    if taken is None:
        taken = spark.createDataFrame([], df.select(bucket, ident).schema).withColumn("slot", F.lit(0).cast("long")).withColumn("tries", F.lit(0))
    return df.join(taken.select(ident, "slot", *["tries"] * told), ident), tries
