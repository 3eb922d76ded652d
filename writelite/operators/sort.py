"""Write-saving sorts on DataFrames.

Each returns a SortResult: rows with their global position, and a ledger of counted block reads and writes, each made
when it is asked for. Rows are placed by splitters, so the result does not depend on chance, only the ledger's bucket
sizes do. What a method writes less often, its result face writes once: the key columns are scanned for a sample and
for counts, then every row crosses the network one time, to the numbered partition that its bucket belongs to.
"""

from __future__ import annotations

import functools
import itertools
import math
from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from writelite.functions.model import LEDGER, MachineParams, ledger_table
from writelite.operators import bucketing
from writelite.operators.keys import SortKey, array_literal, coin_limit, coin_of, order_by, parse, total_order_key
from writelite.operators.prim import cut_lineage
from writelite.plans import planner

MOST_LEVELS = 12
#: Samples of a bucket for each factor of two in n.
OVER = 1.5
#: Rows of a node whose ledger one task carries out, as an array of hashes.
LOCAL = 500_000


@dataclass
class SortResult:
    placed: Callable[[], DataFrame] = field(repr=False)
    counted: Callable[[], DataFrame] = field(repr=False)

    @functools.cached_property
    def rows(self) -> DataFrame:
        return self.placed()

    @functools.cached_property
    def ledger(self) -> DataFrame:
        return self.counted()


def _partitions(df: DataFrame) -> int:
    return int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))


def _names(keys: list[str | SortKey]) -> list[str]:
    return [k.name for k in parse(keys)]


def _key_columns(df: DataFrame, keys: list[str | SortKey], coin: list[str]) -> DataFrame:
    return df.select(*dict.fromkeys([*_names(keys), *coin]))


def ledger_frame(df: DataFrame, rows: list[tuple]) -> DataFrame:
    return df.sparkSession.createDataFrame(rows, LEDGER)


def base_rows(method: str, level: int, sizes: dict[int, int], mp: MachineParams) -> list[tuple]:
    """Ledger of selection sorting nodes of given sizes: every round of M scans all blocks and writes its own."""
    out = []
    for v, n in sorted(sizes.items()):
        rounds, nb = -(-n // mp.M), -(-n // mp.B)
        out += [(method, "base", level, v, r, nb, -(-min(mp.M, n - r * mp.M) // mp.B)) for r in range(rounds)]
    return out


def selection_window(df: DataFrame, keys: list[str | SortKey], mp: MachineParams, by: str | None = None) -> SortResult:
    """Base-case sort: each round emits the M least keys above the last one emitted. rnd is the round of a row."""
    key = total_order_key(df, keys)
    w = W.partitionBy(by).orderBy("__key") if by else None
    frame = df.withColumn("__key", key)
    if by:
        rows = frame.withColumn("pos", F.row_number().over(w).cast("long"))
        sizes = {i: r["cnt"] for i, r in enumerate(bucketing.counts(df, by).orderBy(by).collect())}
    else:
        n = df.count()
        if n > mp.omega * mp.M:
            raise ValueError("the base case is for n of at most kM; sort larger tables by another method or give groups")
        rows, sizes = frame.withColumn("pos", F.row_number().over(W.orderBy("__key")).cast("long")), {0: n}
    rows = rows.withColumn("rnd", F.floor((F.col("pos") - 1) / mp.M).cast("long")).drop("__key")
    return SortResult(lambda: rows, lambda: ledger_frame(df, base_rows("selection", 0, sizes, mp)))


def selection_rounds(df: DataFrame, keys: list[str | SortKey], mp: MachineParams) -> SortResult:
    """The same, one scan a round: the driver keeps the last key emitted, a scan filters above it and takes M.

    A table of more than 4 kM rows is cut into nodes of that many; a round then takes M rows of every node at once.
    """
    n, last, parts, rnd = df.count(), None, [], 0
    if n > (width := mp.omega * mp.M * 4):
        return _selection_nodes(df, keys, mp, n, width)
    while rnd * mp.M < n:
        left = df
        if last is not None:  # above the last key: at most one row, the last one itself, sits on it
            left = bucketing.locate(df, keys, [last], "__above").where("__above = 1").drop("__above").orderBy(*order_by(df, keys)).offset(1)
        part = left.orderBy(*order_by(df, keys)).limit(mp.M)
        last = bucketing.collected(part, keys)[-1]
        ranked = part.withColumn("pos", (F.row_number().over(W.orderBy(*order_by(df, keys))) + rnd * mp.M).cast("long"))
        parts.append(ranked.withColumn("rnd", F.lit(rnd).cast("long")))
        rnd += 1
    rows = parts[0] if parts else df.withColumn("pos", F.lit(0).cast("long")).withColumn("rnd", F.lit(0).cast("long"))
    for p in parts[1:]:
        rows = rows.unionByName(p)
    return SortResult(lambda: rows, lambda: ledger_frame(df, base_rows("selection_rounds", 0, {0: n}, mp)))


def _selection_nodes(df: DataFrame, keys: list[str | SortKey], mp: MachineParams, n: int, width: int) -> SortResult:
    """`selection_rounds` of every node of `width` consecutive rows side by side: a scan a round, and a last key a node on the driver."""
    slots, names = _partitions(df), list(dict.fromkeys(_names(keys)))
    even = bucketing.splitters(df.select(*names), keys, names, n, 4 * slots)
    edges = bucketing.placed(df.select(*names), keys, even, slots).where((F.col("pos") > 1) & (F.col("pos") % width == 1))
    cuts, last, parts = bucketing.collected(edges, keys), {}, []
    sizes = [width] * len(cuts) + [n - width * len(cuts)]
    for rnd in range(width // mp.M):
        took = [min(mp.M, m - rnd * mp.M) for m in sizes]
        # Rows above a node's last key, which is the first of them itself.
        bounds, above = [], []
        for v in range(len(sizes)):
            bounds += cuts[v - 1 : v] if v else []
            above.append(v if v not in last else -1)
            if v in last:
                bounds.append(last[v])
                above.append(v)
        of = lambda values, at: F.get(array_literal(values, "bigint"), F.col(at).cast("int"))
        left = bucketing.locate(df, keys, bounds, "__at").withColumn("__node", of(above, "__at")).where("__node >= 0").drop("__at")
        nth = F.row_number().over(W.partitionBy("__node").orderBy(*order_by(df, keys))) - (1 if rnd else 0)
        part = left.withColumn("__nth", nth).where((F.col("__nth") >= 1) & (F.col("__nth") <= mp.M))
        ends = part.where(F.col("__nth") == of(took, "__node"))
        last |= {r[0]: r[1:] for r in bucketing.collected(ends, keys, "__node")}
        pos = F.col("__node") * width + rnd * mp.M + F.col("__nth")
        parts.append(part.withColumn("pos", pos.cast("long")).withColumn("rnd", F.floor((F.col("pos") - 1) / mp.M).cast("long")).drop("__node", "__nth"))
    rows = functools.reduce(DataFrame.unionByName, parts)
    return SortResult(lambda: rows, lambda: ledger_frame(df, base_rows("selection_rounds", 0, dict(enumerate(sizes)), mp)))


def _salted(hashed: np.ndarray, salt: int) -> np.ndarray:
    """32 bits of a hash of (hash, salt): one coin of every row for each level and purpose."""
    x = hashed + np.uint64((salt + 1) * 0x9E3779B97F4A7C15 % 2**64)
    x = (x ^ (x >> np.uint64(33))) * np.uint64(0xFF51AFD7ED558CCD)
    x = (x ^ (x >> np.uint64(33))) * np.uint64(0xC4CEB9FE1A85EC53)
    return (x ^ (x >> np.uint64(33))) >> np.uint64(32)


def _drawn(hashed: np.ndarray, wanted: int, salt: int) -> list[int]:
    """Places of a sample of about `wanted` of a node's rows, in order."""
    limit = np.uint64(coin_limit(bucketing.sample_rate(len(hashed), wanted)))
    return np.flatnonzero(_salted(hashed, salt) < limit).tolist()


def _every(group: np.ndarray, step: int) -> list[int]:
    """Places of every step-th row of each group, in order."""
    order = np.argsort(group, kind="stable")
    dealt = group[order]
    starts = np.flatnonzero(np.r_[True, dealt[1:] != dealt[:-1]]) if len(dealt) else np.zeros(0, int)
    nth = np.arange(len(dealt)) - np.repeat(starts, np.diff(np.r_[starts, len(dealt)])) + 1
    return np.sort(order[nth % step == 0]).tolist()


def _carried(frame: DataFrame, keys: list[str | SortKey], coin: list[str], cuts: list[tuple], walk: Callable[[int, np.ndarray], list[tuple]]) -> DataFrame:
    """Ledger rows of walk(bucket, hashes of its rows in key order) for each bucket between cuts, made where the buckets lie.

    What a level of distribution costs follows from the ranks of its splitters, so a node needs no keys once it is in
    order: splitters are places in the array of hashes, and sizes their differences.
    """

    def go(table: pa.Table) -> pa.Table:
        order = np.argsort(table.column("__rank").to_numpy(), kind="stable")
        hashed = table.column("__hash").to_numpy()[order].view(np.uint64)
        return ledger_table(walk(table.column("__node")[0].as_py(), hashed))

    rank = F.row_number().over(W.partitionBy("__node").orderBy(*order_by(frame, keys)))
    placed = bucketing.locate(frame, keys, cuts, "__node").select("__node", rank.alias("__rank"), F.xxhash64(*coin).alias("__hash"))
    return placed.groupBy("__node").applyInArrow(go, LEDGER)


def _sample_ledger(df: DataFrame, keys: list[str | SortKey], coin: list[str], n: int, mp: MachineParams, seed: int, over: float, choose: str) -> DataFrame:
    """What each level of the sample sort reads and writes. Nodes of more than LOCAL rows are cut from the driver, level by
    level, with a pass that samples them and one that counts their buckets; what lies below is carried out by one task a
    node. A ledger's node is the place of its first row in the sorted table; a base case has the level that it is reached at.
    """
    frame, cuts, nodes, rows = _key_columns(df, keys, coin), [], [(n, 0)], []
    for level in range(MOST_LEVELS + 1):
        big = {v: m for v, (m, _) in enumerate(nodes) if m > max(LOCAL, mp.k * mp.M)}
        if not big:
            break
        if level == MOST_LEVELS:
            raise RuntimeError("buckets do not shrink; are the keys unique?")
        if choose == "deterministic":
            inner = _deterministic_cuts(frame, keys, coin, cuts, big, mp)
        elif level == 0:
            inner = {0: bucketing.splitters(frame, keys, coin, n, planner.fan_out(n, mp), over, seed)}
        else:
            inner = bucketing.node_splitters(frame, keys, coin, cuts, {v: (m, planner.fan_out(m, mp)) for v, m in big.items()}, over, seed + level)
        cuts, first = bucketing.merged(cuts, inner)
        sizes = bucketing.sizes_of(frame, keys, cuts)
        before, now = _running(sizes), []
        for v, (m, born) in enumerate(nodes):
            own = sizes[first[v] : first[v + 1] if v + 1 < len(first) else len(sizes)]
            if v in big:
                rows += _distribute_rows("sample", level, before[first[v]], m, own, mp)
            now += [(c, level + 1 if v in big else born) for c in own]
        nodes = now
    before = _running([m for m, _ in nodes])

    def walk(v: int, hashed: np.ndarray) -> list[tuple]:
        out, left = [], [(0, len(hashed), nodes[v][1])]
        while left:
            lo, hi, level = left.pop()
            m, node = hi - lo, before[v] + lo
            if m <= mp.k * mp.M:
                out += base_rows("sample", level, {node: m}, mp)
                continue
            if level == MOST_LEVELS:
                raise RuntimeError("buckets do not shrink; are the keys unique?")
            fan = planner.fan_out(m, mp)
            if choose == "deterministic":
                step = max(1, int(math.log2(m)))
                sample = _every(hashed[lo:hi] % np.uint64(max(1, m // max(2, mp.M, 8 * step))), step)
            else:
                sample = _drawn(hashed[lo:hi], math.ceil(over * fan * max(math.log2(m), 1)), seed + level)
            edges = [lo, *(lo + at for at in bucketing.evenly(sample, fan - 1)), hi]
            parts = list(itertools.pairwise(edges))
            out += _distribute_rows("sample", level, node, m, [b - a for a, b in parts], mp)
            left += [(a, b, level + 1) for a, b in parts if b > a]
        return out

    return ledger_frame(df, rows).unionByName(_carried(frame, keys, coin, cuts, walk))


def _deterministic_cuts(frame: DataFrame, keys: list[str | SortKey], coin: list[str], cuts: list[tuple], big: dict[int, int], mp: MachineParams) -> dict[int, list[tuple]]:
    """Splitters without chance: every log n-th key of the sorted chunks of M keys, of which evenly spaced ones are kept."""
    out = {}
    for v, n in big.items():
        rows = bucketing.locate(frame, keys, cuts, "__node").where(F.col("__node") == v).drop("__node")
        step = max(1, int(math.log2(n)))
        thin = bucketing.thinned(rows, keys, F.pmod(F.xxhash64(*coin), F.lit(max(1, n // max(2, mp.M, 8 * step)))), step)
        out[v] = bucketing.ranked_splitters(thin, keys, coin, planner.fan_out(n, mp) - 1)
    return out


def _distribute_rows(method: str, level: int, node: int, m: int, own: list[int], mp: MachineParams) -> list[tuple]:
    """Ledger of dealing a node of m rows out to buckets of the sizes `own`: it is scanned once a round of M/B buckets."""
    per = max(1, mp.M // mp.B)
    return [(method, "distribute", level, node, r, -(-m // mp.B), sum(-(-c // mp.B) for c in own[r * per : (r + 1) * per])) for r in range(-(-len(own) // per))]


def em_sample(df: DataFrame, keys: list[str | SortKey], coin: list[str], mp: MachineParams, seed: int = 42, how: str = "fused", over: float = OVER, choose: str = "random") -> SortResult:
    """External write-saving sample sort.

    Each level picks up to kM/B - 1 splitters a node and deals the node out in k rounds of M/B buckets, every round a
    scan of the whole node; nodes of at most kM are sorted by selection. keys must be unique together; coin names the
    columns that the sample's coin hashes.

    The result face carries out the first level, with as many buckets as the cluster has partitions to fill: a task's
    memory is the machine's M there, so what is left of a bucket is sorted where it lies. how='rounds' runs the scans of
    the level as filters on the source, each with its own key range for the reader to prune by; 'fused' is one scan.
    """
    n = df.count()

    def place() -> DataFrame:
        slots = _partitions(df)
        frame, cuts = _key_columns(df, keys, coin), []
        if n > mp.k * mp.M and choose == "deterministic":
            cuts = _deterministic_cuts(frame, keys, coin, [], {0: n}, mp)[0]
        elif n > mp.k * mp.M:
            cuts = bucketing.splitters(frame, keys, coin, n, max(planner.fan_out(n, mp), min(4 * slots, n // mp.M)), over, seed)
        if how == "rounds" and cuts:
            few = bucketing.evenly(cuts, 4 * slots - 1) if len(cuts) >= 4 * slots else cuts
            return bucketing.positioned(_rounds(df, keys, cuts, mp), keys, few, bucketing.sizes_of(frame, keys, few), slots)
        return bucketing.placed(df, keys, cuts, slots)

    return SortResult(place, lambda: _sample_ledger(df, keys, coin, n, mp, seed, over, choose))


def _rounds(df: DataFrame, keys: list[str | SortKey], cuts: list[tuple], mp: MachineParams) -> DataFrame:
    """The frame as a union of k filtered scans, each of an equal share of the buckets, pruned by the first key's range."""
    per = -(-(len(cuts) + 1) // mp.k)
    edges = [cuts[i] for i in range(per - 1, len(cuts), per)]
    parts, lead = [], parse(keys)[0]
    for r, (lo, hi) in enumerate(zip([None, *edges], [*edges, None], strict=True)):
        part = df
        plain = not lead.desc and dict(df.dtypes)[lead.name] in ("int", "bigint", "double", "string")
        if lo is not None and plain and lo[0] is True:
            part = part.where(F.col(lead.name) >= lo[1])
        if hi is not None and plain and hi[0] is True and lead.nulls_first:
            part = part.where((F.col(lead.name) <= hi[1]) | F.col(lead.name).isNull())
        part = bucketing.locate(part, keys, edges, "__round").where(F.col("__round") == r).drop("__round")
        parts.append(part)
    return functools.reduce(DataFrame.unionByName, parts)


def _parallel_plan(df: DataFrame, keys: list[str | SortKey], coin: list[str], n: int, mp: MachineParams, seed: int) -> tuple[list[tuple], list[tuple], list[int]]:
    """(bucket cuts, cuts of the k processors of every bucket, first processor of every bucket) of the parallel sample sort."""
    if n <= mp.k * mp.M:
        return [], [], [0]
    frame = _key_columns(df, keys, coin)
    fan = max(2, min(mp.fan_out * 16, -(-2 * n // (mp.k * mp.M))))
    # One sample serves both: a bucket's own part of it gives the k - 1 splitters of its base case.
    wanted = min(int(0.9 * bucketing.MOST_SPLITTERS), math.ceil(OVER * fan * max(math.log2(n), 1)))
    sample = bucketing.collected(frame.where(coin_of(coin, coin_limit(bucketing.sample_rate(n, wanted)), seed)), keys)
    cuts = bucketing.evenly(sample, fan - 1)
    inner, at = {}, 0
    for v in range(len(cuts) + 1):
        own = []
        while at < len(sample) and (v == len(cuts) or sample[at] < cuts[v]):
            own.append(sample[at])
            at += 1
        # The bucket's first sampled key is the cut before it.
        inner[v] = bucketing.evenly(own[1:], mp.k - 1)
    fine, first = bucketing.merged(cuts, inner)
    return cuts, fine, first


def em_sample_parallel(df: DataFrame, keys: list[str | SortKey], coin: list[str], mp: MachineParams, seed: int = 42) -> SortResult:
    """Private-cache form: chunks of kM rows count their rows a bucket; prefix sums over (bucket, chunk) give each chunk a
    contiguous place in each bucket before anything is written (`chunk_places`, `parallel_slots`). In the base case k processors share
    a bucket: each reads all of it and keeps the keys between two of its k - 1 splitters. The ledger's node is the
    processor: a chunk while rows are distributed, a part of a bucket in the base case.
    """
    n = df.count()
    cuts, fine, first = _parallel_plan(df, keys, coin, n, mp, seed)
    frame = _key_columns(df, keys, coin)

    def count() -> DataFrame:
        sizes = bucketing.sizes_of(frame, keys, fine) if fine else [n]
        place = chunk_places(frame, keys, coin, cuts, n, mp)
        per = max(1, mp.M // mp.B)
        moved = place.withColumn("rnd", F.floor(F.col("bucket") / per)).groupBy("chunk", "rnd").agg(F.sum(F.ceil(F.col("cnt") / mp.B)).cast("long").alias("writes"))
        own = place.groupBy("chunk").agg(F.sum("cnt").alias("n"))
        named = [F.lit("sample_parallel").alias("method")]
        dealt = moved.join(own, "chunk").select(*named, F.lit("distribute").alias("phase"), F.lit(0).alias("level"), F.col("chunk").alias("node"), F.col("rnd").cast("long").alias("rnd"), F.ceil(F.col("n") / mp.B).cast("long").alias("reads"), "writes")
        ends = [*first[1:], len(sizes)]
        base = [("sample_parallel", "base", 1, p, 0, -(-sum(sizes[a:b]) // mp.B), -(-sizes[p] // mp.B)) for a, b in zip(first, ends, strict=True) for p in range(a, b)]
        return dealt.unionByName(ledger_frame(df, base))

    return SortResult(lambda: bucketing.placed(df, keys, cuts, _partitions(df)), count)


def chunk_places(frame: DataFrame, keys: list[str | SortKey], coin: list[str], cuts: list[tuple], n: int, mp: MachineParams) -> DataFrame:
    """(bucket, chunk, cnt, before): rows of every chunk in every bucket, and where they begin in the distributed array."""
    chunk = F.pmod(F.xxhash64(*coin), F.lit(max(1, -(-n // (mp.k * mp.M))))).cast("long").alias("chunk")
    located = bucketing.locate(frame, keys, cuts, "bucket").withColumn("bucket", F.col("bucket").cast("long")).select("bucket", chunk)
    # Written once: the small table serves several sums, and a join on a searched bucket would unfold its search.
    return bucketing.offsets(cut_lineage(bucketing.counts(located, "bucket", "chunk")), "bucket", "chunk")


def parallel_slots(df: DataFrame, keys: list[str | SortKey], coin: list[str], mp: MachineParams, seed: int = 42) -> DataFrame:
    """Where the parallel sample sort's distribution writes each row: df with bucket, chunk and slot (1-based).

    A (chunk, bucket) range is contiguous and begins where the prefix sums say, so all chunks write at once. Inside a
    range, rows stand in key order; in place of a processor's own order of reading, which a table does not have.
    """
    n = df.count()
    cuts, _, _ = _parallel_plan(df, keys, coin, n, mp, seed)
    chunk = F.pmod(F.xxhash64(*coin), F.lit(max(1, -(-n // (mp.k * mp.M))))).cast("long")
    before = array_literal(_running(bucketing.sizes_of(_key_columns(df, keys, coin), keys, cuts)), "bigint")
    located = bucketing.locate(df, keys, cuts, "bucket").withColumn("bucket", F.col("bucket").cast("long")).withColumn("chunk", chunk)
    nth = F.row_number().over(W.partitionBy("bucket").orderBy("chunk", *order_by(df, keys)))
    return located.withColumn("slot", (F.get(before, F.col("bucket").cast("int")) + nth).cast("long"))


def em_merge(df: DataFrame, keys: list[str | SortKey], coin: list[str], mp: MachineParams, seed: int = 42, pointers: str = "memory") -> SortResult:
    """External write-saving mergesort: base runs of at most kM rows, merged by kM/B at a time.

    The result face does the merges of all levels at once: a range exchange on splitters, then local sorts; an earlier
    level's order does not show, and would be one more write of everything. The ledger carries every merge out on its
    runs, one group function a node, and counts blocks as they move.
    """
    n, slots = df.count(), _partitions(df)
    frame = _key_columns(df, keys, coin)
    cuts = bucketing.splitters(frame, keys, coin, n, 4 * slots, OVER, seed) if n > mp.k * mp.M else []

    def count() -> DataFrame:
        from writelite.operators import pq

        return pq.merge_levels(frame, keys, coin, cuts, n, mp, pointers)

    return SortResult(lambda: bucketing.placed(df, keys, cuts, slots), count)


def pram_sample(df: DataFrame, keys: list[str | SortKey], coin: list[str], ident: str, seed: int = 42, c: float = 4.0, refine: bool = True, place: str = "count") -> SortResult:
    """PRAM sample sort: sample at rate 1/log n (less from about 2 million rows on, so that the driver takes the whole sample), every log n-th sampled key a splitter, locate, place, pack, sort buckets.

    place='random' puts rows into slots of arrays of c log^2 n by tries; 'count' packs by counts and prefix sums at once.
    refine splits every bucket twice more by the deterministic split, all buckets at once. Costs are words, so B is 1.
    """
    n = df.count()
    log = max(1, int(math.log2(max(n, 2))))
    rate = min(1 / log, bucketing.sample_rate(n, int(0.9 * bucketing.MOST_SPLITTERS)))
    columns = _key_columns(df, keys, coin)
    sample = bucketing.collected(columns.where(coin_of(coin, coin_limit(rate), seed)), keys)
    cuts = sample[log - 1 :: log]
    tries = n
    if not refine and place == "count":
        rows = bucketing.placed(df, keys, cuts, _partitions(df))
        nodes = columns
    else:
        nodes = bucketing.locate(df, keys, cuts, "__top")
        if place == "random":
            cap = F.lit(max(1, int(c * max(log * log, n / (len(cuts) + 1)))))
            slotted, left = bucketing.place_random(nodes.withColumnRenamed("__top", "bucket"), cap, ident, seed=seed)
            nodes, tries = slotted.withColumnRenamed("bucket", "__top").drop("slot"), sum(left)
        nodes = nodes.repartition(_partitions(df), "__top").withColumn("node", F.lit(0).cast("long"))
        for _ in range(2 if refine else 0):
            nodes = bucketing.split_nodes(nodes, keys, "__top")
        before = array_literal(_running(bucketing.sizes_of(columns, keys, cuts)), "bigint")
        nth = F.row_number().over(W.partitionBy("__top").orderBy("node", *order_by(df, keys)))
        rows = nodes.withColumn("pos", (F.get(before, F.col("__top")) + nth).cast("long")).drop("__top", "node")

    def count() -> DataFrame:
        words = [("pram", "sample", 0, 0, 0, n + len(sample) * log, len(sample)), ("pram", "locate", 1, 0, 0, n * max(1, int(math.log2(len(cuts) + 2))), n), ("pram", "place", 2, 0, 0, tries, n), ("pram", "pack", 3, 0, 0, n, n)]
        if refine:
            words += [("pram", "refine", 4 + i, 0, 0, n * max(1, int(2 * math.log2(log))), n) for i in range(2)]
            held = bucketing.counts(nodes, "__top", "node")
        else:
            held = bucketing.counts(bucketing.locate(columns, keys, cuts, "__top"), "__top").withColumn("node", F.lit(0).cast("long"))
        m = F.col("cnt")
        leaf = held.select(F.lit("pram").alias("method"), F.lit("sort").alias("phase"), F.lit(6).alias("level"), (F.col("__top") * 4096 * 4096 + F.col("node")).cast("long").alias("node"), F.lit(0).cast("long").alias("rnd"), (m * F.greatest(F.lit(1), F.floor(F.log2((m + 1).cast("double"))))).cast("long").alias("reads"), (4 * m).cast("long").alias("writes"))
        return ledger_frame(df, words).unionByName(leaf)

    return SortResult(lambda: rows, count)


def _running(sizes: list[int]) -> list[int]:
    """Rows before each bucket."""
    return [0, *itertools.accumulate(sizes)][:-1]


def _oblivious_buckets(frame: DataFrame, keys: list[str | SortKey], coin: list[str], omega: int, cuts: list[tuple], big: dict[int, int], seed: int) -> dict[int, list[tuple]]:
    """Cuts of large nodes into sqrt(n/omega) buckets each: rows of sqrt(n/omega) are sorted, every log n-th key of a row
    is sampled, and evenly spaced ones are the splitters. Where the samples of a level are more than the driver takes, a
    coin thins them all by one rate.
    """
    shape = {v: (max(2, math.isqrt(m // omega)), max(1, int(math.log2(m)))) for v, m in big.items()}
    of = lambda pick: F.get(array_literal([pick(v) if v in shape else 0 for v in range(len(cuts) + 1)], "bigint"), F.col("__node"))
    located = bucketing.locate(frame, keys, cuts, "__node").where(of(lambda v: shape[v][0]) > 0)
    row = F.pmod(F.xxhash64(*coin, F.lit(seed)), of(lambda v: max(1, big[v] // shape[v][0])))
    thin = bucketing.thinned(located, keys, row, of(lambda v: shape[v][1]), "__node")
    expected = sum(m / shape[v][1] for v, m in big.items())
    if expected > bucketing.MOST_SPLITTERS:
        thin = thin.where(coin_of(coin, coin_limit(bucketing.MOST_SPLITTERS / expected), seed + 100))
    found = bucketing.picked(thin, keys, "__node", lambda m: F.least(of(lambda v: shape[v][0]), F.greatest(F.lit(2), F.floor(m / 2))) - 1)
    return {v: found.get(v, []) for v in big}


def co_sort(df: DataFrame, keys: list[str | SortKey], coin: list[str], omega: int, base_rows_: int = 1024, M: int = 256, B: int = 16, seed: int = 42) -> SortResult:
    """Cache-oblivious sort: no step looks at M or B, which only price the ledger.

    A node of n rows is cut at splitters into sqrt(n/omega) buckets, a bucket at omega - 1 pivots into omega sub-buckets,
    and so on until `base_rows_`. The result face deals the buckets of the first level out, whole and in order, and sorts
    them where they lie; the ledger carries the levels below out there, one task a bucket. omega 1 is the standard algorithm.
    """
    n = df.count()
    stop = max(base_rows_, omega * omega, 16)
    frame = _key_columns(df, keys, coin)
    cuts = _oblivious_buckets(frame, keys, coin, omega, [], {0: n}, seed)[0] if n > stop else []

    over = max(1.0, math.sqrt(omega * n) / max(1.0, math.log2(max(n, 2))) ** 2 / omega)
    nb = lambda m: -(-m // B)

    def dealt(level: int, node: int, m: int, held: list[int]) -> list[tuple]:
        """What cutting a node of m rows into buckets of the sizes `held` reads and writes."""
        s, drawn = max(2, math.isqrt(m // omega)), m // max(1, int(math.log2(m)))
        # Rows of s are sorted by recursion, at one write and omega scans a level of theirs.
        deep = max(1, math.ceil(math.log(s) / math.log(max(omega * M, 2))))
        merges = max(1, math.ceil(math.log2(max(drawn / M, 2))))
        # A (row, bucket) segment that does not end with a block costs one more.
        segments = min(m, max(1, m // s) * len(held))
        return [
            ("oblivious", "rows", level, node, 0, deep * omega * nb(m), deep * nb(m)),
            ("oblivious", "splitters", level, node, 0, nb(m) + nb(drawn) * merges, nb(drawn) * merges),
            ("oblivious", "gather", level, node, 0, nb(m) + nb(segments), sum(map(nb, held)) + nb(segments)),
        ]

    def based(level: int, node: int, m: int) -> tuple:
        deep = max(1, math.ceil(math.log2(max(m / M, 1) + 1)))
        return "oblivious", "base", level, node, 0, deep * nb(m), deep * nb(m)

    def bucket(level: int, node: int, hashed: np.ndarray, out: list[tuple]) -> None:
        """A bucket is sampled anew, at about max(omega, sqrt(omega n) / log n) keys, for the omega - 1 pivots that its omega scans go by."""
        m, pivots = len(hashed), []
        if m > omega > 1:
            pivots = bucketing.evenly(_drawn(hashed, math.ceil(over * omega * max(math.log2(m), 1)), seed + 200 + level), omega - 1)
        for r, (a, b) in enumerate(itertools.pairwise([0, *pivots, m])):
            if omega > 1:  # one scan of the bucket for each of its parts
                out.append(("oblivious", "subsplit", level, node, r, nb(m), nb(b - a)))
            if b - a > stop:
                split(level + 1, node + a, hashed[a:b], out)
            elif b > a:
                out.append(based(level + 1, node + a, b - a))

    def split(level: int, node: int, hashed: np.ndarray, out: list[tuple]) -> None:
        if level >= MOST_LEVELS:
            raise RuntimeError("nodes do not shrink; are the keys unique?")
        m = len(hashed)
        s = max(2, math.isqrt(m // omega))
        sample = _every(_salted(hashed, seed + level) % np.uint64(max(1, m // s)), max(1, int(math.log2(m))))
        edges = [0, *bucketing.evenly(sample, min(s, max(2, len(sample) // 2)) - 1), m]
        parts = list(itertools.pairwise(edges))
        out += dealt(level, node, m, [b - a for a, b in parts])
        for a, b in parts:
            if b > a:
                bucket(level, node + a, hashed[a:b], out)

    def count() -> DataFrame:
        if n <= stop:
            return ledger_frame(df, [("oblivious", "base", 0, 0, 0, nb(n), nb(n))])
        held = bucketing.sizes_of(frame, keys, cuts)
        before = _running(held)

        def walk(u: int, hashed: np.ndarray) -> list[tuple]:
            out: list[tuple] = []
            bucket(0, before[u], hashed, out)
            return out

        return ledger_frame(df, dealt(0, 0, n, held)).unionByName(_carried(frame, keys, coin, cuts, walk))

    return SortResult(lambda: bucketing.placed(df, keys, cuts, _partitions(df)), count)


def em_heap(df: DataFrame, keys: list[str | SortKey], coin: list[str], mp: MachineParams, seed: int = 42) -> SortResult:
    """External heapsort: rows are dealt to shards by key range; each shard's queue takes all its keys, in hashed order,
    and gives them back. A row's place in its shard is the one at which the queue gave its key back; offsets join shards.
    """
    from writelite.operators import pq

    n = df.count()
    frame = _key_columns(df, keys, coin)
    fan = max(1, min(64, -(-n // (4 * mp.k * mp.M))))
    cuts = bucketing.splitters(frame, keys, coin, n, fan, OVER, seed) if fan > 1 else []
    sizes = bucketing.sizes_of(frame, keys, cuts) if cuts else [n]
    rows = pq.drained(bucketing.locate(df, keys, cuts, "__shard"), keys, coin, mp)
    before = array_literal(_running(sizes), "bigint")
    placed = rows.withColumn("pos", (F.get(before, F.col("__shard")) + F.col("__nth")).cast("long")).drop("__shard", "__nth")
    return SortResult(lambda: placed, lambda: pq.drained_ledger(bucketing.locate(frame, keys, cuts, "__shard"), keys, coin, mp))


def ram_tree(df: DataFrame, keys: list[str | SortKey], by: str) -> DataFrame:
    """Tree sort of each group of `by`: the result face is a local sort, positions are within the group."""
    return df.withColumn("pos", F.row_number().over(W.partitionBy(by).orderBy(*order_by(df, keys))).cast("long"))
