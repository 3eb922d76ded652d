"""Priority queues, dictionaries, tree sorts and merges over groups of a frame: simulators inside group functions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from writelite.functions.model import LEDGER, MachineParams, ledger_table
from writelite.operators import bucketing, simulate
from writelite.operators.keys import SortKey, fields

HEAP = "shard long, key long, nth long, reads long, writes long"


def heap_sort(ops: DataFrame, mp: MachineParams) -> tuple[DataFrame, DataFrame]:
    """Keys (shard, shuffled, key) of each shard in the order that its queue gives them back, and a ledger by shard.

    A shard is one queue in one task: whole numbers, of which memory is the only limit (README).
    """

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        q, n, shard = simulate.Queue(mp), len(pdf), int(pdf.shard.iloc[0])
        for key in pdf.sort_values("shuffled").key.to_numpy():
            q.insert(int(key))
        keys = np.fromiter((q.delete_min() for _ in range(n)), np.int64, n)
        none = np.zeros(n, np.int64)
        return pd.DataFrame({"shard": shard, "key": np.r_[keys, 0], "nth": np.r_[1 : n + 1, 0], "reads": np.r_[none, q.reads], "writes": np.r_[none, q.writes]})

    done = ops.groupBy("shard").applyInPandas(run, HEAP)
    ledger = done.where("nth = 0").select(F.lit("heapsort").alias("method"), F.lit("queue").alias("phase"), F.lit(0).alias("level"), F.col("shard").alias("node"), F.lit(0).cast("long").alias("rnd"), "reads", "writes")
    return done.where("nth > 0").select("shard", "key", "nth"), ledger


def _keyed(df: DataFrame, keys: list[str | SortKey], coin: list[str]) -> DataFrame:
    """df with the fields of its keys (__f0, ...) and a hash of the coin columns (__shuffled)."""
    return df.select("*", *[c.alias(f"__f{i}") for i, (c, _, _) in enumerate(fields(df, keys))], F.xxhash64(*coin).alias("__shuffled"))


def _tuples(table: pa.Table) -> list[tuple]:
    """The key fields of each row as a tuple that orders as Spark does: NaN above all numbers."""
    columns = []
    for name in (n for n in table.column_names if n.startswith("__f")):
        values = table.column(name).to_pylist()
        columns.append([(v != v, 0.0 if v != v else v) for v in values] if pa.types.is_floating(table.schema.field(name).type) else values)
    return list(zip(*columns, strict=True))


def _queue_order(table: pa.Table, mp: MachineParams) -> tuple[list[int], simulate.Queue]:
    """Row numbers in the order in which a queue gives the rows' keys back, put in by hash."""
    simulate.guard(len(table))
    q, keys = simulate.Queue(mp), _tuples(table)
    shuffled = table.column("__shuffled").to_pylist()
    for i in sorted(range(len(keys)), key=shuffled.__getitem__):
        q.insert((*keys[i], i))
    return [q.delete_min()[-1] for _ in keys], q


def drained(df: DataFrame, keys: list[str | SortKey], coin: list[str], mp: MachineParams, shard: str = "__shard") -> DataFrame:
    """df with __nth: the place at which the queue of a row's shard gives its key back."""

    def go(table: pa.Table) -> pa.Table:
        order, _ = _queue_order(table, mp)
        rows = table.take(pa.array(order, pa.int64())).select(columns)
        return rows.append_column("__nth", pa.array(range(1, len(order) + 1), pa.int64()))

    columns = df.columns
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema) + ", __nth long"
    return _keyed(df, keys, coin).groupBy(shard).applyInArrow(go, schema)


def drained_ledger(df: DataFrame, keys: list[str | SortKey], coin: list[str], mp: MachineParams, shard: str = "__shard") -> DataFrame:
    """Blocks that each shard's queue read and wrote while it took and gave back its keys."""

    def go(table: pa.Table) -> pa.Table:
        _, q = _queue_order(table, mp)
        row = ("heapsort", "queue", 0, table.column(shard)[0].as_py(), 0, q.reads, q.writes)
        return ledger_table([row])

    return _keyed(df, keys, coin).groupBy(shard).applyInArrow(go, LEDGER)


def merge_levels(df: DataFrame, keys: list[str | SortKey], coin: list[str], cuts: list[tuple], n: int, mp: MachineParams, pointers: str = "memory") -> DataFrame:
    """Ledger of a whole mergesort: base runs of at most about kM keys, then every merge of kM/B runs, level by level.

    A merge is told by the runs of its keys in order, so the rows are sorted once (by the splitters `cuts`), and each
    level's nodes get two bytes a row, packed. A node's merge runs in one group function; one that passes a key over is
    told as phase 'wrong'.
    """
    count = tops = max(1, -(-n // (mp.k * mp.M)))
    levels, fan = 0, mp.fan_out
    while tops > 1:
        tops, levels = -(-tops // fan), levels + 1
    dtype = np.uint16 if fan <= 2**16 else np.uint32
    frame = df.withColumn("__run", F.pmod(F.xxhash64(*coin), F.lit(count)).cast("long"))
    size, r = F.col("cnt"), F.col("rnd")
    base = bucketing.counts(frame, "__run").withColumn("rnd", F.explode(F.sequence(F.lit(0).cast("long"), F.ceil(size / mp.M) - 1)))
    base = base.select(F.lit("mergesort").alias("method"), F.lit("base").alias("phase"), F.lit(0).alias("level"), F.col("__run").alias("node"), "rnd", F.ceil(size / mp.B).cast("long").alias("reads"), F.ceil(F.least(F.lit(mp.M), size - r * mp.M) / mp.B).cast("long").alias("writes"))
    if not levels:
        return base

    def packed(first: int, runs: np.ndarray) -> pa.RecordBatch:
        out: list[tuple] = []
        for level in range(1, levels + 1):
            node, run = runs // fan**level, (runs // fan ** (level - 1) % fan).astype(dtype)
            order = np.argsort(node, kind="stable")
            node, run = node[order], run[order]
            edges = np.flatnonzero(np.r_[True, node[1:] != node[:-1]]).tolist()
            out += [(level, int(node[a]), first, run[a:b].tobytes()) for a, b in zip(edges, [*edges[1:], len(node)], strict=True)]
        return pa.RecordBatch.from_arrays([pa.array(c, kind) for c, kind in zip(zip(*out, strict=True), (pa.int32(), pa.int64(), pa.int64(), pa.binary()), strict=True)], ["level", "node", "first", "runs"])

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, rows, first = [], 0, 0
        for b in batches:
            if not len(b):
                continue
            first = first if held else b.column("pos")[0].as_py()
            held.append(b.column("__run").to_numpy())
            rows += len(b)
            if rows >= 2**20:
                yield packed(first, np.concatenate(held))
                held, rows = [], 0
        if held:
            yield packed(first, np.concatenate(held))

    def go(table: pa.Table) -> pa.Table:
        found = sorted(zip(table.column("first").to_pylist(), (x.as_buffer() for x in table.column("runs")), strict=True), key=lambda x: x[0])
        runs = [np.frombuffer(x, dtype) for _, x in found]
        m, sizes = sum(map(len, runs)), sum(np.bincount(x, minlength=fan) for x in runs)
        fine, rounds = True, [(m, int((-(-sizes // mp.B)).sum()), -(-m // mp.B))]
        if mp.k > 1:  # else one block of every run stays in memory, so nothing is read twice
            fine, rounds = simulate.merge_ranks(runs, mp, pointers)
        level, node = table.column("level")[0].as_py(), table.column("node")[0].as_py()
        return ledger_table([("mergesort", "merge" if fine else "wrong", level, node, i, r, w) for i, (_, r, w) in enumerate(rounds)])

    parts = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ordered = bucketing.placed(frame, keys, cuts, parts).select("pos", "__run")
    return base.unionByName(ordered.mapInArrow(pack, "level int, node long, first long, runs binary").groupBy("level", "node").applyInArrow(go, LEDGER))


def run(ops: DataFrame, mp: MachineParams, machine: str = "queue") -> DataFrame:
    """Results (shard, seq, k1, k2) of the delete-mins of an operation stream (shard, seq, op I or D, k1, k2).

    machine 'queue' is the write-efficient one, 'tree' the RAM one. A delete-min of an empty queue gives nulls. The
    columns reads and writes hold what the shard has counted up to there.
    """

    def go(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("seq")
        simulate.guard(len(pdf))
        q = simulate.Queue(mp) if machine == "queue" else simulate.Tree()
        rows = []
        for shard, seq, op, k1, k2 in pdf[["shard", "seq", "op", "k1", "k2"]].itertuples(index=False):
            if op == "I":
                q.insert((k1, k2))
                continue
            if machine == "queue":
                got = q.delete_min()
            elif (got := q.least()) is not None:
                q.delete(got)
            rows.append((shard, seq, *(got or (None, None)), q.reads, q.writes))
        return pd.DataFrame(rows, columns=["shard", "seq", "k1", "k2", "reads", "writes"]).astype({"k1": "float64", "k2": "Int64"})

    return ops.groupBy("shard").applyInPandas(go, "shard long, seq long, k1 double, k2 long, reads long, writes long")


def dictionary(ops: DataFrame) -> DataFrame:
    """Whether each search of (shard, seq, op insert|delete|search, key) finds its key."""

    def go(pdf: pd.DataFrame) -> pd.DataFrame:
        tree, rows = simulate.Tree(), []
        for shard, seq, op, key in pdf.sort_values("seq")[["shard", "seq", "op", "key"]].itertuples(index=False):
            if op == "insert":
                tree.insert(key)
            elif op == "delete":
                tree.delete(key)
            else:
                rows.append((shard, seq, tree.search(key)))
        return pd.DataFrame(rows, columns=["shard", "seq", "found"])

    return ops.groupBy("shard").applyInPandas(go, "shard long, seq long, found boolean")


def tree_ledger(df: DataFrame, by: str, key: str) -> DataFrame:
    """Word reads and writes of tree-sorting each group."""

    def go(pdf: pd.DataFrame) -> pd.DataFrame:
        tree = simulate.Tree()
        for k in pdf.sort_values("shuffled").key.tolist():
            tree.insert(k)
        assert tree.walk() == sorted(pdf.key.tolist())
        return pd.DataFrame([("ram_tree", "sort", 0, int(pdf.node.iloc[0]), 0, tree.reads, tree.writes)], columns=LEDGER.names)

    rows = df.select(F.col(by).cast("long").alias("node"), F.xxhash64(key).alias("shuffled"), F.col(key).cast("long").alias("key"))
    return rows.groupBy("node").applyInPandas(go, LEDGER)


def merge_ledger(runs: DataFrame, mp: MachineParams, pointers: str = "memory") -> DataFrame:
    """Ledger by round of merging the runs (node, run, key) of each node, phase 'ok' or 'wrong' by its output."""

    def go(pdf: pd.DataFrame) -> pd.DataFrame:
        lists = [sorted(g.key.tolist()) for _, g in pdf.groupby("run")]
        out, rounds = simulate.merge(lists, mp, pointers)
        phase = "ok" if out == sorted(pdf.key.tolist()) else "wrong"
        return pd.DataFrame([("merge", phase, 0, int(pdf.node.iloc[0]), i, r, w) for i, (_, r, w) in enumerate(rounds)], columns=LEDGER.names)

    return runs.groupBy("node").applyInPandas(go, LEDGER)


def buffer_tree_ledger(df: DataFrame, by: str, key: str, mp: MachineParams) -> DataFrame:
    """(node, n, reads, writes, ok): a buffer tree of each group's keys, inserted in hashed order and drained leaf by leaf."""

    def go(pdf: pd.DataFrame) -> pd.DataFrame:
        tree = simulate.BufferTree(mp)
        for k in pdf.sort_values("shuffled").key.tolist():
            tree.insert(k)
        reads, writes, ok, out = tree.reads, tree.writes, tree.check(), []
        while tree.size:
            out += tree.detach_leftmost()
        return pd.DataFrame([(int(pdf.node.iloc[0]), len(pdf), reads, writes, ok and out == sorted(pdf.key.tolist()))], columns=["node", "n", "reads", "writes", "ok"])

    rows = df.select(F.col(by).cast("long").alias("node"), F.xxhash64(key).alias("shuffled"), F.col(key).cast("long").alias("key"))
    return rows.groupBy("node").applyInPandas(go, "node long, n long, reads long, writes long, ok boolean")


def cache_run(trace: DataFrame, mp: MachineParams, policy: str) -> DataFrame:
    """(shard, misses, clean, dirty, cost) of traces (shard, seq, op, block)."""

    def go(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("seq")
        steps, total = simulate.cache(list(zip(pdf.op, pdf.block, strict=True)), mp.M // mp.B, mp.omega, policy)
        return pd.DataFrame([(int(pdf.shard.iloc[0]), sum(not s[0] for s in steps), sum(s[1] for s in steps), sum(s[2] for s in steps), total)], columns=["shard", "misses", "clean", "dirty", "cost"])

    return trace.groupBy("shard").applyInPandas(go, "shard long, misses long, clean long, dirty long, cost long")

