"""Sorts, splitters, merges, queues and trees over lineitem, events, orders, documents and customer."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from writelite.functions import bounds
from writelite.functions.model import STD, MachineParams, ledger_cost
from writelite.operators import bucketing, pq, prim, simulate, sort
from writelite.operators.keys import portable_coin, portable_coin_sql, total_order_key
from writelite.plans import planner

TIE = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]
REAL = ["l_extendedprice", *TIE]
DUPS = ["l_quantity", *TIE, "l_extendedprice"]


def table(spark: SparkSession, d: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{d}/{name}.parquet")


#: name: (table, keys, coin columns)
INPUTS = {
    "real": ("lineitem", REAL, TIE),
    "dups": ("lineitem", DUPS, TIE),
    "sorted": ("events", ["ts", "event_id"], ["event_id"]),
    "reverse": ("events", ["-ts", "event_id"], ["event_id"]),
    "string": ("documents", ["lang", "-n_chars", "doc_id"], ["doc_id"]),
    "segments": ("customer", ["c_mktsegment", "-c_acctbal", "c_custkey"], ["c_custkey"]),
}


def _plain(keys: list[str]) -> list[str]:
    return [k.lstrip("-") for k in keys]


def _load(spark: SparkSession, d: str, name: str) -> tuple[DataFrame, list[str], list[str]]:
    t, keys, coin = INPUTS[name]
    return table(spark, d, t).select(*dict.fromkeys([*_plain(keys), *coin])), keys, coin


def _order_sql(name: str, by: str | None = None) -> str:
    t, keys, coin = INPUTS[name]
    cols = ", ".join(dict.fromkeys([*_plain(keys), *coin]))
    order = ", ".join(f"{k.lstrip('-')} {'DESC' if k[0] == '-' else 'ASC'}" for k in keys)
    part = f"PARTITION BY {by} " if by else ""
    return f"SELECT {cols}, row_number() OVER ({part}ORDER BY {order})::BIGINT AS pos FROM {t}"


def _sample(name: str, mp: MachineParams = STD, **how):
    def q(spark: SparkSession, d: str) -> DataFrame:
        df, keys, coin = _load(spark, d, name)
        return sort.em_sample(df, keys, coin, mp, **how).rows

    return q


def _other(method, name: str, *args, **how):
    def q(spark: SparkSession, d: str) -> DataFrame:
        df, keys, coin = _load(spark, d, name)
        return method(df, keys, coin, *args, **how).rows

    return q


def _small(spark: SparkSession, d: str) -> DataFrame:
    """At most kM = omega M rows: suppliers' orders of one priority by key range."""
    return table(spark, d, "orders").select("o_orderpriority", "o_totalprice", "o_orderkey")


CLASSIC = MachineParams(256, 16, 8, 1)

# One level of portable splitters, so that bucket counts can be told in SQL.

FAN = 16


def _one_level(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    """(lineitem keys with bucket, splitters (i, key...)): FAN buckets cut at a portable sample of rate 1/20."""
    df = table(spark, d, "lineitem").select(*REAL)
    key = total_order_key(df, REAL)
    sample = df.where(portable_coin(TIE, 0.05, 42)).withColumn("k", key)
    ranked = sample.withColumn("r", F.row_number().over(W.orderBy("k"))).withColumn("n", F.count(F.lit(1)).over(W.partitionBy(F.lit(1))))
    steps = [ranked.where(F.col("r") == F.floor(F.col("n") * i / FAN)).select(F.lit(i).cast("long").alias("i"), *REAL, "k") for i in range(1, FAN)]
    cuts = steps[0]
    for s in steps[1:]:
        cuts = cuts.unionByName(s)
    found = bucketing.collected(cuts, REAL)
    return bucketing.locate(df, REAL, found, "bucket").withColumn("bucket", F.col("bucket").cast("long")), cuts.drop("k")


_CUTS_SQL = f"""
s AS (SELECT {', '.join(REAL)}, row_number() OVER (ORDER BY {', '.join(REAL)}) AS r, count(*) OVER () AS n FROM lineitem WHERE {portable_coin_sql(TIE, 0.05, 42)}),
c AS (SELECT i, {', '.join(REAL)} FROM s JOIN range(1, {FAN}) t(i) ON r = n * i // {FAN}),
b AS (SELECT l.*, (SELECT count(*) FROM c WHERE ({', '.join('c.' + x for x in REAL)}) <= ({', '.join('l.' + x for x in REAL)})) AS bucket FROM lineitem l)"""


def _sample_ledger(mp: MachineParams):
    per = mp.M // mp.B

    def q(spark: SparkSession, d: str) -> DataFrame:
        rows, _ = _one_level(spark, d)
        n = rows.count()
        sizes = bucketing.counts(rows, "bucket")
        rounds = sizes.withColumn("rnd", F.floor(F.col("bucket") / max(1, per // 4))).groupBy("rnd").agg(F.sum(F.ceil(F.col("cnt") / mp.B)).cast("long").alias("writes"))
        out = rounds.select(F.lit("distribute").alias("phase"), "rnd", F.lit(bounds.blocks(n, mp.B)).cast("long").alias("reads"), "writes")
        base = sizes.select(F.lit("base").alias("phase"), F.col("bucket").alias("rnd"), (F.ceil(F.col("cnt") / mp.M) * F.ceil(F.col("cnt") / mp.B)).cast("long").alias("reads"), (F.floor(F.col("cnt") / mp.M) * F.lit(bounds.blocks(mp.M, mp.B)) + F.ceil(F.col("cnt") % mp.M / mp.B)).cast("long").alias("writes"))
        return out.unionByName(base)

    return q


def _sample_ledger_sql(mp: MachineParams) -> str:
    B, M, per = mp.B, mp.M, max(1, mp.M // mp.B // 4)
    return f"""WITH {_CUTS_SQL}, z AS (SELECT bucket, count(*) AS cnt FROM b GROUP BY bucket)
SELECT 'distribute' AS phase, (bucket // {per})::BIGINT AS rnd, (SELECT (count(*) + {B - 1}) // {B} FROM lineitem)::BIGINT AS reads, sum((cnt + {B - 1}) // {B})::BIGINT AS writes FROM z GROUP BY bucket // {per}
UNION ALL SELECT 'base', bucket::BIGINT, (((cnt + {M - 1}) // {M}) * ((cnt + {B - 1}) // {B}))::BIGINT, (cnt // {M} * {-(-M // B)} + (cnt % {M} + {B - 1}) // {B})::BIGINT FROM z"""


def processor_times(ledger: DataFrame, omega: int, ps: tuple[int, ...]) -> dict[int, int]:
    """Time on p processors of a ledger whose phases follow each other: the units (level, phase, node, round) of a phase
    go to the processors in turn, and a phase takes as long as its dearest processor.
    """
    units = ledger.groupBy("level", "phase", "node", "rnd").agg(F.sum(F.col("reads") + omega * F.col("writes")).alias("cost"))
    units = units.withColumn("i", F.row_number().over(W.partitionBy("level", "phase").orderBy("node", "rnd")))
    own = units.withColumn("p", F.explode(F.array(*map(F.lit, ps)))).groupBy("level", "phase", "p", (F.col("i") % F.col("p")).alias("proc")).agg(F.sum("cost").alias("c"))
    return {r["p"]: r["t"] for r in own.groupBy("level", "phase", "p").agg(F.max("c").alias("c")).groupBy("p").agg(F.sum("c").alias("t")).collect()}


def _parallel_time(spark: SparkSession, d: str) -> DataFrame:
    """Whether the time on p processors, counted from the parallel sample sort's ledger, is at most that of fewer, and
    at least the total over p.
    """
    df, keys, coin = _load(spark, d, "real")
    t = processor_times(sort.em_sample_parallel(df, keys, coin, STD).ledger, STD.omega, (1, 2, 4, 8))
    return spark.createDataFrame([(p, t[p] <= t[max(1, p // 2)], t[p] * p >= t[1]) for p in (1, 2, 4, 8)], "p long, falls boolean, bounded boolean")


_PARALLEL_TIME_SQL = "SELECT p::BIGINT AS p, true AS falls, true AS bounded FROM (VALUES (1), (2), (4), (8)) t(p)"


def _splitters_even(spark: SparkSession, d: str) -> DataFrame:
    return _one_level(spark, d)[1]


def _splitters_deterministic(spark: SparkSession, d: str) -> DataFrame:
    """Every 100th key of each group of order keys mod 10, then every 20th of those: no chance involved."""
    o = table(spark, d, "orders").select("o_totalprice", "o_orderkey")
    thin = o.withColumn("i", F.row_number().over(W.partitionBy(F.col("o_orderkey") % 10).orderBy("o_totalprice", "o_orderkey"))).where("i % 10 = 0")
    return thin.withColumn("r", F.row_number().over(W.orderBy("o_totalprice", "o_orderkey"))).where("r % 20 = 0").select("o_totalprice", "o_orderkey")


def _bucket_balance(spark: SparkSession, d: str) -> DataFrame:
    """Largest bucket over the mean is a constant with high probability: below 2 here."""
    rows, _ = _one_level(spark, d)
    c = bucketing.counts(rows, "bucket")
    return c.agg(F.count(F.lit(1)).alias("buckets"), (F.max("cnt") * F.count(F.lit(1)) < 2 * F.sum("cnt")).alias("ok"))


def _check(name: str, bad: DataFrame) -> DataFrame:
    """(measure, ok): ok when no row of `bad` is left."""
    return bad.agg(F.lit(name).alias("measure"), (F.count(F.lit(1)) == 0).alias("ok"))


def _ok_sql(name: str) -> str:
    return f"SELECT '{name}' AS measure, true AS ok"


def merge_bound(df: DataFrame, keys: list[str], coin: list[str], mp: MachineParams, **how) -> DataFrame:
    """Levels of a mergesort's counted ledger that break a bound: a level of merges reads its blocks k + 1 times and
    writes them once, a level of base runs reads them as often as its largest run has rounds; a partial block a run is
    allowed, and a run out of order is not.
    """
    n = df.count()
    led = sort.em_merge(df, keys, coin, mp, **how).ledger
    nb, runs = bounds.blocks(n, mp.B), max(1, -(-n // (mp.k * mp.M)))
    per = led.groupBy("level").agg(F.sum("reads").alias("r"), F.sum("writes").alias("w"), F.max((F.col("phase") == "wrong").cast("int")).alias("wrong"), (F.max("rnd") + 1).alias("rounds"), F.count_distinct("node").alias("nodes"))
    held = F.ceil(F.lit(runs) / F.pow(F.lit(float(mp.fan_out)), F.greatest(F.col("level") - 1, F.lit(0)).cast("double")))
    most = F.when(F.col("level") == 0, F.col("rounds")).otherwise(mp.k + 1 if mp.k > 1 else 1)
    broken = (F.col("wrong") == 1) | (F.col("r") > most * (nb + held)) | (F.col("w") > nb + F.col("nodes") * F.when(F.col("level") == 0, F.col("rounds")).otherwise(1)) | (F.col("level") > bounds.levels(n, mp))
    return per.where(broken)


def _merge_bound(spark: SparkSession, d: str) -> DataFrame:
    return _check("mergesort", merge_bound(*_load(spark, d, "real"), STD))


def _runs(spark: SparkSession, d: str, groups: int = 8, runs: int = 32) -> DataFrame:
    """Unique integer keys of orders as runs of nodes."""
    o = table(spark, d, "orders").select("o_orderkey", (F.round(F.col("o_totalprice") * 100).cast("long") * 1_000_000 + F.col("o_orderkey")).alias("key"))
    return o.select((F.col("o_orderkey") % groups).alias("node"), F.pmod(F.xxhash64("o_orderkey"), F.lit(runs)).alias("run"), "key")


MERGE = MachineParams(64, 8, 8, 4)


def _merge_check(pointers: str):
    def q(spark: SparkSession, d: str) -> DataFrame:
        runs = _runs(spark, d)
        led = pq.merge_ledger(runs, MERGE, pointers)
        nb = bucketing.counts(runs, "node", "run").withColumn("nb", F.ceil(F.col("cnt") / MERGE.B)).groupBy("node").agg(F.sum("nb").alias("nb"), F.sum("cnt").alias("n"))
        total = led.groupBy("node").agg(F.sum("reads").alias("r"), F.sum("writes").alias("w"), F.max((F.col("phase") != "ok").cast("int")).alias("wrong"), F.count(F.lit(1)).alias("rounds")).join(nb, "node")
        writes = F.ceil(F.col("n") / MERGE.B) + (F.col("nb") if pointers == "secondary" else 0)
        return _check("merge" if pointers == "memory" else "merge_secondary_pointers", total.where((F.col("wrong") == 1) | (F.col("r") > (MERGE.k + 1) * F.col("nb")) | (F.col("w") > writes) | (F.col("rounds") > F.ceil(F.col("n") / MERGE.M))))

    return q


def _merge_trace(spark: SparkSession, d: str) -> DataFrame:
    """The two small merges that a literal queue rule gets wrong, on every full group of sixteen keys of orders, told by
    their places in it: output, rounds and reads, and the groups that gave them.
    """
    cases = (("passed_over", [[1, 9], [2], [3], [4]], MachineParams(2, 1, 2, 2)), ("emitted_twice", [[2], [7, 8], [1, 3, 4], [5, 6]], MachineParams(4, 2, 2, 2)))
    names = ["case", "output", "emitted", "reads"]

    def go(batches):
        import pyarrow as pa

        for b in batches:
            rows = []
            for keys in b.column(0).to_pylist():
                for case, runs, mp in cases:
                    out, rounds = simulate.merge([[keys[i] for i in run] for run in runs], mp)
                    rows.append((case, ",".join(str(k - keys[0]) for k in out), ",".join(str(r[0]) for r in rounds), sum(r[1] for r in rounds)))
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], pa.int64() if i == 3 else pa.string()) for i in range(4)], names)

    groups = table(spark, d, "orders").groupBy(F.floor(F.col("o_orderkey") / 16).alias("g")).agg(F.array_sort(F.collect_set("o_orderkey")).alias("keys"))
    done = groups.where(F.size("keys") == 16).select("keys").mapInArrow(go, "case string, output string, emitted string, reads long")
    return done.groupBy(*names).agg(F.count(F.lit(1)).alias("groups"))


_MERGE_TRACE_SQL = "SELECT *, (SELECT count(*) FROM (SELECT 1 FROM orders GROUP BY o_orderkey // 16 HAVING count(DISTINCT o_orderkey) = 16))::BIGINT AS groups FROM (VALUES ('passed_over', '1,2,3,4,9', '2,2,1', 9::BIGINT), ('emitted_twice', '1,2,3,4,5,6,7,8', '5,3', 7::BIGINT)) t(\"case\", output, emitted, reads)"

SEL = MachineParams(256, 16, 8, 8)


def _selection_window(spark: SparkSession, d: str) -> DataFrame:
    return sort.selection_window(_small(spark, d), ["o_totalprice", "o_orderkey"], SEL, by="o_orderpriority").rows


def _selection_rounds(spark: SparkSession, d: str) -> DataFrame:
    s = table(spark, d, "supplier").select("s_acctbal", "s_suppkey")
    return sort.selection_rounds(s, ["s_acctbal", "s_suppkey"], MachineParams(64, 8, 8, 8)).rows


def _selection_ledger(spark: SparkSession, d: str) -> DataFrame:
    led = sort.selection_window(_small(spark, d), ["o_totalprice", "o_orderkey"], SEL, by="o_orderpriority").ledger
    return led.select("node", "rnd", "reads", "writes")


_SELECTION_LEDGER_SQL = f"""WITH c AS (SELECT row_number() OVER (ORDER BY o_orderpriority) - 1 AS node, count(*) AS n FROM orders GROUP BY o_orderpriority)
SELECT node::BIGINT AS node, rnd::BIGINT AS rnd, ((n + {SEL.B - 1}) // {SEL.B})::BIGINT AS reads, ((least({SEL.M}, n - rnd * {SEL.M}) + {SEL.B - 1}) // {SEL.B})::BIGINT AS writes
FROM (SELECT node, n, unnest(range(0, (n + {SEL.M - 1}) // {SEL.M})) AS rnd FROM c)"""



def counted_ledgers(spark: SparkSession, d: str) -> DataFrame:
    """(method, phase, reads, writes) of every round of three methods that SQL can count too."""
    parts = [_sample_ledger(STD)(spark, d).select(F.lit("sample").alias("method"), "phase", "reads", "writes")]
    parts.append(_sample_ledger(CLASSIC)(spark, d).select(F.lit("classic").alias("method"), "phase", "reads", "writes"))
    parts.append(_selection_ledger(spark, d).select(F.lit("selection").alias("method"), F.lit("base").alias("phase"), "reads", "writes"))
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


HEAP = MachineParams(256, 16, 8, 4)


def _heap_by_priority(spark: SparkSession, d: str) -> DataFrame:
    """n inserts and n delete-mins of each priority's orders, in write-efficient queues."""
    o = table(spark, d, "orders").select("o_orderpriority", "o_totalprice", "o_orderkey")
    shard = F.dense_rank().over(W.orderBy("o_orderpriority"))
    names = o.select("o_orderpriority").distinct().withColumn("shard", shard.cast("long"))
    keyed = o.join(F.broadcast(names), "o_orderpriority").withColumn("key", (F.round(F.col("o_totalprice") * 100).cast("long") * 10_000_000 + F.col("o_orderkey")).cast("long"))
    drained, _ = pq.heap_sort(keyed.select("shard", F.xxhash64("o_orderkey").alias("shuffled"), "key"), HEAP)
    return drained.join(keyed, ["shard", "key"]).select("o_orderpriority", "o_totalprice", "o_orderkey", F.col("nth").alias("pos"))


def _heap_global(spark: SparkSession, d: str) -> DataFrame:
    o = table(spark, d, "orders").select("o_totalprice", "o_orderkey")
    return sort.em_heap(o, ["o_totalprice", "o_orderkey"], ["o_orderkey"], HEAP).rows


def _pq_amortised(spark: SparkSession, d: str) -> DataFrame:
    """Reads and writes an operation within 8 times the bound's shape."""
    o = table(spark, d, "orders")
    ops = o.select((F.col("o_orderkey") % 4).alias("shard"), F.xxhash64("o_orderkey").alias("shuffled"), "o_orderkey").select("shard", "shuffled", F.col("o_orderkey").alias("key"))
    drained, led = pq.heap_sort(ops, HEAP)
    n = ops.groupBy("shard").agg(F.count(F.lit(1)).alias("n"))
    total = led.join(n, led["node"] == n["shard"])
    lev = 1 + F.log(F.col("n").cast("double")) / F.log(F.lit(float(HEAP.fan_out)))
    return _check("queue", total.where((F.col("reads") > 8 * 2 * F.col("n") * HEAP.k / HEAP.B * lev) | (F.col("writes") > 8 * 2 * F.col("n") / HEAP.B * lev)))


def _ops(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "events")
    return e.select(F.col("user_id").alias("shard"), F.col("event_id").alias("seq"), F.when(F.col("event_type") == "purchase", "D").otherwise("I").alias("op"), F.col("value").alias("k1"), F.col("event_id").alias("k2"))


def _mixed(machine: str):
    return lambda spark, d: pq.run(_ops(spark, d), HEAP, machine).select("shard", "seq", "k1", "k2")


def _dictionary(spark: SparkSession, d: str) -> DataFrame:
    """Inserts, deletes and searches of props.k by user: signup and purchase insert, error deletes, view and click search."""
    e = table(spark, d, "events")
    op = F.when(F.col("event_type").isin("signup", "purchase"), "insert").when(F.col("event_type") == "error", "delete").otherwise("search")
    return pq.dictionary(e.select(F.col("user_id").alias("shard"), F.col("event_id").alias("seq"), op.alias("op"), F.get_json_object("props", "$.k").cast("long").alias("key")))


_DICTIONARY_SQL = """WITH o AS (SELECT user_id, event_id, event_type, (props->>'$.k')::BIGINT AS k FROM events),
w AS (SELECT *, last_value(CASE WHEN event_type IN ('signup', 'purchase') THEN 1 WHEN event_type = 'error' THEN 0 END IGNORE NULLS) OVER (PARTITION BY user_id, k ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS last FROM o)
SELECT user_id AS shard, event_id AS seq, coalesce(last, 0) = 1 AS found FROM w WHERE event_type IN ('view', 'click')"""


def _beta_check(spark: SparkSession, d: str) -> DataFrame:
    """The implicit deletes of the beta set stay rising in index and falling in key, over order prices by month."""
    import pandas as pd

    def go(pdf: pd.DataFrame) -> pd.DataFrame:
        q = simulate.Queue(MachineParams(32, 4, 8, 4))
        ok = True
        for i, k in enumerate(pdf.sort_values("shuffled").key.tolist()):
            q.insert(k)
            if i % 3 == 2:
                q.delete_min()
            ok &= q.beta.steady
        return pd.DataFrame([(int(pdf.shard.iloc[0]), bool(ok and q.ordered()))], columns=["shard", "ok"])

    o = table(spark, d, "orders").select((F.col("o_orderkey") % 5).alias("shard"), F.xxhash64("o_orderkey").alias("shuffled"), F.col("o_orderkey").alias("key"))
    return _check("beta", o.groupBy("shard").applyInPandas(go, "shard long, ok boolean").where("NOT ok"))


def _tree_check(spark: SparkSession, d: str) -> DataFrame:
    o = table(spark, d, "orders").withColumn("g", F.col("o_orderkey") % 4)
    return _check("buffer_tree", pq.buffer_tree_ledger(o, "g", "o_orderkey", MachineParams(32, 4, 8, 4)).where("NOT ok"))


def _emptying_check(spark: SparkSession, d: str) -> DataFrame:
    """Insertions cost at most 6 times k/B and 1/B a level."""
    o = table(spark, d, "orders").withColumn("g", F.col("o_orderkey") % 4)
    mp = MachineParams(32, 4, 8, 4)
    led = pq.buffer_tree_ledger(o, "g", "o_orderkey", mp)
    lev = 1 + F.log(F.col("n").cast("double")) / F.log(F.lit(float(mp.fan_out)))
    return _check("emptying", led.where((F.col("reads") > 6 * F.col("n") * mp.k / mp.B * lev) | (F.col("writes") > 6 * F.col("n") / mp.B * lev)))


def _ram_tree(spark: SparkSession, d: str) -> DataFrame:
    return sort.ram_tree(_small(spark, d), ["o_totalprice", "o_orderkey"], "o_orderpriority")


def _tree_writes(spark: SparkSession, d: str) -> DataFrame:
    """A tree sort writes at most 12 words a record, and reads at most 3 n log n."""
    o = table(spark, d, "orders").withColumn("g", F.col("o_orderkey") % 4)
    led = pq.tree_ledger(o, "g", "o_orderkey").join(bucketing.counts(o, "g"), F.col("node") == F.col("g"))
    return _check("ram_tree", led.where((F.col("writes") > 12 * F.col("cnt")) | (F.col("reads") > 3 * F.col("cnt") * F.log2(F.col("cnt").cast("double")))))


def _ram_merge(spark: SparkSession, d: str) -> DataFrame:
    c = table(spark, d, "orders").groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"))
    passes = F.filter(F.sequence(F.lit(0), F.lit(62)), lambda t: F.pow(F.lit(2.0), t.cast("double")) >= F.col("n"))[0]
    return c.select("o_orderpriority", "n", (F.col("n") * passes).cast("long").alias("writes"))


def _placement(spark: SparkSession, d: str) -> DataFrame:
    """Random placement into arrays twice as large ends within 4 tries a row in all."""
    o = table(spark, d, "orders").select("o_orderkey", (F.col("o_orderkey") % 16).alias("bucket"))
    sized = o.join(F.broadcast(bucketing.counts(o, "bucket")), "bucket")
    placed, tries = bucketing.place_random(sized, 2 * F.col("cnt"), "o_orderkey")
    n = o.count()
    clash = placed.groupBy("bucket", "slot").count().where("count > 1").count()
    good = placed.count() == n and not clash and sum(tries) <= 4 * n
    return spark.createDataFrame([("placement", bool(good))], "measure string, ok boolean")


def _deterministic(spark: SparkSession, d: str) -> DataFrame:
    import math

    o = table(spark, d, "orders").select((F.round(F.col("o_totalprice") * 100).cast("long") * 1_000_000 + F.col("o_orderkey")).alias("key"))
    m = o.count()
    rows, _ = bucketing.deterministic_split(o, ["key"], m=m)
    bound = m ** (2 / 3) * (math.log2(m) + 1)
    spans = rows.groupBy("bucket").agg(F.count(F.lit(1)).alias("cnt"), F.min("key").alias("lo"), F.max("key").alias("hi"))
    after = F.lead("lo").over(W.orderBy("bucket"))
    return _check("deterministic_split", spans.withColumn("next", after).where((F.col("cnt") > bound) | (F.col("hi") >= F.col("next"))))


def _integer_sort(spark: SparkSession, d: str) -> DataFrame:
    p = table(spark, d, "part").select("p_partkey", "p_size")
    return bucketing.integer_sort(p, "p_size", ["p_partkey"], 8)


def _prefix(spark: SparkSession, d: str) -> DataFrame:
    o = table(spark, d, "orders").select("o_orderkey", F.round(F.col("o_totalprice") * 100).cast("long").alias("cents"))
    return prim.prefix_sum(o, "o_orderkey", "cents", 4096)


def _merge_two(spark: SparkSession, d: str) -> DataFrame:
    def side(t: str, k: str, v: str) -> DataFrame:
        df = table(spark, d, t).select(F.round(F.col(v) * 100).cast("long").alias("cents"), k)
        return df.select("cents", F.row_number().over(W.orderBy("cents", k)).cast("long").alias("pos"))

    return prim.merge_two(side("customer", "c_custkey", "c_acctbal"), side("supplier", "s_suppkey", "s_acctbal"), "cents", 10_000)


_MERGE_TWO_SQL = """WITH a AS (SELECT round(c_acctbal * 100)::BIGINT AS cents, row_number() OVER (ORDER BY round(c_acctbal * 100)::BIGINT, c_custkey) AS pos, 0 AS side FROM customer),
b AS (SELECT round(s_acctbal * 100)::BIGINT AS cents, row_number() OVER (ORDER BY round(s_acctbal * 100)::BIGINT, s_suppkey) AS pos, 1 AS side FROM supplier)
SELECT cents, side, pos, row_number() OVER (ORDER BY cents, side, pos)::BIGINT AS merged_pos FROM (SELECT * FROM a UNION ALL SELECT * FROM b)"""


def _transpose(spark: SparkSession, d: str) -> DataFrame:
    m = table(spark, d, "lineitem").groupBy((F.col("l_partkey") % 16).alias("i"), (F.col("l_suppkey") % 16).alias("j")).agg(F.sum(F.col("l_quantity").cast("long")).alias("v"))
    return prim.transpose(m).withColumn("place", prim.transpose_index(F.col("j") * 16 + F.col("i"), 16, 16).cast("long"))


def _oblivious_check(spark: SparkSession, d: str) -> DataFrame:
    """Writes stay within 8 times the bound's shape and reads within omega times that; a bucket has at most
    2 sqrt(n omega) log n rows (told by the blocks that its scans read) and is read about omega times.
    """
    df, keys, coin = _load(spark, d, "real")
    n, omega, B = df.count(), 4, 16
    ledger = sort.co_sort(df, keys, coin, omega, 256, B=B).ledger
    led = ledger_cost(ledger, omega)
    r, w = bounds.oblivious_sort(n, MachineParams(256, B, omega, 1))
    scans = ledger.where("phase = 'subsplit' AND level = 0").groupBy("node").agg(F.max("reads").alias("blocks"), F.count(F.lit(1)).alias("scans"), F.sum("writes").alias("written"))
    wide = scans.where((F.col("blocks") > 2 * math.sqrt(n * omega) * math.log2(n) / B + 1) | (F.col("scans") > omega) | (F.col("written") > F.col("blocks") + F.col("scans")) | (F.col("written") < F.col("blocks")))
    return _check("oblivious", led.where((F.col("writes") > 8 * w) | (F.col("reads") > 8 * r)).select(F.lit(1).alias("bad")).unionByName(wide.select(F.lit(1).alias("bad"))))


def _slots(spark: SparkSession, d: str) -> DataFrame:
    """The parallel sample sort's slots are 1 to n, each once, and every (bucket, chunk) range is contiguous and begins
    where the prefix sums over counts say.
    """
    df, keys, coin = _load(spark, d, "real")
    n = df.count()
    rows = sort.parallel_slots(df, keys, coin, STD)
    ranges = prim.cut_lineage(rows.groupBy("bucket", "chunk").agg(F.min("slot").alias("lo"), F.max("slot").alias("hi"), F.count(F.lit(1)).alias("rows")))
    cuts = sort._parallel_plan(df, keys, coin, n, STD, 42)[0]
    place = sort.chunk_places(df.select(*dict.fromkeys([*keys, *coin])), keys, coin, cuts, n, STD)
    met = ranges.join(place, ["bucket", "chunk"], "full")
    wrong = met.where("lo IS NULL OR cnt IS NULL OR rows <> cnt OR lo <> before + 1 OR hi <> before + cnt").select(F.lit(1).alias("bad"))
    ends = ranges.agg(F.min("lo").alias("lo"), F.max("hi").alias("hi"), F.sum("rows").alias("n")).where(f"lo <> 1 OR hi <> n OR n <> {n}").select(F.lit(1).alias("bad"))
    return _check("slots", wrong.unionByName(ends))


def _queues(spark: SparkSession, d: str) -> DataFrame:
    """A merge counts the same blocks and puts out the same keys with its queue as sorted array, heaps or tree, and never
    holds more than the queue and a block on either side.
    """
    import pandas as pd

    def go(pdf: pd.DataFrame) -> pd.DataFrame:
        lists = [sorted(g.key.tolist()) for _, g in pdf.groupby("run")]
        peak: list[int] = []
        found = [simulate.merge(lists, MERGE, queue=q, peak=peak) for q in simulate.QUEUES]
        ok = all(f == found[0] for f in found) and found[0][0] == sorted(pdf.key.tolist()) and max(peak) <= MERGE.M + 2 * MERGE.B
        return pd.DataFrame([(int(pdf.node.iloc[0]), ok)], columns=["node", "ok"])

    return _check("merge_queues", _runs(spark, d).groupBy("node").applyInPandas(go, "node long, ok boolean").where("NOT ok"))


def _skewed(spark: SparkSession, d: str) -> DataFrame:
    """Buckets of skewed columns against their bounds: evenly spaced splitters of a sample (twice the mean), the
    deterministic split (m^(2/3) (log m + 1)), and the cache-oblivious sort's buckets (2 sqrt(n omega) log n).
    """
    inputs = [("events.user_id", table(spark, d, "events").select("user_id", "event_id"), ["user_id", "event_id"], ["event_id"])]
    inputs.append(("lineitem.l_suppkey", table(spark, d, "lineitem").select("l_suppkey", *REAL[:4]), ["l_suppkey", *REAL[:4]], TIE[:3]))
    one = table(spark, d, "events").select(F.when(F.col("event_id") % 10 > 0, F.lit(1).cast("long")).otherwise(F.col("user_id")).alias("hot"), "event_id")
    inputs.append(("events.nine_tenths_one_key", one, ["hot", "event_id"], ["event_id"]))
    out = []
    for name, df, keys, coin in inputs:
        n, omega = df.count(), 4
        cuts = bucketing.splitters(df, keys, coin, n, FAN)
        even = max(bucketing.sizes_of(df, keys, cuts))
        split, _ = bucketing.deterministic_split(df, keys, n)
        most = split.groupBy("bucket").agg(F.count(F.lit(1)).alias("cnt")).agg(F.max("cnt")).first()[0]
        wide = max(bucketing.sizes_of(df, keys, sort._oblivious_buckets(df.select(*dict.fromkeys([*keys, *coin])), keys, coin, omega, [], {0: n}, 42)[0]))
        out.append((name, even * FAN < 2 * n, most <= n ** (2 / 3) * (math.log2(n) + 1), wide <= 2 * math.sqrt(n * omega) * math.log2(n)))
    return spark.createDataFrame(out, "input string, sampled_ok boolean, deterministic_ok boolean, oblivious_ok boolean")


def _tries(spark: SparkSession, d: str) -> DataFrame:
    """Random placement in groups of log n rows: the mean group takes at most 2 tries a row, the largest at most 6 log n."""
    o = table(spark, d, "orders").select("o_orderkey", (F.col("o_orderkey") % 16).alias("bucket"))
    n = o.count()
    log = max(1, int(math.log2(n)))
    sized = o.join(bucketing.counts(o, "bucket"), "bucket")
    took = bucketing.place_random(sized, 2 * F.col("cnt"), "o_orderkey", told=True)[0]
    group = took.groupBy(F.floor(F.col("o_orderkey") / log).alias("g")).agg(F.sum("tries").alias("tries"), F.count(F.lit(1)).alias("rows"))
    return group.agg(F.lit("tries").alias("measure"), ((F.sum("tries") <= 2 * F.sum("rows")) & (F.max("tries") <= 6 * log)).alias("ok"))


def _late(spark: SparkSession, d: str) -> DataFrame:
    """Wide rows ordered by a narrow key: only keys are placed, the payload joins at the end by its id."""
    t = table(spark, d, "documents")
    placed = sort.em_sample(t.select("lang", "n_chars", "doc_id"), ["lang", "-n_chars", "doc_id"], ["doc_id"], STD).rows
    return placed.select("doc_id", "pos").join(t.select("doc_id", "source", F.md5("text").alias("text_md5")), "doc_id")


def _sizes(spark: SparkSession, d: str) -> DataFrame:
    """Sizes around the boundaries: 0, 1, a block, memory, the base case, and beyond."""
    mp = MachineParams(64, 8, 8, 4)
    o = table(spark, d, "orders").select("o_orderkey", "o_totalprice")
    ranked = o.withColumn("r", F.row_number().over(W.orderBy("o_orderkey")))
    out = None
    for n in (0, 1, mp.B - 1, mp.B, mp.B + 1, mp.M, mp.M + 1, mp.k * mp.M, mp.k * mp.M + 1, 3 * mp.k * mp.M + 5):
        rows = sort.em_sample(ranked.where(F.col("r") <= n).drop("r"), ["o_totalprice", "o_orderkey"], ["o_orderkey"], mp).rows
        part = rows.agg(F.lit(n).alias("n"), F.count(F.lit(1)).alias("rows"), F.coalesce(F.sum(F.col("pos") * (F.col("o_orderkey") % 1000)), F.lit(0)).cast("long").alias("mark"))
        out = part if out is None else out.unionByName(part)
    return out


_SIZES_SQL = """WITH s AS (SELECT unnest([0, 1, 7, 8, 9, 64, 65, 256, 257, 773]) AS n), o AS (SELECT *, row_number() OVER (ORDER BY o_orderkey) AS r FROM orders),
p AS (SELECT n, o_orderkey, row_number() OVER (PARTITION BY n ORDER BY o_totalprice, o_orderkey) AS pos FROM s JOIN o ON r <= n)
SELECT s.n, count(o_orderkey)::BIGINT AS rows, coalesce(sum(pos * (o_orderkey % 1000)), 0)::BIGINT AS mark FROM s LEFT JOIN p USING (n) GROUP BY s.n"""

COUNTED_SQL = f"""SELECT 'sample' AS method, phase, reads, writes FROM ({_sample_ledger_sql(STD)})
UNION ALL SELECT 'classic', phase, reads, writes FROM ({_sample_ledger_sql(CLASSIC)}) UNION ALL SELECT 'selection', 'base', reads, writes FROM ({_SELECTION_LEDGER_SQL})"""
QUERIES = {
    **{f"sort_sample_{n}": _sample(n) for n in INPUTS},
    "sort_sample_rounds": _sample("real", how="rounds"),
    "sort_sample_deterministic": _sample("real", choose="deterministic"),
    "sort_sample_classic": _sample("real", CLASSIC),
    "sort_sample_tiny": _sample("real", MachineParams(64, 8, 8, 4)),
    "sort_sample_sizes": _sizes,
    "sort_sample_late_payload": _late,
    "sort_sample_ledger": _sample_ledger(STD),
    "sort_sample_classic_ledger": _sample_ledger(CLASSIC),
    "sort_sample_parallel": _other(sort.em_sample_parallel, "real", STD),
    **{f"sort_sample_parallel_{n}": _other(sort.em_sample_parallel, n, STD) for n in ("dups", "reverse", "string")},
    **{f"sort_merge_{n}": _other(sort.em_merge, n, STD) for n in ("sorted", "reverse", "string", "segments")},
    **{f"sort_oblivious_{n}": _other(sort.co_sort, n, 4) for n in ("dups", "reverse", "string")},
    **{f"sort_heap_{n}": _other(sort.em_heap, n, HEAP) for n in ("dups", "reverse", "segments")},
    **{f"sort_pram_{n}": _other(sort.pram_sample, n, INPUTS[n][2][0]) for n in ("dups", "sorted", "segments")},
    "parallel_slots_check": _slots,
    "merge_queues_check": _queues,
    "bucket_balance_skewed": _skewed,
    "placement_group_tries_check": _tries,
    "sort_sample_parallel_time": _parallel_time,
    "splitters_evenly_spaced": _splitters_even,
    "splitters_deterministic": _splitters_deterministic,
    "bucket_balance": _bucket_balance,
    "sort_merge_real": _other(sort.em_merge, "real", STD),
    "sort_merge_dups": _other(sort.em_merge, "dups", STD),
    "sort_merge_classic": _other(sort.em_merge, "real", CLASSIC),
    "sort_merge_bound": _merge_bound,
    "merge_node_check": _merge_check("memory"),
    "merge_trace_fix": _merge_trace,
    "merge_secondary_pointers": _merge_check("secondary"),
    "sort_selection_window": _selection_window,
    "sort_selection_rounds": _selection_rounds,
    "sort_selection_ledger": _selection_ledger,
    "sort_heap_by_priority": _heap_by_priority,
    "sort_heap_global": _heap_global,
    "pq_amortised_check": _pq_amortised,
    "pq_mixed_ops": _mixed("queue"),
    "pq_ram_ops": _mixed("tree"),
    "dictionary_ops": _dictionary,
    "beta_invariant_check": _beta_check,
    "buffer_tree_check": _tree_check,
    "buffer_emptying_check": _emptying_check,
    "sort_ram_tree": _ram_tree,
    "ram_tree_writes_check": _tree_writes,
    "ram_merge_writes": _ram_merge,
    "sort_pram": _other(sort.pram_sample, "real", "l_orderkey"),
    "sort_pram_unrefined": _other(sort.pram_sample, "string", "doc_id", refine=False, place="random"),
    "placement_tries_check": _placement,
    "deterministic_split_check": _deterministic,
    "integer_sort": _integer_sort,
    "sort_oblivious": _other(sort.co_sort, "real", 4),
    "sort_oblivious_standard": _other(sort.co_sort, "real", 1),
    "sort_oblivious_check": _oblivious_check,
    "prefix_sum": _prefix,
    "merge_two_sorted": _merge_two,
    "transpose_matrix": _transpose,
}

_REAL = _order_sql("real")
_BY_PRIORITY = "SELECT o_orderpriority, o_totalprice, o_orderkey, row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice, o_orderkey)::BIGINT AS pos"
SQL = {
    **{f"sort_sample_{n}": _order_sql(n) for n in INPUTS},
    **dict.fromkeys(["sort_sample_rounds", "sort_sample_deterministic", "sort_sample_classic", "sort_sample_tiny", "sort_sample_parallel", "sort_merge_real", "sort_merge_classic", "sort_pram", "sort_oblivious", "sort_oblivious_standard"], _REAL),
    "sort_sample_sizes": _SIZES_SQL,
    "sort_sample_late_payload": "SELECT doc_id, source, md5(text) AS text_md5, row_number() OVER (ORDER BY lang, n_chars DESC, doc_id)::BIGINT AS pos FROM documents",
    "sort_sample_ledger": _sample_ledger_sql(STD),
    "sort_sample_classic_ledger": _sample_ledger_sql(CLASSIC),
    **{f"sort_{m}_{n}": _order_sql(n) for m, names in (("sample_parallel", ("dups", "reverse", "string")), ("merge", ("sorted", "reverse", "string", "segments")), ("oblivious", ("dups", "reverse", "string")), ("heap", ("dups", "reverse", "segments")), ("pram", ("dups", "sorted", "segments"))) for n in names},
    "parallel_slots_check": _ok_sql("slots"),
    "merge_queues_check": _ok_sql("merge_queues"),
    "bucket_balance_skewed": "SELECT * FROM (VALUES ('events.user_id', true, true, true), ('lineitem.l_suppkey', true, true, true), ('events.nine_tenths_one_key', true, true, true)) t(input, sampled_ok, deterministic_ok, oblivious_ok)",
    "placement_group_tries_check": _ok_sql("tries"),
    "sort_sample_parallel_time": _PARALLEL_TIME_SQL,
    "splitters_evenly_spaced": f"WITH {_CUTS_SQL} SELECT i::BIGINT AS i, {', '.join(REAL)} FROM c",
    "splitters_deterministic": "SELECT o_totalprice, o_orderkey FROM (SELECT *, row_number() OVER (ORDER BY o_totalprice, o_orderkey) AS r FROM (SELECT *, row_number() OVER (PARTITION BY o_orderkey % 10 ORDER BY o_totalprice, o_orderkey) AS i FROM orders) WHERE i % 10 = 0) WHERE r % 20 = 0",
    "bucket_balance": f"SELECT {FAN}::BIGINT AS buckets, true AS ok",
    "sort_merge_dups": _order_sql("dups"),
    "sort_merge_bound": _ok_sql("mergesort"),
    "merge_node_check": _ok_sql("merge"),
    "merge_trace_fix": _MERGE_TRACE_SQL,
    "merge_secondary_pointers": _ok_sql("merge_secondary_pointers"),
    "sort_selection_window": f"{_BY_PRIORITY}, ((row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice, o_orderkey) - 1) // {SEL.M})::BIGINT AS rnd FROM orders",
    "sort_selection_rounds": "SELECT s_acctbal, s_suppkey, row_number() OVER (ORDER BY s_acctbal, s_suppkey)::BIGINT AS pos, ((row_number() OVER (ORDER BY s_acctbal, s_suppkey) - 1) // 64)::BIGINT AS rnd FROM supplier",
    "sort_selection_ledger": _SELECTION_LEDGER_SQL,
    "sort_heap_by_priority": f"{_BY_PRIORITY} FROM orders",
    "sort_heap_global": "SELECT o_totalprice, o_orderkey, row_number() OVER (ORDER BY o_totalprice, o_orderkey)::BIGINT AS pos FROM orders",
    "pq_amortised_check": _ok_sql("queue"),
    "dictionary_ops": _DICTIONARY_SQL,
    "beta_invariant_check": _ok_sql("beta"),
    "buffer_tree_check": _ok_sql("buffer_tree"),
    "buffer_emptying_check": _ok_sql("emptying"),
    "sort_ram_tree": f"{_BY_PRIORITY} FROM orders",
    "ram_tree_writes_check": _ok_sql("ram_tree"),
    "sort_pram_unrefined": _order_sql("string"),
    "placement_tries_check": _ok_sql("placement"),
    "deterministic_split_check": _ok_sql("deterministic_split"),
    "integer_sort": "SELECT p_partkey, p_size, row_number() OVER (ORDER BY p_size, p_partkey)::BIGINT AS pos FROM part",
    "sort_oblivious_check": _ok_sql("oblivious"),
    "prefix_sum": "SELECT o_orderkey, round(o_totalprice * 100)::BIGINT AS cents, sum(round(o_totalprice * 100)::BIGINT) OVER (ORDER BY o_orderkey)::BIGINT AS running FROM orders",
    "merge_two_sorted": _MERGE_TWO_SQL,
    "transpose_matrix": "SELECT l_suppkey % 16 AS i, l_partkey % 16 AS j, sum(l_quantity::BIGINT)::BIGINT AS v, ((l_suppkey % 16) * 16 + l_partkey % 16)::BIGINT AS place FROM lineitem GROUP BY 1, 2",
}
SQL["ram_merge_writes"] = "SELECT o_orderpriority, n::BIGINT AS n, (n * list_filter(range(0, 63), lambda t: pow(2, t) >= n)[1])::BIGINT AS writes FROM (SELECT o_orderpriority, count(*) AS n FROM orders GROUP BY o_orderpriority)"
