"""Planner, bounds, devices, caches, transforms and products over the given tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from writelite.functions import bounds, metrics, model
from writelite.functions.model import MachineParams
from writelite.operators import linalg, pq, simulate, spectral
from writelite.plans import planner
from writelite.workloads import sorting
from writelite.workloads.sorting import _check, _ok_sql, table

SETTINGS = [(64, 8, 4), (64, 8, 8), (64, 8, 16), (64, 8, 40), (256, 16, 4), (256, 16, 8), (256, 16, 16), (256, 16, 40), (1024, 32, 4), (1024, 32, 8), (1024, 32, 16), (1024, 32, 40)]


def _k_table(spark: SparkSession, d: str) -> DataFrame:
    n = table(spark, d, "lineitem").agg(F.count(F.lit(1)).alias("n"))
    return planner.k_table(spark, n, SETTINGS)


def _choose(spark: SparkSession, d: str) -> DataFrame:
    return _k_table(spark, d).where("best").select("n", "M", "B", "omega", "k", "levels", "cost")


def _k_range(spark: SparkSession, d: str) -> DataFrame:
    """How many k of 2..omega beat the classic mergesort, and the saving of the best."""
    t = _k_table(spark, d)
    classic = F.max(F.when(F.col("k") == 1, F.col("cost"))).over(W.partitionBy("M", "B", "omega"))
    t = t.withColumn("classic", classic)
    return t.groupBy("n", "M", "B", "omega").agg(F.sum(((F.col("k") > 1) & (F.col("cost") < F.col("classic"))).cast("long")).alias("good"), F.max("classic").alias("classic"), F.min("cost").alias("best_cost"))


def _sweep(spark: SparkSession, d: str) -> DataFrame:
    return _k_table(spark, d).where((F.col("M") == 256) & (F.col("omega") == 16)).select("k", "levels", "cost")


_GRID = f"""g AS (SELECT M, B, omega, unnest(range(1, omega + 1)) AS k FROM (VALUES {', '.join(map(str, SETTINGS))}) t(M, B, omega)),
f AS (SELECT (SELECT count(*) FROM lineitem) AS n, M::BIGINT AS M, B::BIGINT AS B, omega::BIGINT AS omega, k::BIGINT AS k, greatest(2, k * M // B) AS fan FROM g),
l AS (SELECT *, (n + B - 1) // B AS nb, list_filter(range(1, 64), lambda t: pow(fan, t) >= (n + B - 1) // B)[1]::BIGINT AS levels FROM f),
t AS (SELECT n, M, B, omega, k, levels, ((CASE WHEN k = 1 THEN omega + 1 ELSE omega + k + 1 END) * nb * levels)::BIGINT AS cost FROM l),
r AS (SELECT *, row_number() OVER (PARTITION BY M, B, omega ORDER BY cost, k) = 1 AS best FROM t)"""


def _bounds_table(spark: SparkSession, d: str) -> DataFrame:
    """Blocks, levels and bounds of each sort of lineitem at the default machine."""
    n = table(spark, d, "lineitem").count()
    mp = model.STD
    rows = [("classic", *(bounds.mergesort_io(n, mp.with_k(1)))), ("mergesort", *bounds.mergesort_io(n, mp)), ("merge", *bounds.merge_io(n, mp)), ("base", *bounds.base_io(mp.k * mp.M, mp))]
    return spark.createDataFrame(rows, "method string, reads long, writes long")


_M, _B, _K = model.STD.M, model.STD.B, model.STD.k
_NB = f"(((SELECT count(*) FROM lineitem) + {_B - 1}) // {_B})"
_LEV = lambda k: f"(SELECT min(t) FROM range(1, 64) r(t) WHERE pow({k * _M // _B}, t) >= {_NB})"
_BOUNDS_SQL = f"""SELECT 'classic' AS method, ({_NB} * {_LEV(1)})::BIGINT AS reads, ({_NB} * {_LEV(1)})::BIGINT AS writes
UNION ALL SELECT 'mergesort', ({_K + 1} * {_NB} * {_LEV(_K)})::BIGINT, ({_NB} * {_LEV(_K)})::BIGINT
UNION ALL SELECT 'merge', ({_K + 1} * {_NB})::BIGINT, {_NB}::BIGINT
UNION ALL SELECT 'base', ({_K} * ({_K * _M} // {_B}))::BIGINT, ({_K * _M} // {_B})::BIGINT"""


def counted(spark: SparkSession, d: str, name: str, column: str) -> DataFrame:
    """(n): values of a column of a table."""
    return table(spark, d, name).agg(F.count(column).alias("n"))


def _devices(spark: SparkSession, d: str) -> DataFrame:
    """Devices, and what one read and one write of all blocks of lineitem's prices cost on them, in units of a read."""
    nb = F.ceil(F.col("n") / model.STD.B)
    return model.device_presets(spark).crossJoin(counted(spark, d, "lineitem", "l_extendedprice")).withColumn("rewrite", (nb * (1 + F.col("omega"))).cast("long")).drop("n")


_DEVICES = ", ".join(f"('{a}', {b!r}::DOUBLE, {c!r}::DOUBLE, '{u}', '{k}')" for a, b, c, u, k in model.DEVICES)
_DEVICES_SQL = f'SELECT device, "read", "write", unit, kind, round("write" / "read")::BIGINT AS omega FROM (VALUES {_DEVICES}) t(device, "read", "write", unit, kind)'


def _device_cost(spark: SparkSession, d: str) -> DataFrame:
    """Counted reads and writes of one level of the sample sort of lineitem and its base case, write-saving and classic
    (k = 1), in read units of each device.
    """
    led = sorting.counted_ledgers(spark, d).groupBy("method").agg(F.sum("reads").alias("reads"), F.sum("writes").alias("writes"))
    p = model.device_presets(spark).select("device", "omega")
    return led.where("method <> 'selection'").crossJoin(F.broadcast(p)).select("device", "method", (F.col("reads") + F.col("writes") * F.col("omega")).cast("long").alias("cost"))


_PRICED_SQL = f"SELECT *, (((SELECT count(l_extendedprice) FROM lineitem) + {model.STD.B - 1}) // {model.STD.B} * (1 + omega))::BIGINT AS rewrite FROM ({_DEVICES_SQL})"
_DEVICE_COST_SQL = f"WITH l AS ({sorting.COUNTED_SQL}), p AS ({_DEVICES_SQL}) SELECT device, method, sum(reads + writes * omega)::BIGINT AS cost FROM l, p WHERE method <> 'selection' GROUP BY device, method"
_NBO = "(((SELECT count(*) FROM orders) + 15) // 16)"
_LEVO = lambda f: f"(SELECT min(t) FROM range(1, 64) r(t) WHERE pow({f}, t) >= {_NBO})"

# Caches: events as an instruction trace, one shard a user.

CACHE = MachineParams(32, 4, 8, 1)


def trace(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "events")
    op = F.when(F.col("event_type").isin("view", "click"), "R").otherwise("W")
    return e.select(F.col("user_id").alias("shard"), F.col("event_id").alias("seq"), op.alias("op"), F.floor(F.get_json_object("props", "$.k").cast("long") / 4).cast("long").alias("block"))


def rw_lru_cost(t: DataFrame, cap: int, omega: int) -> DataFrame:
    """(shard, reads missed, writes missed, cost) of the two-pool LRU without any state.

    The pools are LRUs over reads alone and writes alone; an access hits if fewer than cap other blocks were accessed by
    the same operation since its last one, which is a count of distinct blocks between two places.
    """
    w = W.partitionBy("shard", "op").orderBy("seq")
    seq = t.withColumn("i", F.row_number().over(w)).withColumn("last", F.lag("i").over(W.partitionBy("shard", "op", "block").orderBy("i")))
    a, b = seq.alias("a"), seq.select("shard", "op", "block", "i").alias("b")
    near = a.join(b, (F.col("a.shard") == F.col("b.shard")) & (F.col("a.op") == F.col("b.op")) & (F.col("b.i") > F.col("a.last")) & (F.col("b.i") < F.col("a.i")), "left")
    dist = near.groupBy("a.shard", "a.op", "a.i", "a.last").agg(F.count_distinct("b.block").alias("between"))
    miss = (F.col("last").isNull() | (F.col("between") >= cap)).cast("long")
    per = dist.withColumn("miss", miss).groupBy("shard").agg(F.sum(F.when(F.col("op") == "R", F.col("miss")).otherwise(0)).alias("r"), F.sum(F.when(F.col("op") == "W", F.col("miss")).otherwise(0)).alias("w"))
    return per.select("shard", F.col("r").alias("read_misses"), F.col("w").alias("write_misses"), (F.greatest(F.col("r") - cap, F.lit(0)) + (1 + omega) * F.greatest(F.col("w") - cap, F.lit(0))).cast("long").alias("cost"))


_TRACE_SQL = "t AS (SELECT user_id AS shard, event_id AS seq, CASE WHEN event_type IN ('view', 'click') THEN 'R' ELSE 'W' END AS op, (props->>'$.k')::BIGINT // 4 AS block FROM events)"
_RW_SQL = f"""WITH {_TRACE_SQL}, s AS (SELECT *, row_number() OVER (PARTITION BY shard, op ORDER BY seq) AS i FROM t),
q AS (SELECT *, lag(i) OVER (PARTITION BY shard, op, block ORDER BY i) AS last FROM s),
m AS (SELECT shard, op, (last IS NULL OR (SELECT count(DISTINCT b.block) FROM s b WHERE b.shard = q.shard AND b.op = q.op AND b.i > q.last AND b.i < q.i) >= 8)::INT AS miss FROM q),
p AS (SELECT shard, sum(CASE WHEN op = 'R' THEN miss ELSE 0 END) AS r, sum(CASE WHEN op = 'W' THEN miss ELSE 0 END) AS w FROM m GROUP BY shard)
SELECT shard, r::BIGINT AS read_misses, w::BIGINT AS write_misses, (greatest(r - 8, 0) + 9 * greatest(w - 8, 0))::BIGINT AS cost FROM p"""
_LRU_SQL = f"""WITH {_TRACE_SQL}, s AS (SELECT *, row_number() OVER (PARTITION BY shard ORDER BY seq) AS i FROM t),
q AS (SELECT *, lag(i) OVER (PARTITION BY shard, block ORDER BY i) AS last FROM s),
m AS (SELECT shard, (last IS NULL OR (SELECT count(DISTINCT b.block) FROM s b WHERE b.shard = q.shard AND b.i > q.last AND b.i < q.i) >= 8)::INT AS miss FROM q)
SELECT shard, sum(miss)::BIGINT AS misses, sum(miss)::BIGINT AS cost FROM m GROUP BY shard"""


def windows(accesses: list, width: int = 14) -> list[list]:
    """A trace as a whole, and its consecutive windows."""
    return [accesses, *(accesses[i : i + width] for i in range(0, len(accesses), width))]


def _competitive(spark: SparkSession, d: str) -> DataFrame:
    """The two-pool LRU of pools twice as large stays within its lemma of the optimum, over the trace of every user and its windows."""
    import pandas as pd

    def go(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("seq")
        small, large, omega = 2, 4, 8
        ok, parts = True, windows([(op, int(b)) for op, b in zip(pdf.op, pdf.block, strict=True)])
        for t in parts:
            best = simulate.ideal_cost(t, small, omega)
            _, cost = simulate.cache(t, large, omega, "rw_lru")
            ok &= cost <= bounds.rw_lru_bound(best, small, large, omega, 1) + 1e-9
        return pd.DataFrame([(int(pdf.shard.iloc[0]), ok)], columns=["shard", "ok"])

    return _check("rw_lru", trace(spark, d).groupBy("shard").applyInPandas(go, "shard long, ok boolean").where("NOT ok"))


def _parallel_table(spark: SparkSession, d: str) -> DataFrame:
    """(omega w + r) / p + depth of the PRAM sort of orders."""
    n = table(spark, d, "orders").agg(F.count(F.lit(1)).alias("n"))
    p = spark.createDataFrame([(1,), (16,), (256,)], "p long")
    log = F.ceil(F.log2("n"))
    return n.crossJoin(p).select("p", F.floor((8 * 4 * F.col("n") + F.col("n") * log) / F.col("p") + 8 * log).cast("long").alias("time"))


_PARALLEL_SQL = "SELECT p::BIGINT AS p, floor((32 * n + n * ceil(log2(n))) / p + 8 * ceil(log2(n)))::BIGINT AS time FROM (SELECT count(*) AS n FROM orders), (VALUES (1), (16), (256)) t(p)"


def _stealing(spark: SparkSession, d: str) -> DataFrame:
    q1 = bounds.mergesort_cost(table(spark, d, "orders").count(), model.STD)
    rows = [(p, int(bounds.work_stealing(q1, MachineParams(256, 16, 8, 4, p, 100)))) for p in (1, 8, 64)]
    return spark.createDataFrame(rows, "p long, bound long")


def _depth_first(spark: SparkSession, d: str) -> DataFrame:
    q1 = bounds.mergesort_cost(table(spark, d, "orders").count(), model.STD)
    rows = [(p, *map(int, bounds.pdf_shared(q1, MachineParams(256, 16, 8, 4, p, 100)))) for p in (1, 8, 64)]
    return spark.createDataFrame(rows, "p long, bound long, cache long")


_Q1 = f"(13 * {_NBO} * {_LEVO(64)})"


def _rollup(spark: SparkSession, d: str) -> DataFrame:
    """Counted ledgers of three methods rolled up by method and phase."""
    out = sorting.counted_ledgers(spark, d).rollup("method", "phase").agg(F.sum("reads").cast("long").alias("reads"), F.sum("writes").cast("long").alias("writes"))
    return out.withColumn("cost", model.cost(8))


_ROLLUP_SQL = f"SELECT method, phase, sum(reads)::BIGINT AS reads, sum(writes)::BIGINT AS writes, sum(reads + 8 * writes)::BIGINT AS cost FROM ({sorting.COUNTED_SQL}) GROUP BY ROLLUP (method, phase)"

# Transforms.


def signal(spark: SparkSession, d: str, n: int) -> DataFrame:
    e = table(spark, d, "events")
    return e.groupBy((F.col("event_id") % n).alias("idx")).agg(F.sum(F.round(F.col("value") * 100).cast("long")).alias("re")).withColumn("im", F.lit(0).cast("long"))


def _rounded(df: DataFrame, digits: int = 2) -> DataFrame:
    return df.select(*[c for c in df.columns if c not in ("re", "im")], (F.round("re", digits) + 0.0).alias("re"), (F.round("im", digits) + 0.0).alias("im"))


def _fft(n: int, omega: int):
    return lambda spark, d: _rounded(spectral.fft(signal(spark, d, n), n, omega))


def _dft_sql(n: int) -> str:
    return f"""WITH s AS (SELECT event_id % {n} AS idx, sum(round(value * 100)::BIGINT) AS re FROM events GROUP BY 1)
SELECT k::BIGINT AS idx, round(sum(re * cos(-2 * pi() / {n} * ((k * idx) % {n}))), 2) + 0.0 AS re, round(sum(re * sin(-2 * pi() / {n} * ((k * idx) % {n}))), 2) + 0.0 AS im FROM s, range(0, {n}) t(k) GROUP BY k"""


def _fft_embeddings(spark: SparkSession, d: str) -> DataFrame:
    cells = table(spark, d, "embeddings").select("vec_id", F.posexplode("embedding").alias("idx", "x")).select("vec_id", F.col("idx").cast("long").alias("idx"), F.round(F.col("x").cast("double") * 1000).alias("re"))
    return _rounded(spectral.fft_groups(cells, "vec_id", 64, 4))


_FFT_EMBEDDINGS_SQL = """WITH s AS (SELECT vec_id, unnest(range(0, 64)) AS idx, unnest(list_transform(embedding, lambda x: round(x::DOUBLE * 1000))) AS re FROM embeddings)
SELECT vec_id, k::BIGINT AS idx, round(sum(re * cos(-2 * pi() / 64 * ((k * idx) % 64))), 2) + 0.0 AS re, round(sum(re * sin(-2 * pi() / 64 * ((k * idx) % 64))), 2) + 0.0 AS im FROM s, range(0, 64) t(k) GROUP BY vec_id, k"""


def _roundtrip(spark: SparkSession, d: str) -> DataFrame:
    back = spectral.ifft(spectral.fft(signal(spark, d, 256), 256, 4), 256, 4)
    return back.select("idx", F.round("re").cast("long").alias("re"))


def _parseval(spark: SparkSession, d: str) -> DataFrame:
    s = signal(spark, d, 256)
    a = spectral.energy(s.select(F.col("re").cast("double"), F.col("im").cast("double"))).withColumnRenamed("energy", "a")
    b = spectral.energy(spectral.fft(s, 256, 4)).withColumnRenamed("energy", "b")
    return _check("parseval", a.crossJoin(b).where(F.abs(F.col("b") / 256 - F.col("a")) > 1e-9 * F.col("a")))


def _fft_accuracy(spark: SparkSession, d: str) -> DataFrame:
    """Largest absolute error against the brute-force transform, relative to the largest value."""
    s = signal(spark, d, 1024)
    a, b = spectral.fft(s, 1024, 4), spectral.dft_bruteforce(s, 1024).select("idx", F.col("re").alias("r"), F.col("im").alias("i"))
    e = a.join(b, "idx").agg(F.max(F.abs(F.col("re") - F.col("r")) + F.abs(F.col("im") - F.col("i"))).alias("e"), F.max(F.abs("r")).alias("m"))
    return _check("fft_accuracy", e.where(F.col("e") > 1e-10 * F.col("m")))


def _ntt(spark: SparkSession, d: str) -> DataFrame:
    return spectral.ntt(signal(spark, d, 64).select("idx", F.col("re").alias("v")), 64)


_ROOT = pow(spectral.GENERATOR, (spectral.PRIME - 1) // 64, spectral.PRIME)
_NTT_SQL = f"""WITH RECURSIVE w(e, r) AS (SELECT 0, 1::BIGINT UNION ALL SELECT e + 1, r * {_ROOT} % {spectral.PRIME} FROM w WHERE e < 63),
s AS (SELECT event_id % 64 AS idx, sum(round(value * 100)::BIGINT)::BIGINT AS v FROM events GROUP BY 1)
SELECT k::BIGINT AS idx, (sum((v % {spectral.PRIME}) * r % {spectral.PRIME}) % {spectral.PRIME})::BIGINT AS v FROM s, range(0, 64) t(k), w WHERE w.e = (k * idx) % 64 GROUP BY k"""


def power_of_two(n: int) -> int:
    """The least that is at least n."""
    return 1 << max(0, n - 1).bit_length()


def _fft_ledger(spark: SparkSession, d: str) -> DataFrame:
    """Reads and writes of transforms of the values of events, sampled 4, 64 and 1024 times as often (and filled up to a
    power of two): standard, write-saving, and with fused steps.
    """
    parts, least = [], power_of_two(counted(spark, d, "events", "value").first()["n"])
    for n in (4 * least, 64 * least, 1024 * least):
        for name, omega, fuse in (("standard", 1, False), ("saving", 16, False), ("fused", 16, True)):
            led = spectral.ledger(spark, n, 256, 16, omega, fuse)
            parts.append(led.agg(F.sum("reads").cast("long").alias("reads"), F.sum("writes").cast("long").alias("writes")).select(F.lit(n).cast("long").alias("n"), F.lit(name).alias("form"), "reads", "writes"))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def _fft_fused(spark: SparkSession, d: str) -> DataFrame:
    """Fused steps write less: in the ledger at every length, and in rows that Spark itself shuffles for 1024 values."""
    led = _fft_ledger(spark, d).groupBy("n").pivot("form", ["standard", "saving", "fused"]).agg(F.first("writes"))
    s = signal(spark, d, 1024)
    moved = [metrics.io_of(spark, lambda f=f: spectral.fft(s, 1024, 16, fuse=f).write.format("noop").mode("overwrite").save())["records"] for f in (True, False)]
    return _check("fft_fused", led.where(F.lit(moved[0] >= moved[1]) | (F.col("fused") >= F.col("saving"))))


# Products.


def matrices(spark: SparkSession, d: str, n: int) -> tuple[DataFrame, DataFrame]:
    ln = table(spark, d, "lineitem")
    cell = lambda i, j: ln.groupBy((F.col(i) % n).alias("i"), (F.col(j) % n).alias("j")).agg(F.sum(F.col("l_quantity").cast("long")).alias("v"))
    return cell("l_partkey", "l_suppkey"), cell("l_suppkey", "l_partkey")


def _product(method, n: int, *args, **how):
    return lambda spark, d: method(*matrices(spark, d, n), *args, **how)


def _product_sql(n: int) -> str:
    return f"""WITH a AS (SELECT l_partkey % {n} AS i, l_suppkey % {n} AS j, sum(l_quantity::BIGINT) AS v FROM lineitem GROUP BY 1, 2),
b AS (SELECT l_suppkey % {n} AS i, l_partkey % {n} AS j, sum(l_quantity::BIGINT) AS v FROM lineitem GROUP BY 1, 2)
SELECT a.i, b.j, sum(a.v * b.v)::BIGINT AS v FROM a JOIN b ON a.j = b.i GROUP BY a.i, b.j"""


def rounded(name: str) -> Column:
    """A double to six places, a tie away from zero, as DuckDB counts it: by arithmetic, as `round` makes a decimal number of
    each value, which costs more than all else on a table of pairs. Values whose millionths a double does not hold go there.
    """
    t = F.abs(name) * 1e6
    r = F.rint(t)
    up = F.when(t - r == 0.5, r + 1).otherwise(r) / 1e6
    return F.when(F.abs(name) < 1e9, F.when(F.col(name) < 0, -up).otherwise(up)).otherwise(F.round(name, 6))


def _gram(spark: SparkSession, d: str) -> DataFrame:
    g = linalg.gram(table(spark, d, "embeddings"), "vec_id", "embedding")
    return g.select("i", "j", (rounded("v") + 0.0).alias("v"))


_GRAM_SQL = """WITH e AS (SELECT vec_id, unnest(range(0, 64)) AS d, unnest(embedding)::DOUBLE AS x FROM embeddings)
SELECT a.vec_id AS i, b.vec_id AS j, round(sum(a.x * b.x), 6) + 0.0 AS v FROM e a JOIN e b USING (d) GROUP BY a.vec_id, b.vec_id"""


def _sides(spark: SparkSession, d: str) -> list[int]:
    """4, 8, 16 and 32 times the side of the least matrix of a power of two that takes the quantities of lineitem."""
    n = counted(spark, d, "lineitem", "l_quantity").first()["n"]
    side = next(1 << t for t in range(64) if 4**t >= n)
    return [f * side for f in (4, 8, 16, 32)]


def _product_ledger(spark: SparkSession, d: str) -> DataFrame:
    """Base products of the recursion for the sides that lineitem gives by first split, M = 1024, B = 16, omega = 8."""
    rows = []
    for n in _sides(spark, d):
        for first in (1, 2, 4, 8):
            led = linalg.ledger_rows(n, 1024, 16, 8, first)
            rows.append((n, first, sum(r[5] for r in led), sum(r[6] for r in led)))
    return spark.createDataFrame(rows, "n long, first long, reads long, writes long")


def _expected(spark: SparkSession, d: str) -> DataFrame:
    """Expected reads and writes over those of the standard algorithm, rounded."""
    rows, sides = [], _sides(spark, d)
    for omega in (4, 8, 16):
        for n in sides:
            r, w = bounds.matmul_recurrence(n, 1024, omega)
            std = n**3 / 32
            rows.append((omega, n, round(w / std, 3), round(r / std, 3), round((omega * w + r) / ((omega + 2) * std), 3)))
    return spark.createDataFrame(rows, "omega long, n long, writes double, reads double, cost double")


_PRODUCT_LEDGER_SQL = """WITH RECURSIVE a AS (SELECT f * (SELECT min(1::BIGINT << t) FROM range(0, 31) r(t) WHERE pow(4, t) >= (SELECT count(l_quantity) FROM lineitem)) AS n FROM (VALUES (4), (8), (16), (32)) s(f)),
g AS (SELECT n, first, n AS size, 1::HUGEINT AS cnt, 0 AS level FROM a, (VALUES (1), (2), (4), (8)) b(first)
UNION ALL SELECT n, first, (size + f - 1) // f, cnt * f * f * f, level + 1 FROM (SELECT *, CASE WHEN level = 0 AND first > 1 THEN first ELSE 8 END AS f FROM g WHERE size > 256))
SELECT n::BIGINT AS n, first::BIGINT AS first, (cnt * 16 * ((size * size + 15) // 16))::BIGINT AS reads, (cnt * ((size * size + 15) // 16))::BIGINT AS writes FROM g WHERE size <= 256"""



def _pram(spark: SparkSession, d: str) -> DataFrame:
    """Bounds of the PRAM sort of orders and of the deterministic sorts whose depth it matches."""
    n = table(spark, d, "orders").count()
    rows = [(name, *map(round, f(n, 8))) for name, f in (("write_saving", bounds.pram_sort), ("matching_depth", bounds.pram_sort_matching))]
    return spark.createDataFrame(rows, "method string, reads long, writes long, depth long")


_PRAM_SQL = "SELECT method, round(n * log2(n))::BIGINT AS reads, round(CASE WHEN method = 'write_saving' THEN n ELSE n * log2(n) END)::BIGINT AS writes, round(8 * log2(n))::BIGINT AS depth FROM (SELECT count(*) AS n FROM orders), (VALUES ('write_saving'), ('matching_depth')) t(method)"


def _condition(spark: SparkSession, d: str) -> DataFrame:
    """How many k of 2..omega meet the rule k / log k < (omega + 1) / log(M/B), which leaves ceilings out, and how many
    beat the classic mergesort of lineitem, where ceilings count.
    """
    rows = [(M, B, omega, sum(planner.k_condition(k, MachineParams(M, B, omega)) for k in range(2, omega + 1))) for M, B, omega in SETTINGS]
    rule = spark.createDataFrame(rows, "M long, B long, omega long, good long")
    t = planner.k_table(spark, counted(spark, d, "lineitem", "l_extendedprice"), SETTINGS)
    t = t.withColumn("classic", F.max(F.when(F.col("k") == 1, F.col("cost"))).over(W.partitionBy("M", "B", "omega")))
    cheaper = t.groupBy("M", "B", "omega").agg(F.sum(((F.col("k") > 1) & (F.col("cost") < F.col("classic"))).cast("long")).alias("cheaper"))
    return rule.join(F.broadcast(cheaper), ["M", "B", "omega"])


_CONDITION_SQL = f"WITH g AS (SELECT M, B, omega, unnest(range(2, omega + 1)) AS k FROM (VALUES {', '.join(map(str, SETTINGS))}) t(M, B, omega)) SELECT M::BIGINT AS M, B::BIGINT AS B, omega::BIGINT AS omega, sum((k / ln(k) < (omega + 1) / ln(M / B))::INT)::BIGINT AS good FROM g GROUP BY M, B, omega"


def _tall(spark: SparkSession, d: str) -> DataFrame:
    """Which of the planner's machines have a tall cache, M at least B^2, and the blocks that lineitem's prices take on them."""
    shapes = spark.createDataFrame([(M, B, bounds.tall_cache(MachineParams(M, B, omega))) for M, B, omega in SETTINGS if omega == 4], "M long, B long, tall boolean")
    return shapes.crossJoin(counted(spark, d, "lineitem", "l_extendedprice")).withColumn("blocks", F.ceil(F.col("n") / F.col("B")).cast("long")).drop("n")


_TALL_SQL = "SELECT M::BIGINT AS M, B::BIGINT AS B, M >= B * B AS tall, (((SELECT count(l_extendedprice) FROM lineitem) + B - 1) // B)::BIGINT AS blocks FROM (VALUES (64, 8), (256, 16), (1024, 32)) t(M, B)"

QUERIES = {
    "choose_k": _choose, "k_range_table": _k_range, "k_sweep_cost": _sweep, "bounds_table": _bounds_table, "device_presets": _devices, "device_cost": _device_cost,
    "cache_rw_lru_cost": lambda spark, d: rw_lru_cost(trace(spark, d), CACHE.M // CACHE.B, CACHE.omega),
    "cache_rw_lru_simulated": lambda spark, d: pq.cache_run(trace(spark, d), CACHE, "rw_lru").select("shard", "cost"),
    "cache_lru_cost": lambda spark, d: pq.cache_run(trace(spark, d), CACHE, "lru").select("shard", "misses", "cost"),
    "cache_lru_dirty": lambda spark, d: pq.cache_run(trace(spark, d), CACHE, "lru_dirty"),
    "cache_opt_misses": lambda spark, d: pq.cache_run(trace(spark, d), CACHE, "opt"),
    "cache_competitive_check": _competitive, "parallel_time_table": _parallel_table, "work_stealing_bound": _stealing, "depth_first_bound": _depth_first, "cost_rollup": _rollup,
    "fft_64": _fft(64, 4), "fft_256": _fft(256, 4), "fft_1024": _fft(1024, 16), "fft_nonsquare_128": _fft(128, 4), "fft_embeddings": _fft_embeddings,
    "fft_unfused": lambda spark, d: _rounded(spectral.fft(signal(spark, d, 256), 256, 4, fuse=False)),
    "fft_standard": lambda spark, d: _rounded(spectral.fft_standard(signal(spark, d, 256), 256)), "dft_bruteforce": lambda spark, d: _rounded(spectral.dft_bruteforce(signal(spark, d, 256), 256)),
    "ntt_exact": _ntt, "fft_inverse_roundtrip": _roundtrip, "fft_parseval_check": _parseval, "fft_accuracy_check": _fft_accuracy, "fft_fused": _fft_fused, "fft_ledger": _fft_ledger,
    "matmul_naive": _product(linalg.matmul_naive, 64), "matmul_blocked": _product(linalg.matmul_blocked, 64, 16), "matmul_strips": _product(linalg.matmul_blocked, 64, 32, how="strips"),
    "matmul_replicated": _product(linalg.matmul_blocked, 64, 16, how="replicate"), "matmul_oblivious": _product(linalg.matmul_co, 64, 64, 4, 64), "matmul_quadrant": _product(linalg.matmul_quadrant, 64, 64, 1),
    "matmul_blocked_128": _product(linalg.matmul_blocked, 128, 32), "matmul_oblivious_256": _product(linalg.matmul_co, 256, 256, 8, 256),
    "gram_matrix": _gram, "tall_cache_table": _tall, "pram_bounds_table": _pram, "k_condition_table": _condition, "matmul_ledger": _product_ledger, "matmul_expected_cost": _expected,
}

SQL = {
    "choose_k": f"WITH {_GRID} SELECT n, M, B, omega, k, levels, cost FROM r WHERE best",
    "k_range_table": f"WITH {_GRID}, c AS (SELECT *, max(CASE WHEN k = 1 THEN cost END) OVER (PARTITION BY M, B, omega) AS classic FROM r) SELECT n, M, B, omega, sum((k > 1 AND cost < classic)::INT)::BIGINT AS good, max(classic) AS classic, min(cost) AS best_cost FROM c GROUP BY n, M, B, omega",
    "k_sweep_cost": f"WITH {_GRID} SELECT k, levels, cost FROM r WHERE M = 256 AND omega = 16",
    "bounds_table": _BOUNDS_SQL, "device_presets": _PRICED_SQL, "device_cost": _DEVICE_COST_SQL,
    "cache_rw_lru_cost": _RW_SQL, "cache_rw_lru_simulated": f"SELECT shard, cost FROM ({_RW_SQL})", "cache_lru_cost": _LRU_SQL,
    "cache_competitive_check": _ok_sql("rw_lru"), "parallel_time_table": _PARALLEL_SQL,
    "work_stealing_bound": f"SELECT p::BIGINT AS p, ({_Q1} + p * 8 * 100 * 16)::BIGINT AS bound FROM (VALUES (1), (8), (64)) t(p)",
    "depth_first_bound": f"SELECT p::BIGINT AS p, {_Q1}::BIGINT AS bound, (256 + p * 16 * 100)::BIGINT AS cache FROM (VALUES (1), (8), (64)) t(p)",
    "cost_rollup": _ROLLUP_SQL,
    "fft_64": _dft_sql(64), "fft_256": _dft_sql(256), "fft_1024": _dft_sql(1024), "fft_nonsquare_128": _dft_sql(128), "fft_embeddings": _FFT_EMBEDDINGS_SQL, "fft_standard": _dft_sql(256), "fft_unfused": _dft_sql(256), "dft_bruteforce": _dft_sql(256),
    "ntt_exact": _NTT_SQL, "fft_inverse_roundtrip": "SELECT event_id % 256 AS idx, sum(round(value * 100)::BIGINT)::BIGINT AS re FROM events GROUP BY 1",
    "fft_parseval_check": _ok_sql("parseval"), "fft_accuracy_check": _ok_sql("fft_accuracy"), "fft_fused": _ok_sql("fft_fused"),
    **dict.fromkeys(["matmul_naive", "matmul_blocked", "matmul_strips", "matmul_replicated", "matmul_oblivious", "matmul_quadrant"], _product_sql(64)),
    "matmul_blocked_128": _product_sql(128), "matmul_oblivious_256": _product_sql(256),
    "gram_matrix": _GRAM_SQL, "tall_cache_table": _TALL_SQL, "pram_bounds_table": _PRAM_SQL, "k_condition_table": f"WITH {_GRID}, c AS (SELECT *, max(CASE WHEN k = 1 THEN cost END) OVER (PARTITION BY M, B, omega) AS classic FROM r), h AS (SELECT M, B, omega, sum((k > 1 AND cost < classic)::INT)::BIGINT AS cheaper FROM c GROUP BY M, B, omega) SELECT M, B, omega, good, cheaper FROM ({_CONDITION_SQL}) JOIN h USING (M, B, omega)", "matmul_ledger": _PRODUCT_LEDGER_SQL,
}
