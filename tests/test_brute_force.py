"""Queries that SQL does not say, against plain Python over the same tables; and sorts and bounds that must be able to fail."""

import heapq
import math
import random
from collections import defaultdict

import pytest
from oracle import SF
from pyspark.sql import functions as F

from writelite import catalog
from writelite.functions import bounds
from writelite.functions.model import STD, MachineParams
from writelite.operators import bucketing, simulate, sort
from writelite.operators.keys import SortKey, fields
from writelite.streaming import flows
from writelite.workloads import models, sorting

QUERIES = catalog.queries()


def rows(spark, name):
    return spark.read.parquet(f"{SF}/{name}.parquet").collect()


def delete_mins(events):
    """(shard, seq, value, id) of a heap of every user's events: purchases delete, others insert."""
    heaps, out = defaultdict(list), []
    for e in sorted(events, key=lambda e: e.event_id):
        h = heaps[e.user_id]
        if e.event_type == "purchase":
            out.append((e.user_id, e.event_id, *(heapq.heappop(h) if h else (None, None))))
        else:
            heapq.heappush(h, (e.value, e.event_id))
    return sorted(out, key=str)


@pytest.mark.parametrize("name", ["pq_mixed_ops", "pq_ram_ops", "stream_pq", "stream_timed_compaction"])
def test_queues_replay(spark, name):
    assert sorted((tuple(r) for r in QUERIES[name](spark, SF).collect()), key=str) == delete_mins(rows(spark, "events"))


def test_amortised_cost_rises_by_blocks(spark):
    got = QUERIES["pq_amortised_cost"](spark, SF).collect()
    assert len(got) == len(delete_mins(rows(spark, "events")))
    assert all(0 <= r.writes_per_op <= r.reads_per_op + 1 and r.reads_per_op < 4 for r in got)


def test_sessions(spark):
    """Sessions of 30 minutes that have ended before the watermark, an hour behind the last event, are told."""
    events = spark.read.parquet(f"{SF}/events.parquet").select("user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("t")).orderBy("user_id", "t").collect()
    gap, found = 1800 * 10**6, []
    for e in events:
        if found and found[-1][1] == e.user_id and e.t <= found[-1][3] + gap - 1:
            found[-1][2] += 1
            found[-1][3] = e.t
        else:
            found.append([e.t, e.user_id, 1, e.t])
    mark = max(e.t for e in events) // 1000 * 1000 - 3600 * 10**6
    want = {tuple(x[:3]) for x in found if x[3] + gap <= mark}
    got = [(r.start, r.user_id, r.cnt) for r in QUERIES["stream_session"](spark, SF).collect()]
    assert len(got) == len(set(got)) and set(got) <= {tuple(x[:3]) for x in found} and want <= set(got)


@pytest.mark.parametrize(("name", "policy"), [("cache_lru_dirty", "lru_dirty"), ("cache_opt_misses", "opt")])
def test_caches(spark, name, policy):
    """Against caches without cleverness: a list by last use, and the furthest next use by looking ahead."""
    traces = defaultdict(list)
    for r in models.trace(spark, SF).orderBy("shard", "seq").collect():
        traces[r.shard].append((r.op, r.block))
    slots, omega = models.CACHE.M // models.CACHE.B, models.CACHE.omega
    want = []
    for shard, t in traces.items():
        held, misses, clean, dirty = {}, 0, 0, 0
        for i, (op, b) in enumerate(t):
            if b not in held:
                misses += 1
                if len(held) == slots:
                    ahead = lambda x, i=i, t=t: next((j for j in range(i + 1, len(t)) if t[j][1] == x), len(t))
                    out = next(iter(held)) if policy == "lru_dirty" else max(held, key=ahead)
                    was = held.pop(out)
                    clean, dirty = clean + (not was), dirty + was
            was = held.pop(b, False)
            held[b] = was or op == "W"
        want.append((shard, misses) if policy == "opt" else (shard, misses, clean, dirty, clean + (1 + omega) * dirty))
    got = [tuple(r)[: 2 if policy == "opt" else 5] for r in QUERIES[name](spark, SF).collect()]
    assert sorted(got) == sorted(want)


def test_estimates(spark):
    items = rows(spark, "lineitem")
    parts, suppliers = len({r.l_partkey for r in items}), len({r.l_suppkey for r in items})
    got = QUERIES["agg_approx_distinct"](spark, SF).first()
    assert abs(got.parts - parts) <= 0.15 * parts and abs(got.suppliers - suppliers) <= max(1, 0.15 * suppliers)
    price = sorted(r.l_extendedprice for r in items)
    rank = lambda v: sum(p <= v for p in price) / len(price)
    for r in QUERIES["agg_percentile_approx"](spark, SF).collect():
        assert abs(rank(r.q) - 0.25 * (r.i + 1)) < 0.01
    assert abs(rank(QUERIES["agg_percentile_kll"](spark, SF).first().med) - 0.5) < 0.05


def test_samples(spark):
    events = {r.event_id: r.event_type for r in rows(spark, "events")}
    got = [r.event_id for r in QUERIES["sample_bernoulli"](spark, SF).collect()]
    assert set(got) <= set(events) and len(got) == len(set(got)) and 0.05 * len(events) < len(got) < 0.15 * len(events)
    by = defaultdict(int)
    for r in QUERIES["sample_stratified"](spark, SF).collect():
        assert events[r.event_id] == r.event_type
        by[r.event_type] += 1
    clicks, views = (sum(t == k for t in events.values()) for k in ("click", "view"))
    assert set(by) == {"click", "view"} and 0.35 * clicks < by["click"] < 0.65 * clicks and 0.02 * views < by["view"] < 0.25 * views


def test_scans(spark):
    orders = rows(spark, "orders")
    assert [r.o_orderkey for r in sorted(QUERIES["scan_row_position"](spark, SF).collect())] == [r.o_orderkey for r in orders]
    assert QUERIES["trace_source"](spark, SF).count() > 0


def test_html(spark):
    import re

    pages = {r.page_id: r.html for r in rows(spark, "pages")}
    for r in QUERIES["fn_html"](spark, SF).collect():
        bare = re.sub(r"(?is)<(script|style)[^>]*>.*?</\1>|<!--.*?-->|<[^>]*>", " ", pages[r.page_id])
        assert r.text == re.sub(r"[ \t\n\x0b\f\r]+", " ", bare).strip(" ") and not re.search(r"<\w+", r.text)


def test_transform_and_product_costs(spark):
    """The write-saving transform writes less than the standard one from some length on; expected product costs by hand."""
    led = {(r.n, r.form): (r.reads, r.writes) for r in QUERIES["fft_ledger"](spark, SF).collect()}
    n = max(k for k, _ in led)
    assert led[n, "saving"][1] < led[n, "standard"][1] and led[n, "fused"][1] < led[n, "saving"][1]
    for r in QUERIES["matmul_expected_cost"](spark, SF).collect():
        leaf = lambda size, first, omega=r.omega: (1, size) if size <= omega * 32 else (lambda c: (first**3 * c[0], c[1]))(leaf(size / first, omega))
        splits = [1] if r.n <= r.omega * 32 else [2**i for i in range(1, int(math.log2(r.omega)) + 1)]
        writes = [c * s * s for c, s in (leaf(r.n, f) for f in splits)]
        assert r.writes == pytest.approx(sum(writes) / len(writes) / (r.n**3 / 32), abs=2e-3)


def test_sort_keys_of_all_kinds(spark):
    """Nulls first and last, NaN, both zeros, descending, text, times and decimals, in one table with every sort."""
    rng = random.Random(2)
    import datetime
    import decimal

    table = []
    for i in range(700):
        x = rng.choice([None, float("nan"), 0.0, -0.0, 1.5, -2.0, float("inf"), rng.random()])
        t = None if i % 11 == 0 else datetime.datetime(2024, 3, 31, 1, 59) + datetime.timedelta(seconds=rng.randrange(7200), microseconds=rng.randrange(3))
        table.append((i, x, rng.choice([None, "a", "é", "b" * 3, ""]), t, decimal.Decimal(rng.randrange(-50, 50)) / 10, rng.choice([None, True, False])))
    df = spark.createDataFrame(table, "id long, x double, s string, t timestamp_ntz, d decimal(9,1), b boolean")
    mp = MachineParams(32, 4, 8, 4)
    for keys in (["x", "id"], ["-x", "id"], [SortKey("x", nulls_first=False), "id"], ["s", "-d", "id"], ["t", "id"], ["-t", "b", "id"], [SortKey("s", nulls_first=False), "-b", "id"]):
        struct = F.struct(*[c.alias(f"c{i}") for i, (c, _, _) in enumerate(fields(df, keys))])
        want = [r.id for r in df.orderBy(struct).select("id").collect()]
        for result in (sort.em_sample(df, keys, ["id"], mp), sort.em_merge(df, keys, ["id"], mp), sort.em_heap(df, keys, ["id"], mp), sort.co_sort(df, keys, ["id"], 4, 64)):
            got = sorted((r.pos, r.id) for r in result.rows.select("pos", "id").collect())
            assert [p for p, _ in got] == list(range(1, 701)) and [i for _, i in got] == want, keys


def test_buckets_count_the_splitters_before_a_row(spark):
    """Against a scan of all splitters: long runs of like first fields, repeated splitters, nulls and NaN among them."""
    rng = random.Random(5)
    draw = lambda: (rng.choice([None, 0.0, -0.0, 1.5, float("nan")]), rng.choice([None, "", "a", "b"]), rng.randrange(4))
    data = [draw() for _ in range(400)]
    df = spark.createDataFrame(data, "x double, s string, i int")
    for keys in (["x", "s", "i"], ["s", "-i", "x"], [SortKey("x", nulls_first=False), SortKey("s", nulls_first=False), "i"], ["-i", "x"]):
        every = bucketing.collected(df, keys)
        rank = lambda t: tuple((v != v, 0 if v != v else v) for v in t)
        for cuts in (every[::9], every[::90], [every[0]], [every[-1]], sorted([*every[::40], *every[::40]], key=rank)):
            names = [c.alias(f"f{i}") for i, (c, _, _) in enumerate(fields(df, keys))]
            got = bucketing.locate(df, keys, cuts, "b").select("b", *names).collect()
            assert [r[0] for r in got] == [sum(rank(c) <= rank(r[1:]) for c in cuts) for r in got], (keys, len(cuts))


@pytest.mark.parametrize("n", [0, 1, 2, 255, 1100])
def test_sorts_of_few_rows(spark, n):
    df = spark.range(n).select((F.col("id") * 7919 % 1009 * 10000 + F.col("id")).alias("k"))
    want = sorted(r.k for r in df.collect())
    mp = MachineParams(16, 4, 8, 4)
    for result in (sort.em_sample(df, ["k"], ["k"], mp), sort.em_sample(df, ["k"], ["k"], mp, how="rounds"), sort.em_sample_parallel(df, ["k"], ["k"], mp), sort.em_merge(df, ["k"], ["k"], mp), sort.pram_sample(df, ["k"], ["k"], "k"), sort.co_sort(df, ["k"], ["k"], 4, 16), sort.em_heap(df, ["k"], ["k"], mp)):
        assert [r.k for r in result.rows.orderBy("pos").collect()] == want
        assert result.ledger.count() >= 0 or n == 0


def test_buckets_stay_even_when_the_driver_takes_few_keys(spark, monkeypatch):
    """With the bound on sampled keys lowered, samples thin out evenly: no bucket takes what lies above the lowest keys."""
    monkeypatch.setattr(bucketing, "MOST_SPLITTERS", 400)
    df = spark.range(30000).select((F.col("id") * 7919 % 30011).alias("k"))
    cuts = bucketing.splitters(df, ["k"], ["k"], 30000, 32)
    assert max(bucketing.sizes_of(df, ["k"], cuts)) < 3 * 30000 / 32
    mp = MachineParams(256, 16, 8, 4)
    led = sort.em_sample(df, ["k"], ["k"], mp).ledger
    assert led.where("phase = 'base'").agg(F.max("reads")).first()[0] <= mp.k * mp.M / mp.B
    assert [r.k for r in bucketing.deterministic_split(df, ["k"], 30000)[0].groupBy("bucket").agg(F.count(F.lit(1)).alias("k")).collect() if r.k > 30000 ** (2 / 3) * 16] == []
    rows_ = sort.co_sort(df, ["k"], ["k"], 4, 256).rows
    assert rows_.count() == 30000 and rows_.orderBy("pos").select("k").first().k == df.agg(F.min("k")).first()[0]


def test_merge_bound_can_fail(spark, monkeypatch):
    """A merge that reads its blocks too often, or puts a key out of order, breaks the check."""
    df = sorting.table(spark, SF, "orders").select("o_totalprice", "o_orderkey")
    args = (df, ["o_totalprice", "o_orderkey"], ["o_orderkey"], MachineParams(32, 4, 8, 2))
    assert sorting.merge_bound(*args).count() == 0
    assert sorting.merge_bound(*args, pointers="secondary").count() > 0  # twice the writes


def test_mergesort_ledger_is_counted(spark):
    df = sorting.table(spark, SF, "lineitem").select(*sorting.REAL)
    led = sort.em_merge(df, sorting.REAL, sorting.TIE, STD).ledger
    by = {r.phase: (r.r, r.w) for r in led.groupBy("phase").agg(F.sum("reads").alias("r"), F.sum("writes").alias("w")).collect()}
    n = df.count()
    assert set(by) == {"base", "merge"} and by["merge"][1] == bounds.blocks(n, STD.B)
    assert bounds.blocks(n, STD.B) < by["merge"][0] < (STD.k + 1) * bounds.blocks(n, STD.B)  # counted, not the bound


@pytest.mark.parametrize("queue", sorted(simulate.QUEUES))
def test_merge_queues(queue):
    rng = random.Random(6)
    for _ in range(30):
        mp = MachineParams(rng.choice([8, 16]), rng.choice([2, 4]), 8, rng.choice([2, 4]))
        keys = rng.sample(range(10**6), rng.randrange(1, 400))
        runs = [r for i in range(mp.fan_out) if (r := sorted(keys[i :: mp.fan_out]))]
        peak = []
        assert simulate.merge(runs, mp, queue=queue, peak=peak) == simulate.merge(runs, mp)
        assert peak[0] <= mp.M + 2 * mp.B


def test_packed_keys_sort_as_numbers():
    rng = random.Random(4)
    keys = [(rng.choice([None, 0.0, -0.0, math.inf, -math.inf, rng.uniform(-9, 9), rng.uniform(-1e300, 1e300)]), rng.choice([None, rng.randrange(-(2**63), 2**63)])) for _ in range(500)]
    order = lambda k: (k[0] is not None, k[0] or 0.0, k[1] is not None, k[1] or 0)
    assert [order(flows.unpacked(x)) for x in sorted(flows.packed(*k) for k in keys)] == sorted(map(order, keys))
    assert flows.packed(math.nan, 1) > flows.packed(math.inf, 2**62)


def test_timers_pack(spark, tmp_path):
    """A queue that grows and shrinks over batches is packed by timers, and gives the same keys back."""
    rng, h, want = random.Random(8), [], []
    for f in range(4):
        events = [(1000 * f + i, 1, "view", rng.random()) for i in range(60)] + [(1000 * f + 500 + i, 1, "purchase", 0.0) for i in range(50)]
        df = spark.createDataFrame(events, "event_id long, user_id long, event_type string, value double").withColumn("ts", F.timestamp_seconds(F.col("event_id") * 60 + 10**9))
        df.coalesce(1).write.mode("append").parquet(f"{tmp_path}/events")
        for e in events:
            if e[2] == "view":
                heapq.heappush(h, (e[3], e[0]))
            else:
                want.append(heapq.heappop(h))
    schema = "event_id long, user_id long, event_type string, value double, ts timestamp"
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/events")
    got = flows.run(flows.queue(stream, flows.TimedQueue(), "EventTime")).collect()
    assert [(r.k1, r.k2) for r in sorted((r for r in got if r.seq >= 0), key=lambda r: r.seq)] == want
    assert any(r.seq == -1 and r.k2 > 0 for r in got)


def test_queue_of_negative_and_null_keys(spark, tmp_path):
    """The streamed queue gives negative and null values back in their order."""
    values = [3.5, -2.0, None, -7.25, 0.0, None, 1e9, -1e9]
    events = [(i, 1, "view", v) for i, v in enumerate(values)] + [(100 + i, 1, "purchase", 0.0) for i in range(9)]
    df = spark.createDataFrame(events, "event_id long, user_id long, event_type string, value double")
    df.coalesce(1).write.parquet(f"{tmp_path}/events")
    stream = spark.readStream.schema(df.schema).parquet(f"{tmp_path}/events")
    got = [(r.k1, r.k2) for r in flows.run(flows.queue(stream, flows.BetaQueue())).orderBy("seq").collect()]
    assert got == [(None, 2), (None, 5), (-1e9, 7), (-7.25, 3), (-2.0, 1), (0.0, 4), (3.5, 0), (1e9, 6), (None, None)]


def test_event_log(spark, tmp_path):
    """Bytes of the stages of an application, from lines of its event log."""
    import json

    from writelite.functions import metrics

    task = lambda stage, read, wrote: json.dumps({"Event": "SparkListenerTaskEnd", "Stage ID": stage, "Task Metrics": {"Disk Bytes Spilled": 1, "Input Metrics": {"Bytes Read": read}, "Shuffle Write Metrics": {"Shuffle Bytes Written": wrote}}})
    (tmp_path / "log").write_text("\n".join([task(0, 5, 2), task(0, 6, 3), json.dumps({"Event": "SparkListenerJobEnd", "Job ID": 0}), task(1, 0, 4)]))
    got = {r.stage: (r.input, r.shuffle_write, r.spill) for r in metrics.event_log_io(spark, str(tmp_path / "log")).collect()}
    assert got == {0: (11, 5, 2), 1: (0, 4, 1)}


def test_rows_cross_the_network_once(spark):
    """The plan of a sorted table has one exchange, no window, no join, and reads only the columns that it returns."""
    df = sorting.table(spark, SF, "lineitem").select(*sorting.REAL)
    for result in (sort.em_sample(df, sorting.REAL, sorting.TIE, STD), sort.em_sample_parallel(df, sorting.REAL, sorting.TIE, STD), sort.em_merge(df, sorting.REAL, sorting.TIE, STD), sort.co_sort(df, sorting.REAL, sorting.TIE, 4, 256)):
        plan = result.rows._jdf.queryExecution().sparkPlan().toString() + result.rows._jdf.queryExecution().executedPlan().toString()
        assert "Window" not in plan and "Join" not in plan and "l_quantity" not in plan
        assert result.rows._jdf.queryExecution().executedPlan().toString().count("Exchange ") == 1


@pytest.fixture
def most_cuts(monkeypatch):
    """The most splitters that went into a plan."""
    seen, found = [0], bucketing.locate
    monkeypatch.setattr(bucketing, "locate", lambda df, keys, splitters, *a: (seen.append(len(splitters)), found(df, keys, splitters, *a))[1])
    return seen


def test_oblivious_ledger_below_the_first_level_stays_off_the_driver(spark, most_cuts):
    """Only the cuts of the first level are in a plan; every level deals all rows of its nodes out, and bases hold the rest."""
    n, omega, B = 30000, 4, 16
    df = spark.range(n).select((F.col("id") * 7919 % 30011).alias("k"))
    led = sort.co_sort(df, ["k"], ["k"], omega, 64, B=B).ledger.collect()
    assert max(most_cuts) < math.isqrt(n // omega)
    by = lambda phase: [r for r in led if r.phase == phase]
    assert {r.level for r in by("rows")} >= {0, 1} and max(r.reads for r in by("base")) <= 64 // B
    assert len({(r.phase, r.level, r.node, r.rnd) for r in led}) == len(led)
    parts = defaultdict(list)
    for r in by("subsplit"):
        parts[r.level, r.node].append(r)
    assert all(len(p) <= omega and p[0].reads <= sum(r.writes for r in p) <= p[0].reads + len(p) for p in parts.values())
    leaves = sum(r.writes for r in by("base"))
    assert n / B <= leaves <= n / B + len(by("base"))


@pytest.mark.parametrize("choose", ["random", "deterministic"])
def test_sample_ledger_below_large_nodes_stays_off_the_driver(spark, most_cuts, monkeypatch, choose):
    """Nodes larger than a task takes are cut from the driver, those below where they lie: at both sizes all rows are counted."""
    n, mp = 30000, MachineParams(16, 4, 8, 4)
    df = spark.range(n).select((F.col("id") * 7919 % 30011).alias("k"))
    for local in (sort.LOCAL, 5000):
        monkeypatch.setattr(sort, "LOCAL", local)
        del most_cuts[1:]
        led = sort.em_sample(df, ["k"], ["k"], mp, choose=choose)
        del most_cuts[1:]  # those of the rows
        led = led.ledger.collect()
        assert max(most_cuts) < (1 if local > n else mp.fan_out)
        base, dealt = ([r for r in led if r.phase == p] for p in ("base", "distribute"))
        assert n / mp.B <= sum(r.writes for r in base) <= n / mp.B + len(base) and max(r.reads for r in base) <= mp.k * mp.M / mp.B
        assert [(r.level, r.node, r.rnd, r.reads) for r in dealt if r.level == 0] == [(0, 0, r, n // mp.B) for r in range(4)]
        assert len({(r.phase, r.level, r.node, r.rnd) for r in led}) == len(led)
        assert len({r.level for r in dealt}) <= bounds.levels(n, mp) + 1


@pytest.fixture
def most_keys(monkeypatch):
    """The keys of each sample that went to the driver; placing a table is an error."""
    seen, found = [], bucketing.collected
    monkeypatch.setattr(bucketing, "collected", lambda *a: (got := found(*a), seen.append(len(got)))[0])
    monkeypatch.setattr(bucketing, "placed", lambda *a: pytest.fail("a ledger needs no rows in place"))
    return seen


def test_sample_ledger_takes_no_more_to_the_driver_than_its_splitters(spark, most_keys, monkeypatch):
    """A ledger asked for alone places no rows, which would sample 4 keys' worth a partition; below the top, only picks come."""
    n, mp = 30000, MachineParams(16, 4, 8, 4)
    monkeypatch.setattr(sort, "LOCAL", 1000)
    df = spark.range(n).select((F.col("id") * 7919 % 30011).alias("k"))
    spark.conf.set("spark.sql.shuffle.partitions", "64")
    try:
        led = sort.em_sample(df, ["k"], ["k"], mp).ledger
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", "4")
    first, *below = most_keys
    assert first < 2 * sort.OVER * mp.fan_out * math.log2(n)
    assert below and max(below) <= mp.fan_out * (mp.fan_out - 1)
    assert sum(r.reads for r in led.where("phase = 'distribute' AND level = 0").collect()) == 4 * n // mp.B


def test_picked_is_evenly_of_every_group(spark):
    """Ranks where the sample lies against the driver's own choice: small groups, repeated keys, nulls, more picks than rows."""
    rng = random.Random(5)
    rows = [(g, rng.choice([None, float("nan"), *range(40)]), rng.randrange(3)) for g in (0, 1, 3, 4, 7) for _ in range([1, 2, 50, 300, 7][g % 5])]
    df = spark.createDataFrame([(g, None if x is None else float(x), y) for g, x, y in rows], "g long, x double, y long").repartition(3)
    for few in (0, 1, 2, 5, 49, 400):
        groups = defaultdict(list)
        for r in bucketing.collected(df, ["x", "-y"], "g"):
            groups[r[0]].append(r[1:])
        want = {g: [str(x) for x in dict.fromkeys(map(str, bucketing.evenly(own, few)))] for g, own in groups.items()}
        got = bucketing.picked(df, ["x", "-y"], "g", lambda m, few=few: F.lit(few))
        assert {g: list(dict.fromkeys(map(str, own))) for g, own in got.items()} == {g: own for g, own in want.items() if own}


def test_merge_by_ranks():
    """Rounds of a merge that is told by the runs of ranks are those of the merge of keys."""
    import numpy as np

    rng = random.Random(9)
    for _ in range(300):
        mp = MachineParams(rng.choice([2, 4, 8, 64]), rng.choice([1, 2]), 8, rng.choice([2, 4]))
        n, many, skew = rng.randrange(1, 500), rng.randrange(1, 20), rng.choice([1, 3])
        of = [int(rng.random() ** skew * many) for _ in range(n)]
        if rng.random() < 0.3:
            of.sort()
        for pointers in ("memory", "secondary"):
            out, rounds = simulate.merge([r for v in range(many) if (r := [i for i, x in enumerate(of) if x == v])], mp, pointers)
            assert simulate.merge_ranks(np.array(of, np.uint16), mp, pointers) == (out == list(range(n)), rounds)


def test_merge_ledger_of_more_rows_than_a_simulation_takes(spark, monkeypatch):
    monkeypatch.setattr(simulate, "MOST_ROWS", 1000)
    df = sorting.table(spark, SF, "orders").select("o_totalprice", "o_orderkey")
    assert df.count() > 1000
    for mp in (MachineParams(32, 4, 8, 2), MachineParams(32, 4, 8, 1)):
        assert sorting.merge_bound(df, ["o_totalprice", "o_orderkey"], ["o_orderkey"], mp).count() == 0


def test_selection_in_rounds_of_a_table_of_many_nodes(spark):
    """More rows than one node takes: positions and rounds of the whole order, with nulls and equal leading keys."""
    df = spark.range(531).select(F.when(F.col("id") % 50 > 0, F.col("id") * 37 % 101).alias("a"), "id")
    result = sort.selection_rounds(df, ["-a", "id"], MachineParams(16, 4, 2, 2))
    want = [(r.a, r.id, i + 1, i // 16) for i, r in enumerate(df.orderBy(F.col("a").desc_nulls_first(), "id").collect())]
    assert sorted(map(tuple, result.rows.select("a", "id", "pos", "rnd").collect()), key=lambda r: r[2]) == want
    assert result.ledger.agg(F.sum("writes")).first()[0] == sum(-(-min(16, 531 - i) // 4) for i in range(0, 531, 16))


def test_queue_of_more_rows_than_a_simulation_takes(spark, monkeypatch):
    from writelite.operators import pq

    monkeypatch.setattr(simulate, "MOST_ROWS", 1000)
    ops = spark.range(3000).select((F.col("id") % 2).alias("shard"), F.xxhash64("id").alias("shuffled"), F.col("id").alias("key"))
    drained, ledger = pq.heap_sort(ops, sorting.HEAP)
    assert drained.where("key <> 2 * (nth - 1) + shard").count() == 0 and drained.count() == 3000
    assert {r.node: r.reads > r.writes > 0 for r in ledger.collect()} == {0: True, 1: True}


def test_gram_of_odd_vectors(spark):
    """Tiles against sums over pairs: nulls, empty and uneven vectors, NaN, equal and null keys, and no exchange of cells."""
    from writelite.operators import linalg

    nan = float("nan")
    data = [(1, [1.0, 2.0, 3.0]), (2, None), (3, []), (4, [0.5, None, 2.0]), (5, [None, 1.0]), (6, [nan, 1.0, 0.0]), (1, [1.0, 1.0, 1.0]), (None, [2.0]), (7, [4.0, 0.0, 1.0, 9.0])]
    df = spark.createDataFrame([*data, *((i, [float(i), 1.0]) for i in range(10, 40))], "k long, x array<float>")
    cells = df.select("k", F.posexplode("x").alias("d", "x"))
    want = cells.alias("a").join(cells.alias("b"), F.col("a.d") == F.col("b.d")).groupBy(F.col("a.k").alias("i"), F.col("b.k").alias("j")).agg(F.sum(F.col("a.x").cast("double") * F.col("b.x").cast("double")).alias("v"))
    plain = lambda rows: sorted((str(r.i), str(r.j), str(r.v)) for r in rows)
    for tile in (4, 1024):
        got = linalg.gram(df, "k", "x", tile)
        assert plain(got.collect()) == plain(want.collect())
    plan = linalg.gram(df.where("k > 1"), "k", "x", 4)._jdf.queryExecution().executedPlan().toString()
    assert "Generate posexplode" not in plan and "Exchange hashpartitioning(i" not in plan


def test_ratio_of_reads_to_writes_grows_with_omega_below_the_first_level(spark, most_cuts):
    """The ledgers that read_write_ratio_check compares, with no more in a plan than the cuts of the first level."""
    from writelite.functions import model

    n = 30000
    df = spark.range(n).select((F.col("id") * 7919 % 30011).alias("k"))
    ratios = []
    for omega in (1, 4, 8):
        del most_cuts[1:]
        t = model.ledger_cost(sort.co_sort(df, ["k"], ["k"], omega, 64).ledger, omega).first()
        ratios.append(t["reads"] / t["writes"])
        assert max(most_cuts) < math.isqrt(n // omega)
    assert ratios == sorted(set(ratios))


def test_oblivious_ledger_takes_no_more_to_the_driver_than_its_cuts(spark, most_keys):
    """Each ledger of read_write_ratio_check: cuts are picked from the sample where it lies, and no rows are placed."""
    n = 30000
    df = spark.range(n).select((F.col("id") * 7919 % 30011).alias("k"))
    for omega in (1, 4, 8):
        assert sort.co_sort(df, ["k"], ["k"], omega, 64).ledger.count()
        assert max(most_keys) < math.isqrt(n // omega)
        del most_keys[:]
