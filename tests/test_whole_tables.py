"""Queries over whole tables: nothing of their inputs is left out."""

from oracle import SF

from writelite import catalog

QUERIES = catalog.queries()


def test_all_embeddings(spark):
    n = spark.read.parquet(f"{SF}/embeddings.parquet").count()
    assert QUERIES["fft_embeddings"](spark, SF).count() == 64 * n
    assert QUERIES["gram_matrix"](spark, SF).count() == n * n


def test_all_joined(spark):
    docs, labels, orders, customers = (spark.read.parquet(f"{SF}/{t}.parquet") for t in ("documents", "labels", "orders", "customer"))
    count = {name: QUERIES[name](spark, SF).count() for name in QUERIES if name in ("join_left", "join_right", "join_full") or name.startswith("join_") and name.endswith("_orders")}
    idle = customers.join(orders, customers.c_custkey == orders.o_custkey, "left_anti").count()
    assert count["join_left"] == count["join_full"] == docs.count() and count["join_right"] == labels.count()
    assert count["join_left_orders"] == orders.count() and count["join_right_orders"] == count["join_full_orders"] == orders.count() + idle


def test_windows_cover_the_trace():
    from writelite.workloads.models import windows

    t = [("R", i) for i in range(45)]
    whole, *parts = windows(t)
    assert whole == t and [x for p in parts for x in p] == t and max(map(len, parts)) == 14


def test_pram_splitters_reach_the_high_keys(spark, monkeypatch):
    """A sample larger than the driver's bound is thinned, not cut to its lowest keys."""
    from writelite.operators import bucketing, sort

    monkeypatch.setattr(bucketing, "MOST_SPLITTERS", 400)
    df = spark.range(20000)
    out = sort.pram_sample(df, ["id"], ["id"], "id", refine=False)
    sizes = [r.writes // 4 for r in out.ledger.where("phase = 'sort'").collect()]
    assert sum(sizes) == 20000 and max(sizes) < 4000
    assert out.rows.where("pos <> id + 1").count() == 0 and out.rows.count() == 20000


def test_levels_follow_the_table(spark):
    orders = spark.read.parquet(f"{SF}/orders.parquet")
    least = next(t for t in range(1, 64) if 16**t * 16 >= orders.count())
    assert [r.lev for r in QUERIES["cte_recursive_levels"](spark, SF).collect()] == [least]


def test_devices_are_priced_by_the_table(spark):
    nb = -(-spark.read.parquet(f"{SF}/lineitem.parquet").count() // 16)
    assert {r.rewrite // (1 + r.omega) for r in QUERIES["device_presets"](spark, SF).collect()} == {nb}


def test_transform_lengths_follow_the_table(spark):
    n = spark.read.parquet(f"{SF}/events.parquet").where("value IS NOT NULL").count()
    least = next(2**t for t in range(64) if 2**t >= n)
    assert {r.n for r in QUERIES["fft_ledger"](spark, SF).collect()} == {4 * least, 64 * least, 1024 * least}


def test_bits_of_the_table(spark):
    ids = {r.event_id % 256 for r in spark.read.parquet(f"{SF}/events.parquet").collect()}
    assert {r.i: r.r for r in QUERIES["fn_bits"](spark, SF).collect()} == {i: int(f"{i:08b}"[::-1], 2) for i in ids}
    plan = QUERIES["fn_bits"](spark, SF)._jdf.queryExecution().optimizedPlan().toString()
    assert "event_id" in plan


def test_rule_for_k_beside_the_cost(spark):
    want = {(r.M, r.B, r.omega): r.good for r in QUERIES["k_range_table"](spark, SF).collect()}
    assert {(r.M, r.B, r.omega): r.cheaper for r in QUERIES["k_condition_table"](spark, SF).collect()} == want


def test_expected_costs_follow_the_table(spark):
    n = spark.read.parquet(f"{SF}/lineitem.parquet").count()
    side = next(2**t for t in range(64) if 4**t >= n)
    assert {r.n for r in QUERIES["matmul_expected_cost"](spark, SF).collect()} == {f * side for f in (4, 8, 16, 32)}


def test_product_ledgers_follow_the_table(spark):
    n = spark.read.parquet(f"{SF}/lineitem.parquet").count()
    side = next(2**t for t in range(64) if 4**t >= n)
    assert {r.n for r in QUERIES["matmul_ledger"](spark, SF).collect()} == {f * side for f in (4, 8, 16, 32)}


def test_pointers_follow_the_table(spark):
    import math

    n = spark.read.parquet(f"{SF}/lineitem.parquet").count()
    got = {r.method: r.records for r in QUERIES["memory_footprint"](spark, SF).collect()}
    assert abs(got["merge"] - got["base"] - 16 - 2 * math.log2(n) / 512 * 64) < 1e-3


def test_small_merges_on_the_table(spark):
    full = spark.read.parquet(f"{SF}/orders.parquet").count() // 16
    assert {(r.case, r.groups) for r in QUERIES["merge_trace_fix"](spark, SF).collect()} == {("passed_over", full), ("emitted_twice", full)}


def test_shapes_beside_the_blocks_of_the_table(spark):
    n = spark.read.parquet(f"{SF}/lineitem.parquet").count()
    assert all(r.blocks == -(-n // r.B) for r in QUERIES["tall_cache_table"](spark, SF).collect())


def test_trace_of_the_table_is_that_of_the_source(spark):
    from writelite.sources import trace

    spark.dataSource.register(trace.TraceSource)
    ids = {r.event_id for r in spark.read.parquet(f"{SF}/events.parquet").collect()}
    made = spark.read.format("memory_trace").options(rows=max(ids) + 1, addresses=32, writes=25).load().collect()
    assert sorted(map(tuple, QUERIES["trace_source"](spark, SF).collect())) == sorted(tuple(r) for r in made if r.seq in ids)


def test_gram_deals_each_vector_once(spark):
    """A vector is written once for each job, not once for every block that it meets; all pairs are there, with their sums."""
    import numpy as np

    from writelite.functions import metrics
    from writelite.operators import linalg

    x = np.random.default_rng(7).standard_normal((600, 32))
    df = spark.createDataFrame([(i, v) for i, v in enumerate(x.tolist())], "k long, x array<double>").repartition(4)
    made = []
    io = metrics.io_of(spark, lambda: made.append(linalg.gram(df, "k", "x", tile=60).toArrow()))
    got = np.full((600, 600), np.nan)
    got[made[0].column("i").to_numpy(), made[0].column("j").to_numpy()] = made[0].column("v").to_numpy()
    assert len(made[0]) == 600 * 600 and np.allclose(got, x @ x.T)
    assert io["shuffle_write"] < 8 * x.nbytes


def test_pairs_are_rounded_as_duckdb_rounds(spark):
    """Ties and their neighbours too, where a decimal number of the value's shortest text rounds another way."""
    import duckdb
    import numpy as np

    from writelite.workloads.models import rounded

    ties = (np.random.default_rng(1).integers(-(10**9), 10**9, 3000) + 0.5) / 1e6
    v = [*ties, *np.nextafter(ties, 9e9), *np.nextafter(ties, -9e9), 0.0, -0.0, 5e-7, -5e-7, 0.49999999999999994e-6, 999999999.9999995, 1e9, -1e300, np.inf, -np.inf, np.nan]
    df = spark.createDataFrame([(float(x),) for x in v], "v double")
    got = df.select("v", (rounded("v") + 0.0).alias("r")).toArrow()
    assert duckdb.sql("SELECT count(*) FROM got WHERE r IS DISTINCT FROM round(v, 6) + 0.0 AND NOT isnan(v)").fetchall() == [(0,)]
