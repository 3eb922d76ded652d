"""Sources, projections, joins, aggregates, windows, sets, functions, user functions and subqueries around the methods."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from writelite.operators import bucketing
from writelite.operators.keys import portable_coin, portable_coin_sql
from writelite.sources import formats, trace
from writelite.workloads.sorting import table

QUERIES: dict = {}
SQL: dict[str, str] = {}


def op(name: str, sql: str | None = None):
    """Registers a query and its SQL."""

    def put(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return put


def plain(name: str, tables: str, f, sql: str | None = None) -> None:
    """A query whose function takes the named tables."""
    op(name, sql)(lambda spark, d: f(*[table(spark, d, t) for t in tables.split()]))


c = F.col
cents = lambda x: F.sum(F.round(c(x) * 100).cast("long")).cast("long")
CENTS = lambda x: f"sum(round({x} * 100)::BIGINT)::BIGINT"
n = lambda: F.count(F.lit(1))

# Sources and sinks.
plain("scan_parquet", "lineitem", lambda t: t.where(c("l_quantity") > 45).select("l_orderkey", "l_linenumber", "l_partkey", "l_quantity"), "SELECT l_orderkey, l_linenumber, l_partkey, l_quantity FROM lineitem WHERE l_quantity > 45")
for kind in ("csv", "json", "orc"):
    plain(f"roundtrip_{kind}", "orders", lambda t, kind=kind: formats.roundtrip(t.select("o_orderkey", "o_custkey", "o_totalprice", "o_orderpriority"), kind), "SELECT o_orderkey, o_custkey, o_totalprice, o_orderpriority FROM orders")
plain("roundtrip_text", "benchmark", lambda t: formats.roundtrip(t.select(F.translate("text", "\n", " ").alias("value")), "text"), "SELECT replace(text, chr(10), ' ') AS value FROM benchmark")
plain("sink_range_sorted", "lineitem", lambda t: formats.range_sorted(t.select("l_orderkey", "l_shipdate"), 8, "l_shipdate").groupBy("file").agg(F.min("l_shipdate").alias("lo"), F.max("l_shipdate").alias("hi"), n().alias("cnt")).withColumn("next", F.lead("lo").over(W.orderBy("lo", "hi"))).agg(F.sum("cnt").cast("long").alias("cnt"), F.max(F.coalesce(c("hi") > c("next"), F.lit(False))).alias("overlap")), "SELECT count(*)::BIGINT AS cnt, false AS overlap FROM lineitem")
plain("sink_partitioned", "events", lambda t: formats.partitioned(t.select("event_id", "user_id", "event_type"), "event_type").where("event_type = 'click'").select("event_id", "user_id"), "SELECT event_id, user_id FROM events WHERE event_type = 'click'")
plain("sink_bucketed", "orders lineitem", lambda o, l: formats.bucketed(o.select("o_orderkey", "o_orderpriority"), "o_orderkey").join(formats.bucketed(l.select("l_orderkey", "l_quantity"), "l_orderkey"), c("o_orderkey") == c("l_orderkey")).groupBy("o_orderpriority").agg(F.sum(c("l_quantity").cast("long")).alias("q")), "SELECT o_orderpriority, sum(l_quantity::BIGINT)::BIGINT AS q FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
plain("scan_row_position", "orders", lambda t: t.select(c("_metadata.row_index").alias("pos"), "o_orderkey"))


def _accesses(batches):
    import pyarrow as pa

    for b in batches:
        rows = [trace.record(i, 32, 25) for i in b.column(0).to_pylist()]
        yield pa.RecordBatch.from_pydict(dict(zip(("seq", "op", "addr"), zip(*rows, strict=True), strict=True)) if rows else {"seq": pa.array([], "int64"), "op": pa.array([], "string"), "addr": pa.array([], "int64")})


#: The instruction trace of the data source (`trace.TraceSource`, which makes its places up) at the ids of events.
plain("trace_source", "events", lambda t: t.select("event_id").where("event_id IS NOT NULL").mapInArrow(_accesses, trace.SCHEMA))


def _reuse(t: DataFrame) -> DataFrame:
    from writelite.operators.prim import cut_lineage

    kept = cut_lineage(t.select("l_orderkey", "l_quantity"))
    return kept.agg(n().alias("cnt")).crossJoin(kept.agg(F.sum(c("l_quantity").cast("long")).alias("q")))


plain("cache_reuse", "lineitem", _reuse, "SELECT count(*)::BIGINT AS cnt, sum(l_quantity::BIGINT)::BIGINT AS q FROM lineitem")

# Projections and filters.
plain("project_compute", "lineitem", lambda t: t.select("l_orderkey", "l_linenumber", "l_partkey", (F.round(c("l_extendedprice") * 100).cast("long") * F.round((1 - c("l_discount")) * 100).cast("long")).alias("net")), "SELECT l_orderkey, l_linenumber, l_partkey, round(l_extendedprice * 100)::BIGINT * round((1 - l_discount) * 100)::BIGINT AS net FROM lineitem")
plain("filter_range", "lineitem", lambda t: t.where(c("l_shipdate").between("1995-01-01", "1995-06-30")).select("l_orderkey", "l_shipdate"), "SELECT l_orderkey, l_shipdate FROM lineitem WHERE l_shipdate BETWEEN '1995-01-01' AND '1995-06-30'")
plain("filter_mixed", "orders", lambda t: t.where((c("o_orderstatus").isin("O", "F") & c("o_orderpriority").like("1%")) | ~(c("o_totalprice") > 1000) | c("o_custkey").isNull()).select("o_orderkey"), "SELECT o_orderkey FROM orders WHERE (o_orderstatus IN ('O', 'F') AND o_orderpriority LIKE '1%') OR NOT (o_totalprice > 1000) OR o_custkey IS NULL")
plain("case_bucket", "part", lambda t: t.select("p_partkey", F.when(c("p_size") < 10, "small").when(c("p_size") < 30, "medium").otherwise("large").alias("size")), "SELECT p_partkey, CASE WHEN p_size < 10 THEN 'small' WHEN p_size < 30 THEN 'medium' ELSE 'large' END AS size FROM part")
plain("sample_portable", "lineitem", lambda t: t.where(portable_coin(["l_orderkey", "l_linenumber", "l_partkey"], 0.1, 7)).select("l_orderkey", "l_linenumber", "l_partkey"), f"SELECT l_orderkey, l_linenumber, l_partkey FROM lineitem WHERE {portable_coin_sql(['l_orderkey', 'l_linenumber', 'l_partkey'], 0.1, 7)}")
plain("sample_bernoulli", "events", lambda t: t.sample(False, 0.1, 42).select("event_id"))
plain("sample_stratified", "events", lambda t: t.sampleBy("event_type", {"click": 0.5, "view": 0.1}, 42).select("event_id", "event_type"))
plain("distinct_rows", "documents", lambda t: t.select("text").distinct().select(F.md5("text").alias("h")), "SELECT md5(text) AS h FROM (SELECT DISTINCT text FROM documents)")
plain("drop_duplicates_by", "documents", lambda t: t.groupBy(F.md5("text").alias("h")).agg(F.min("doc_id").alias("doc_id")).select("doc_id"), "SELECT min(doc_id) AS doc_id FROM documents GROUP BY md5(text)")

# Joins.
_OL = "SELECT o_orderpriority, sum(l_quantity::BIGINT)::BIGINT AS q FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1"
_ol = lambda o, l, hint=None: (o.join(l.hint(hint) if hint else l, o["o_orderkey"] == l["l_orderkey"]).groupBy("o_orderpriority").agg(F.sum(c("l_quantity").cast("long")).alias("q")))


def small(df: DataFrame, most_mb: int = 64) -> DataFrame:
    """Broadcast behind a check of bytes, rows times a row's width: beyond `most_mb` the optimiser picks a join by exchange."""
    width = 16 + sum(8 + 32 * (kind in ("string", "binary")) for _, kind in df.dtypes)
    return F.broadcast(df) if df.count() * width <= most_mb * 1_000_000 else df


plain("join_broadcast_hash", "lineitem part", lambda l, p: l.join(small(p.select("p_partkey", "p_brand")), c("l_partkey") == c("p_partkey")).groupBy("p_brand").agg(F.sum(c("l_quantity").cast("long")).alias("q")), "SELECT p_brand, sum(l_quantity::BIGINT)::BIGINT AS q FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1")
plain("join_sort_merge", "orders lineitem", lambda o, l: _ol(o, l, "merge"), _OL)
plain("join_shuffle_hash", "orders customer", lambda o, u: o.join(u.hint("shuffle_hash"), c("o_custkey") == c("c_custkey")).groupBy("c_mktsegment").agg(n().alias("cnt")), "SELECT c_mktsegment, count(*)::BIGINT AS cnt FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
for how in ("left", "right", "full"):
    plain(f"join_{how}", "documents labels", lambda x, y, how=how: x.select("doc_id", "lang").join(y.select("doc_id", "quality"), "doc_id", how), f"SELECT doc_id, lang, quality FROM documents {how.upper()} JOIN labels USING (doc_id)")
    plain(f"join_{how}_orders", "orders customer", lambda o, u, how=how: o.select("o_orderkey", "o_custkey").join(u.select("c_custkey", "c_mktsegment"), c("o_custkey") == c("c_custkey"), how), f"SELECT o_orderkey, o_custkey, c_custkey, c_mktsegment FROM orders {how.upper()} JOIN customer ON o_custkey = c_custkey")
plain("join_semi", "customer orders", lambda u, o: u.join(o, c("c_custkey") == c("o_custkey"), "left_semi").select("c_custkey"), "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)")
plain("join_anti", "documents labels", lambda x, y: x.join(y, "doc_id", "left_anti").select("doc_id"), "SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
plain("join_nested_loop", "part nation", lambda p, m: p.join(F.broadcast(m.select("n_nationkey")), (c("p_size") > c("n_nationkey") * 2) & (c("n_nationkey") > 20)).select("p_partkey", "n_nationkey"), "SELECT p_partkey, n_nationkey FROM part JOIN nation ON p_size > n_nationkey * 2 AND n_nationkey > 20")


@op("join_range_bucket", "SELECT floor(l_extendedprice / 10000)::BIGINT AS bucket, count(*)::BIGINT AS cnt FROM lineitem GROUP BY 1")
def _range(spark: SparkSession, d: str) -> DataFrame:
    t = table(spark, d, "lineitem").select("l_extendedprice")
    s = spark.range(0, 1000).select((c("id") * 10000).cast("double").alias("lo"), ((c("id") + 1) * 10000).cast("double").alias("hi"), c("id").alias("bucket"))
    return bucketing.locate_join(t, "l_extendedprice", s).groupBy("bucket").agg(n().alias("cnt"))


def _asof(e: DataFrame) -> DataFrame:
    """Each view with the last click before it of its user: one window over the union of both."""
    last = F.last(F.when(c("event_type") == "click", c("event_id")), True).over(W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, -1))
    return e.where(c("event_type").isin("view", "click")).withColumn("click_id", last).where("event_type = 'view'").select("event_id", "click_id")


plain("join_asof", "events", _asof, "SELECT v.event_id, k.event_id AS click_id FROM (SELECT * FROM events WHERE event_type = 'view') v ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'click') k ON v.user_id = k.user_id AND v.ts >= k.ts")


def _interval(e: DataFrame) -> DataFrame:
    """Pairs of a click and a purchase of a user within an hour: equality on user and hour, the next hour added."""
    t = F.unix_micros(c("ts").cast("timestamp"))
    hour = F.floor(t / 3_600_000_000)
    a = e.where("event_type = 'click'").select("user_id", c("event_id").alias("click_id"), t.alias("ta"), F.explode(F.array(hour, hour + 1)).alias("hour"))
    b = e.where("event_type = 'purchase'").select("user_id", c("event_id").alias("purchase_id"), t.alias("tb"), hour.alias("hour"))
    return a.join(b, ["user_id", "hour"]).where((c("tb") >= c("ta")) & (c("tb") - c("ta") <= 3_600_000_000)).select("click_id", "purchase_id")


plain("join_interval", "events", _interval, "SELECT a.event_id AS click_id, b.event_id AS purchase_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
plain("join_cross", "region nation", lambda r, m: r.crossJoin(F.broadcast(m)).select("r_regionkey", "n_nationkey"), "SELECT r_regionkey, n_nationkey FROM region, nation")
plain("join_lateral", "customer orders", lambda u, o: u.join(o.withColumn("r", F.row_number().over(W.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey"))).where("r <= 2"), c("c_custkey") == c("o_custkey")).select("c_custkey", "o_orderkey"), "SELECT c_custkey, o_orderkey FROM customer, LATERAL (SELECT o_orderkey FROM orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 2)")


def _sliced(o: DataFrame, l: DataFrame) -> DataFrame:
    """The build side in four key slices; the probe side is scanned again for each, and only its slice is exchanged."""
    parts = [_ol(o.where(c("o_orderkey") % 4 == i), l.where(c("l_orderkey") % 4 == i)) for i in range(4)]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out.groupBy("o_orderpriority").agg(F.sum("q").cast("long").alias("q"))


plain("join_sliced", "orders lineitem", _sliced, _OL)
plain("join_self_pairs", "events", lambda e: e.select("event_id", F.lead("event_id").over(W.partitionBy("user_id").orderBy("ts", "event_id")).alias("next_id")).where("next_id IS NOT NULL"), "SELECT event_id, next_id FROM (SELECT event_id, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS next_id FROM events) WHERE next_id IS NOT NULL")

# Aggregates.
plain("agg_hash", "lineitem", lambda t: t.groupBy("l_returnflag", "l_linestatus").agg(n().alias("cnt"), cents("l_extendedprice").alias("total")), f"SELECT l_returnflag, l_linestatus, count(*)::BIGINT AS cnt, {CENTS('l_extendedprice')} AS total FROM lineitem GROUP BY 1, 2")
plain("agg_sort", "orders", lambda t: t.groupBy("o_custkey").agg(F.max("o_orderpriority").alias("top")), "SELECT o_custkey, max(o_orderpriority) AS top FROM orders GROUP BY 1")
plain("agg_distinct", "events", lambda t: t.groupBy("event_type").agg(F.count_distinct("user_id").alias("users"), F.count_distinct(F.get_json_object("props", "$.k")).alias("ks")), "SELECT event_type, count(DISTINCT user_id)::BIGINT AS users, count(DISTINCT props->>'$.k')::BIGINT AS ks FROM events GROUP BY 1")
plain("agg_approx_distinct", "lineitem", lambda t: t.agg(F.approx_count_distinct("l_partkey").alias("parts"), F.hll_sketch_estimate(F.hll_sketch_agg("l_suppkey")).alias("suppliers")))
plain("agg_rollup", "customer nation", lambda u, m: u.join(F.broadcast(m), c("c_nationkey") == c("n_nationkey")).rollup("n_name", "c_mktsegment").agg(n().alias("cnt")), "SELECT n_name, c_mktsegment, count(*)::BIGINT AS cnt FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY ROLLUP (n_name, c_mktsegment)")
plain("agg_cube", "lineitem", lambda t: t.cube("l_returnflag", "l_linestatus").agg(n().alias("cnt")), "SELECT l_returnflag, l_linestatus, count(*)::BIGINT AS cnt FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
plain("agg_grouping_sets", "orders", lambda t: t.groupingSets([["o_orderstatus"], ["o_orderpriority"], []], "o_orderstatus", "o_orderpriority").agg(n().alias("cnt"), F.grouping_id().cast("long").alias("gid")), "SELECT o_orderstatus, o_orderpriority, count(*)::BIGINT AS cnt, grouping_id(o_orderstatus, o_orderpriority)::BIGINT AS gid FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")
plain("agg_pivot", "events", lambda t: t.groupBy("user_id").pivot("event_type", ["click", "view"]).agg(n()).select("user_id", F.coalesce("click", F.lit(0)).alias("click"), F.coalesce("view", F.lit(0)).alias("view")), "SELECT user_id, count(*) FILTER (event_type = 'click')::BIGINT AS click, count(*) FILTER (event_type = 'view')::BIGINT AS view FROM events GROUP BY 1")
plain("unpivot", "part", lambda t: t.select("p_partkey", c("p_size").cast("double").alias("size"), c("p_retailprice").alias("price")).unpivot("p_partkey", ["size", "price"], "name", "value"), "SELECT p_partkey, 'size' AS name, p_size::DOUBLE AS value FROM part UNION ALL SELECT p_partkey, 'price', p_retailprice FROM part")
plain("agg_percentile_exact", "lineitem", lambda t: t.groupBy("l_returnflag").agg(F.round(F.expr("percentile(l_extendedprice, 0.5)"), 4).alias("med")), "SELECT l_returnflag, round(quantile_cont(l_extendedprice, 0.5), 4) AS med FROM lineitem GROUP BY 1")
plain("agg_percentile_approx", "lineitem", lambda t: t.agg(F.percentile_approx("l_extendedprice", [0.25, 0.5, 0.75]).alias("q")).select(F.posexplode("q").alias("i", "q")))
plain("agg_percentile_kll", "lineitem", lambda t: t.agg(F.expr("kll_sketch_get_quantile_double(kll_sketch_agg_double(l_extendedprice), 0.5D)").alias("med")))
plain("agg_arg_min", "orders", lambda t: t.groupBy("o_custkey").agg(F.min_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("cheapest")), "SELECT o_custkey, arg_min(o_orderkey, (o_totalprice, o_orderkey)) AS cheapest FROM orders GROUP BY 1")
plain("agg_collect_ordered", "conversations", lambda t: t.groupBy("conv_id").agg(F.array_sort(F.collect_list(F.struct("turn", "role"))).alias("x")).select("conv_id", F.array_join("x.role", ",").alias("roles")), "SELECT conv_id, string_agg(role, ',' ORDER BY turn, role) AS roles FROM conversations GROUP BY 1")
plain("agg_histogram", "lineitem", lambda t: t.groupBy(F.width_bucket("l_extendedprice", F.lit(0.0), F.lit(100000.0), F.lit(10)).alias("b")).agg(n().alias("cnt")), "SELECT CASE WHEN l_extendedprice < 0 THEN 0 WHEN l_extendedprice >= 100000 THEN 11 ELSE floor(l_extendedprice / 10000) + 1 END::BIGINT AS b, count(*)::BIGINT AS cnt FROM lineitem GROUP BY 1")
plain("agg_having", "orders", lambda t: t.groupBy("o_custkey").agg(n().alias("cnt")).where("cnt > 12"), "SELECT o_custkey, count(*)::BIGINT AS cnt FROM orders GROUP BY 1 HAVING count(*) > 12")
plain("agg_stats", "part", lambda t: t.agg(F.round(F.stddev("p_size"), 6).alias("sd"), F.round(F.corr("p_size", "p_retailprice"), 6).alias("r"), F.bool_and(c("p_size") > 0).alias("positive")), "SELECT round(stddev(p_size), 6) AS sd, round(corr(p_size, p_retailprice), 6) AS r, bool_and(p_size > 0) AS positive FROM part")
plain("agg_filtered", "events", lambda t: t.groupBy("user_id").agg(F.count_if(c("event_type").isin("view", "click")).alias("reads"), F.sum(F.when(~c("event_type").isin("view", "click"), 1).otherwise(0)).cast("long").alias("writes")), "SELECT user_id, count(*) FILTER (event_type IN ('view', 'click'))::BIGINT AS reads, count(*) FILTER (event_type NOT IN ('view', 'click'))::BIGINT AS writes FROM events GROUP BY 1")

# Windows.
_wc = lambda: W.partitionBy("o_custkey").orderBy("o_totalprice", "o_orderkey")
_ws = "(PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey)"
plain("win_rank_family", "orders", lambda t: t.select("o_orderkey", F.row_number().over(_wc()).cast("long").alias("rn"), F.rank().over(_wc()).cast("long").alias("rk"), F.dense_rank().over(_wc()).cast("long").alias("dr"), F.ntile(4).over(_wc()).cast("long").alias("nt"), F.round(F.percent_rank().over(_wc()), 6).alias("pr"), F.round(F.cume_dist().over(_wc()), 6).alias("cd")), f"SELECT o_orderkey, row_number() OVER {_ws} AS rn, rank() OVER {_ws} AS rk, dense_rank() OVER {_ws} AS dr, ntile(4) OVER {_ws} AS nt, round(percent_rank() OVER {_ws}, 6) AS pr, round(cume_dist() OVER {_ws}, 6) AS cd FROM orders")
plain("win_lag_lead", "events", lambda t: t.select("event_id", F.lag("event_id").over(W.partitionBy("user_id").orderBy("event_id")).alias("prev"), F.lead("event_id", 2).over(W.partitionBy("user_id").orderBy("event_id")).alias("next2")), "SELECT event_id, lag(event_id) OVER w AS prev, lead(event_id, 2) OVER w AS next2 FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)")
plain("win_running_sum", "orders", lambda t: t.select("o_orderkey", F.sum(F.round(c("o_totalprice") * 100).cast("long")).over(W.partitionBy("o_custkey").orderBy("o_orderkey").rowsBetween(W.unboundedPreceding, 0)).alias("run")), "SELECT o_orderkey, sum(round(o_totalprice * 100)::BIGINT) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS UNBOUNDED PRECEDING)::BIGINT AS run FROM orders")
plain("win_moving_rows", "events", lambda t: t.select("event_id", F.sum("event_id").over(W.partitionBy("user_id").orderBy("event_id").rowsBetween(-3, 3)).alias("s")), "SELECT event_id, sum(event_id) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 3 PRECEDING AND 3 FOLLOWING)::BIGINT AS s FROM events")
plain("win_range_interval", "events", lambda t: t.withColumn("s", F.unix_seconds(c("ts").cast("timestamp"))).select("event_id", n().over(W.partitionBy("user_id").orderBy("s").rangeBetween(-86400, 0)).alias("cnt")), "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY floor(epoch(ts))::BIGINT RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW)::BIGINT AS cnt FROM events")
_we = lambda: W.partitionBy("user_id").orderBy("event_id").rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
plain("win_first_last_nth", "events", lambda t: t.select("event_id", F.first("event_id").over(_we()).alias("f"), F.last(F.when(c("event_type") == "click", c("event_id")), True).over(_we()).alias("l"), F.nth_value("event_id", 3).over(_we()).alias("third")), "SELECT event_id, first_value(event_id) OVER w AS f, last_value(CASE WHEN event_type = 'click' THEN event_id END IGNORE NULLS) OVER w AS l, nth_value(event_id, 3) OVER w AS third FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")


@op("win_global_rank", "SELECT o_orderkey, row_number() OVER (ORDER BY o_totalprice, o_orderkey)::BIGINT AS pos FROM orders")
def _global(spark: SparkSession, d: str) -> DataFrame:
    from writelite.functions.model import STD
    from writelite.operators import sort

    return sort.em_sample_parallel(table(spark, d, "orders").select("o_totalprice", "o_orderkey"), ["o_totalprice", "o_orderkey"], ["o_orderkey"], STD).rows.select("o_orderkey", "pos")


def _sessions(t: DataFrame) -> DataFrame:
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    gap = (F.unix_micros(c("ts").cast("timestamp")) - F.unix_micros(F.lag("ts").over(w).cast("timestamp"))) > 1_800_000_000
    return t.withColumn("new", F.coalesce(gap, F.lit(True)).cast("long")).select("event_id", F.sum("new").over(w.rowsBetween(W.unboundedPreceding, 0)).alias("session"))


plain("win_sessionize", "events", _sessions, "SELECT event_id, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING)::BIGINT AS session FROM (SELECT *, coalesce(ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) > INTERVAL 30 MINUTE, true)::INT AS new FROM events)")

# Order and limits.
plain("sort_multi", "documents", lambda t: t.select("doc_id", F.row_number().over(W.orderBy(c("lang").desc_nulls_last(), c("n_chars").asc_nulls_first(), "doc_id")).cast("long").alias("r")), "SELECT doc_id, row_number() OVER (ORDER BY lang DESC NULLS LAST, n_chars ASC NULLS FIRST, doc_id) AS r FROM documents")


def _sort_within(o: DataFrame) -> DataFrame:
    """Rows of each partition against the row before them there: none may be smaller."""
    rows = o.select("o_custkey", "o_orderkey").repartition(8, "o_custkey").sortWithinPartitions("o_custkey", "o_orderkey")
    rows = rows.select("*", F.spark_partition_id().alias("p"), F.monotonically_increasing_id().alias("at"))
    before = F.lag(F.struct("o_custkey", "o_orderkey")).over(W.partitionBy("p").orderBy("at"))
    return rows.withColumn("before", before).agg(n().alias("rows"), F.coalesce(F.sum((c("before") > F.struct("o_custkey", "o_orderkey")).cast("long")), F.lit(0)).alias("wrong"))


plain("sort_within", "orders", _sort_within, "SELECT count(*)::BIGINT AS rows, 0::BIGINT AS wrong FROM orders")
plain("topk_global", "lineitem", lambda t: t.select("l_orderkey", "l_linenumber", "l_partkey", "l_extendedprice").orderBy(F.desc("l_extendedprice"), "l_orderkey", "l_linenumber", "l_partkey").limit(100), "SELECT l_orderkey, l_linenumber, l_partkey, l_extendedprice FROM lineitem ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber, l_partkey LIMIT 100")
plain("topk_per_group", "orders", lambda t: t.withColumn("r", F.row_number().over(W.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey"))).where("r <= 3").select("o_custkey", "o_orderkey"), "SELECT o_custkey, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 3")
plain("page_offset", "part", lambda t: t.orderBy("p_retailprice", "p_partkey").select("p_partkey", "p_retailprice").offset(50).limit(50), "SELECT p_partkey, p_retailprice FROM part ORDER BY p_retailprice, p_partkey LIMIT 50 OFFSET 50")


def _ranges(l: DataFrame) -> DataFrame:
    """The dates of each partition against those of the next one: ranges may not overlap, and there is more than one."""
    parts = l.select("l_shipdate").repartitionByRange(8, "l_shipdate").select("l_shipdate", F.spark_partition_id().alias("p"))
    spans = parts.groupBy("p").agg(F.min("l_shipdate").alias("lo"), F.max("l_shipdate").alias("hi"), n().alias("cnt"))
    after = F.lead("lo").over(W.orderBy("p"))
    return spans.withColumn("after", after).agg(F.sum("cnt").alias("rows"), F.coalesce(F.sum((c("hi") >= c("after")).cast("long")), F.lit(0)).alias("overlaps"), (n() > 1).alias("many"))


plain("range_partition", "lineitem", _ranges, "SELECT count(*)::BIGINT AS rows, 0::BIGINT AS overlaps, true AS many FROM lineitem")
plain("bottomk_threshold", "lineitem", lambda t: t.where("l_extendedprice > 20000").select("l_extendedprice", "l_orderkey", "l_linenumber", "l_partkey").orderBy("l_extendedprice", "l_orderkey", "l_linenumber", "l_partkey").limit(64), "SELECT l_extendedprice, l_orderkey, l_linenumber, l_partkey FROM lineitem WHERE l_extendedprice > 20000 ORDER BY ALL LIMIT 64")
plain("topk_quality_docs", "documents labels", lambda x, y: x.join(y, "doc_id").orderBy(F.desc("quality"), F.desc("n_chars"), "doc_id").select("doc_id", "quality", "n_chars").limit(50), "SELECT doc_id, quality, n_chars FROM documents JOIN labels USING (doc_id) ORDER BY quality DESC, n_chars DESC, doc_id LIMIT 50")

# Sets.
_ck = lambda u: u.select((c("c_custkey") % 700).alias("k"))
_ok = lambda o: o.select((c("o_custkey") % 900).alias("k"))
for key, f, words in (("union_all", lambda a, b: a.unionByName(b), "UNION ALL"), ("union_distinct", lambda a, b: a.unionByName(b).distinct(), "UNION"), ("intersect", lambda a, b: a.intersect(b), "INTERSECT"), ("intersect_all", lambda a, b: a.intersectAll(b), "INTERSECT ALL"), ("except", lambda a, b: b.subtract(a), "EXCEPT"), ("except_all", lambda a, b: b.exceptAll(a), "EXCEPT ALL")):
    x, y = ("o_custkey % 900 AS k FROM orders", "c_custkey % 700 AS k FROM customer") if key.startswith("except") else ("c_custkey % 700 AS k FROM customer", "o_custkey % 900 AS k FROM orders")
    plain(key, "customer orders", lambda u, o, f=f: f(_ck(u), _ok(o)), f"SELECT {x} {words} SELECT {y}")

# Scalar functions.
plain("fn_string", "part", lambda t: t.select("p_partkey", F.upper(F.substring("p_name", 1, 5)).alias("u"), F.trim(F.concat(F.lit("  "), "p_brand")).alias("t"), F.regexp_replace("p_type", "[aeiou]", "*").alias("r"), F.regexp_extract("p_brand", "([0-9]+)", 1).alias("x"), F.size(F.split("p_name", " ")).cast("long").alias("s"), F.length("p_type").cast("long").alias("l"), F.concat_ws("-", "p_brand", "p_type").alias("c"), F.instr("p_type", "E").cast("long").alias("i"), F.lpad(c("p_size").cast("string"), 4, "0").alias("p"), F.translate("p_brand", "Bd", "bD").alias("tr"), F.levenshtein("p_brand", F.lit("Brand#11")).cast("long").alias("lev"), F.md5("p_name").alias("h")), "SELECT p_partkey, upper(substr(p_name, 1, 5)) AS u, trim('  ' || p_brand) AS t, regexp_replace(p_type, '[aeiou]', '*', 'g') AS r, regexp_extract(p_brand, '([0-9]+)', 1) AS x, len(string_split(p_name, ' ')) AS s, length(p_type) AS l, concat_ws('-', p_brand, p_type) AS c, instr(p_type, 'E') AS i, lpad(p_size::VARCHAR, 4, '0') AS p, translate(p_brand, 'Bd', 'bD') AS tr, levenshtein(p_brand, 'Brand#11') AS lev, md5(p_name) AS h FROM part")
plain("fn_date", "orders", lambda t: t.select("o_orderkey", F.year("o_orderdate").cast("long").alias("y"), F.quarter("o_orderdate").cast("long").alias("q"), F.month("o_orderdate").cast("long").alias("m"), F.datediff("o_orderdate", F.lit("1992-01-01").cast("date")).cast("long").alias("d"), F.date_format(F.add_months("o_orderdate", 3), "yyyy-MM-dd").alias("a"), F.date_format(F.trunc("o_orderdate", "month"), "yyyy-MM-dd").alias("t"), F.unix_seconds(c("o_orderdate").cast("timestamp")).alias("e")), "SELECT o_orderkey, year(o_orderdate) AS y, quarter(o_orderdate) AS q, month(o_orderdate) AS m, date_diff('day', DATE '1992-01-01', o_orderdate::DATE) AS d, strftime(o_orderdate::DATE + INTERVAL 3 MONTH, '%Y-%m-%d') AS a, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS t, epoch(o_orderdate)::BIGINT AS e FROM orders")
plain("fn_math", "lineitem", lambda t: t.groupBy("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey").agg(F.max("l_quantity").alias("q")).select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", F.round(F.log("q"), 6).alias("ln"), F.round(F.exp(c("q") / 50), 6).alias("ex"), F.round(F.pow("q", F.lit(1.5)), 4).alias("pw"), F.round(F.sqrt("q"), 6).alias("sq"), F.pmod(-c("l_orderkey"), F.lit(7)).alias("pm"), c("l_partkey").bitwiseAND(12).alias("ba"), F.shiftleft("l_linenumber", 2).cast("long").alias("sh"), (F.round(F.cos(c("q")), 6) + 0.0).alias("co")), "SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, round(ln(q), 6) AS ln, round(exp(q / 50), 6) AS ex, round(pow(q, 1.5), 4) AS pw, round(sqrt(q), 6) AS sq, ((-l_orderkey % 7) + 7) % 7 AS pm, l_partkey & 12 AS ba, (l_linenumber * 4)::BIGINT AS sh, round(cos(q), 6) + 0.0 AS co FROM (SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, max(l_quantity) AS q FROM lineitem GROUP BY ALL)")
plain("fn_array", "embeddings", lambda t: t.withColumn("e", F.transform("embedding", lambda x: F.round(x.cast("double") * 1000).cast("long"))).select("vec_id", F.aggregate("e", F.lit(0).cast("long"), lambda a, x: a + x).alias("s"), F.size(F.filter("e", lambda x: x > 0)).cast("long").alias("pos"), F.aggregate(F.zip_with(F.slice("e", 1, 8), F.slice("e", 9, 8), lambda a, b: a * b), F.lit(0).cast("long"), lambda a, x: a + x).alias("dot"), F.element_at(F.array_sort("e"), -1).alias("top")), "SELECT vec_id, list_sum(e)::BIGINT AS s, len(list_filter(e, lambda x: x > 0)) AS pos, list_sum(list_transform(range(1, 9), lambda i: e[i] * e[i + 8]))::BIGINT AS dot, list_max(e) AS top FROM (SELECT vec_id, list_transform(embedding, lambda x: round(x::DOUBLE * 1000)::BIGINT) AS e FROM embeddings)")
plain("fn_map", "events", lambda t: t.groupBy("user_id", "event_type").agg(n().alias("cnt")).groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "cnt"))).alias("m")).select("user_id", F.array_join(F.array_sort(F.map_keys(F.map_filter("m", lambda k, v: v >= 10))), ",").alias("often"), F.aggregate(F.map_values(F.transform_values("m", lambda k, v: v * 2)), F.lit(0).cast("long"), lambda a, x: a + x).alias("twice")), "SELECT user_id, coalesce(string_agg(event_type, ',' ORDER BY event_type) FILTER (cnt >= 10), '') AS often, (sum(cnt) * 2)::BIGINT AS twice FROM (SELECT user_id, event_type, count(*) AS cnt FROM events GROUP BY 1, 2) GROUP BY 1")
plain("fn_json", "events", lambda t: t.select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"), F.from_json("props", "k long")["k"].alias("k2"), F.to_json(F.struct(c("event_id").alias("e"))).alias("j"), F.try_variant_get(F.parse_json("props"), "$.k", "long").alias("k3")), "SELECT event_id, (props->>'$.k')::BIGINT AS k, (props->>'$.k')::BIGINT AS k2, '{\"e\":' || event_id || '}' AS j, (props->>'$.k')::BIGINT AS k3 FROM events")
plain("fn_struct_key", "orders", lambda t: t.where(F.struct("o_orderpriority", "o_orderkey") < F.struct(F.lit("2-HIGH"), F.lit(500).cast("long"))).select("o_orderkey"), "SELECT o_orderkey FROM orders WHERE (o_orderpriority, o_orderkey) < ('2-HIGH', 500)")
plain("fn_cast", "lineitem", lambda t: t.groupBy("l_returnflag").agg(F.sum(c("l_extendedprice").cast("decimal(18,2)")).cast("string").alias("d"), F.sum(F.expr("try_cast(l_linestatus AS int)")).alias("none")).select("l_returnflag", "d", c("none").cast("long").alias("none")), "SELECT l_returnflag, sum(l_extendedprice::DECIMAL(18,2))::VARCHAR AS d, sum(try_cast(l_linestatus AS INT))::BIGINT AS none FROM lineitem GROUP BY 1")
plain("fn_conditional", "part", lambda t: t.select("p_partkey", F.coalesce(F.nullif("p_size", F.lit(10)), F.lit(-1)).cast("long").alias("z"), F.greatest("p_size", F.lit(25)).cast("long").alias("g"), F.least("p_size", F.lit(25)).cast("long").alias("l")), "SELECT p_partkey, coalesce(nullif(p_size, 10), -1)::BIGINT AS z, greatest(p_size, 25)::BIGINT AS g, least(p_size, 25)::BIGINT AS l FROM part")


@op("fn_bits", "SELECT i::BIGINT AS i, list_sum(list_transform(range(0, 8), lambda b: ((i >> b) & 1) << (7 - b)))::BIGINT AS r FROM (SELECT DISTINCT event_id % 256 AS i FROM events)")
def _bits(spark: SparkSession, d: str) -> DataFrame:
    """The bit-reversal permutation of 256 places, at those that ids of events take."""
    return table(spark, d, "events").select((c("event_id") % 256).alias("id")).distinct().select(c("id").alias("i"), F.conv(F.reverse(F.lpad(F.conv(c("id").cast("string"), 10, 2), 8, "0")), 2, 10).cast("long").alias("r"))


plain("fn_html", "pages", lambda t: t.select("page_id", F.trim(F.regexp_replace(F.regexp_replace("html", r"(?is)<(script|style)[^>]*>.*?</\1>|<!--.*?-->|<[^>]*>", " "), r"\s+", " ")).alias("text")))


# User functions.


plain("udf_arrow_locate", "lineitem", lambda t: t.groupBy(bucketing.locate_arrow("l_extendedprice", [10000.0 * i for i in range(1, 1000)]).alias("bucket")).agg(n().alias("cnt")), SQL["join_range_bucket"])


def _fold(v: pd.Series) -> int:
    return int(v.sum())


plain("udaf_ledger_fold", "orders", lambda t: t.groupBy("o_orderpriority").agg(F.pandas_udf(_fold, "long", F.PandasUDFType.GROUPED_AGG)(F.col("o_orderkey")).alias("s")), "SELECT o_orderpriority, sum(o_orderkey)::BIGINT AS s FROM orders GROUP BY 1")


class SortPlan:
    """A row for each k of a setting: the cost of sorting n records."""

    def eval(self, n: int, M: int, B: int, omega: int):
        from writelite.functions import bounds
        from writelite.functions.model import MachineParams

        for k in range(1, omega + 1):
            yield k, bounds.mergesort_cost(n, MachineParams(M, B, omega, k))


@op("udtf_sort_plan", "WITH g AS (SELECT unnest(range(1, 9)) AS k), f AS (SELECT k, greatest(2, k * 16) AS fan, 938 AS nb FROM g) SELECT k::BIGINT AS k, ((CASE WHEN k = 1 THEN 9 ELSE 9 + k END) * nb * list_filter(range(1, 64), lambda t: pow(fan, t) >= nb)[1])::BIGINT AS cost FROM f")
def _udtf(spark: SparkSession, d: str) -> DataFrame:
    spark.udtf.register("sort_plan", F.udtf(SortPlan, returnType="k long, cost long"))
    return spark.sql("SELECT * FROM sort_plan(15000, 256, 16, 8)")


plain("group_apply", "orders", lambda t: t.select("o_orderpriority", "o_orderkey").groupBy("o_orderpriority").applyInPandas(lambda p: pd.DataFrame({"o_orderpriority": p.o_orderpriority[:1], "span": [int(p.o_orderkey.max() - p.o_orderkey.min())]}), "o_orderpriority string, span long"), "SELECT o_orderpriority, max(o_orderkey) - min(o_orderkey) AS span FROM orders GROUP BY 1")
plain("cogroup_apply", "customer supplier", lambda u, s: u.select("c_nationkey", "c_custkey").groupBy("c_nationkey").cogroup(s.select("s_nationkey", "s_suppkey").groupBy("s_nationkey")).applyInPandas(lambda a, b: pd.DataFrame({"nation": [int(a.c_nationkey.iloc[0] if len(a) else b.s_nationkey.iloc[0])], "pairs": [len(a) * len(b)]}), "nation long, pairs long"), "SELECT coalesce(c_nationkey, s_nationkey)::BIGINT AS nation, (coalesce(a, 0) * coalesce(b, 0))::BIGINT AS pairs FROM (SELECT c_nationkey, count(*) AS a FROM customer GROUP BY 1) FULL JOIN (SELECT s_nationkey, count(*) AS b FROM supplier GROUP BY 1) ON c_nationkey = s_nationkey")


@op("sql_function_cost", "SELECT l_returnflag, (count(*) + 8 * count(DISTINCT l_orderkey))::BIGINT AS cost FROM lineitem GROUP BY 1")
def _sql_function(spark: SparkSession, d: str) -> DataFrame:
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION aem_cost(r BIGINT, w BIGINT, omega BIGINT) RETURNS BIGINT RETURN r + omega * w")
    table(spark, d, "lineitem").createOrReplaceTempView("writelite_lineitem")
    return spark.sql("SELECT l_returnflag, aem_cost(reads, writes, 8) AS cost FROM (SELECT l_returnflag, count(*) AS reads, count(DISTINCT l_orderkey) AS writes FROM writelite_lineitem GROUP BY 1)")


@op("sql_view", "SELECT o_orderkey, row_number() OVER (ORDER BY o_totalprice, o_orderkey)::BIGINT AS pos FROM orders")
def _view(spark: SparkSession, d: str) -> DataFrame:
    QUERIES["win_global_rank"](spark, d).createOrReplaceTempView("writelite_ranked")
    return spark.sql("SELECT o_orderkey, pos FROM writelite_ranked")


def _arrow_rows(batches):
    import pyarrow.compute as pc

    for b in batches:
        yield b.filter(pc.greater(b.column("p_size"), 40))


plain("map_arrow", "part", lambda t: t.select("p_partkey", "p_size").mapInArrow(_arrow_rows, "p_partkey long, p_size int"), "SELECT p_partkey, p_size FROM part WHERE p_size > 40")


# Subqueries.
def sql(name: str, text: str, tables: str, oracle: str | None = None) -> None:
    """A query given in SQL that both engines take."""

    def q(spark: SparkSession, d: str) -> DataFrame:
        for t in tables.split():
            table(spark, d, t).createOrReplaceTempView(t)
        return spark.sql(text)

    op(name, oracle or text)(q)


sql("subq_scalar", "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT avg(o_totalprice) * 1.5 FROM orders)", "orders")
sql("subq_exists_correlated", "SELECT c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 300000)", "customer orders")
sql("subq_in", "SELECT p_partkey FROM part WHERE p_partkey IN (SELECT l_partkey FROM lineitem WHERE l_quantity > 49)", "part lineitem")
sql("not_in_null_safe", "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_custkey IS NOT NULL)", "customer orders")
sql("cte_chain", "WITH a AS (SELECT o_custkey, count(*) AS cnt FROM orders GROUP BY o_custkey), b AS (SELECT max(cnt) AS top FROM a) SELECT o_custkey, cnt FROM a JOIN b ON cnt = top", "orders")
sql("cte_recursive_levels", "WITH RECURSIVE l(t, reach, blocks) AS (SELECT 1, CAST(16 AS BIGINT), CAST(ceil(count(o_totalprice) / 16.0) AS BIGINT) FROM orders UNION ALL SELECT t + 1, reach * 16, blocks FROM l WHERE reach < blocks) SELECT CAST(max(t) AS BIGINT) AS lev FROM l", "orders")
