"""Streams over the events table: windows, joins, deduplication, and a priority queue as keyed state.

A flow is built from a streaming frame; run() drains a file source with availableNow into a Parquet sink and reads the
sink back, so that a batch query sees the final result. Event time is cast to TIMESTAMP, which watermarks need.
"""

from __future__ import annotations

import bisect
import heapq
import json
import math
import struct
import uuid

from pyspark.errors import StreamingQueryException
from pyspark.sql import DataFrame, Row, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from writelite.sources.formats import scratch

STORE = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


def source(spark: SparkSession, d: str, files: int = 1) -> DataFrame:
    """events as a stream of files; files > 1 cuts the table first, so that several micro-batches arrive in time order."""
    path = f"{d}/events.parquet"
    batch = spark.read.parquet(path)
    if files > 1:
        top = batch.agg(F.max("event_id")).first()[0] or 0
        path = scratch(spark, "events")
        for i in range(files):
            part = batch.where((F.col("event_id") > top * i // files) | (F.lit(i == 0))).where(F.col("event_id") <= top * (i + 1) // files)
            part.coalesce(1).write.mode("append").parquet(path)
        stream = spark.readStream.schema(batch.schema).option("maxFilesPerTrigger", 1).parquet(path)
    else:
        # A stream's path is a folder or a pattern, so a single file is named by a pattern.
        stream = spark.readStream.schema(batch.schema).parquet(f"{d}/events.parque[t]")
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def run(flow: DataFrame, mode: str = "append", checkpoint: str | None = None, sink: str | None = None) -> DataFrame:
    """Everything that is available, through a sink in the shared folder; update and complete go through foreachBatch.

    Each batch's rows carry the batch number; latest() keeps the last row of every key for update mode.
    """
    spark = flow.sparkSession
    checkpoint, sink = checkpoint or scratch(spark, "stream-state"), sink or scratch(spark, "stream-sink")
    writer = flow.writeStream.outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True)
    if mode == "append":
        query = writer.format("parquet").option("path", sink).start()
    else:
        query = writer.foreachBatch(lambda df, i: df.withColumn("__batch", F.lit(i)).write.mode("append").parquet(sink)).start()
    query.awaitTermination()
    schema = flow.schema if mode == "append" else flow.schema.add("__batch", "long")
    return spark.read.schema(schema).parquet(sink)


def latest(rows: DataFrame, *keys: str) -> DataFrame:
    """The last batch's row of every key."""
    rest = [c for c in rows.columns if c not in keys and c != "__batch"]
    got = rows.groupBy(*keys).agg(F.max_by(F.struct(*rest), "__batch").alias("x"))
    return got.select(*keys, "x.*")


def scan_watermark(s: DataFrame) -> DataFrame:
    return s.withWatermark("ts", "1 hour").where("event_type = 'click'").select("event_id", "user_id")


def tumbling(s: DataFrame) -> DataFrame:
    return s.withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour").alias("w"), "event_type").agg(F.count(F.lit(1)).alias("cnt")).select(F.unix_seconds(F.col("w.start")).alias("start"), "event_type", "cnt")


def sliding(s: DataFrame) -> DataFrame:
    return s.groupBy(F.window("ts", "1 hour", "15 minutes").alias("w")).agg(F.count(F.lit(1)).alias("cnt")).select(F.unix_seconds(F.col("w.start")).alias("start"), "cnt")


def sessions(s: DataFrame) -> DataFrame:
    return s.withWatermark("ts", "1 hour").groupBy(F.session_window("ts", "30 minutes").alias("w"), "user_id").agg(F.count(F.lit(1)).alias("cnt")).select(F.unix_micros(F.col("w.start")).alias("start"), "user_id", "cnt")


def dedup(s: DataFrame) -> DataFrame:
    twice = s.unionByName(s)
    return twice.withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"]).select("event_id")


def static_join(s: DataFrame, customers: DataFrame) -> DataFrame:
    return s.join(F.broadcast(customers), F.col("user_id") == F.col("c_custkey")).select("event_id", "c_mktsegment")


def interval_join(s: DataFrame) -> DataFrame:
    a = s.where("event_type = 'click'").select(F.col("user_id").alias("ua"), F.col("event_id").alias("click_id"), F.col("ts").alias("ta")).withWatermark("ta", "1 hour")
    b = s.where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("purchase_id"), F.col("ts").alias("tb")).withWatermark("tb", "1 hour")
    return a.join(b, F.expr("ua = user_id AND tb >= ta AND tb <= ta + INTERVAL 1 HOUR")).select("click_id", "purchase_id")


def packed(k1: float | None, k2: int | None) -> str:
    """A (double, long) key as text of one length that sorts as the key does: nulls first, then by number, NaN last.

    >>> sorted([(2.5, 1), (-3.0, 9), (None, 4), (-3.0, -9)], key=lambda k: packed(*k))
    [(None, 4), (-3.0, -9), (-3.0, 9), (2.5, 1)]
    """
    bits = struct.unpack(">Q", struct.pack(">d", k1 + 0.0 if k1 == k1 else math.nan))[0] if k1 is not None else 0
    number = "0" * 17 if k1 is None else f"1{bits ^ (2**64 - 1) if bits >> 63 else bits | 1 << 63:016x}"
    return number + ("0" * 17 if k2 is None else f"1{k2 + 2**63:016x}")


def unpacked(item: str) -> tuple[float | None, int | None]:
    """The key of a packed text.

    >>> unpacked(packed(-0.5, -7)), unpacked(packed(None, None))
    ((-0.5, -7), (None, None))
    """
    bits = int(item[1:17], 16)
    bits = bits ^ (1 << 63) if bits >> 63 else bits ^ (2**64 - 1)
    return (struct.unpack(">d", struct.pack(">Q", bits))[0] if item[0] == "1" else None), (int(item[18:], 16) - 2**63 if item[17] == "1" else None)


class BetaQueue(StatefulProcessor):
    """A priority queue a key: a small sorted alpha as one value, a beta list that is only appended to, and pairs
    (index, key) that say that of beta's first `index` records those with keys up to `key` are dead.

    Deletes take from alpha; an empty alpha takes the least live records of beta by one scan, which adds a pair; pairs
    rise in index and fall in key. After some such scans beta is packed. An append costs one put.
    """

    ROOM, SCANS, LAZY = 16, 4, True

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle = handle
        self.alpha = handle.getValueState("alpha", "items array<string>")
        self.dead = handle.getValueState("dead", "pairs array<struct<i: long, k: string>>, live long, length long, scans long, puts long")
        self.beta = handle.getListState("beta", "item string")

    def _load(self) -> None:
        self.items = list(self.alpha.get()[0]) if self.alpha.exists() else []
        pairs, self.live, self.length, self.scans, self.puts = self.dead.get() if self.dead.exists() else ([], 0, 0, 0, 0)
        self.pairs = [(p[0], p[1]) for p in pairs]

    def _save(self) -> None:
        self.alpha.update((self.items,))
        self.dead.update((self.pairs, self.live, self.length, self.scans, self.puts))

    def handleInputRows(self, key, rows, timerValues):
        self._load()
        out = []
        for r in sorted(rows, key=lambda r: r.seq):
            if r.op == "I":
                self._insert(packed(r.k1, r.k2))
                continue
            if not self.items and self.live:
                self._refill(timerValues)
            got = self.items.pop(0) if self.items else None
            k1, k2 = unpacked(got) if got else (None, None)
            out.append(Row(shard=key[0], seq=r.seq, k1=k1, k2=k2, puts=self.puts))
        self._save()
        yield from out

    def _insert(self, item: str) -> None:
        if self.items and item < self.items[-1] or not self.items and not self.live:
            bisect.insort(self.items, item)
            if len(self.items) <= self.ROOM:
                return
            item = self.items.pop()
        if not self.live and self.length:
            self._reset()
        self._append(item)
        self.length, self.live = self.length + 1, self.live + 1

    def _alive(self) -> list[str]:
        out, j = [], 0
        for i, (x,) in enumerate(self.beta.get()):
            while j < len(self.pairs) and self.pairs[j][0] <= i:
                j += 1
            if j == len(self.pairs) or x > self.pairs[j][1]:
                out.append(x)
        return out

    def _refill(self, timerValues) -> None:
        self.items = heapq.nsmallest(self.ROOM, self._alive())
        while self.pairs and self.pairs[-1][1] <= self.items[-1]:
            self.pairs.pop()
        self.pairs.append((self.length, self.items[-1]))
        self.live, self.scans = self.live - len(self.items), self.scans + 1
        if not self.live:
            self._reset()
        elif self.scans >= self.SCANS:
            self._compact(timerValues)

    def _compact(self, timerValues) -> None:
        self._pack()

    def _pack(self) -> None:
        keep = self._alive()
        self._reset()
        if keep:
            self.beta.put([(x,) for x in keep])
        self.length, self.live, self.puts = len(keep), len(keep), self.puts + len(keep)

    def _reset(self) -> None:
        self.beta.clear()
        self.pairs, self.live, self.length, self.scans = [], 0, 0, 0

    def _append(self, item: str) -> None:
        self.beta.appendValue((item,))
        self.puts += 1

    def close(self) -> None:
        pass


class EagerQueue(BetaQueue):
    """Rewrites the whole list at each insertion, for comparison."""

    def _append(self, item: str) -> None:
        whole = [*self.beta.get(), (item,)] if self.length else [(item,)]
        self.beta.put(whole)
        self.puts += len(whole)


class TimedQueue(BetaQueue):
    """Leaves packing to a timer on the watermark, which fires in a later batch, so that no delete waits for it."""

    def _compact(self, timerValues) -> None:
        if not list(self.handle.listTimers()):
            self.handle.registerTimer(timerValues.getCurrentWatermarkInMs() + 1)

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo):
        self._load()
        packed_away = self.length - self.live
        self._pack()
        self._save()
        yield Row(shard=key[0], seq=-1, k1=None, k2=packed_away, puts=self.puts)


def queue(s: DataFrame, processor: StatefulProcessor, time: str = "None") -> DataFrame:
    """Delete-mins (shard, seq, k1, k2, puts) of the events of each user: purchases delete, others insert (value, id).

    With time "EventTime" timers fire on a watermark; what one of them packed away is a row of its own, with seq -1.
    (Timers on the clock would keep a stream that drains what is available from ever ending.)
    """
    s.sparkSession.conf.set("spark.sql.streaming.stateStore.providerClass", STORE)
    ops = s.select(F.col("user_id").alias("shard"), F.col("event_id").alias("seq"), F.when(F.col("event_type") == "purchase", "D").otherwise("I").alias("op"), F.col("value").alias("k1"), F.col("event_id").alias("k2"), *["ts"] * (time == "EventTime"))
    ops = ops.withWatermark("ts", "1 minute") if time == "EventTime" else ops
    return ops.groupBy("shard").transformWithState(processor, "shard long, seq long, k1 double, k2 long, puts long", "Append", time)


def running_top(spark: SparkSession, stream: DataFrame, m: int = 20) -> DataFrame:
    """Top m values by foreachBatch: a batch's rows below the m-th value so far are skipped before they are ordered."""
    best: list[tuple] = []

    def merge(df: DataFrame, _: int) -> None:
        nonlocal best
        if len(best) == m:
            df = df.where(F.col("value") >= best[-1][0])
        rows = [(r.value, r.event_id) for r in df.select("value", "event_id").orderBy(F.desc("value"), "event_id").limit(m).collect()]
        best = sorted({*best, *rows}, key=lambda x: (-x[0], x[1]))[:m]

    query = stream.writeStream.foreachBatch(merge).option("checkpointLocation", scratch(spark, "stream-state")).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.createDataFrame(best, "value double, event_id long")


def dropped_late(spark: SparkSession, d: str) -> DataFrame:
    """Whether a 10-minute watermark drops exactly the groups that it must when the oldest rows arrive in a last file.

    The query's progress counts what comes to the state operator: the late rows' windows that have ended before the
    watermark. Late rows are held against the watermark of the batch before, which the first file has set.
    """
    batch = spark.read.parquet(f"{d}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    path, late = scratch(spark, "late"), F.pmod(F.xxhash64("event_id"), F.lit(20)) == 0
    mid = batch.agg(F.percentile_approx("event_id", 0.5)).first()[0] or 0
    for part in (batch.where((F.col("event_id") <= mid) & ~late), batch.where((F.col("event_id") > mid) & ~late), batch.where((F.col("event_id") <= mid) & late)):
        part.coalesce(1).write.mode("append").parquet(path)
    stream = spark.readStream.schema(batch.schema).option("maxFilesPerTrigger", 1).parquet(path)
    flow = stream.withWatermark("ts", "10 minutes").groupBy(F.window("ts", "1 hour")).agg(F.count(F.lit(1)).alias("cnt"))
    query = flow.writeStream.format("noop").outputMode("append").option("checkpointLocation", scratch(spark, "stream-state")).trigger(availableNow=True).start()
    query.awaitTermination()
    dropped = sum(o["numRowsDroppedByWatermark"] for p in map(_progress, query.recentProgress) for o in p["stateOperators"])
    mark = batch.where((F.col("event_id") <= mid) & ~late).agg(F.max(F.unix_micros("ts"))).first()[0] - 600_000_000
    gone = batch.where((F.col("event_id") <= mid) & late).select((F.floor(F.unix_micros("ts") / 3_600_000_000) + 1).alias("hour")).where(F.col("hour") * 3_600_000_000 <= mark // 1000 * 1000).distinct().count()
    return spark.createDataFrame([("late", dropped == gone and gone > 0)], "measure string, ok boolean")


def _progress(p) -> dict:
    return json.loads(p.json) if hasattr(p, "json") else p


def restart(spark: SparkSession, d: str) -> DataFrame:
    """Clicks through a stream that is broken off in its second batch, after that batch was written but before it was
    committed, and started again on its checkpoint: the batch comes again, replaces its own folder, and every row is
    there once.
    """
    name = uuid.uuid4().hex
    state, sink = scratch(spark, f"restart-state-{name}"), scratch(spark, f"restart-sink-{name}")
    stream = scan_watermark(source(spark, d, 3))

    def start(broken: bool) -> None:
        def write(df: DataFrame, i: int) -> None:
            df.write.mode("overwrite").parquet(f"{sink}/batch={i}")
            if broken and i == 1:
                raise RuntimeError("broken off")

        query = stream.writeStream.foreachBatch(write).option("checkpointLocation", state).trigger(availableNow=True).start()
        query.awaitTermination()

    try:
        start(True)
        raise AssertionError("the stream was not broken off")
    except StreamingQueryException:
        start(False)
    return spark.read.schema(stream.schema.add("batch", "integer")).parquet(sink).drop("batch")
