"""Shared helpers: folders that executors share, vectorised word hashes, and exchanges of packed arrays.

Words are the maximal runs of bytes other than space and 0x09-0x0D. Hashes are 64 bits wide and depend only on
the bytes, so a task that is run again on another executor gives the same rows.
"""

from __future__ import annotations

import ctypes
import functools
import tempfile
import uuid
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

U64 = np.uint64


#: Tables that this process has written in the shared folder and not yet swept away.
_written: list[str] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder that the driver and all executors see: spark.checkpoint.dir, or in local mode one of its own."""
    sc = spark.sparkContext
    if not sc.getCheckpointDir():
        folder = spark.conf.get("spark.checkpoint.dir", None)
        if not folder and not (sc.master == "local" or sc.master.startswith("local[")):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors see")
        sc.setCheckpointDir(folder or tempfile.mkdtemp(prefix="writelite_"))
    return sc.getCheckpointDir().rstrip("/")


def stored(df: DataFrame, name: str, files: int | None = None) -> DataFrame:
    """Write a table once in the shared folder and read it back: later scans prune columns, and lineage ends here.

    files: at most so many, where the table is known to be small for its number of partitions.
    """
    path = f"{shared_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    (df.coalesce(files) if files else df).write.parquet(path)
    _written.append(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def written() -> frozenset[str]:
    """The tables that `stored` has written in this process and `sweep` has not deleted."""
    return frozenset(_written)


def sweep(spark: SparkSession, paths: Iterable[str]) -> None:
    """Delete tables in the shared folder, when nothing reads them any more."""
    for path in paths:
        at = spark._jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)
        if path in _written:
            _written.remove(path)


def tasks_for(spark: SparkSession, size: int, each: int = 32_000_000) -> int:
    """Tasks for `size` bytes: one for each `each` of them, and no fewer than the cluster runs at once."""
    return max(spark.sparkContext.defaultParallelism, -(-int(size) // each), 1)


@functools.lru_cache(maxsize=1)
def _libc():
    try:
        return ctypes.CDLL("libc.so.6")
    except OSError:
        return None


def give_back() -> None:
    """Hand freed memory back to the system: allocators keep it otherwise, in every worker that waits for its next task."""
    pa.default_memory_pool().release_unused()
    if (libc := _libc()) is not None:
        libc.malloc_trim(0)


def lean(go: Callable) -> Callable:
    """A function over Arrow batches that gives its memory back when a partition ends."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from go(batches)
        finally:
            give_back()

    return run


_seen = [0]


def _passed(size: int, each: int = 8_000_000) -> None:
    _seen[0] += size
    if _seen[0] >= each:
        _seen[0] = 0
        give_back()


def lean_group(go: Callable) -> Callable:
    """A function over the Arrow table of a group that gives memory back after some megabytes of groups."""

    def run(table: pa.Table) -> pa.Table:
        out, size = go(table), table.nbytes
        _passed(size)
        return out

    return run


def lean_pair(go: Callable) -> Callable:
    """The same for the two tables of a cogroup."""

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        out, size = go(left, right), left.nbytes + right.nbytes
        _passed(size)
        return out

    return run


def bucket_count(spark: SparkSession, items: int, each: int) -> int:
    """Buckets for an exchange of packed arrays: enough that each holds about `each` items, and as many as partitions."""
    return int(max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-max(items, 0) // each), 1))


def _powers(base: int, n: int) -> np.ndarray:
    out = np.full(n, base, dtype=U64)
    if n:
        out[0] = 1
    with np.errstate(over="ignore"):
        return np.multiply.accumulate(out)


def mix(h: np.ndarray) -> np.ndarray:
    """A bijection on 64 bits that spreads every input bit."""
    h = (h ^ (h >> U64(30))) * U64(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> U64(27))) * U64(0x94D049BB133111EB)
    return h ^ (h >> U64(31))


class Rolling:
    """Hashes of slices of a sequence of 64-bit values, by differences of one running sum."""

    BASE = 0x9E3779B97F4A7C15 | 1
    KEPT = 1_000_000

    def __init__(self) -> None:
        self.up = self.down = np.ones(0, dtype=U64)

    def tables(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        """Powers of the base and of its inverse; kept up to KEPT of them, made anew for longer sequences."""
        if len(self.up) < n:
            made = _powers(self.BASE, n), _powers(pow(self.BASE, -1, 2**64), n)
            if n > self.KEPT:
                return made
            self.up, self.down = made
        return self.up[:n], self.down[:n]

    def slices(self, values: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        up, down = self.tables(len(values) + 1)
        total = np.zeros(len(values) + 1, dtype=U64)
        np.cumsum(values * up[:-1], out=total[1:])
        return mix((total[end] - total[start]) * down[start] + (end - start).astype(U64) * U64(0xD6E8FEB86659FD93))


ROLLING = Rolling()
_rng = np.random.Generator(np.random.PCG64(20240117))
BYTE = _rng.integers(0, 2**64, 256, dtype=U64)
BYTE_LOWER = BYTE.copy()
BYTE_LOWER[65:91] = BYTE[97:123]
SPACE = np.zeros(256, dtype=bool)
SPACE[[9, 10, 11, 12, 13, 32]] = True


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of an Arrow string column; a null is an empty text."""
    column = column.cast(pa.large_string()).fill_null("")
    offsets = np.frombuffer(column.buffers()[1], dtype=np.int64)[column.offset : column.offset + len(column) + 1]
    data = column.buffers()[2]
    data = np.frombuffer(data, dtype=np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return data[offsets[0] : offsets[-1]] if len(offsets) else data, offsets - offsets[0]


def word_hashes(data: np.ndarray, offsets: np.ndarray, lower: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """(hash of every word, word offsets of every text) of texts that lie one after another in `data`."""
    if not len(data):
        return np.zeros(0, dtype=U64), np.zeros(len(offsets), dtype=np.int64)
    ink = ~SPACE[data]
    first = np.zeros(len(data) + 1, dtype=bool)
    first[offsets] = True
    start = ink.copy()
    start[1:] &= ~ink[:-1] | first[1:-1]
    end = ink.copy()
    end[:-1] &= ~ink[1:] | first[1:-1]
    start, end = np.flatnonzero(start), np.flatnonzero(end) + 1
    with np.errstate(over="ignore"):
        hashes = ROLLING.slices((BYTE_LOWER if lower else BYTE)[data], start, end)
    return hashes, np.searchsorted(start, offsets).astype(np.int64)


def window_hashes(words: np.ndarray, width: int) -> np.ndarray:
    """Hash of the `width` words from each place on; shorter than `words` by width - 1."""
    n = max(len(words) - width + 1, 0)
    at = np.arange(n)
    with np.errstate(over="ignore"):
        return ROLLING.slices(words, at, at + width)


def slabs(batch: pa.RecordBatch, column: str, most: int = 2_000_000) -> Iterator[pa.RecordBatch]:
    """Slices of a batch of about `most` bytes of text each (a longer text is a slice of its own)."""
    _, offsets = text_bytes(batch.column(column))
    i = 0
    while i < len(batch):
        j = max(int(np.searchsorted(offsets, offsets[i] + most, side="right")) - 1, i + 1)
        yield batch.slice(i, j - i)
        i = j


def scatter(bucket: np.ndarray, *arrays: np.ndarray) -> Iterator[tuple[int, list[bytes]]]:
    """The rows of `arrays` dealt out by bucket, packed: (bucket, bytes of each array)."""
    if not len(bucket):
        return
    order = np.argsort(bucket, kind="stable")
    bucket = bucket[order]
    arrays = tuple(a[order] for a in arrays)
    cuts = np.flatnonzero(np.r_[True, bucket[1:] != bucket[:-1]])
    for i, j in zip(cuts, np.r_[cuts[1:], len(bucket)], strict=True):
        yield int(bucket[i]), [a[i:j].tobytes() for a in arrays]


def gather(table: pa.Table, column: str, kind: str) -> np.ndarray:
    """The packed arrays of a column one after another."""
    return np.frombuffer(b"".join(x for x in table.column(column).to_pylist() if x), dtype=kind)


def runs(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and lengths of the runs of equal sorted keys."""
    if not len(keys):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    starts = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]])
    return starts, np.diff(np.r_[starts, len(keys)])


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def lowest(df: DataFrame, key: str, wanted: int, *ties: str) -> DataFrame:
    """The `wanted` rows whose keys hash lowest. Rows that cannot be among them are left out by a bound on the hash before
    anything is ordered, so that no task or driver gets `wanted` rows of every partition.
    """
    n = df.count()
    share = min(1.0, (1.1 * wanted + 300) / max(n, 1))
    few = df if share >= 1 else df.where(F.xxhash64(key) <= int(-(2**63) + share * (2**64 - 1)))
    return few.orderBy(F.xxhash64(key), *ties).limit(wanted)


def total_bytes(df: DataFrame, text: str | Column) -> int:
    """UTF-8 bytes of a text column over all rows; sizes exchanges."""
    return int(df.agg(F.sum(F.octet_length(text)).alias("b")).first()["b"] or 0)


def components(links: DataFrame) -> DataFrame:
    """Connected components of links (a long, b long): rows (node, root), root the least node; isolated nodes do not occur.

    Alternates two steps until nothing changes: every node tells its larger neighbours of its least neighbour, then
    every node tells its smaller neighbours and itself of it. Rounds grow with the logarithm of the longest chain. Links stay distributed, a
    hub's links are reduced by partial minima before they meet, and each round is written in the shared folder.
    """

    def both(e: DataFrame) -> DataFrame:
        return e.select("a", "b").union(e.select(F.col("b").alias("a"), F.col("a").alias("b")))

    def least(e: DataFrame) -> DataFrame:
        return e.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))

    # Tables of links are narrow: as many files as tasks run at once, and more only where the links are many.
    files = tasks_for(links.sparkSession, 0)
    edges = stored(links.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).where("a <> b").distinct(), "links", files)
    last = edges.agg(F.count(F.lit(1)), F.sum(F.hash("a", "b").cast("long"))).first()
    if not last[0]:
        return edges.select(F.col("a").alias("node"), F.col("b").alias("root"))
    while True:
        files = tasks_for(links.sparkSession, 16 * last[0])
        wide = both(edges)
        large = wide.join(least(wide), "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).distinct()
        low = least(large)
        small = large.join(low, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).union(low.select("a", F.col("m").alias("b")))
        edges = stored(small.where("a <> b").distinct(), "links", files)
        now = edges.agg(F.count(F.lit(1)), F.sum(F.hash("a", "b").cast("long"))).first()
        if now == last:
            break
        last = now
    star = edges.groupBy("a").agg(F.min("b").alias("root")).select(F.col("a").alias("node"), "root")
    return star.union(star.select(F.col("root").alias("node"), "root").distinct())
