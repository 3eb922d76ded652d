"""Benchmark decontamination by the q-gram lemma.

An item of m characters that occurs in a text with at most k edits shares at least m - q + 1 - k q of its q-grams with
the text, and their diagonals (place in the text less place in the item) lie within k of each other. Shared q-grams are
counted in diagonal bands 2k + 1 wide that overlap by half; a band that reaches the bound is a region, which banded
alignment then verifies. k is `edits` times the item's length. Texts are compared in lower case with runs of white
space as one blank. The benchmark is a stated query set: it is broadcast in blocks of at most BLOCK_MB, one scan each.
"""

from __future__ import annotations

import functools
import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from writelite.llm.common import lean

Q, EDITS, BLOCK_MB = 8, 0.1, 16
U64 = np.uint64


def normal(text: str) -> str:
    """Lower case, white space runs as one blank, none at the ends.

    >>> normal("  A\\n b ")
    'a b'
    """
    return " ".join(text.lower().split())


def codes(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le", "surrogatepass"), dtype=np.uint32)


def grams(c: np.ndarray, q: int) -> np.ndarray:
    """A 64-bit hash of the q characters from each place on, of a byte each; q is at most 8."""
    n = len(c) - q + 1
    if n <= 0:
        return np.zeros(0, dtype=U64)
    folded = np.zeros(len(c) + 8, dtype=np.uint8)
    folded[: len(c)] = (c ^ (c >> 8) ^ (c >> 16)).astype(np.uint8)
    packed = np.ndarray((n,), dtype="<u8", buffer=folded.data, strides=(1,))
    with np.errstate(over="ignore"):
        h = (packed & U64((1 << 8 * q) - 1)) * U64(0x9E3779B97F4A7C15)
        return h ^ (h >> U64(29))


class Items:
    """The benchmark's q-grams by hash, with a bitmap that most q-grams of a text fail."""

    BITS = 20

    def __init__(self, items: list[tuple[int, str]], q: int, edits: float) -> None:
        if not 1 <= q <= 8:
            raise ValueError("q must be 1 to 8")
        self.ids = [i for i, _ in items]
        self.codes = [codes(normal(t)) for _, t in items]
        self.q = q
        m = np.array([len(c) for c in self.codes], dtype=np.int64)
        # An item too short for the lemma at its budget gets the largest budget that leaves it a bound of 1.
        self.budget = np.maximum(np.minimum((edits * m).astype(np.int64), (m - q) // q), 0)
        self.least = np.maximum(m - q + 1 - self.budget * q, 1)
        per = [grams(c, q) for c in self.codes]
        every = np.concatenate([np.zeros(0, U64), *per])
        item = np.repeat(np.arange(len(per)), [len(x) for x in per])
        place = np.concatenate([np.zeros(0, np.int64), *[np.arange(len(x)) for x in per]])
        order = np.argsort(every, kind="stable")
        self.hash, self.first, self.count = np.unique(every[order], return_index=True, return_counts=True)
        self.item, self.place = item[order], place[order]
        self.bitmap = np.zeros(1 << self.BITS, dtype=bool)
        self.bitmap[self._slot(self.hash)] = True

    def _slot(self, h: np.ndarray) -> np.ndarray:
        return (h >> U64(64 - self.BITS)).astype(np.int64)

    def regions(self, texts: list[np.ndarray]) -> list[tuple[int, int, int, int]]:
        """(text, item, least, largest diagonal) of the bands that reach the item's bound."""
        if not len(self.hash):
            return []
        ends = np.cumsum([len(t) for t in texts])
        g = grams(np.concatenate(texts), self.q)
        at = np.flatnonzero(self.bitmap[self._slot(g)])
        found = np.minimum(np.searchsorted(self.hash, g[at]), len(self.hash) - 1)
        same = self.hash[found] == g[at]
        at, found = at[same], found[same]
        text = np.searchsorted(ends, at, side="right")
        inside = at + self.q <= ends[text]
        at, found, text = at[inside], found[inside], text[inside]
        n = self.count[found]
        where = np.repeat(self.first[found] - np.r_[0, np.cumsum(n)[:-1]][: len(n)], n) + np.arange(n.sum())
        item, text, at = self.item[where], np.repeat(text, n), np.repeat(at, n)
        # No band of an item holds more q-grams than the whole text shares with it.
        pair = text * len(self.ids) + item
        _, back, shared = np.unique(pair, return_inverse=True, return_counts=True)
        near = shared[back] >= self.least[item]
        # From here a pair goes by its rank: ranks and diagonals fit in 64 bits together, whatever texts and items are.
        item, text, at, pair, where = item[near], text[near], at[near], back[near], where[near]
        # Bands start at multiples of k + 1 and are 2k + 2 wide, so diagonals within k of each other share a band.
        width, shift = self.budget[item] + 1, 1 << 32
        starts = np.r_[0, ends[:-1]]
        half = (at - starts[text] - self.place[where] + shift) // width
        keys, first, counts = np.unique(np.concatenate([pair << 33 | half, pair << 33 | (half - 1)]), return_index=True, return_counts=True)
        first %= max(len(pair), 1)
        good = counts >= self.least[item[first]] if len(keys) else np.zeros(0, bool)
        keys, first = keys[good], first[good]
        w = self.budget[item[first]] + 1
        low = (keys & ((1 << 33) - 1)) * w - shift
        return list(zip(text[first].tolist(), item[first].tolist(), low.tolist(), (low + 2 * w - 1).tolist(), strict=True))

    def verify(self, text: np.ndarray, item: int, low: int, high: int) -> tuple[int, int] | None:
        """(edits, end in the text) of the best alignment of the whole item inside the band, or None above its budget."""
        pattern, k = self.codes[item], int(self.budget[item])
        for d in range(max(low, 0), min(high, len(text) - len(pattern)) + 1):
            if np.array_equal(text[d : d + len(pattern)], pattern):
                return 0, d + len(pattern)
        diagonals = np.arange(low - k, high + k + 1)
        inside = np.zeros(len(diagonals) + len(pattern), dtype=np.int64)  # text along the band; 0 outside the text
        lo, hi = max(low - k, 0), min(high + k + len(pattern), len(text))
        if hi <= lo:
            return None
        inside[lo - (low - k) : hi - (low - k)] = text[lo:hi].astype(np.int64) + 1
        far, steps = len(pattern) + k + 1, np.arange(len(diagonals))
        row = np.where((diagonals >= 0) & (diagonals <= len(text)), 0, far)  # an alignment may start anywhere
        for i, c in enumerate(pattern):
            new = row + (inside[i : i + len(diagonals)] != int(c) + 1)
            new[:-1] = np.minimum(new[:-1], row[1:] + 1)
            row = np.minimum.accumulate(new - steps) + steps
            if row.min() > k:
                return None
        row = np.where(diagonals + len(pattern) <= len(text), row, far)
        end = int(row.argmin())
        return (int(row[end]), int(diagonals[end]) + len(pattern)) if row[end] <= k else None

    def find(self, texts: list[str | None], slab: int = 1_000_000) -> list[list[tuple[int, int, int]]]:
        """For every text, (item id, edits, end) of each item that it holds: the best of its bands."""
        out: list[list[tuple[int, int, int]]] = []
        i = 0
        while i < len(texts):
            some, size = [], 0
            while i + len(some) < len(texts) and size < slab:
                some.append(codes(normal(texts[i + len(some)] or "")))
                size += len(some[-1])
            best: dict[tuple[int, int], tuple[int, int]] = {}
            for t, item, low, high in self.regions(some):
                if best.get((t, item), (1, 0))[0] > 0 and (x := self.verify(some[t], item, low, high)) and x < best.get((t, item), (len(some[t]) + 1, 0)):
                    best[t, item] = x
            per: list[list[tuple[int, int, int]]] = [[] for _ in some]
            for (t, item), (e, end) in sorted(best.items()):
                per[t].append((self.ids[item], e, end))
            out += per
            i += len(some)
        return out


_built: dict[str, Items] = {}


def _items(sent: Broadcast, stamp: str, q: int, edits: float) -> Items:
    """The index of a block, built once in a worker process."""
    if stamp not in _built:
        _built.clear()
        _built[stamp] = Items(sent.value, q, edits)
    return _built[stamp]


def _find_rows(sent: Broadcast, stamp: str, q: int, edits: float):
    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        items = _items(sent, stamp, q, edits)
        for batch in batches:
            rows, order = [], []
            for r, found in enumerate(items.find(batch.column(1).to_pylist())):
                order += [r] * len(found)
                rows += found
            kind = pa.int64()
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(order, kind)), *[pa.array([x[j] for x in rows], kind) for j in range(3)]], names=["k", "item_id", "edits", "end"])

    return go


def _clean_rows(sent: Broadcast, stamp: str, q: int, edits: float, text: str):
    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        items = _items(sent, stamp, q, edits)
        for batch in batches:
            yield batch.filter(pa.array([not x for x in items.find(batch.column(text).to_pylist())], pa.bool_()))

    return go


def _blocks(items: DataFrame, q: int, block_mb: float) -> Iterator[tuple[Broadcast, str]]:
    spark = items.sparkSession
    asked = items.select(F.col("item_id").cast("long").alias("i"), F.col("text").alias("t")).where("t IS NOT NULL AND i IS NOT NULL")
    mb = (asked.agg(F.sum(F.octet_length("t")).alias("b")).first()["b"] or 0) / 1e6
    blocks = max(1, int(-(-mb // block_mb)))
    for b in range(blocks):
        part = sorted((r["i"], r["t"]) for r in asked.where(F.pmod(F.xxhash64("i", "t"), F.lit(blocks)) == b).collect())
        part = [x for x in part if len(normal(x[1])) >= q]
        yield spark.sparkContext.broadcast(part), hashlib.sha256(repr((part, q)).encode()).hexdigest()


def hits(df: DataFrame, items: DataFrame, key: str = "doc_id", text: str = "text", q: int = Q, edits: float = EDITS, block_mb: float = BLOCK_MB) -> DataFrame:
    """Rows (key, item_id, edits, end) for every item that occurs in a text within its edit budget.

    end is the place after the occurrence in the normalised text. Null and empty texts hold nothing; items that are
    null or shorter than q characters when normalised match nothing; equal item texts all match; repeated rows give
    repeated hits; a null key is kept; empty tables give no rows.
    """
    schema = f"`{key}` {dict(df.dtypes)[key]}, item_id long, edits long, end long"
    found = [df.select(key, text).mapInArrow(lean(_find_rows(sent, stamp, q, edits)), schema) for sent, stamp in _blocks(items, q, block_mb)]
    return functools.reduce(DataFrame.unionByName, found)


def report(df: DataFrame, items: DataFrame) -> DataFrame:
    """(doc_id, n_items, item_ids, least_edits) of the documents that hold an item; item_ids in order, joined by commas."""
    found = hits(df, items).groupBy("doc_id").agg(F.array_sort(F.collect_set("item_id")).alias("i"), F.min("edits").alias("least_edits"))
    return found.select("doc_id", F.size("i").cast("long").alias("n_items"), F.array_join(F.transform("i", lambda x: x.cast("string")), ",").alias("item_ids"), "least_edits")


def clean(df: DataFrame, items: DataFrame, text: str = "text", q: int = Q, edits: float = EDITS, block_mb: float = BLOCK_MB) -> DataFrame:
    """The rows of df that hold no item, with all their columns; nothing is shuffled."""
    for sent, stamp in _blocks(items, q, block_mb):
        df = df.mapInArrow(lean(_clean_rows(sent, stamp, q, edits, text)), df.schema)
    return df
