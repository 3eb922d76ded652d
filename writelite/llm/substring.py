"""Substring dedup by difference-cover anchors.

A window is `width` consecutive words. Positions of a text are covered modulo a period so that for any two shifts some
offset below the period puts both on covered positions; hence two equal windows share an aligned anchor of
width - period + 1 words at covered positions of both. Only anchors are exchanged at first. Windows around an anchor
that occurs twice are then hashed whole, and every one but the earliest of its words is dropped.

Exact copies of a text are settled beforehand by its hash: all windows of a later copy start earlier. Equal hashes
inside a task are settled there and only one of them is sent, so a passage that many texts share costs one record a task.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from writelite.llm.common import bucket_count, gather, lean, lean_group, runs, scatter, slabs, text_bytes, total_bytes, window_hashes, word_hashes

WIDTH, PERIOD, COVER = 20, 13, (0, 1, 3, 9)
LAST = np.iinfo(np.int64).max
U64 = np.uint64
SENT = "b int, hash binary, who binary, pos binary, ks binary, hs binary, fwho binary, fpos binary"
TOLD = "g int, ks binary, hs binary, at binary"
FOUND = "k long, h long, at binary"


def covers(period: int, cover: tuple[int, ...]) -> bool:
    """Whether any two residues have a common offset that puts both on the cover: every difference is one of two of its members.

    >>> covers(13, (0, 1, 3, 9)), covers(13, (0, 1, 3))
    (True, False)
    """
    return {(a - b) % period for a in cover for b in cover} == set(range(period))


def _sorted_groups(h: np.ndarray, *order: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(permutation by hash then by order, run starts, run lengths)."""
    p = np.lexsort((*order[::-1], h)) if order else np.argsort(h, kind="stable")
    starts, n = runs(h[p])
    return p, starts, n


def _send(buckets: int, hashes: np.ndarray, who: np.ndarray, pos: np.ndarray, ks: np.ndarray, hs: np.ndarray, known: tuple[np.ndarray, np.ndarray]) -> list[tuple]:
    rows: dict[int, list] = {}
    for b, (x, w, p) in scatter((hashes % U64(buckets)).astype(np.int64), hashes, who.astype("<u4"), pos.astype("<u4")):
        rows[b] = [x, w, p, b"", b""]
    fwho, fpos = known
    owner = (hs[fwho].view(U64) % U64(buckets)).astype(np.int64) if len(fwho) else np.zeros(0, np.int64)
    for b, (w, p) in scatter(owner, fwho.astype("<u4"), fpos.astype("<u4")):
        rows.setdefault(b, [b"", b"", b"", b"", b""])[3:] = [w, p]
    out = []
    for b, (x, w, p, fw, fp) in rows.items():
        # Each row has its own list of the texts that it names.
        used, back = np.unique(np.frombuffer(w + fw, "<u4"), return_inverse=True)
        back = back.astype("<u4")
        n = len(w) // 4
        out.append((b, x, back[:n].tobytes(), p, ks[used].tobytes(), hs[used].tobytes(), back[n:].tobytes(), fp))
    return out


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    types = [pa.int32(), *[pa.binary()] * 7]
    return pa.RecordBatch.from_arrays([pa.array([r[c] for r in rows], t) for c, t in enumerate(types)], names=[x.split()[0] for x in SENT.split(", ")])


def _texts(part: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(word hashes, word offsets, keys with null as the last, text hashes)."""
    words, offsets = word_hashes(*text_bytes(part.column("t")))
    return words, offsets, part.column("k").fill_null(LAST).to_numpy(), part.column("h").to_numpy()


def _anchor_rows(width: int, period: int, cover: tuple[int, ...], buckets: int):
    size = width - period + 1

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slabs(batch, "t"):
                words, offsets, ks, hs = _texts(part)
                if not len(words):
                    continue
                n = np.diff(offsets)
                who = np.repeat(np.arange(len(n)), n)
                pos = np.arange(len(words)) - offsets[who]
                on = np.isin(np.arange(period), cover)[pos % period] & (pos + size <= n[who]) & (n[who] >= width)
                at = np.flatnonzero(on)
                if not len(at):
                    continue
                h, who, pos = window_hashes(words, size)[at], who[at], pos[at]
                p, starts, count = _sorted_groups(h)
                again = p[np.repeat(count > 1, count)]
                one = p[starts]
                yield _batch(_send(buckets, h[one], who[one], pos[one], ks, hs, (who[again], pos[again])))

    return go


def _window_rows(width: int, period: int, buckets: int):
    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slabs(batch, "t"):
                words, offsets, ks, hs = _texts(part)
                n = np.diff(offsets)
                delta = np.zeros(len(words) + 1, dtype=np.int64)
                for i, packed in enumerate(part.column("at").to_pylist()):
                    a = np.frombuffer(packed, "<u4").astype(np.int64)
                    low, high = np.maximum(a - period + 1, 0), np.minimum(a, n[i] - width)
                    np.add.at(delta, offsets[i] + low, 1)
                    np.add.at(delta, offsets[i] + high + 1, -1)
                at = np.flatnonzero(np.cumsum(delta[:-1]) > 0)
                if not len(at):
                    continue
                who = np.searchsorted(offsets, at, side="right") - 1
                h, pos = window_hashes(words, width)[at], at - offsets[who]
                p, starts, count = _sorted_groups(h, ks[who], hs[who], pos)
                first = np.repeat(p[starts], count)
                later = ~((who[p] == who[first]) & (pos[p] == pos[first])) & ~((ks[who[p]] == ks[who[first]]) & (hs[who[p]] == hs[who[first]]) & (pos[p] == pos[first]))
                again, one = p[later], p[starts]
                yield _batch(_send(buckets, h[one], who[one], pos[one], ks, hs, (who[again], pos[again])))

    return go


def _meet(keep_first: bool, groups: int):
    """Of the records of a bucket: positions whose hash occurs twice, or with keep_first all of a hash but its earliest.

    They go back packed, a row for each group of texts, so that rows do not multiply with buckets.
    """

    def go(table: pa.Table) -> pa.Table:
        h, pos, fpos = (gather(table, c, t) for c, t in (("hash", "<u8"), ("pos", "<u4"), ("fpos", "<u4")))
        ks, hs = gather(table, "ks", "<i8"), gather(table, "hs", "<i8")
        base, whos, fwhos = 0, [], []
        for w, fw, k in zip(*[table.column(c).to_pylist() for c in ("who", "fwho", "ks")], strict=True):
            whos.append(np.frombuffer(w, "<u4").astype(np.int64) + base)
            fwhos.append(np.frombuffer(fw, "<u4").astype(np.int64) + base)
            base += len(k) // 8
        who, fwho = np.concatenate(whos), np.concatenate(fwhos)
        if keep_first:
            p, starts, count = _sorted_groups(h, ks[who], hs[who], pos)
            first = np.repeat(p[starts], count) if len(p) else p
            same = (ks[who[p]] == ks[who[first]]) & (hs[who[p]] == hs[who[first]]) & (pos[p] == pos[first])
            hit = p[~same]
        else:
            p, starts, count = _sorted_groups(h)
            hit = p[np.repeat(count > 1, count)]
        who, pos = np.concatenate([who[hit], fwho]), np.concatenate([pos[hit], fpos])
        rows = list(scatter((hs[who].view(U64) % U64(groups)).astype(np.int64), ks[who], hs[who], pos.astype("<u4")))
        return pa.table({"g": pa.array([g for g, _ in rows], pa.int32()), **{c: pa.array([x[i] for _, x in rows], pa.binary()) for i, c in enumerate(("ks", "hs", "at"))}})

    return go


def _regroup(table: pa.Table) -> pa.Table:
    """The positions told to a group, one row a text."""
    ks, hs, pos = gather(table, "ks", "<i8"), gather(table, "hs", "<i8"), gather(table, "at", "<u4")
    order = np.lexsort((pos, hs, ks))
    ks, hs, pos = ks[order], hs[order], pos[order]
    cuts = np.flatnonzero(np.r_[True, (ks[1:] != ks[:-1]) | (hs[1:] != hs[:-1])]) if len(ks) else np.zeros(0, np.int64)
    at = [np.unique(pos[i:j]).astype("<u4").tobytes() for i, j in zip(cuts, np.r_[cuts[1:], len(ks)], strict=True)] if len(ks) else []
    return pa.Table.from_arrays([pa.array(ks[cuts], pa.int64()), pa.array(hs[cuts], pa.int64()), pa.array(at, pa.binary())], names=["k", "h", "at"])


def _keep_rows(width: int, digest: bool):
    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            total, removed, kept = [], [], []
            for t, copy, packed in zip(*[batch.column(c).to_pylist() for c in ("t", "copy", "at")], strict=True):
                words = (t or "").encode().split()
                n = len(words)
                if copy and n >= width:
                    left: list[bytes] = []
                elif packed:
                    a = np.frombuffer(packed, "<u4").astype(np.int64)
                    delta = np.zeros(n + 1, dtype=np.int64)
                    np.add.at(delta, a, 1)
                    np.add.at(delta, a + width, -1)
                    left = [words[i] for i in np.flatnonzero(np.cumsum(delta[:-1]) == 0)]
                else:
                    left = words
                total.append(n)
                removed.append(n - len(left))
                text = b" ".join(left)
                kept.append(hashlib.sha256(text).hexdigest() if digest else text.decode())
            kind = pa.int64()
            yield pa.RecordBatch.from_arrays([batch.column("key"), pa.array(total, kind), pa.array(removed, kind), pa.array(kept, pa.string())], names=["k", "n_words", "n_removed", "kept"])

    return go


def dedup(df: DataFrame, key: str = "doc_id", text: str = "text", width: int = WIDTH, period: int = PERIOD, cover: tuple[int, ...] = COVER, digest: bool = False) -> DataFrame:
    """Rows (key, n_words, n_removed, kept): kept words of every text joined by blanks, or their SHA-256 with `digest`.

    A word goes if a window over it has words that also start earlier: at a smaller key (a null key is the largest), at
    an equal key in a text of smaller hash, or earlier in the same text. Rows of equal key and text are one document and
    each give a row. Null and empty texts have no words; an empty table gives no rows; other columns are ignored.
    """
    if not (0 < period <= width and covers(period, cover)):
        raise ValueError("the cover must hold every difference modulo a period of at most the width")
    spark = df.sparkSession
    rows = df.select(F.coalesce(F.col(key).cast("long"), F.lit(int(LAST))).alias("k"), F.xxhash64(F.coalesce(F.col(text), F.lit(""))).alias("h"), F.coalesce(F.col(text), F.lit("")).alias("t"))
    buckets = bucket_count(spark, total_bytes(rows, "t"), 32_000_000)
    n = max(buckets, int(spark.conf.get("spark.sql.shuffle.partitions")))
    # One exchange of the texts serves all three joins.
    texts = rows.repartition(n, "k", "h")
    firsts = rows.groupBy(F.md5(F.encode("t", "UTF-8")).alias("m")).agg(F.min(F.struct("k", "h")).alias("x")).select(F.col("x.k").alias("k"), F.col("x.h").alias("h"), F.lit(True).alias("first"))
    own = texts.join(firsts.hint("shuffle_hash"), ["k", "h"]).select("k", "h", "t")
    sent = own.mapInArrow(lean(_anchor_rows(width, period, cover, buckets)), SENT)
    anchors = sent.groupBy("b").applyInArrow(lean_group(_meet(False, buckets)), TOLD).groupBy("g").applyInArrow(lean_group(_regroup), FOUND)
    near = texts.join(anchors.hint("shuffle_hash"), ["k", "h"]).select("k", "h", "t", "at")
    found = near.mapInArrow(lean(_window_rows(width, period, buckets)), SENT).groupBy("b").applyInArrow(lean_group(_meet(True, buckets)), TOLD)
    spans = found.groupBy("g").applyInArrow(lean_group(_regroup), FOUND)
    marked = texts.join(firsts.hint("shuffle_hash"), ["k", "h"], "left").join(spans.hint("shuffle_hash"), ["k", "h"], "left")
    out = marked.select(F.nullif("k", F.lit(int(LAST))).alias("key"), "t", F.col("first").isNull().alias("copy"), "at")
    return out.mapInArrow(lean(_keep_rows(width, digest)), f"`{key}` long, n_words long, n_removed long, kept string")


def report(df: DataFrame) -> DataFrame:
    """(doc_id, n_words, n_removed, kept_sha256) of documents."""
    return dedup(df, digest=True).withColumnRenamed("kept", "kept_sha256")
