"""N-gram Jaccard self-join by T-occurrence search, and its connected components.

A document is the set of its distinct word shingles; a partner at Jaccard >= 0.8 shares at least T = ceil(0.8 n) of its
n shingles. The search divides the inverted lists of a document's shingles into short and long ones and skips what
cannot reach T:

1. Documents of one set are one (their least key), so copies never multiply.
2. Among the shingles of least hash, n - T + c of them, a partner shares at least about c; a document with fewer that
   occur anywhere else is dropped. Most documents end here, before their whole sets are looked at.
3. For the rest, list lengths are counted over whole sets. A document with fewer than T shingles in lists of two or
   more is dropped; the others keep their n - T + c shortest lists.
4. Short lists are merged: pairs are counted over them, and those with c occurrences are verified by probing the sorted
   set of one with the shingles of the other.
5. Documents whose kept lists include long ones meet in tiles named after the first document of the list, whatever the
   number of lists they share, and a tile links its documents without writing down pairs.

Every pair at the threshold either shares a long kept list (5) or c short ones (4), so no link between different sets
is lost, and links inside a tile are reduced to a forest.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from writelite.llm.common import bucket_count, components, gather, lean, lean_group, lean_pair, runs, scatter, slabs, stored, tasks_for, text_bytes, window_hashes, word_hashes

SHINGLE, LONG_LIST, TILE = 5, 64, 1024
#: Bytes of text whose words are hashed at once.
SLAB = 500_000
#: Up to this many keys of survivors (16 MB) are broadcast; beyond, they are joined by an exchange.
BROADCAST_KEYS = 2_000_000
U64 = np.uint64


def needed(n: np.ndarray) -> np.ndarray:
    """T: the least overlap of a set of n with a partner at Jaccard 0.8."""
    return (4 * n + 4) // 5


def spare(n: np.ndarray) -> np.ndarray:
    """c: how many matches are asked for among the kept shingles."""
    return 1 + n // 10


def sure(n: np.ndarray) -> np.ndarray:
    """The least c of any partner of a set of n, whose size is at least T."""
    return spare(needed(n))


def linked(overlap: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return 100 * overlap >= 80 * (a + b - overlap)


def sets(part: pa.RecordBatch, width: int) -> Iterator[np.ndarray]:
    """The sorted distinct shingle hashes of each text; shorter texts have one shingle of all their words."""
    words, offsets = word_hashes(*text_bytes(part.column("t")), lower=True)
    h = window_hashes(words, width)
    for i, j in zip(offsets[:-1], offsets[1:], strict=True):
        if j - i >= width:
            yield np.unique(h[i : j - width + 1])
        elif j > i:
            yield window_hashes(words[i:j], int(j - i))
        else:
            yield np.zeros(0, dtype=U64)


def _sign_rows(width: int):
    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slabs(batch, "t", SLAB):
                n, keys, low = [], [], []
                for s in sets(part, width):
                    m = np.int64(len(s))
                    n.append(int(m))
                    keys.append(xxhash.xxh3_128_digest(s.tobytes()))
                    low.append(s[: int(m - needed(m) + spare(m))].tobytes() if m else b"")
                yield pa.RecordBatch.from_arrays([part.column("k"), pa.array(n, pa.int64()), pa.array(keys, pa.binary()), pa.array(low, pa.binary())], names=["k", "n", "same", "low"])

    return go


def _set_rows(width: int, groups: int):
    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slabs(batch, "t", SLAB):
                packed = [s.tobytes() for s in sets(part, width)]
                k = part.column("k")
                yield pa.RecordBatch.from_arrays([k, pa.array([len(s) // 8 for s in packed], pa.int64()), pa.array([xxhash.xxh3_64_intdigest(np.int64(x).tobytes()) % groups for x in k.to_pylist()], pa.int32()), pa.array(packed, pa.binary())], names=["k", "n", "g", "shingles"])

    return go


def _low_rows(buckets: int):
    """Shingles by bucket; one that occurs twice here is counted here and sent once, marked as counted."""

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            packed = batch.column("low").to_pylist()
            ks = batch.column("k").to_numpy()
            h = np.frombuffer(b"".join(packed), "<u8")
            who = np.repeat(np.arange(len(ks)), [len(x) // 8 for x in packed])
            if not len(h):
                continue
            p = np.argsort(h, kind="stable")
            starts, n = runs(h[p])
            counted = np.bincount(who[p[np.repeat(n > 1, n)]], minlength=len(ks))
            one = p[starts]
            rows = {b: [*x, b"", b""] for b, x in scatter((h[one] % U64(buckets)).astype(np.int64), h[one], ks[who[one]], (n > 1).astype(np.uint8))}
            mine = np.flatnonzero(counted)
            for b, x in scatter(ks[mine] % buckets, ks[mine], counted[mine].astype("<i8")):
                rows.setdefault(b, [b"", b"", b"", b"", b""])[3:] = x
            yield pa.RecordBatch.from_arrays([pa.array(list(rows), pa.int32()), *[pa.array([r[c] for r in rows.values()], pa.binary()) for c in range(5)]], names=["b", "hash", "k", "done", "fk", "fn"])

    return go


def _count_low(groups: int):
    """How many of each document's shingles occur elsewhere, as far as this bucket knows; packed by groups of documents."""

    def go(table: pa.Table) -> pa.Table:
        h, k, done = gather(table, "hash", "<u8"), gather(table, "k", "<i8"), gather(table, "done", "u1")
        p = np.argsort(h, kind="stable")
        _, n = runs(h[p])
        again = p[np.repeat(n > 1, n)]
        met, told = k[again[done[again] == 0]], gather(table, "fk", "<i8")
        keys, back = np.unique(np.concatenate([met, told]), return_inverse=True)
        weights = np.concatenate([np.ones(len(met), np.int64), gather(table, "fn", "<i8")])
        found = np.bincount(back, weights, len(keys)).astype("<i8")
        rows = list(scatter(keys % groups, keys, found))
        return pa.table({"g": pa.array([g for g, _ in rows], pa.int32()), **{c: pa.array([x[i] for _, x in rows], pa.binary()) for i, c in enumerate(("ks", "found"))}})

    return go


def _sum_low(table: pa.Table) -> pa.Table:
    keys, back = np.unique(gather(table, "ks", "<i8"), return_inverse=True)
    found = np.bincount(back, gather(table, "found", "<i8"), len(keys)).astype(np.int64)
    return pa.table({"k": pa.array(keys, pa.int64()), "found": pa.array(found, pa.int64())})


def _group_lists(buckets: int):
    """Of a group of documents: each shingle once, with its count and its least key in the group."""

    def go(table: pa.Table) -> pa.Table:
        packed = table.column("shingles").to_pylist()
        ks = np.array(table.column("k").to_pylist(), dtype=np.int64)
        h = np.frombuffer(b"".join(packed), "<u8")
        k = np.repeat(ks, [len(x) // 8 for x in packed])
        p = np.lexsort((k, h))
        starts, n = runs(h[p])
        one = p[starts]
        rows = list(scatter((h[one] % U64(buckets)).astype(np.int64), h[one], n.astype("<i8"), k[one]))
        g = table.column("g")[0].as_py()
        return pa.table({"b": pa.array([b for b, _ in rows], pa.int32()), "g": pa.array([g] * len(rows), pa.int32()), **{c: pa.array([x[i] for _, x in rows], pa.binary()) for i, c in enumerate(("hash", "n", "lead"))}})

    return go


def _sum_lists(table: pa.Table) -> pa.Table:
    """Length and first document of every list of two or more, for each group that has the shingle."""
    h, n, lead = (gather(table, c, t) for c, t in (("hash", "<u8"), ("n", "<i8"), ("lead", "<i8")))
    g = np.repeat(np.array(table.column("g").to_pylist(), dtype=np.int64), [len(x) // 8 for x in table.column("hash").to_pylist()])
    p = np.lexsort((lead, h))
    starts, count = runs(h[p])
    total = np.repeat(np.add.reduceat(n[p], starts) if len(starts) else n[:0], count)
    first = np.repeat(lead[p[starts]], count)
    keep = total > 1
    rows = list(scatter(g[p][keep], h[p][keep], total[keep], first[keep]))
    return pa.table({"g": pa.array([b for b, _ in rows], pa.int32()), **{c: pa.array([x[i] for _, x in rows], pa.binary()) for i, c in enumerate(("hash", "n", "lead"))}})


PARTS = "b int, i int, j int, lead long, k long, n long, shingles binary"


def _divide(buckets: int, long_list: int, tile: int):
    """The kept lists of a group's documents: short ones to buckets of their hash, long ones as places in tiles."""

    def go(docs: pa.Table, lists: pa.Table) -> pa.Table:
        h, n, lead = (gather(lists, c, t) for c, t in (("hash", "<u8"), ("n", "<i8"), ("lead", "<i8")))
        p = np.argsort(h)
        h, n, lead = h[p], n[p], lead[p]
        short: list[list[np.ndarray]] = [[], [], []]
        rows = []
        for k, size, packed in zip(docs.column("k").to_pylist(), docs.column("n").to_pylist(), docs.column("shingles").to_pylist(), strict=True):
            s = np.frombuffer(packed, "<u8")
            at = np.minimum(np.searchsorted(h, s), max(len(h) - 1, 0))
            there = h[at] == s if len(h) else np.zeros(len(s), bool)
            shared = at[there]
            t = int(needed(np.int64(size)))
            if len(shared) < t:
                continue
            keep = size - t + int(spare(np.int64(size))) - (size - len(shared))  # lists of one come first
            if keep <= 0:
                continue
            kept = shared[np.lexsort((h[shared], n[shared]))[:keep]]
            few = kept[n[kept] <= long_list]
            for store, values in zip(short, (h[few], np.full(len(few), k), np.full(len(few), size)), strict=True):
                store.append(values)
            many = kept[n[kept] > long_list]
            if len(many):
                # The tiles of a list grow with its length; a document is in those of its own part with every part.
                parts = 1 << np.maximum(np.ceil(np.log2(n[many] / tile)).astype(np.int64), 0)
                for first, q in {*zip(lead[many].tolist(), parts.tolist(), strict=True)}:
                    own = xxhash.xxh3_64_intdigest(np.int64(k).tobytes(), seed=1) % q
                    rows += [(-1, min(own, other) * 64 + int(q).bit_length(), max(own, other), first, k, size, packed) for other in range(q)]
        if short[0]:
            hs, ks, ns = (np.concatenate(x) for x in short)
            for b, x in scatter((hs % U64(buckets)).astype(np.int64), hs.astype("<u8"), ks.astype("<i8"), ns.astype("<i8")):
                rows.append((b, 0, 0, 0, 0, len(x[0]) // 8, b"".join(x)))
        types = [pa.int32(), pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.binary()]
        return pa.Table.from_arrays([pa.array([r[c] for r in rows], t) for c, t in enumerate(types)], names=[x.split()[0] for x in PARTS.split(", ")])

    return go


def _merge_short(table: pa.Table) -> pa.Table:
    """Pairs that meet in the short lists of a bucket, with their number of meetings there."""
    parts = [np.frombuffer(x, "<u8").reshape(3, -1) for x in table.column("shingles").to_pylist()]
    h, k, n = (np.concatenate([x[i] for x in parts]) for i in range(3))
    k, n = k.view(np.int64), n.view(np.int64)
    p = np.lexsort((k, h))
    h, k, n = h[p], k[p], n[p]
    starts, count = runs(h)
    a, b = [], []
    for d in range(1, int(count.max()) if len(count) else 1):  # lists are at most LONG_LIST long
        i = np.flatnonzero(h[:-d] == h[d:])
        x, y = n[i], n[i + d]
        i = i[(4 * np.maximum(x, y) <= 5 * np.minimum(x, y)) & (k[i] != k[i + d])]
        a.append(i)
        b.append(i + d)
    empty = np.zeros(0, np.int64)
    a, b = np.concatenate([empty, *a]), np.concatenate([empty, *b])
    low, high, c = np.minimum(k[a], k[b]), np.maximum(k[a], k[b]), np.minimum(sure(n[a]), sure(n[b]))
    order = np.lexsort((high, low))
    low, high, c = low[order], high[order], c[order]
    cuts = np.flatnonzero(np.r_[True, (low[1:] != low[:-1]) | (high[1:] != high[:-1])]) if len(low) else np.zeros(0, np.int64)
    met = np.diff(np.r_[cuts, len(low)])
    return pa.table({"a": low[cuts], "b": high[cuts], "met": met.astype(np.int64), "least": c[cuts].astype(np.int64)})


def _link_tile(table: pa.Table) -> pa.Table:
    """A forest of the links between the documents of a tile, by the products of their incidence rows."""
    seen: dict[int, bytes] = dict(zip(table.column("k").to_pylist(), table.column("shingles").to_pylist(), strict=True))
    ks = np.array(sorted(seen), dtype=np.int64)
    packed = [np.frombuffer(seen[int(k)], "<u8") for k in ks]
    n = np.array([len(s) for s in packed], dtype=np.int64)
    every = np.concatenate(packed)
    who = np.repeat(np.arange(len(ks)), n)
    p = np.argsort(every, kind="stable")
    starts, count = runs(every[p])
    token = np.repeat(np.arange(len(starts)), count)
    keep = np.repeat(count > 1, count)
    token, who = token[keep], who[p][keep]
    _, token = np.unique(token, return_inverse=True)
    m, width = len(ks), int(token.max()) + 1 if len(token) else 0
    overlap = np.zeros((m, m), dtype=np.float32)
    step = max(1, 16_000_000 // max(m, 1))
    for first in range(0, width, step):
        inside = (token >= first) & (token < first + step)
        x = np.zeros((m, min(step, width - first)), dtype=np.float32)
        x[who[inside], token[inside] - first] = 1
        overlap += x @ x.T
    label = np.arange(m)
    for i in range(m):
        near = np.flatnonzero(linked(overlap[i].astype(np.int64), n[i], n))
        old = np.unique(label[near])
        if len(old) > 1:
            label[np.isin(label, old)] = old[0]
    hit = np.flatnonzero(label != np.arange(m))
    return pa.table({"a": pa.array(ks[label[hit]], pa.int64()), "b": pa.array(ks[hit], pa.int64())})


def _probe_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        ok = []
        for x, y in zip(batch.column("sa").to_pylist(), batch.column("sb").to_pylist(), strict=True):
            x, y = np.frombuffer(x, "<u8"), np.frombuffer(y, "<u8")
            if len(x) > len(y):
                x, y = y, x
            at = np.minimum(np.searchsorted(y, x), len(y) - 1)
            ok.append(bool(linked(np.count_nonzero(y[at] == x), len(x), len(y))))
        yield pa.RecordBatch.from_arrays([batch.column("a"), batch.column("b")], names=["a", "b"]).filter(pa.array(ok, pa.bool_()))


def search(df: DataFrame, key: str = "doc_id", text: str = "text", width: int = SHINGLE, long_list: int = LONG_LIST, tile: int = TILE) -> tuple[DataFrame, DataFrame]:
    """(signatures (k, n, same, low) of all rows, links (a, b) between the least keys of different sets)."""
    spark = df.sparkSession
    rows = df.select(F.col(key).cast("long").alias("k"), F.coalesce(F.col(text), F.lit("")).alias("t"))
    signed = stored(rows.mapInArrow(lean(_sign_rows(width)), "k long, n long, same binary, low binary"), "shingle-signatures")
    alone = signed.where("k IS NOT NULL AND n > 0").groupBy("same").agg(F.min(F.struct("k", "n", "low")).alias("x")).select("x.k", "x.n", "x.low")
    n_rows, n_all, n_low = signed.agg(F.count(F.lit(1)), F.coalesce(F.sum("n"), F.lit(0)), F.coalesce(F.sum(F.octet_length("low") / 8), F.lit(0))).first()
    buckets = bucket_count(spark, int(n_low), 3_000_000)
    low = alone.select("k", "low").mapInArrow(lean(_low_rows(buckets)), "b int, hash binary, k binary, done binary, fk binary, fn binary")
    found = low.groupBy("b").applyInArrow(lean_group(_count_low(buckets)), "g int, ks binary, found binary").groupBy("g").applyInArrow(lean_group(_sum_low), "k long, found long")
    t = F.floor((4 * F.col("n") + 4) / 5)
    few = signed.where("k IS NOT NULL AND n > 0").groupBy("same").agg(F.min(F.struct("k", "n")).alias("x")).select("x.k", "x.n")
    left = stored(few.join(found, "k").where(F.col("found") >= 1 + F.floor(t / 10)).select(F.col("k").alias("s"), "n"), "shingle-survivors", tasks_for(spark, 16 * n_rows))
    size = left.agg(F.count(F.lit(1)), F.coalesce(F.sum("n"), F.lit(0))).first()
    chosen = left.select("s")
    chosen = F.broadcast(chosen) if size[0] <= BROADCAST_KEYS else chosen
    groups = bucket_count(spark, size[1], 1_000_000)
    # Repeated rows of one key would be two documents here; one row a set is enough.
    own = rows.join(chosen, F.col("k") == F.col("s")).select("k", "t")
    whole = stored(own.mapInArrow(lean(_set_rows(width, groups)), "k long, n long, g int, shingles binary").dropDuplicates(["k", "shingles"]), "shingle-sets", tasks_for(spark, 8 * size[1]))
    lists = whole.groupBy("g").applyInArrow(lean_group(_group_lists(groups)), "b int, g int, hash binary, n binary, lead binary").groupBy("b").applyInArrow(lean_group(_sum_lists), "g int, hash binary, n binary, lead binary")
    parts = stored(whole.groupBy("g").cogroup(lists.groupBy("g")).applyInArrow(lean_pair(_divide(groups, long_list, tile)), PARTS), "shingle-lists", tasks_for(spark, 24 * size[1]))
    pairs = parts.where("b >= 0").groupBy("b").applyInArrow(lean_group(_merge_short), "a long, b long, met long, least long")
    pairs = pairs.groupBy("a", "b").agg(F.sum("met").alias("met"), F.min("least").alias("least")).where("met >= least").select("a", "b")
    side = whole.select("k", "shingles")
    probed = pairs.join(side.select(F.col("k").alias("a"), F.col("shingles").alias("sa")), "a").join(side.select(F.col("k").alias("b"), F.col("shingles").alias("sb")), "b").select("a", "b", "sa", "sb")
    short = probed.mapInArrow(lean(_probe_rows), "a long, b long")
    long = parts.where("b < 0").groupBy("lead", "i", "j").applyInArrow(lean_group(_link_tile), "a long, b long")
    return signed, short.unionByName(long)


def classes(df: DataFrame, key: str = "doc_id", text: str = "text", width: int = SHINGLE, salts: int = 16) -> DataFrame:
    """Rows (key, n_shingles, component_id), one for each row of df.

    component_id is the least key reachable by links. Null and empty texts have no shingles and stand alone; a row with a
    null key is linked with nothing and has a null component; rows of one key are one document of several texts, linked
    by the key; an empty table gives none; other columns are ignored.
    """
    signed, links = search(df, key, text, width)
    # A set's copies hang on its least key; a component of sets then names the least key of them all. Sets of one row
    # need no partner in this join, and the copies of a set meet its least key under several salts, in as many tasks.
    least = signed.where("k IS NOT NULL AND n > 0").groupBy("same").agg(F.min("k").alias("first"), F.count(F.lit(1)).alias("m")).where("m > 1")
    least = least.select("same", "first", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))).alias("salt"))
    own = signed.select("k", "n", "same", F.pmod(F.xxhash64("k"), F.lit(salts)).cast("int").alias("salt"))
    member = own.join(least, ["same", "salt"], "left").select("k", "n", F.when(F.col("n") > 0, F.coalesce("first", "k")).alias("first"))
    # Only a key of several sets needs links of its own besides those between first keys.
    ties = member.where("k IS NOT NULL AND first IS NOT NULL").groupBy("k").agg(F.min("first").alias("a"), F.max("first").alias("z"), F.count(F.lit(1)).alias("m"))
    ties = ties.where("a <> z OR (m > 1 AND a <> k)").select(F.explode(F.array(F.struct(F.col("a").alias("a"), F.col("k").alias("b")), F.struct(F.col("z").alias("a"), F.col("k").alias("b")))).alias("x")).select("x.a", "x.b")
    root = components(links.unionByName(ties)).select(F.col("node").alias("first"), "root")
    out = member.withColumn("first", F.coalesce("first", "k")).join(root, "first", "left")
    return out.select(F.col("k").alias(key), F.col("n").alias("n_shingles"), F.when(F.col("k").isNotNull(), F.coalesce("root", "first")).alias("component_id"))


def keep_one(df: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """The rows of df that stand for their class: one row of the least key of each; rows with a null key are kept.

    Repeated rows of a key that stays are reduced to one.
    """
    chosen = classes(df, key, text).where(F.col(key) == F.col("component_id")).select(F.col(key).alias("__class_of_one")).distinct()
    stay = df.join(chosen, F.col(key) == F.col("__class_of_one"), "left_semi").dropDuplicates([key])
    return stay.unionByName(df.where(F.col(key).isNull()))


def report(df: DataFrame) -> DataFrame:
    return classes(df.select("doc_id", "text"))
