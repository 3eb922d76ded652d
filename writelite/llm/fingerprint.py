"""Document fingerprints by a randomised edit embedding.

A walk over a text emits, at each of 3n steps, the character under a pointer, which then moves on or stays by a random
bit that depends on the step and the character. The bits are shared by all texts, so two texts that differ by few
edits fall back into step and their walks differ in few places: edit distance becomes Hamming distance. A walk is kept
at sampled steps only, SAMPLES in each octave of steps [2^o, 2^(o+1)) and the same for all texts, 4 bits of a hash of
the character each, one hex digit. Likeness weighs the equal digits of an octave by the octave's share of the steps.
"""

from __future__ import annotations

import functools
import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from writelite.llm.common import bucket_count, components, lean, mix, stored, total_bytes
from writelite.operators import bucketing

SAMPLES = 64
U64 = np.uint64
HEX = np.frombuffer(b"0123456789abcdef", dtype=np.uint8)


#: Steps whose bits are made at once, and the number of live walks from which they are stepped side by side.
STEPS = 12288
SIDE_BY_SIDE = 24
STOPPED = 63
#: Bounds between ranges are part of the plan; beyond this many ranges they grow instead.
MOST_PARTS = 10_000


def _step_hashes(part: int) -> np.ndarray:
    """64 random bits for each of the STEPS steps of a part, one for each class of characters; STOPPED never moves on."""
    with np.errstate(over="ignore"):
        h = mix(np.arange(part * STEPS, (part + 1) * STEPS, dtype=U64) * U64(0x9E3779B97F4A7C15) + U64(77))
    return h & ~(U64(1) << U64(STOPPED))


@functools.lru_cache(maxsize=16)
def _bits(part: int) -> np.ndarray:
    """The bits of a part as a table of step and class."""
    return ((_step_hashes(part)[:, None] >> np.arange(64, dtype=U64)) & U64(1)).astype(np.uint8)


@functools.lru_cache(maxsize=16)
def _scalar_bits(part: int) -> list[int]:
    return _step_hashes(part).tolist()


@functools.lru_cache(maxsize=64)
def sampled_steps(octave: int) -> np.ndarray:
    """The steps of an octave that a fingerprint keeps, in order."""
    n = 1 << octave
    if n <= SAMPLES:
        return np.arange(n, 2 * n)
    cell = n // SAMPLES
    with np.errstate(over="ignore"):
        at = mix(np.arange(SAMPLES, dtype=U64) + U64(octave * 1000003)) % U64(cell)
    return n + np.arange(SAMPLES) * cell + at.astype(np.int64)


def _hashed(c: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    with np.errstate(over="ignore"):
        h = mix(c.astype(U64) + U64(0x51ED2701))
        return (h % U64(STOPPED)).astype(np.uint8), (U64(1) + (h >> U64(8)) % U64(15)).astype(np.uint8)


@functools.lru_cache(maxsize=1)
def _table() -> tuple[np.ndarray, np.ndarray]:
    return _hashed(np.arange(65536))


def _char_tables(c: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(class below 63 for the walk, digit of 1-15 for the fingerprint) of code points; digit 0 is for past the end."""
    if len(c) and int(c.max()) > 65535:
        return _hashed(c)
    kinds, digits = _table()
    return np.take(kinds, c, mode="clip"), np.take(digits, c, mode="clip")


@functools.lru_cache(maxsize=1)
def _all_samples() -> np.ndarray:
    """The sampled steps of all octaves that a text can reach, from 0 on, in order of their place in a fingerprint."""
    return np.concatenate([sampled_steps(o) for o in range(40)]) - 1


@functools.lru_cache(maxsize=65536)
def _digits(n: int) -> int:
    """Digits of the fingerprint of a text of n characters: the samples among its 3n steps."""
    out, o = 0, 0
    while n and (1 << o) <= 3 * n:
        out += int(np.searchsorted(sampled_steps(o), 3 * n, side="right"))
        o += 1
    return out


def _walk_alone(kind: bytes, at: int, step: int, when: list[int]) -> list[int]:
    """Where a walk that is at place `at` at a step stands at each later step of `when`."""
    out, n = [], len(kind) - 1
    for stop in when:
        while step < stop and at < n:
            part, lo = divmod(step, STEPS)
            hi = min(lo + stop - step, STEPS)
            for h in _scalar_bits(part)[lo:hi]:
                at += (h >> kind[at]) & 1
            step += hi - lo
        out.append(at)
        if at >= n:
            step = stop
    return out


def fingerprints(texts: list[np.ndarray]) -> list[str]:
    """Fingerprints of texts given as arrays of code points.

    Every text is one walk over all of it. Many walks go side by side, a step at a time; once fewer than SIDE_BY_SIDE
    are left, each goes on by itself. Equal texts have equal fingerprints whatever they are walked with.

    >>> a = np.frombuffer("banana".encode("utf-32-le"), np.uint32)
    >>> fingerprints([a, a])[0] == fingerprints([a])[0]
    True
    """
    out = [np.zeros(_digits(len(t)), dtype=np.uint8) for t in texts]
    owner = sorted((i for i, t in enumerate(texts) if len(t)), key=lambda i: -len(texts[i]))
    if owner:
        lens = np.array([len(texts[i]) for i in owner], dtype=np.int64)
        end = np.cumsum(lens + 1) - 1
        gap = np.zeros(1, np.uint32)
        kind, digit = _char_tables(np.concatenate([x for i in owner for x in (texts[i], gap)]))
        kind[end], digit[end] = STOPPED, 0
        at = end - lens
        begin = at.copy()
        samples = _all_samples()
        count = np.array([len(out[i]) for i in owner])
        shared = 3 * int(lens[SIDE_BY_SIDE - 1]) if len(owner) >= SIDE_BY_SIDE else 0
        place, step = 0, 0
        while step < shared:
            live = int(np.searchsorted(-3 * lens, -step, side="left"))
            until = min(shared, 3 * int(lens[live - 1]), (step // STEPS + 1) * STEPS)
            bits, a = _bits(step // STEPS), at[:live]
            k, move = np.empty(live, np.uint8), np.empty(live, np.uint8)
            for s in range(step, until):
                if s == samples[place]:
                    for w, d in enumerate(digit[a].tolist()):
                        out[owner[w]][place] = d
                    place += 1
                np.take(kind, a, out=k, mode="clip")
                np.take(bits[s % STEPS], k, out=move, mode="clip")
                np.add(a, move, out=a)
            step = until
        for w in range(len(owner)):
            if count[w] > place:
                lo, hi = int(begin[w]), int(end[w])
                went = _walk_alone(kind[lo : hi + 1].tobytes(), int(at[w]) - lo, step, samples[place : count[w]].tolist())
                out[owner[w]][place : count[w]] = digit[lo + np.array(went)]
    return [HEX[x].tobytes().decode() for x in out]


def _octave_of(n: int) -> tuple[np.ndarray, np.ndarray]:
    """(octave, steps that a digit stands for) of each of the first n digits of a fingerprint."""
    octs, per, o = [], [], 0
    while len(octs) < n:
        k = len(sampled_steps(o))
        octs += [o] * k
        per += [(1 << o) / k] * k
        o += 1
    return np.array(octs[:n]), np.array(per[:n])


@functools.lru_cache(maxsize=4096)
def _weights(n: int) -> np.ndarray:
    return _octave_of(n)[1]


def likeness(a: str, b: str) -> float:
    """Estimated share of steps at which two walks agree, 0 to 1: over the steps of the longer one; both empty: 1.

    >>> likeness("", ""), likeness("12", "12"), likeness("12", "")
    (1.0, 1.0, 0.0)
    """
    n = max(len(a), len(b))
    if not n:
        return 1.0
    w, m = _weights(n), min(len(a), len(b))
    x, y = np.frombuffer(a.encode(), np.uint8)[:m], np.frombuffer(b.encode(), np.uint8)[:m]
    return float(np.dot(w[:m], x == y) / w.sum())


def code_points(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le", "surrogatepass"), dtype=np.uint32)


def _digest_rows(size: int):
    """Documents of a partition in descending order, each with the one after it; a row marked as context only follows."""

    def emit(rows: list[tuple]) -> pa.RecordBatch | None:
        arrays, owners = [], []
        for i, (_, text, _, context) in enumerate(rows[:-1]):
            arrays.append(code_points(text))
        arrays.append(code_points(rows[-1][1]))
        mine = [i for i in range(len(rows) - 1) if not rows[i][3]]
        if not mine:
            return None
        edited, digests = [], []
        for i in mine:
            x, y = arrays[i], arrays[i + 1]
            half = len(x) // 2
            z = np.concatenate([x[: len(x) - half], y[:half]])
            edited.append(z)
            digests.append(hashlib.sha256(z.tobytes().decode("utf-32-le", "surrogatepass").encode("utf-8", "surrogatepass")).hexdigest())
        every = sorted({*mine, *(i + 1 for i in mine)})
        made = fingerprints([arrays[i] for i in every] + edited)
        own = dict(zip(every, made, strict=False))
        changed = made[len(every) :]
        fp = [own[i] for i in mine]
        return pa.RecordBatch.from_arrays(
            [
                pa.array([rows[i][0] for i in mine], pa.int64()), pa.array([len(arrays[i]) for i in mine], pa.int64()), pa.array(digests), pa.array(fp), pa.array(changed),
                pa.array([likeness(a, b) for a, b in zip(fp, changed, strict=True)], pa.float64()), pa.array([likeness(own[i], own[i + 1]) for i in mine], pa.float64()),
            ],
            names=["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"],
        )

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        chars = 0
        for batch in batches:
            for row in zip(*[batch.column(c).to_pylist() for c in ("k", "t", "part", "context")], strict=True):
                if held and row[2] != held[-1][2]:  # another range begins: what is held ends with its context row
                    if (out := emit(held)) is not None:
                        yield out
                    held, chars = [], 0
                held.append(row)
                chars += len(row[1])
                if chars >= size and len(held) > 1:
                    if (out := emit(held)) is not None:
                        yield out
                    held, chars = held[-1:], len(row[1])
        if len(held) > 1 and (out := emit(held)) is not None:
            yield out

    return go


OUT = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"


def with_edits(df: DataFrame, key: str = "doc_id", text: str = "text", size: int = 2_000_000, partitions: int | None = None) -> DataFrame:
    """Fingerprints of every text and of its edited text, and their likeness (OUT).

    The edited text is the text with its last half replaced by the start of the next document, by descending key; the
    last one is followed by the first. A null text is empty and has an empty fingerprint; two empty ones are alike (1).
    Rows with a null key come last; rows of one key are ordered by text, descending; repeated rows follow each other;
    a single row follows itself; an empty table gives none.

    The table is dealt into ranges of the key once, with bounds from the keys alone; the first row of a range is also
    sent to the range before it, as context, so no range needs another one.
    """
    rows = df.select(F.col(key).cast("long").alias("k"), F.coalesce(F.col(text), F.lit("")).alias("t"))
    spark = df.sparkSession
    # Rows of one key stay in one range, so that bounds can be keys; a null key sorts below all.
    n_parts = partitions or min(bucket_count(spark, total_bytes(rows, "t"), 48_000_000), MOST_PARTS)
    keys = rows.where("k IS NOT NULL").agg(F.percentile_approx("k", [i / n_parts for i in range(1, n_parts)], 10 * n_parts + 1000) if n_parts > 1 else F.array().cast("array<long>"), F.max("k")).first()
    top = keys[1]
    # Ranges are (bound, next bound], highest first. Every bound is a key, and so is the top of its range.
    bounds = sorted(set(keys[0] or []) - {top}, reverse=True)
    tops = [top, *bounds] if top is not None else []
    # Part of a key: how many bounds are at or above it; keys of b + 1 and more have passed the bound b.
    first = bucketing.locate(rows, ["k"], [(True, b + 1) for b in reversed(bounds)], "part").select("k", "t", (F.lit(len(bounds)) - F.col("part")).cast("int").alias("part"), F.lit(False).alias("context"))
    if top is None:
        heads = first.groupBy("part").agg(F.max("t").alias("t")).select(F.lit(None).cast("long").alias("k"), "t", F.lit(0).alias("part"), F.lit(True).alias("context"))
    else:
        # The row that leads each range: of its top key the one whose text sorts last, found on the few rows that have
        # one of the top keys, MOST_PARTS at most.
        wanted = F.broadcast(spark.createDataFrame([(t,) for t in tops], "top long"))
        lead = first.join(wanted, F.col("k") == F.col("top")).groupBy("k", "part").agg(F.max("t").alias("t"))
        before = F.when(F.col("part") == 0, len(tops) - 1).otherwise(F.col("part") - 1)
        heads = lead.select("k", "t", before.cast("int").alias("part"), F.lit(True).alias("context"))
    dealt = first.unionByName(heads).repartition(max(n_parts, 1), "part").sortWithinPartitions("part", "context", F.col("k").desc_nulls_last(), F.col("t").desc())
    return dealt.mapInArrow(lean(_digest_rows(size)), OUT)


def _fingerprint_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        made = fingerprints([code_points(t or "") for t in batch.column(1).to_pylist()])
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(made, pa.string())], names=["k", "t", "fingerprint"])


def _padded(prints: list[str], fill: int) -> tuple[np.ndarray, np.ndarray]:
    lens = np.array([len(f) for f in prints], dtype=np.int64)
    out = np.full((len(prints), int(lens.max(initial=0))), fill, dtype=np.uint8)
    for i, f in enumerate(prints):
        out[i, : len(f)] = np.frombuffer(f.encode(), np.uint8)
    return out, lens


def _likeness_of(x: np.ndarray, m: int, others: np.ndarray, lens: np.ndarray, weights: np.ndarray, total: np.ndarray) -> np.ndarray:
    """likeness() of one padded fingerprint of m digits with many, whose padding is another value."""
    w = min(m, others.shape[1])
    most = total[np.maximum(lens, m)]
    return np.where(most > 0, ((others[:, :w] == x[:w]) @ weights[:w]) / np.maximum(most, 1.0), 1.0)


def near_pairs(df: DataFrame, key: str = "doc_id", text: str = "text", bands: int = 24, digits: int = 6, least: float = 0.7, tile: int = 512, salts: int = 16) -> DataFrame:
    """Pairs (a, b, likeness) of near texts: fingerprints that agree on a band of sampled digits, then verified.

    Null and empty texts have no digits and are in no pair; rows with a null key are left out; rows of one key and
    several texts are paired like others, but not with each other; repeated rows are one; an empty table gives none.

    A band is `digits` digits drawn from the two octaves below the last whole one, so texts of like length share its
    places. Equal texts stand as one (their least key), so copies never multiply. Pairs are of different texts.

    All pairs of a band's members are verified. A band of more than `tile` members is cut into blocks by a hash, and
    each two blocks meet in a tile of their own, so that no task gets a whole hot band; the work still grows with the
    square of its members. A pair is told by the first band that it shares only.
    """
    spark = df.sparkSession
    one = df.select(F.col(key).cast("long").alias("k"), F.coalesce(F.col(text), F.lit("")).alias("t")).groupBy("t").agg(F.min("k").alias("k")).where("k IS NOT NULL")
    made = one.select("k", "t").mapInArrow(lean(_fingerprint_rows), "k long, t string, fingerprint string")
    made = stored(made.select("k", F.xxhash64("t").alias("h"), "fingerprint"), "fingerprints")
    tables = [[sorted({int(x) for x in mix(np.arange(digits, dtype=U64) + U64(o * 7919 + b * 104729)) % U64(len(sampled_steps(o)))}) for b in range(bands)] for o in range(40)]
    starts = np.cumsum([0, *[len(sampled_steps(o)) for o in range(40)]])

    def whole_of(n):
        return np.searchsorted(starts, n, side="right") - 1

    def band_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at, keys = [], []
            for i, f in enumerate(batch.column(2).to_pylist()):
                whole = int(whole_of(len(f)))
                for o in range(max(whole - 2, 0), whole):
                    for b, places in enumerate(tables[o]):
                        at.append(i)
                        keys.append(f"{o}.{b}." + "".join(f[starts[o] + p] for p in places))
            rows = pa.array(at, pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0).take(rows), batch.column(1).take(rows), pa.array(keys, pa.string())], names=["k", "h", "band"])

    banded = made.mapInArrow(lean(band_rows), "k long, h long, band string")
    salt = F.explode(F.sequence(F.lit(0), F.lit(salts - 1))).alias("salt")
    sizes = banded.groupBy("band").agg(F.ceil(F.count(F.lit(1)) / tile).cast("int").alias("blocks"), F.count(F.lit(1)).alias("n")).where("n > 1").select("band", "blocks", salt)
    met = banded.withColumn("salt", F.pmod("h", F.lit(salts)).cast("int")).join(sizes, ["band", "salt"]).withColumn("block", F.pmod(F.xxhash64("k", "h"), F.col("blocks")).cast("int"))
    met = met.select("k", "h", "band", "block", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other"))
    met = met.select("k", "h", "band", "block", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"))

    def settle(rows: list[tuple]) -> pa.RecordBatch | None:
        """The near pairs of a tile: between its two blocks, or within its only one."""
        band, i, j = rows[0][:3]
        octave, number = (int(v) for v in band.split(".")[:2])
        same = i == j
        left = rows if same else [r for r in rows if r[3] == i]
        right = rows if same else [r for r in rows if r[3] == j]
        if not left or not right:
            return None
        (x, lx), (y, ly) = _padded([r[6] for r in left], 0), _padded([r[6] for r in right], 1)
        weights = _weights(max(x.shape[1], y.shape[1]))
        total = np.concatenate([[0.0], np.cumsum(weights)])
        kx, ky = (np.array([r[4] for r in side], dtype=np.int64) for side in (left, right))
        wx, wy = whole_of(lx), whole_of(ly)
        out = []
        for r in range(len(left)):
            at = r + 1 if same else 0
            near = _likeness_of(x[r], int(lx[r]), y[at:], ly[at:], weights, total)
            hit = at + np.flatnonzero((near >= least) & (ky[at:] != kx[r]))
            first = np.ones(len(hit), dtype=bool)
            for o in range(max(int(wx[r]) - 2, 0), min(int(wx[r]), octave + 1)):
                shared = (o >= wy[hit] - 2) & (o < wy[hit])
                for places in tables[o][: number if o == octave else bands]:
                    p = starts[o] + np.array(places)
                    if shared.any() and p[-1] < y.shape[1]:
                        first &= ~(shared & (y[np.ix_(hit, p)] == x[r, p]).all(axis=1))
            for c in hit[first]:
                out.append((min(kx[r], ky[c]), max(kx[r], ky[c]), near[c - at]))
        if not out:
            return None
        return pa.RecordBatch.from_arrays([pa.array([v[n] for v in out], t) for n, t in enumerate((pa.int64(), pa.int64(), pa.float64()))], names=["a", "b", "likeness"])

    def verified(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        for batch in batches:
            for row in zip(*[batch.column(c).to_pylist() for c in ("band", "i", "j", "block", "k", "h", "fingerprint")], strict=True):
                if held and row[:3] != held[-1][:3]:
                    if (out := settle(held)) is not None:
                        yield out
                    held = []
                held.append(row)
        if held and (out := settle(held)) is not None:
            yield out

    tiles = met.join(made, ["k", "h"])
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    dealt = tiles.repartition(parts, "band", "i", "j").sortWithinPartitions("band", "i", "j").select("band", "i", "j", "block", "k", "h", "fingerprint")
    return dealt.mapInArrow(lean(verified), "a long, b long, likeness double").groupBy("a", "b").agg(F.max("likeness").alias("likeness"))


def near_groups(df: DataFrame, **options) -> DataFrame:
    """(node, root) of the components of near_pairs, with its odd cases; keys without a pair do not occur."""
    return components(near_pairs(df, **options).select("a", "b"))


def near_report(df: DataFrame) -> DataFrame:
    """(doc_id, n_near, group_id) of every row: near texts of other keys found by banding, copies not counted, and the
    least key of its group of near texts and copies. A null key has no group; empty texts are alone.
    """
    rows = df.select(F.col("doc_id").cast("long").alias("k"), F.coalesce("text", F.lit("")).alias("t"))
    pairs = stored(near_pairs(df), "near-pairs")
    least = rows.where("k IS NOT NULL AND t <> ''").groupBy(F.xxhash64("t").alias("h"), F.md5("t").alias("m")).agg(F.min("k").alias("first"))
    own = rows.select("k", F.xxhash64("t").alias("h"), F.md5("t").alias("m")).join(least, ["h", "m"], "left").select("k", F.coalesce("first", "k").alias("first"))
    both = pairs.select("a", "b").union(pairs.select("b", "a")).groupBy("a").agg(F.count(F.lit(1)).alias("n_near")).withColumnRenamed("a", "first")
    links = pairs.select("a", "b").union(own.where("k IS NOT NULL AND k <> first").select(F.col("first").alias("a"), F.col("k").alias("b")))
    root = components(links).select(F.col("node").alias("k"), "root")
    out = own.join(both, "first", "left").join(root, "k", "left")
    return out.select(F.col("k").alias("doc_id"), F.coalesce("n_near", F.lit(0)).alias("n_near"), F.coalesce("root", "k").alias("group_id"))
