"""Byte-level BPE by overlapping chunks.

A text longer than a chunk is cut into chunks that overlap. Chunks are pre-tokenised in parallel, each from its own
start. The pattern looks only ahead, so once two neighbours have a boundary at the same place inside their overlap,
everything after it is the same for both: there the text is cut, and the pieces between cuts are encoded in parallel.
A cut stands after a character that is not white space, where a piece by itself ends as it does in its text.
Neighbours that never agree (a token longer than the overlap) are one piece.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator

import numpy as np
import public_tokenizers
import pyarrow as pa
import tiktoken
from pyspark import Broadcast
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from writelite.llm.common import lean, slabs

CHUNK, OVERLAP = 16_384, 512
#: Bytes of text that a worker encodes before it hands the ids on.
SLAB = 1_000_000
VOCABULARY = "byte_bpe_multi_50k.tiktoken"
_cached: dict[str, tiktoken.Encoding] = {}


def load_ranks(path: str) -> bytes:
    """The rank file, read by the driver and sent to the executors (its size is that of a vocabulary)."""
    with open(path, "rb") as f:
        return f.read()


def encoding(ranks: bytes, pattern: str) -> tiktoken.Encoding:
    """An encoder of this process, built once."""
    name = hashlib.sha256(ranks + pattern.encode()).hexdigest()
    if name not in _cached:
        table = {base64.b64decode(a): int(b) for a, b in map(bytes.split, ranks.splitlines()) if a}
        _cached[name] = tiktoken.Encoding(name, pat_str=pattern, mergeable_ranks=table, special_tokens={})
    return _cached[name]


def boundaries(pattern: str, piece: str) -> list[int]:
    """Places inside the piece where a pre-token begins after a character that is not white space.

    >>> boundaries(public_tokenizers.PATTERN, "it's  so")
    [2, 4]
    """
    import regex

    return [m.start() for m in regex.finditer(pattern, piece) if m.start() and not piece[m.start() - 1].isspace()]


def narrow(enc: tiktoken.Encoding) -> str:
    """The type that ids have while they are exchanged."""
    return "<u2" if enc.max_token_value < 1 << 16 else "<u4"


def _encode_rows(ranks: Broadcast, pattern: str, column: str, packed: bool):
    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoding(ranks.value, pattern)
        kind = narrow(enc) if packed else "<u4"
        for batch in (part for b in batches for part in slabs(b, column, SLAB)):
            ids = [enc.encode_to_numpy(t or "", disallowed_special=()).astype(kind).tobytes() for t in batch.column(column).to_pylist()]
            at = batch.schema.get_field_index(column)
            yield batch.set_column(at, pa.field("ids", pa.binary()), pa.array(ids, pa.binary()))

    return go


def _split_rows(pattern: str, chunk: int, overlap: int):
    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            heads, tails = [], []
            for start, piece in zip(batch.column("__at").to_pylist(), batch.column("__piece").to_pylist(), strict=True):
                found = boundaries(pattern, piece)
                heads.append([start, *(start + b for b in found if b < overlap)])
                tails.append([start + b for b in found if chunk <= b < chunk + overlap] if len(piece) == chunk + overlap else [start + b for b in found if b >= chunk])
            kind = pa.list_(pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column("__h"), batch.column("__len"), batch.column("__at"), pa.array(heads, kind), pa.array(tails, kind)], names=["__h", "__len", "__at", "__head", "__tail"])

    return go


def _join_rows(ranks: Broadcast, pattern: str):
    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = narrow(encoding(ranks.value, pattern))
        for batch in batches:
            at = batch.schema.get_field_index("ids")
            ids = [np.frombuffer(b"".join(x), kind).astype("<u4").tobytes() for x in batch.column(at).to_pylist()]
            yield batch.set_column(at, pa.field("ids", pa.binary()), pa.array(ids, pa.binary()))

    return go


def encode(df: DataFrame, key: str = "doc_id", text: str = "text", path: str | None = None, pattern: str = public_tokenizers.PATTERN, chunk: int = CHUNK, overlap: int = OVERLAP) -> DataFrame:
    """Rows (key, ids): ids is the binary of little-endian unsigned 32-bit token ids.

    A null text is an empty one and has no ids; repeated rows each give a row; keys may be null or tie; an empty table
    gives none; other columns are ignored. Texts of any length are encoded whole.
    """
    if not 0 < overlap < chunk:
        raise ValueError("overlap must be positive and less than chunk")
    spark: SparkSession = df.sparkSession
    ranks = spark.sparkContext.broadcast(load_ranks(path or public_tokenizers.path(VOCABULARY)))
    rows = df.select(F.col(key).alias("__k"), F.coalesce(F.col(text), F.lit("")).alias("__t"))
    kind = dict(rows.dtypes)["__k"]
    length = F.length("__t")
    short = rows.where(length <= chunk).mapInArrow(lean(_encode_rows(ranks, pattern, "__t", False)), f"__k {kind}, ids binary")

    # A long text is named by a digest of its key and itself; equal rows are one text that is given as often at the end.
    named = rows.where(length > chunk).withColumn("__h", F.md5(F.concat(F.coalesce(F.concat(F.lit("k"), F.col("__k").cast("string")), F.lit("n")), F.lit("|"), "__t")))
    names = named.groupBy("__h").agg(F.first("__k").alias("__k"), F.count(F.lit(1)).alias("__n"))
    pieces = named.select("__h", length.cast("long").alias("__len"), "__t", F.explode(F.sequence(F.lit(0), length - 1, F.lit(chunk))).alias("__at"))
    pieces = pieces.select("__h", "__len", F.col("__at").cast("long").alias("__at"), F.substring("__t", F.col("__at") + 1, F.lit(chunk + overlap)).alias("__piece"))
    # One exchange of the pieces serves the pre-tokens and, once the cuts are known, the encoding.
    dealt = pieces.repartition(int(spark.conf.get("spark.sql.shuffle.partitions")), "__h", "__at").dropDuplicates(["__h", "__at"])
    ends = dealt.mapInArrow(lean(_split_rows(pattern, chunk, overlap)), "__h string, __len long, __at long, __head array<long>, __tail array<long>")
    along = W.partitionBy("__h").orderBy("__at")
    meet: Column = F.array_min(F.array_intersect("__tail", F.lead("__head").over(along)))
    cuts = ends.withColumn("__cut", F.when(F.col("__at") + chunk >= F.col("__len"), F.col("__len")).otherwise(meet))
    # Chunks without a cut between them go together under the place of the first one.
    begins = F.coalesce(F.lag("__cut").over(along).isNotNull(), F.lit(False)) | (F.col("__at") == 0)
    first = F.last(F.when(begins, F.col("__at")), ignorenulls=True).over(along.rowsBetween(W.unboundedPreceding, 0))
    to = F.coalesce("__cut", F.col("__at") + chunk)
    cuts = cuts.select("__h", "__at", to.alias("__to"), F.coalesce(F.lag("__cut").over(along), F.col("__at")).alias("__from"), first.alias("__first"), (begins & F.col("__cut").isNotNull()).alias("__alone"))
    met = dealt.join(cuts.hint("shuffle_hash"), ["__h", "__at"])
    own = F.substring("__piece", (F.col("__from") - F.col("__at") + 1).cast("int"), (F.col("__to") - F.col("__from")).cast("int")).alias("__t")
    apart = met.where("__alone").select("__h", "__at", own)
    together = met.where("NOT __alone").select("__h", "__first", "__at", own).groupBy("__h", "__first").agg(F.array_sort(F.collect_list(F.struct("__at", "__t"))).alias("p"))
    texts = apart.unionByName(together.select("__h", F.col("__first").alias("__at"), F.array_join("p.__t", "").alias("__t")))
    parts = texts.mapInArrow(lean(_encode_rows(ranks, pattern, "__t", True)), "__h string, __at long, ids binary")
    joined = parts.groupBy("__h").agg(F.array_sort(F.collect_list(F.struct("__at", "ids"))).alias("p")).join(names, "__h").select("__k", F.col("p.ids").alias("ids"), "__n")
    long = joined.mapInArrow(lean(_join_rows(ranks, pattern)), f"__k {kind}, ids binary, __n long").select("__k", "ids", F.explode(F.sequence(F.lit(1), F.col("__n")))).select("__k", "ids")
    return short.unionByName(long).withColumnRenamed("__k", key)


def _decode_rows(ranks: Broadcast, pattern: str, digest: bool):
    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoding(ranks.value, pattern)
        for batch in (b.slice(i, 500) for b in batches for i in range(0, len(b), 500)):
            out, packed = [], batch.column("ids").to_pylist()
            for x in packed:
                raw = enc.decode_bytes(np.frombuffer(x or b"", dtype="<u4").tolist())
                out.append((hashlib.sha256(raw).hexdigest(), hashlib.sha256(x or b"").hexdigest()) if digest else (raw, None))
            cols = [batch.column(0), batch.column(1)] if not digest else [batch.column(0), pa.array([len(x or b"") // 4 for x in packed], pa.int64()), pa.array([b for _, b in out])]
            yield pa.RecordBatch.from_arrays([*cols, pa.array([a for a, _ in out], pa.string() if digest else pa.binary())], names=["k", "n_tokens", "ids_sha256", "decoded_sha256"] if digest else ["k", "ids", "decoded"])

    return go


def decode(encoded: DataFrame, key: str = "doc_id", path: str | None = None, pattern: str = public_tokenizers.PATTERN) -> DataFrame:
    """Rows (key, ids, decoded): the raw bytes of the ids, one token's after another's. A null list decodes to no bytes."""
    ranks = encoded.sparkSession.sparkContext.broadcast(load_ranks(path or public_tokenizers.path(VOCABULARY)))
    kind = dict(encoded.dtypes)[key]
    return encoded.select(key, "ids").mapInArrow(lean(_decode_rows(ranks, pattern, False)), f"`{key}` {kind}, ids binary, decoded binary")


def report(df: DataFrame, path: str | None = None) -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256) of documents: encoded, then decoded from the ids."""
    ranks = df.sparkSession.sparkContext.broadcast(load_ranks(path or public_tokenizers.path(VOCABULARY)))
    encoded = encode(df.select("doc_id", "text"), path=path)
    return encoded.mapInArrow(lean(_decode_rows(ranks, public_tokenizers.PATTERN, True)), f"doc_id {dict(df.dtypes)['doc_id']}, n_tokens long, ids_sha256 string, decoded_sha256 string")
