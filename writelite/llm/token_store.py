"""Token ids in compressed binary blocks.

Ids are 16-bit where the vocabulary allows, else 32-bit, little-endian. Each document is a zstandard frame of its own,
compressed with one shared dictionary that is trained on the serialized ids of a bounded sample of documents. A block
holds the frames of consecutive documents with an index of offsets, so a short document is read without its
neighbours; each block names the dictionary by its SHA-256. A store is a folder of two tables that Spark writes and
reads, so any file system that Spark reaches will do: `blocks`, one file for each shard, shards and the rows in them in
ascending document id; and `head`, one row with the dictionary, the vocabulary's SHA-256 and the type of ids. Nothing
but the folder's path is needed to read it.

The encoder gives what the tokenizers library gives. The library runs at about 1 MB a second and core, most of it
normalisation with alignments, so texts of plain characters (ASCII and the letters from U+00C0 to U+00FF) take another
way to the same ids: the texts of a batch are lower-cased and cut into the pre-tokens of the file's pattern at once,
and the file's merges run over the bytes of each distinct pre-token, a blank standing for the end of a word. All other
texts go through the library.
"""

from __future__ import annotations

import hashlib
import json
import re
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import public_tokenizers
import pyarrow as pa
import tiktoken
import zstandard
from pyspark import Broadcast
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from writelite.llm.common import BYTE, ROLLING, bucket_count, lean, lowest, shared_dir, total_bytes
from writelite.operators import bucketing

VOCABULARY = "word_bpe_49k.json"
SAMPLE_DOCS, SAMPLE_BYTES, DICT_BYTES, LEVEL, BLOCK_BYTES = 512, 4096, 32_768, 3, 4_000_000
#: Bounds between shards are part of the plan; beyond this many shards they grow instead. Blocks do not.
MOST_SHARDS = 10_000


#: What the vocabulary's pattern splits off after a quote.
ONE = np.frombuffer(b"stmd", dtype=np.uint8)
TWO = np.array([a << 8 | b for a, b in (b"re", b"ve", b"ll")])
#: ASCII and the letters from U+00C0 to U+00FF, without the two signs among them.
PLAIN = re.compile("[\x00-\x7f\xc0-\xd6\xd8-\xf6\xf8-\xff]*")
#: The parts of a tokenizer file that the way for plain texts follows. Any other file goes to the library.
SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
KNOWN = {
    "truncation": None,
    "padding": None,
    "normalizer": {"type": "Sequence", "normalizers": [{"type": "NFC"}, {"type": "Replace", "pattern": {"Regex": r"\s+"}, "content": " "}, {"type": "Lowercase"}]},
    "pre_tokenizer": {"type": "Sequence", "pretokenizers": [{"type": "Split", "pattern": {"Regex": SPLIT}, "behavior": "Removed", "invert": True}, {"type": "ByteLevel", "add_prefix_space": False, "trim_offsets": True, "use_regex": False}]},
    "post_processor": None,
}
MODEL = {"type": "BPE", "dropout": None, "unk_token": None, "continuing_subword_prefix": None, "end_of_word_suffix": "</w>", "fuse_unk": False, "byte_fallback": False, "ignore_merges": False}
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
#: Of a byte of a plain text: 0 white space, 1 of a letter, 2 digit, 3 other.
KIND = np.full(256, 3, dtype=np.uint8)
KIND[[9, 10, 11, 12, 13, 32]] = 0
KIND[97:123] = KIND[128:] = 1
KIND[48:58] = 2


class WordEncoder:
    """The vocabulary of a tokenizer file, by its library and, for plain texts, by byte ranks."""

    def __init__(self, file: str) -> None:
        self.library = Tokenizer.from_str(file)
        spec = json.loads(file)
        model, vocab = spec["model"], spec["model"]["vocab"]
        self.size = max([*vocab.values(), *(t["id"] for t in spec["added_tokens"])]) + 1
        self.special = [t["content"] for t in spec["added_tokens"]]
        self.fast: tiktoken.Encoding | None = None
        plain = all(not t.get(c) for t in spec["added_tokens"] for c in ("single_word", "lstrip", "rstrip", "normalized"))
        if plain and {k: spec.get(k) for k in KNOWN} == KNOWN and {k: model.get(k) for k in MODEL} == MODEL:
            self._ranks(vocab, model["merges"])

    def _ranks(self, vocab: dict[str, int], merges: list) -> None:
        shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
        rest = [b for b in range(256) if b not in shown]
        byte = {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(rest)}
        end = b" "  # no word holds a blank

        def raw(token: str) -> bytes:
            stem = token.removesuffix("</w>")
            return bytes(byte[c] for c in stem) + end * (stem != token)

        ranks: dict[bytes, int] = {bytes([b]): b for b in range(256)}
        for b in range(256):
            ranks.setdefault(bytes([b]) + end, len(ranks))
        for m in merges:
            ranks.setdefault(raw("".join(m) if isinstance(m, list) else m.replace(" ", "")), len(ranks))
        self.back = np.zeros(len(ranks), dtype=np.uint32)
        for token, i in vocab.items():
            if token not in self.special and (r := ranks.get(raw(token))) is not None:
                self.back[r] = i
        self.ends = np.zeros(len(ranks), dtype=bool)
        for token, r in ranks.items():
            self.ends[r] = token.endswith(end) and len(token) > 1
        self.fast = tiktoken.Encoding("words", pat_str="[^ ]+ ", mergeable_ranks=ranks, special_tokens={})

    def plain(self, text: str) -> bool:
        return self.fast is not None and not any(x in text for x in self.special) and PLAIN.fullmatch(text) is not None

    def _words(self, words: np.ndarray, start: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(ids of the distinct words one after another, where each begins, which of them each word is)."""
        with np.errstate(over="ignore"):
            h = ROLLING.slices(BYTE[words], start, end)
        _, first, which = np.unique(h, return_index=True, return_inverse=True)
        n = end[first] - start[first] + 1
        to = np.cumsum(n)
        text = words[np.minimum(np.repeat(start[first] - to + n, n) + np.arange(to[-1]), len(words) - 1)]
        text[to - 1] = 32
        ranks = self.fast.encode_to_numpy(text.tobytes().decode(), disallowed_special=())
        stops = np.flatnonzero(self.ends[ranks]) + 1
        return self.back[ranks], np.r_[0, stops], which

    def _plain_batch(self, texts: list[bytes]) -> list[np.ndarray]:
        offsets = np.cumsum([0, *map(len, texts)])
        raw = np.frombuffer(b"".join(texts), dtype=np.uint8)
        words = LOWER[raw]
        second = np.flatnonzero(raw == 0xC3) + 1
        words[second] += np.where(raw[second] <= 0x9E, 0x20, 0).astype(np.uint8)
        kind = KIND[words]
        inner = offsets[1:-1]
        begins = np.ones(len(raw), dtype=bool)
        begins[1:] = (kind[1:] != kind[:-1]) | (kind[1:] == 2)
        begins[inner[inner < len(raw)]] = True
        # A contraction begins at a quote that does not go on a run of other characters, and ends before what follows.
        quote = np.flatnonzero((words == 39) & begins)
        if len(quote):
            after = np.r_[words, 0, 0, 0]
            limit = offsets[np.searchsorted(offsets, quote, side="right")]
            a, b = after[quote + 1], after[quote + 2]
            one = np.isin(a, ONE) & (quote + 2 <= limit)
            two = np.isin(a.astype(np.int64) << 8 | b, TWO) & (quote + 3 <= limit)
            begins[quote[one | two] + 1] = False
            nxt = np.r_[quote[one] + 2, quote[two & ~one] + 3]
            begins[nxt[nxt < len(raw)]] = True
        begins &= kind > 0
        start = np.flatnonzero(begins)
        if not len(start):
            return [np.zeros(0, np.uint32)] * len(texts)
        stop = np.r_[begins[1:] | (kind[1:] == 0), True]
        stop[inner[inner > 0] - 1] = True
        end = np.flatnonzero(stop & (kind > 0)) + 1
        ids, at, which = self._words(words, start, end)
        n = (at[1:] - at[:-1])[which]
        to = np.cumsum(n)
        out = ids[np.repeat(at[which] - to + n, n) + np.arange(to[-1])]
        cuts = np.r_[0, to][np.searchsorted(start, offsets)]
        return [out[i:j] for i, j in zip(cuts[:-1], cuts[1:], strict=True)]

    def encode_batch(self, texts: list[str], slab: int = 1_000_000) -> list[np.ndarray]:
        out: list[np.ndarray | None] = [None] * len(texts)
        held, raws, size = [], [], 0
        for i, t in enumerate(texts):
            if not self.plain(t):
                out[i] = np.array(self.library.encode(t, add_special_tokens=False).ids, dtype=np.uint32)
                continue
            raws.append(t.encode())
            held.append(i)
            size += len(raws[-1])
            if size >= slab:
                for j, x in zip(held, self._plain_batch(raws), strict=True):
                    out[j] = x
                held, raws, size = [], [], 0
        if held:
            for j, x in zip(held, self._plain_batch(raws), strict=True):
                out[j] = x
        return out

    @property
    def kind(self) -> str:
        return "<u2" if self.size <= 1 << 16 else "<u4"


_built: dict[str, WordEncoder] = {}


def encoder(file: str, stamp: str) -> WordEncoder:
    if stamp not in _built:
        _built[stamp] = WordEncoder(file)
    return _built[stamp]


def train_dictionary(samples: list[bytes]) -> bytes:
    """A zstandard dictionary of at most DICT_BYTES; empty where there is too little to train on."""
    try:
        return zstandard.train_dictionary(DICT_BYTES, samples).as_bytes() if sum(map(len, samples)) > 4 * 1024 else b""
    except zstandard.ZstdError:
        return b""


def _shared(raw: bytes) -> zstandard.ZstdCompressionDict | None:
    return zstandard.ZstdCompressionDict(raw) if raw else None


def _encode_rows(sent: Broadcast, stamp: str, end_id: int | None, dictionary: bytes):
    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(sent.value, stamp)
        pack = zstandard.ZstdCompressor(level=LEVEL, dict_data=_shared(dictionary), write_content_size=True, write_checksum=False)
        tail = np.array([] if end_id is None else [end_id], dtype=enc.kind)
        for batch in (b.slice(i, 1000) for b in batches for i in range(0, len(b), 1000)):
            n, frames = [], []
            for ids in enc.encode_batch([t or "" for t in batch.column(1).to_pylist()]):
                ids = np.concatenate([ids.astype(enc.kind), tail])
                n.append(len(ids))
                frames.append(pack.compress(ids.tobytes()))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array(n, pa.int64()), pa.array(frames, pa.binary())], names=["k", "shard", "n", "frame"])

    return go


def _pack_rows(kind: str, stamp: str):
    """Ordered frames of a shard as blocks; no more than a block of them is held."""
    types = [pa.int32(), pa.int32(), pa.list_(pa.int64()), pa.binary(), pa.binary(), pa.binary(), pa.int64(), pa.string(), pa.string()]
    names = [x.split()[0] for x in BLOCK.split(", ")]

    def block(rows: list[tuple], nth: int) -> pa.RecordBatch:
        offsets = np.cumsum([0, *(len(r[2]) for r in rows)]).astype("<i8")
        one = (rows[0][3], nth, [r[0] for r in rows], np.array([r[1] for r in rows], "<i8").tobytes(), offsets.tobytes(), b"".join(r[2] for r in rows), sum(r[1] for r in rows), kind, stamp)
        return pa.RecordBatch.from_arrays([pa.array([v], t) for v, t in zip(one, types, strict=True)], names=names)

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size, nth = [], 0, 0
        for batch in batches:
            for row in zip(*[batch.column(c).to_pylist() for c in ("k", "n", "frame", "shard")], strict=True):
                if held and size + len(row[2]) > BLOCK_BYTES:
                    yield block(held, nth)
                    held, size, nth = [], 0, nth + 1
                held.append(row)
                size += len(row[2])
        if held:
            yield block(held, nth)

    return go


BLOCK = "shard int, block int, keys array<long>, counts binary, offsets binary, payload binary, n_ids long, id_type string, dictionary_sha256 string"
HEAD = "dictionary binary, dictionary_sha256 string, vocabulary_sha256 string, id_type string"


def write(df: DataFrame, key: str = "doc_id", text: str = "text", path: str | None = None, end_id: int | None = 2, shard_bytes: int = 32_000_000, to: str | None = None) -> str:
    """Encode and write documents; the folder of the store (`to`, or a new one in the shared folder).

    A null or empty text has only its end id; a null key sorts first; rows of one key are kept and lie side by side;
    other columns are ignored; an empty table gives no blocks. The dictionary is trained on SAMPLE_DOCS documents of at
    most SAMPLE_BYTES bytes, those whose keys hash lowest. A shard is dealt out by key range, sorted by Spark and packed
    as its rows pass, so many rows of one key need no more memory than others.
    """
    spark = df.sparkSession
    with open(path or public_tokenizers.path(VOCABULARY), encoding="utf-8") as f:
        file = f.read()
    stamp = hashlib.sha256(file.encode()).hexdigest()
    enc, sent = encoder(file, stamp), spark.sparkContext.broadcast(file)
    rows = df.select(F.col(key).cast("long").alias("k"), F.coalesce(F.col(text), F.lit("")).alias("t"))
    some = lowest(rows.where(F.octet_length("t").between(1, SAMPLE_BYTES)), "k", SAMPLE_DOCS, "t").collect()
    dictionary = train_dictionary([x.astype(enc.kind).tobytes() for x in enc.encode_batch([r["t"] for r in some])])
    mark = hashlib.sha256(dictionary).hexdigest()
    n = min(bucket_count(spark, total_bytes(rows, "t"), shard_bytes), MOST_SHARDS)
    found = rows.agg(F.percentile_approx("k", [i / n for i in range(1, n)], 10 * n + 1000)).first()[0] if n > 1 else None
    # Keys up to a bound are in its shard: a bound b is passed by keys of b + 1 and more.
    bounds = [(True, b + 1) for b in sorted(set(found or [])) if b < 2**63 - 1]
    dealt = bucketing.locate(rows, ["k"], bounds, "shard").select("k", "t", "shard")
    encoded = dealt.mapInArrow(lean(_encode_rows(sent, stamp, end_id, dictionary)), "k long, shard int, n long, frame binary")
    ordered = encoded.repartitionById(len(bounds) + 1, F.col("shard")).sortWithinPartitions(F.col("k").asc_nulls_first(), "n", "frame")
    store = to or f"{shared_dir(spark)}/token-store-{uuid.uuid4().hex}"
    ordered.mapInArrow(lean(_pack_rows(enc.kind, mark)), BLOCK).write.parquet(f"{store}/blocks")
    spark.createDataFrame([(dictionary, mark, stamp, enc.kind)], HEAD).coalesce(1).write.parquet(f"{store}/head")
    return store


def opened(spark: SparkSession, store: str) -> tuple[DataFrame, bytes]:
    """(blocks, dictionary) of a store, from its folder alone; a dictionary that is not what its hash says is refused."""
    head = spark.read.schema(HEAD).parquet(f"{store}/head").first()
    if hashlib.sha256(head["dictionary"]).hexdigest() != head["dictionary_sha256"]:
        raise ValueError(f"the dictionary of {store} is damaged")
    return spark.read.schema(BLOCK).parquet(f"{store}/blocks"), bytes(head["dictionary"])


def _frames(batch: pa.RecordBatch, dictionary: bytes, wanted: set[int] | None = None) -> Iterator[tuple]:
    """(shard, block, key, first id within the block, ids) of the documents of blocks, or of the wanted keys only."""
    unpack = zstandard.ZstdDecompressor(dict_data=_shared(dictionary))
    for row in batch.to_pylist():
        if row["dictionary_sha256"] != hashlib.sha256(dictionary).hexdigest():
            raise ValueError(f"block {row['shard']}.{row['block']} was written with another dictionary")
        counts, offsets = np.frombuffer(row["counts"], "<i8"), np.frombuffer(row["offsets"], "<i8")
        starts = np.r_[0, np.cumsum(counts)]
        for i, k in enumerate(row["keys"]):
            if wanted is None or k in wanted:
                raw = unpack.decompress(row["payload"][offsets[i] : offsets[i + 1]], max_output_size=int(counts[i]) * 4 + 16)
                yield row["shard"], row["block"], k, int(starts[i]), np.frombuffer(raw, row["id_type"])


def read(spark: SparkSession, store: str, keys: list[int] | None = None) -> DataFrame:
    """Rows (k, ids binary of 32-bit ids) of all documents of a store, or of the keys asked for: other blocks and frames are skipped."""
    blocks, dictionary = opened(spark, store)

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [(k, ids.astype("<u4").tobytes()) for _, _, k, _, ids in _frames(batch, dictionary, set(keys) if keys is not None else None)]
            yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.binary())], names=["k", "ids"])

    if keys is not None:
        blocks = blocks.where(F.arrays_overlap("keys", F.array(*map(F.lit, keys)).cast("array<long>")))
    return blocks.mapInArrow(lean(go), "k long, ids binary")


def _digest_rows(dictionary: bytes):
    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [(s, b, k, at, len(ids), zlib.crc32(ids.astype("<u4").tobytes())) for s, b, k, at, ids in _frames(batch, dictionary)]
            yield pa.RecordBatch.from_arrays([pa.array([r[c] for r in rows], t) for c, t in enumerate([pa.int32(), pa.int32(), *[pa.int64()] * 4])], names=["shard", "block", "k", "at", "n", "crc"])

    return go


def report(df: DataFrame, path: str | None = None) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) read back from the written blocks."""
    blocks, dictionary = opened(df.sparkSession, write(df.select("doc_id", "text"), path=path))
    order = W.orderBy("shard", "block").rowsBetween(W.unboundedPreceding, -1)  # one row for each block of 4 MB
    before = blocks.select("shard", "block", F.coalesce(F.sum("n_ids").over(order), F.lit(0)).alias("before"))
    rows = blocks.mapInArrow(lean(_digest_rows(dictionary)), "shard int, block int, k long, at long, n long, crc long")
    return rows.join(before, ["shard", "block"]).select(F.col("k").alias("doc_id"), (F.col("before") + F.col("at")).alias("start"), F.col("n").alias("n_tokens"), F.col("crc").alias("ids_crc32"))
