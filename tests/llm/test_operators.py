"""Operators against brute force, and the odd cases that each of them defines: nulls, empty and long texts, ties, repeated
rows, empty tables, and further columns with clashing names."""

import hashlib
import zlib

import pytest
import public_tokenizers
from oracle import SF, compare
from pyspark.sql import functions as F

from writelite.llm import bpe, decontam, fingerprint, licenses, lines, ngram_join, quality, queries, sharding, substring, token_store

BASE = " ".join(f"w{i}" for i in range(60))
NEAR = BASE.replace("w30 ", "changed ")
LONG = "Ünïcode word, " * 4000 + "x" * 30000
ROWS = [
    (1, BASE), (2, NEAR), (3, BASE), (4, None), (5, ""), (6, " \n\t"), (7, LONG), (7, LONG), (8, "it's  a\n\n tie"), (8, "another text of key eight"), (None, BASE), (9, "one"), (10, "ONE"), (11, LONG + " end"), (12, "Released under the MIT License.\nA\nB"),
]
SCHEMA = "doc_id long, text string, source string, lang string, k string, t string, n long, h string, b int, pos int, __k string, ids string, part int, key string, score double, n_lines long"


def extra(rows):
    return [(i, t, f"s{(i or 0) % 2}", "en", "k", "t", 1, "h", 2, 3, "u", "ids", 4, "key", 0.5, 9) for i, t in rows]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame(extra(ROWS), SCHEMA)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{SF}/documents.parquet")


def words(text):
    return (text or "").encode().split()


def shingles(text):
    w = [x.lower() for x in words(text)]
    return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


@pytest.mark.parametrize("name", sorted(queries.SQL))
def test_sql(spark, name):
    compare(spark, queries.QUERIES[name], queries.SQL[name])


def brute_classes(rows):
    sets = [(k, shingles(t)) for k, t in rows]
    root = {k: k for k, _ in sets if k is not None}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, (a, x) in enumerate(sets):
        for b, y in sets[i + 1 :]:
            if a is not None and b is not None and x and y and 100 * len(x & y) >= 80 * len(x | y):
                p, q = sorted((find(a), find(b)))
                root[q] = p
    return sorted(((k, len(s), None if k is None else find(k)) for k, s in sets), key=str)


def test_join_odd(odd, none):
    got = sorted(((r[0], r[1], r[2]) for r in ngram_join.report(odd).collect()), key=str)
    assert got == brute_classes(ROWS)
    assert ngram_join.report(none).count() == 0


def test_join_brute_force(docs):
    rows = [(r.doc_id, r.text) for r in docs.collect()]
    assert sorted(((r[0], r[1], r[2]) for r in ngram_join.report(docs).collect()), key=str) == brute_classes(rows)


def test_join_long_lists(spark):
    """A group whose lists are longer than the limit for pairs meets in tiles, over several parts."""
    import random

    rng, base = random.Random(4), [f"v{i}" for i in range(80)]
    rows = []
    for i in range(150):
        w = list(base)
        for _ in range(rng.randrange(0, 4)):
            w[rng.randrange(80)] = f"x{rng.randrange(10**6)}"
        rows.append((i, " ".join(w)))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    signed, links = ngram_join.search(df, long_list=8, tile=32)
    root = {i: i for i, _ in rows}
    for a, b in links.collect():
        while root[a] != a:
            a = root[a]
        while root[b] != b:
            b = root[b]
        root[max(a, b)] = min(a, b)
    least = {}
    for r in signed.collect():
        least[bytes(r["same"])] = min(r["k"], least.get(bytes(r["same"]), 10**9))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    got = sorted((r["k"], r["n"], find(least[bytes(r["same"])])) for r in signed.collect())
    assert got == sorted(brute_classes(rows))


def test_keep_one(odd):
    kept = sorted((r.doc_id for r in ngram_join.keep_one(odd).select("doc_id").collect()), key=str)
    assert kept == sorted([1, 4, 5, 6, 7, 8, 9, 11, 12, None], key=str)


def brute_substrings(rows, width=20):
    order = sorted({(k if k is not None else 2**63, t or "") for k, t in rows})
    seen, out = set(), {}
    for k, t in order:
        w = words(t)
        gone = [False] * len(w)
        for i in range(len(w) - width + 1):
            g = tuple(w[i : i + width])
            if g in seen:
                gone[i : i + width] = [True] * width
            else:
                seen.add(g)
        out[k if k < 2**63 else None, t] = (len(w), sum(gone), hashlib.sha256(b" ".join(x for x, d in zip(w, gone, strict=True) if not d)).hexdigest())
    return sorted((str(k), *out[k, t or ""]) for k, t in rows)


def test_substring_odd(odd, none):
    assert sorted((str(r[0]), r[1], r[2], r[3]) for r in substring.report(odd).collect()) == brute_substrings(ROWS)
    assert substring.report(none).count() == 0
    with pytest.raises(ValueError):
        substring.dedup(none, cover=(0, 1, 3))


def test_substring_brute_force(docs):
    rows = [(r.doc_id, r.text) for r in docs.collect()]
    assert sorted((str(r[0]), r[1], r[2], r[3]) for r in substring.report(docs).collect()) == brute_substrings(rows)


def library_ids(rows):
    enc = bpe.encoding(bpe.load_ranks(public_tokenizers.path(bpe.VOCABULARY)), public_tokenizers.PATTERN)
    return sorted((str(k), len(i), hashlib.sha256(b"".join(x.to_bytes(4, "little") for x in i)).hexdigest(), hashlib.sha256((t or "").encode()).hexdigest()) for k, t in rows for i in [enc.encode_ordinary(t or "")])


def test_bpe(odd, none, docs):
    assert sorted((str(r[0]), r[1], r[2], r[3]) for r in bpe.report(odd).collect()) == library_ids(ROWS)
    assert bpe.report(none).count() == 0
    rows = [(r.doc_id, r.text) for r in docs.collect()]
    assert sorted((str(r[0]), r[1], r[2], r[3]) for r in bpe.report(docs).collect()) == library_ids(rows)


def test_bpe_small_chunks(spark):
    """Chunks of 64 characters with white space runs, contractions and tokens longer than the overlap at their edges."""
    import random

    rng = random.Random(9)
    texts = ["".join(rng.choice("ab'st  \n\n\té1!") for _ in range(rng.randrange(60, 700))) for _ in range(150)] + ["y" * 500, " " * 300, "a" + "\n" * 200 + "b"]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    enc = bpe.encoding(bpe.load_ranks(public_tokenizers.path(bpe.VOCABULARY)), public_tokenizers.PATTERN)
    got = {r.doc_id: bytes(r.ids) for r in bpe.encode(df, chunk=64, overlap=16).collect()}
    assert got == {i: b"".join(x.to_bytes(4, "little") for x in enc.encode_ordinary(t)) for i, t in enumerate(texts)}
    back = {r.doc_id: bytes(r.decoded).decode() for r in bpe.decode(bpe.encode(df)).collect()}
    assert back == dict(enumerate(texts))


@pytest.fixture(scope="module")
def tokenizer():
    with open(public_tokenizers.path(token_store.VOCABULARY), encoding="utf-8") as f:
        return token_store.WordEncoder(f.read())


def test_word_encoder_is_the_library(tokenizer, docs):
    import random

    rng = random.Random(2)
    letters = "aB'sStTlLrReEvVmMdD .,!0129éÉßñ_-\n\t²½ªº\xa0İı\x1cΣ中́<|endoftext|>"
    texts = ["".join(rng.choice(letters) for _ in range(rng.randrange(40))) for _ in range(3000)] + [r.text for r in docs.collect()] + ["<|endoftext|> a", "", "don't'S we'VE '''s"]
    assert [x.tolist() for x in tokenizer.encode_batch(texts)] == [tokenizer.library.encode(t, add_special_tokens=False).ids for t in texts]


def test_token_store(tokenizer, odd, none, docs):
    got = sorted((r.start, str(r.doc_id), r.n_tokens, r.ids_crc32) for r in token_store.report(odd).collect())
    at = 0
    for start, _, n, _ in got:
        assert start == at
        at += n
    ids = {}
    for k, t in ROWS:
        x = [*tokenizer.library.encode(t or "", add_special_tokens=False).ids, 2]
        ids.setdefault(str(k), []).append((len(x), zlib.crc32(b"".join(i.to_bytes(4, "little") for i in x))))
    assert sorted((k, n, c) for _, k, n, c in got) == sorted((k, *x) for k, xs in ids.items() for x in xs)
    assert [k for _, k, _, _ in got][0] == "None" and [int(k) for _, k, _, _ in got[1:]] == sorted(k for k, _ in ROWS if k is not None)
    assert token_store.report(none).count() == 0
    spark = docs.sparkSession
    store = token_store.write(docs)
    blocks, dictionary = token_store.opened(spark, store)
    assert len(dictionary) > 0
    some = {r.k: bytes(r.ids) for r in token_store.read(spark, store, [5, 77]).collect()}
    text = {r.doc_id: r.text for r in docs.collect()}
    assert some == {k: b"".join(i.to_bytes(4, "little") for i in [*tokenizer.library.encode(text[k], add_special_tokens=False).ids, 2]) for k in (5, 77)}
    with pytest.raises(ValueError, match="another dictionary"):
        next(token_store._frames(blocks.limit(1).toArrow().to_batches()[0], b""))


def test_token_store_stands_alone(spark, docs, tmp_path):
    """A store is read from its folder alone, files and rows lie in key order, and a damaged dictionary is refused."""
    import glob
    import os

    import pyarrow.parquet as pq

    store = token_store.write(docs, to=str(tmp_path / "store"), shard_bytes=50_000)
    keys = [k for f in sorted(glob.glob(f"{store}/blocks/part-*"), key=os.path.basename) for row in pq.read_table(f).column("keys").to_pylist() for k in row]
    assert keys == sorted(r.doc_id for r in docs.select("doc_id").collect())
    head = pq.read_table(glob.glob(f"{store}/head/part-*")[0]).to_pylist()[0]
    with open(public_tokenizers.path(token_store.VOCABULARY), encoding="utf-8") as f:
        assert head["vocabulary_sha256"] == hashlib.sha256(f.read().encode()).hexdigest()
    assert token_store.read(spark.newSession(), store).count() == len(keys)
    spark.createDataFrame([(b"x" + head["dictionary"], head["dictionary_sha256"], "", "<u2")], token_store.HEAD).write.parquet(f"{tmp_path}/bad/head")
    with pytest.raises(ValueError, match="damaged"):
        token_store.opened(spark, f"{tmp_path}/bad")


def test_token_store_many_rows_of_one_key(spark, tokenizer):
    rows = [(None, f"text {i}") for i in range(300)] + [(7, f"other {i % 3}") for i in range(300)] + [(2**63 - 1, "last"), (-5, "first")]
    got = sorted((r.start, r.doc_id, r.n_tokens) for r in token_store.report(spark.createDataFrame(rows, "doc_id long, text string")).collect())
    assert [k for _, k, _ in got] == [None] * 300 + [-5] + [7] * 300 + [2**63 - 1]
    at = 0
    for start, _, n in got:
        assert start == at
        at += n


def test_other_tokenizer_files_go_through_the_library(tokenizer):
    import json

    with open(public_tokenizers.path(token_store.VOCABULARY), encoding="utf-8") as f:
        spec = json.load(f)
    spec["pre_tokenizer"]["pretokenizers"][0]["pattern"]["Regex"] = "[a-z]+"
    other = token_store.WordEncoder(json.dumps(spec))
    assert tokenizer.fast is not None and other.fast is None
    assert other.encode_batch(["it's 12"])[0].tolist() == other.library.encode("it's 12", add_special_tokens=False).ids


def test_quality(spark, odd, none, docs):
    labels = spark.read.parquet(f"{SF}/labels.parquet")
    got = quality.report(docs, labels).join(labels, "doc_id").where("held_out").collect()
    right = sum(r.predicted == r.quality for r in got)
    assert right >= 0.9 * len(got)
    assert quality.report(odd, labels).count() == len(ROWS)
    assert all(0 <= r.score <= 1 for r in quality.report(odd, labels.where("false")).collect())
    assert quality.report(none, labels).count() == 0
    one = quality.fit(docs, labels.where("quality = 1"))
    assert not one.rules
    assert not quality.fit(docs, labels.select("doc_id", F.lit(None).cast("int").alias("quality"))).rules


def edits(pattern, text):
    """Least edits of the pattern against any part of the text."""
    row = [0] * (len(text) + 1)
    for i, p in enumerate(pattern, 1):
        new = [i]
        for j, t in enumerate(text, 1):
            new.append(min(row[j - 1] + (p != t), row[j] + 1, new[-1] + 1))
        row = new
    return min(row)


def test_decontamination(spark, odd, none, docs):
    import random

    rng = random.Random(6)
    items = ["".join(rng.choice("abcdefgh ") for _ in range(90)) for _ in range(6)]
    texts = []
    for i in range(60):
        x = list(items[i % 6])
        for _ in range(rng.randrange(0, 14)):
            at = rng.randrange(len(x))
            x[at : at + rng.choice([0, 1, 1])] = rng.choice("abcxyz")
        texts.append("".join(rng.choice("abcdefgh ") for _ in range(rng.randrange(100))) + "".join(x) + "tail " * rng.randrange(5))
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    bench = spark.createDataFrame([*enumerate(items), (7, None), (8, "ab"), (None, "x" * 50)], "item_id long, text string")
    want = sorted((d, i, e) for d, t in enumerate(texts) for i, p in enumerate(items) for e in [edits(decontam.normal(p), decontam.normal(t))] if e <= int(0.1 * len(decontam.normal(p))))
    assert sorted((r[0], r[1], r[2]) for r in decontam.hits(df, bench).collect()) == want
    assert sorted((r[0], r[1], r[2]) for r in decontam.hits(df, bench, block_mb=0.0002).collect()) == want
    assert sorted(r.doc_id for r in decontam.clean(df, bench).collect()) == sorted(set(range(60)) - {d for d, _, _ in want})
    assert decontam.hits(odd, bench).count() == 0 and decontam.clean(odd, bench).count() == len(ROWS)
    assert decontam.report(none, bench).count() == 0 and decontam.report(docs, bench.where("false")).count() == 0


def test_lines(spark, odd, none):
    rows = [(i, f"head\nown {i}\n\nhead \nfoot", "a") for i in range(20)] + [(90, "head", "b"), (91, "foot\n", None), (92, None, None)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = {r.doc_id: (r.text, r.n_dropped) for r in lines.clean(df).collect()}
    assert got[3] == ("own 3\n", 3) and got[90] == ("head", 0) and got[91] == ("foot\n", 0) and got[92] == (None, 0)
    assert lines.clean(odd).count() == len(ROWS) and lines.clean(none).count() == 0
    assert lines.clean(odd).columns == [*(c for c in odd.columns if c != "n_lines"), "n_lines", "n_dropped"]


def test_lines_copies(spark):
    """A host where a third of the pages are copies of one: its body stays on every copy, the line of all pages goes."""
    rows = [(i, f"own {i}\nfoot", "a") for i in range(20)] + [(i, "body one\nbody two\nfoot", "a") for i in range(20, 30)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = {r.doc_id: (r.text, r.n_dropped) for r in lines.clean(df).collect()}
    assert got == {**{i: (f"own {i}", 1) for i in range(20)}, **{i: ("body one\nbody two", 1) for i in range(20, 30)}}


def brute_licences(text):
    """(name, dice, hits) by the units of the docstring, one after another."""
    import re

    t = (text or "").lower()
    norm = lambda x: " ".join(re.findall("[a-z0-9]+", x))
    paragraphs = [p for p in map(norm, re.split(licenses.PARAGRAPHS, t)) if p]
    most = licenses._bounds(licenses.TEMPLATES, licenses.DICE)[1]
    units = {norm(t), *map(norm, t.split("\n")), *map(norm, re.split(licenses.SENTENCES, t)), *paragraphs}
    for i in range(len(paragraphs)):
        for j in range(i + 1, len(paragraphs)):
            if sum(len(p.split()) for p in paragraphs[i : j + 1]) <= most:
                units.add(" ".join(paragraphs[i : j + 1]))
    found = []
    for u in units:
        g = set(licenses.bigrams(u))
        for name, template in licenses.TEMPLATES.items():
            b = set(licenses.bigrams(template))
            d = 2 * len(g & b) / (len(g) + len(b))
            if d >= licenses.DICE:
                found.append((d, name))
    best = max(found, default=(None, None))
    return best[1], best[0], len({n for _, n in found})


def test_licenses(odd, none):
    got = [(r.licence, r.dice, r.n_hits) for r in licenses.scan(odd).collect()]
    assert sorted(got, key=str) == sorted((brute_licences(t) for _, t in ROWS), key=str)
    assert licenses.scan(none).count() == 0


def test_licenses_by_row(spark):
    """Rows of one key, or without a key, do not share a licence; licences of several paragraphs and inside prose are found."""
    mit = licenses.TEMPLATES["MIT"]
    at = [mit.index(" The above"), mit.index(" THE SOFTWARE IS")]
    layout = mit[: at[0]] + "\n\n" + mit[at[0] + 1 : at[1]] + "\n \n" + mit[at[1] + 1 :]
    gpl = licenses.TEMPLATES["GPL-3.0-header"].replace(" This program is distributed", "\n\nThis program is distributed")
    rows = [
        (None, "Released under the MIT License."), (None, "nothing at all here"), (None, None), (3, "Licensed under CC BY-NC 4.0."), (3, "other words"), (3, "other words"),
        (4, f"A file of ours, with some words of its own at the head.\n\n{layout}\n\nAnd a paragraph that comes after it, also with words."),
        (5, f"Copyright by us\n\n{gpl}\n\ncode follows"), (6, "We wrote this last year. Released under the MIT License. Have fun with it, and tell us what you did."),
        (7, " ".join(["license"] * 5000)), (8, "\n\n".join(["license"] * 700)),
    ]
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumn("licence", F.lit("clash")).withColumn("__h", F.lit(1))
    got = licenses.scan(df).collect()
    key = lambda r: (str(r[0]), str(r[1]), r[3])
    assert sorted([(r.doc_id, r.licence, r.dice, r.n_hits) for r in got], key=key) == sorted([(k, *brute_licences(t)) for k, t in rows], key=key)
    by = {r.doc_id: r.licence for r in got}
    assert (by[4], by[5], by[6]) == ("MIT", "GPL-3.0-header", "MIT-notice")


def brute_lines(rows, ratio=lines.RATIO, least=lines.LEAST_PAGES, distinct=True):
    """(key, text, lines, dropped) of (key, text, host) rows, page by page."""
    from collections import defaultdict

    pages = defaultdict(list)
    for _, t, h in rows:
        pages[h].append(t)
    bad = {}
    for h, texts in pages.items():
        texts = list(dict.fromkeys(texts)) if distinct else texts
        count = defaultdict(int)
        for t in texts:
            for line in {x.strip(" \t\r") for x in (t or "").split("\n")} - {""}:
                count[line] += 1
        bad[h] = {x for x, c in count.items() if c >= least and c > ratio * len(texts)}
    out = []
    for k, t, h in rows:
        every = [] if t is None else t.split("\n")
        kept = [x for x in every if x.strip(" \t\r") not in bad[h]]
        out.append((k, t if len(kept) == len(every) else "\n".join(kept), len(every), len(every) - len(kept)))
    return sorted(out, key=str)


@pytest.mark.parametrize("distinct", [True, False])
def test_lines_brute_force(spark, odd, docs, distinct):
    for df in (odd, docs):
        got = [(r.doc_id, r.text, r.n_lines, r.n_dropped) for r in lines.clean(df, distinct=distinct).collect()]
        assert sorted(got, key=str) == brute_lines([(r.doc_id, r.text, r.source) for r in df.collect()], distinct=distinct)


def test_odd_rows_by_value(spark, odd):
    """Decontamination, sharding and quality on the odd table: what each row gets, not only how many there are."""
    bench = spark.createDataFrame([(1, "w10 w11 w12 w13 w14 w15 w16 w17"), (2, "Ünïcode word, Ünïcode word,"), (2, "Released under the MIT License."), (None, "one"), (3, None), (4, "")], "item_id long, text string")
    found = sorted({(r.doc_id, r.item_id, r.edits) for r in decontam.hits(odd, bench).collect()}, key=str)
    assert found == sorted([(1, 1, 0), (2, 1, 0), (3, 1, 0), (None, 1, 0), (7, 2, 0), (11, 2, 0), (12, 2, 0)], key=str)
    assert sorted((r.doc_id for r in decontam.clean(odd, bench).collect()), key=str) == sorted([4, 5, 6, 8, 8, 9, 10], key=str)
    got = sharding.shard(odd).collect()
    size = lambda t: (len((t or "").encode()) + 1, zlib.crc32((t or "").encode()))
    assert sorted(((r.doc_id, r.size, r.text_crc32) for r in got), key=str) == sorted(((k, *size(t)) for k, t in ROWS), key=str)
    place = {}
    for r in got:
        assert place.setdefault(r.doc_id, (r.shard, r.grown_shard)) == (r.shard, r.grown_shard)
    labels = spark.createDataFrame([(k, i % 2) for i, (k, _) in enumerate(ROWS * 30) if k is not None] + [(None, 1), (3, None), (5, 7)], "doc_id long, quality int")
    scores = {}
    for r in quality.report(odd, labels).collect():
        text = [t or "" for k, t in ROWS if k == r.doc_id]
        scores.setdefault((r.doc_id, r.score), 0)
        assert r.held_out == (r.doc_id is not None and zlib.crc32(str(r.doc_id).encode()) % 5 == 0) and r.predicted == int(r.score >= 0.3) and text
    by = {k: s for k, s in scores}
    assert by[1] == by[3] == by[None] and by[4] == by[5]


def test_walk_is_the_definition():
    """Fingerprints against a walk one step at a time: the character under the pointer at the sampled steps."""
    import random

    rng = random.Random(1)
    samples = set(fingerprint._all_samples()[:2000].tolist())
    for n in (0, 1, 2, 30, 700, 5000):
        text = "".join(rng.choices("abcé ф😀", k=n))
        kind, digit = fingerprint._hashed(fingerprint.code_points(text))
        at, out = 0, ""
        for step in range(3 * n):
            if step in samples:
                out += "0123456789abcdef"[int(digit[at]) if at < n else 0]
            if at < n:
                at += int(fingerprint._step_hashes(step // fingerprint.STEPS)[step % fingerprint.STEPS]) >> int(kind[at]) & 1
        assert fingerprint.fingerprints([fingerprint.code_points(text)]) == [out]


def test_likeness_is_the_definition():
    """Equal digits weighed by the steps that they stand for, over the steps of the longer one."""
    import random

    rng = random.Random(2)
    for _ in range(50):
        a = "".join(rng.choices("0123", k=rng.randrange(300)))
        b = "".join(x if rng.random() < 0.8 else "9" for x in a)[: rng.randrange(300)]
        weight, o = [], 0
        while len(weight) < max(len(a), len(b)):
            weight += [2**o / len(fingerprint.sampled_steps(o))] * len(fingerprint.sampled_steps(o))
            o += 1
        whole = sum(weight[: max(len(a), len(b))])
        want = sum(w for w, x, y in zip(weight, a, b, strict=False) if x == y) / whole if whole else 1.0
        assert abs(fingerprint.likeness(a, b) - want) < 1e-12


def test_pipeline_leaves_one_table(spark):
    """run() deletes what its stages wrote on the way, and nothing that others wrote."""
    import os

    import corpus_pipeline as cp

    from writelite.llm.common import shared_dir, stored, written

    mine = stored(spark.range(5).toDF("a"), "mine")
    before = set(os.listdir(shared_dir(spark).removeprefix("file:")))
    out = cp.run(spark, SF)
    assert out.count() > 0 and mine.count() == 5
    new = set(os.listdir(shared_dir(spark).removeprefix("file:"))) - before
    assert len(new) == 1 and os.listdir(f"{shared_dir(spark).removeprefix('file:')}/{new.pop()}") == ["byte_bpe"] and any("mine" in p for p in written())


def test_sharding(spark, odd, none, docs):
    rows = sharding.shard(docs).collect()
    by = {}
    for r in rows:
        by.setdefault(r.shard, []).append(r.slot)
        assert r.grown_shard in (r.shard, 16) and r.law == "key"
    assert all(sorted(v) == list(range(len(v))) for v in by.values()) and set(by) <= set(range(16))
    sizes = {r.doc_id: (r.size, r.text_crc32) for r in rows}
    assert sizes == {r.doc_id: (len(r.text.encode()) + 1, zlib.crc32(r.text.encode())) for r in docs.collect()}
    assert sharding.shard(odd).count() == len(ROWS) and sharding.shard(none).count() == 0
    big = sharding.shard(spark.range(40000).select(F.col("id").alias("doc_id"), F.lit("x").alias("text"))).groupBy("shard").count().collect()
    assert all(2100 < r["count"] < 2900 for r in big)
    heavy = sharding.Branch("root", children=(sharding.Branch("a", 3, shard=0), sharding.Branch("b", 1, shard=1)))
    placed = spark.range(20000).select(sharding.place(F.col("id"), heavy).alias("s")).where("s = 0").count()
    assert 14500 < placed < 15500


def test_fingerprints(spark, odd, none):
    got = fingerprint.with_edits(odd, partitions=3).collect()
    order = sorted(ROWS, key=lambda r: (r[0] is not None, r[0] or 0, r[1] or ""), reverse=True)
    want = []
    for i, (k, t) in enumerate(order):
        t, nxt = t or "", order[(i + 1) % len(order)][1] or ""
        half = len(t) // 2
        want.append((str(k), len(t), hashlib.sha256((t[: len(t) - half] + nxt[:half]).encode()).hexdigest()))
    assert sorted((str(r.doc_id), r.n_chars, r.edited_sha256) for r in got) == sorted(want)
    prints = {}
    for r in got:
        prints.setdefault(r.doc_id, set()).add(r.fingerprint)
    assert prints[1] == prints[3] == prints[None] and prints[4] == {""}
    assert all(0 <= r.near_edited <= 1 and 0 <= r.near_next <= 1 for r in got)
    assert fingerprint.with_edits(none).count() == 0
    one = fingerprint.with_edits(spark.createDataFrame([(5, "abcdef")], "doc_id long, text string")).collect()
    assert [(r.edited_sha256, r.near_next) for r in one] == [(hashlib.sha256(b"abcabc").hexdigest(), 1.0)]
    nulls = fingerprint.with_edits(spark.createDataFrame([(None, "ab"), (None, "cd")], "doc_id long, text string")).collect()
    assert len(nulls) == 2


def test_fingerprint_likeness(docs):
    rows = fingerprint.with_edits(docs).where("n_chars > 400").collect()
    edited, nxt = [r.near_edited for r in rows], [r.near_next for r in rows]
    assert sum(edited) / len(edited) > 0.5 and sum(nxt) / len(nxt) < 0.2
    assert sum(a > b for a, b in zip(edited, nxt, strict=True)) > 0.95 * len(rows)


def test_long_texts_fall_back_into_step():
    """The cost of an edit near the start of a long text is paid once, not again in each part of it; the median of draws."""
    import random

    rng = random.Random(5)
    letters = "etaoinshrdlu "
    for size in (32768, 50000):
        inserted, deleted = [], []
        for _ in range(9):
            t = "".join(rng.choices(letters, k=size))
            texts = [t, t[:200] + "".join(rng.choices(letters, k=10)) + t[200:], t[:200] + t[210:]]
            a, b, c = fingerprint.fingerprints([fingerprint.code_points(x) for x in texts])
            inserted.append(fingerprint.likeness(a, b))
            deleted.append(fingerprint.likeness(a, c))
        assert sorted(inserted)[4] > 0.94 and sorted(deleted)[4] > 0.94, (size, inserted, deleted)


def test_walks_alone_and_together():
    """Texts of 0 to 30,000 characters have the same fingerprints walked side by side as one by one."""
    import random

    rng = random.Random(8)
    points = [fingerprint.code_points("".join(rng.choices("abc déф😀", k=n))) for n in [0, 1, 2, 30000, 4096, 4097, 12288, 12289, *range(5, 8000, 190)]]
    assert fingerprint.fingerprints(points) == [fingerprint.fingerprints([x])[0] for x in points]


def test_near_groups(spark):
    base = "the quick brown fox jumps over the lazy dog and runs through the old forest again " * 6
    rows = [(0, base), (1, base.replace("lazy", "lazi", 1)), (2, "something else entirely, with no word in common " * 9), (3, base)]
    got = {r.node: r.root for r in fingerprint.near_groups(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {0: 0, 1: 0}


def test_near_texts(spark, odd, none):
    """One row a row; copies and near texts share a group; the odd rows of the table too."""
    got = sorted(((r.doc_id, r.n_near, r.group_id) for r in fingerprint.near_report(odd).collect()), key=str)
    by = {k: g for k, _, g in got}
    assert len(got) == len(ROWS) and (None, 1, None) in got or (None, 0, None) in got
    assert by[1] == by[3] == 1 and by[4] == 4 and by[5] == 5 and by[9] == 9
    assert fingerprint.near_report(none).count() == 0


def test_near_pairs_recall(spark):
    """Texts over few letters, whose bands have many members and many near pairs besides those with the least: pairs against brute force, in tiles too."""
    import random

    rng, texts = random.Random(12), []
    for _ in range(150):
        texts.append("".join(rng.choices("eat", [15, 3, 2], k=400)))
    for i in range(100, 150):
        x = list(texts[i])
        x[300 + rng.randrange(100)] = "z"
        texts.append("".join(x))
    prints = fingerprint.fingerprints([fingerprint.code_points(t) for t in texts])
    want = {(i, j): v for i, a in enumerate(prints) for j, b in enumerate(prints) if i < j for v in [fingerprint.likeness(a, b)] if v >= 0.7}
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    for tile in (512, 16):
        rows = fingerprint.near_pairs(df, tile=tile).collect()
        got = {(r.a, r.b): r.likeness for r in rows}
        assert len(got) == len(rows) and got == {p: want[p] for p in got}
        assert len(want) > 1000 and len(got) >= 0.95 * len(want)


def test_components(spark):
    from writelite.llm.common import components

    links = [(i, i + 1) for i in range(100, 140)] + [(7, 3), (3, 7), (9, 7), (5, 5)]
    got = {r.node: r.root for r in components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert got == {**dict.fromkeys(range(100, 141), 100), 3: 3, 7: 3, 9: 3}


def test_bpe_joins_only_what_disagrees(spark):
    """A long run of one letter holds together the chunks that it covers, and no others."""
    text = "some words here, " * 100 + "z" * 300 + " and more words; " * 100
    enc = bpe.encoding(bpe.load_ranks(public_tokenizers.path(bpe.VOCABULARY)), public_tokenizers.PATTERN)
    df = spark.createDataFrame([(1, text), (2, "z" * 900), (3, text + "q")], "doc_id long, text string")
    got = {r.doc_id: bytes(r.ids) for r in bpe.encode(df, chunk=64, overlap=32).collect()}
    assert got == {i: b"".join(x.to_bytes(4, "little") for x in enc.encode_ordinary(t)) for i, t in ((1, text), (2, "z" * 900), (3, text + "q"))}


def test_decontamination_of_many_pairs():
    """Thousands of texts and items in one block: pairs times diagonals outgrow 64 bits unless pairs go by rank."""
    import random

    rng = random.Random(3)
    items = [(i, "".join(rng.choices("abcdefghij", k=24))) for i in range(250_000)]
    index = decontam.Items(items, 8, 0.0)
    texts = ["".join(rng.choices("klmnop", k=5))] * 12_000 + ["xx " + items[249_999][1] + " yy", items[7][1]]
    found = index.find(texts, slab=10**9)
    assert [len(x) for x in found[:12_000]] == [0] * 12_000
    assert [[i for i, _, _ in x] for x in found[12_000:]] == [[249_999], [7]]


def test_quality_expression_is_the_rules(spark, docs):
    """The compiled column against the rules applied to arrays of the same statistics."""
    import numpy as np

    labels = spark.read.parquet(f"{SF}/labels.parquet")
    model = quality.fit(docs, labels)
    stats = quality.statistics(F.col("text"))
    rows = quality.score(docs, model).select("doc_id", "__score", *[c.cast("double").alias(n) for n, c in stats.items()]).toPandas()
    x = {n: rows[n].to_numpy() for n in stats}
    z = model.intercept + sum(r.weight * r.holds(x) for r in model.rules)
    assert len(model.rules) > 3 and np.abs(1 / (1 + np.exp(-z)) - rows["__score"].to_numpy()).max() < 1e-12


def test_quality_repeated_keys(spark, docs):
    """Repeated rows and labels of a key are learnt from once, whatever their order."""
    labels = spark.read.parquet(f"{SF}/labels.parquet")
    once = quality.fit(docs, labels)
    again = quality.fit(docs.unionByName(docs).orderBy(F.rand(3)), labels.unionByName(labels))
    assert once == again


def test_sharding_places_by_the_tree(spark):
    """The expression against a walk down the tree in Python, with the engine's own hash of (key, child)."""
    import math

    tree = sharding.default_tree(17)
    names = []

    def collect(branch):
        names.extend(c.name for c in branch.children)
        for c in branch.children:
            collect(c)

    collect(tree)
    df = spark.range(300).select(F.col("id").alias("k"))
    rows = df.select("k", sharding.place(F.col("k"), tree).alias("s"), *[F.xxhash64("k", F.lit(n)).alias(n) for n in names]).collect()
    for r in rows:
        at = tree
        while at.children:
            at = min(at.children, key=lambda c: -math.log((((r[c.name] % 2**64) >> 11) + 0.5) / 2**53) / c.mass)
        assert at.shard == r.s


def test_pipeline_odd_rows(spark, odd, none):
    """Every stage on null and empty texts, ties, repeated rows, null keys and sources, an empty table, and clashing names."""
    import corpus_pipeline as cp

    for name, stage in cp.STAGES:
        for docs, empty in ((odd.withColumn("n_chars", F.lit(3).cast("long")).withColumn("item_id", F.lit(1)).withColumn("quality", F.lit(0)).withColumn("text_of", F.col("text")), False), (none.withColumn("n_chars", F.lit(3).cast("long")), True)):
            out = stage(spark, docs, SF)
            rows = out.collect()
            assert name == "byte_bpe" or out.columns == docs.columns
            if empty:
                assert rows == []
            elif name == "line_dedup":
                assert sorted(str(r.doc_id) for r in rows) == sorted(str(k) for k, _ in ROWS)
                assert sorted(str(r.text) for r in rows) == sorted(str(t) for _, t in ROWS)
            elif name == "ngram_jaccard_join":
                assert sorted((str(r.doc_id) for r in rows)) == sorted(map(str, [1, 4, 5, 6, 7, 8, 9, 11, 12, None]))
            elif name == "benchmark_decontamination":
                assert len(rows) == len(ROWS)
            elif name == "byte_bpe":
                assert sorted((str(r[0]), r[1], r[2], r[3]) for r in rows) == library_ids(ROWS)
            else:
                kept = {r.text for r in rows}
                # Equal texts share a fate.
                assert len(rows) == sum(t in kept for _, t in ROWS)


def test_pipeline(spark):
    """Every stage against a plain version of it over the rows that the stage before kept."""
    import corpus_pipeline as cp

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    for name, stage in cp.STAGES[:-1]:
        before = {r.doc_id: r.text for r in docs.collect()}
        out = stage(spark, docs, SF)
        assert out.columns == docs.columns
        after = {r.doc_id: r.text for r in out.collect()}
        assert set(after) <= set(before)
        if name == "ngram_jaccard_join":
            assert set(after) == {k for k, _, root in brute_classes(list(before.items())) if k == root}
        elif name == "benchmark_decontamination":
            items = [decontam.normal(r.text) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
            assert not any(i in decontam.normal(t) for t in after.values() for i in items)
        elif name == "line_dedup":
            assert set(after) == set(before)
        docs = spark.createDataFrame(out.collect(), docs.schema)
    assert sorted((str(r[0]), r[1], r[2], r[3]) for r in cp.encode(spark, docs, SF).collect()) == library_ids([(r.doc_id, r.text) for r in docs.collect()])
    assert cp.run(spark, SF).count() == docs.count()
