"""Quality classifier: a sparse ensemble of rules over text statistics.

Boosted shallow trees are grown on labelled rows, every path from a root becomes a conjunctive rule, a lasso logistic
fit leaves few rules with a weight, and these are compiled into one Spark column expression. Statistics are Spark
column expressions too, so scoring is one pass without Python. Training reads a bounded sample of labelled rows
(TRAIN_ROWS, those whose keys hash lowest); everything else covers all rows.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from writelite.llm.common import lowest

TRAIN_ROWS, TREES, DEPTH, SHRINK, BINS, LASSO = 20_000, 40, 3, 0.2, 32, 0.002
THRESHOLD = 0.3


def statistics(text: Column) -> dict[str, Column]:
    """Statistics of a text; all are 0 for an empty one. They look at the text alone."""
    t = F.coalesce(text, F.lit(""))
    n = F.greatest(F.length(t), F.lit(1))
    count = lambda pattern: F.regexp_count(t, F.lit(pattern))
    words = F.filter(F.split(t, r"[ \t\r\n\x0b\f]+"), lambda w: w != "")
    lines = F.split(t, "\n")
    return {
        "chars": F.log1p(F.length(t).cast("double")),
        "words": F.log1p(F.size(words).cast("double")),
        "word_length": F.length(t) / F.greatest(F.size(words), F.lit(1)),
        "distinct_words": F.size(F.array_distinct(words)) / F.greatest(F.size(words), F.lit(1)),
        "upper": count(r"\p{Lu}") / n,
        "marks": count(r"[!#$%&*@^~<>{}\\[\\]+=_]") / n,
        "bars": count(r"[|]") / n,
        "stops": count(r"[.,;:?]") / n,
        "digits": count(r"[0-9]") / n,
        "accents": count(r"[^\x00-\x7f]") / n,
        "lines": F.size(lines) / n * 100,
        "line_copies": 1 - F.size(F.array_distinct(lines)) / F.greatest(F.size(lines), F.lit(1)),
        "shouts": count(r"\p{Lu}{2,}") / F.greatest(F.size(words), F.lit(1)),
        "sentences": count(r"[.!?]\s") / F.greatest(F.size(words), F.lit(1)),
        "links": count(r"https?://|www\.|@") / n * 100,
    }


@dataclass(frozen=True)
class Rule:
    """A conjunction of (statistic, is above, cut)."""

    terms: tuple[tuple[str, bool, float], ...]
    weight: float = 0.0

    def holds(self, x: dict[str, np.ndarray]) -> np.ndarray:
        return np.logical_and.reduce([x[f] > c if above else x[f] <= c for f, above, c in self.terms])

    def column(self, stats: dict[str, Column]) -> Column:
        out = F.lit(True)
        for f, above, c in self.terms:
            out = out & ((stats[f] > c) if above else (stats[f] <= c))
        return out


@dataclass(frozen=True)
class Model:
    intercept: float
    rules: tuple[Rule, ...]

    def score(self, stats: dict[str, Column]) -> Column:
        """Probability of label 1."""
        z = F.lit(self.intercept)
        for r in self.rules:
            z = z + F.when(r.column(stats), r.weight).otherwise(0.0)
        return 1 / (1 + F.exp(-z))


def _tree_rules(bins: np.ndarray, cuts: list[np.ndarray], names: list[str], gradient: np.ndarray, hessian: np.ndarray, depth: int) -> tuple[list[tuple], np.ndarray]:
    """Paths of one regression tree by gradient histograms, and its fitted values."""
    rules, values = [], np.zeros(len(gradient))
    stack: list[tuple[np.ndarray, tuple]] = [(np.arange(len(gradient)), ())]
    while stack:
        rows, path = stack.pop()
        g, h = gradient[rows], hessian[rows]
        best = (1e-6, None)
        if len(path) < depth and len(rows) >= 20:
            total_g, total_h = g.sum(), h.sum()
            for f in range(bins.shape[1]):
                if not len(cuts[f]):
                    continue
                b = bins[rows, f]
                left_g = np.cumsum(np.bincount(b, g, len(cuts[f]) + 1))[:-1]
                left_h = np.cumsum(np.bincount(b, h, len(cuts[f]) + 1))[:-1]
                right_g, right_h = total_g - left_g, total_h - left_h
                gain = left_g**2 / (left_h + 1) + right_g**2 / (right_h + 1) - total_g**2 / (total_h + 1)
                gain[(left_h < 0.5) | (right_h < 0.5)] = 0
                at = int(gain.argmax())
                if gain[at] > best[0]:
                    best = (gain[at], (f, at))
        if path:
            rules.append(path)
        if best[1] is None:
            values[rows] = -g.sum() / (h.sum() + 1)
            continue
        f, at = best[1]
        low = bins[rows, f] <= at
        stack.append((rows[low], (*path, (names[f], False, float(cuts[f][at])))))
        stack.append((rows[~low], (*path, (names[f], True, float(cuts[f][at])))))
    return rules, values


def _lasso(x: np.ndarray, y: np.ndarray, strength: float, rounds: int = 300) -> tuple[float, np.ndarray]:
    """Logistic weights with an L1 penalty, by accelerated proximal gradient; the intercept is free."""
    n, k = x.shape
    mean = x.mean(0)
    spread = np.sqrt(np.maximum(mean * (1 - mean), 1e-4)).astype(np.float32)
    z = (x - mean) / spread
    step = 4 * n / (np.linalg.norm(z @ (z.T @ (np.ones(n, np.float32) / np.sqrt(n)))) + 1e-9)
    v = np.ones(k, np.float32) / max(k, 1) ** 0.5
    for _ in range(20):  # largest eigenvalue of z'z / n
        u = z.T @ (z @ v) / n
        norm = float(np.linalg.norm(u)) or 1.0
        v = u / norm
    step = 4 / (norm * 1.05 + 0.5)
    b, w = float(np.log((y.mean() + 1e-3) / (1 - y.mean() + 1e-3))), np.zeros(k, np.float32)
    wb, ww, t = b, w.copy(), 1.0
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-(z @ ww + wb)))
        r = ((p - y) / n).astype(np.float32)
        new = ww - step * (z.T @ r)
        new = np.sign(new) * np.maximum(np.abs(new) - step * strength, 0)
        new_b = wb - step * float(r.sum())
        t2 = (1 + (1 + 4 * t * t) ** 0.5) / 2
        ww, wb = new + (t - 1) / t2 * (new - w), new_b + (t - 1) / t2 * (new_b - b)
        w, b, t = new, new_b, t2
    w = w / spread
    return float(b - (w * mean).sum()), w


def fit_rows(x: dict[str, np.ndarray], y: np.ndarray, trees: int = TREES, depth: int = DEPTH, strength: float = LASSO) -> Model:
    """Fit on arrays of statistics and labels 0/1. With no rows the model scores 0.5; with one label it scores its share."""
    if not len(y):
        return Model(0.0, ())
    base = float(np.log((y.mean() + 1e-3) / (1 - y.mean() + 1e-3)))
    if y.min() == y.max():
        return Model(base, ())
    names = list(x)
    cuts = []
    for f in names:
        q = np.unique(np.quantile(x[f], np.linspace(0, 1, BINS + 1)[1:-1]))
        cuts.append(np.unique((q[1:] + q[:-1]) / 2) if len(q) > 2 else q)
    bins = np.stack([np.searchsorted(c, x[f], side="left") for f, c in zip(names, cuts, strict=True)], axis=1)
    z, paths = np.full(len(y), base), {}
    for _ in range(trees):
        p = 1 / (1 + np.exp(-z))
        found, values = _tree_rules(bins, cuts, names, p - y, p * (1 - p), depth)
        paths |= dict.fromkeys(tuple(sorted(set(f))) for f in found)
        z += SHRINK * values
    rules = [Rule(p) for p in paths]
    held = np.stack([r.holds(x) for r in rules], axis=1).astype(np.float32)
    _, once = np.unique(np.packbits(held.astype(bool), axis=0), axis=1, return_index=True)
    once = np.sort(once[(held[:, once].any(0)) & ~held[:, once].all(0)]) if len(once) else once
    if not len(once):
        return Model(base, ())
    b, w = _lasso(held[:, once], y, strength)
    kept = [Rule(rules[i].terms, float(v)) for i, v in zip(once, w, strict=True) if abs(v) > 1e-4]
    return Model(b, tuple(kept))


def held_out(key: Column) -> Column:
    """Rows whose labels are never learnt from: crc32 of the key as text is a multiple of 5."""
    return F.pmod(F.crc32(F.encode(key.cast("string"), "UTF-8")), F.lit(5)) == 0


def fit(df: DataFrame, labels: DataFrame, key: str = "doc_id", text: str = "text", label: str = "quality", rows: int = TRAIN_ROWS) -> Model:
    """Fit on at most `rows` labelled rows outside the held-out fifth. Null labels, keys and texts are not learnt from.

    A key of several labels counts as 1 if one of them is; of several texts, the one whose statistics sort first is
    learnt from. The keys of the sample are broadcast: at most `rows` of them, and as many rows come to the driver.
    """
    known = labels.select(F.col(key).alias("__k"), F.col(label).cast("int").alias("__y")).where("__k IS NOT NULL AND __y IN (0, 1)")
    some = lowest(known.where(~held_out(F.col("__k"))).groupBy("__k").agg(F.max("__y").alias("__y")), "__k", rows)
    stats = statistics(F.col("__t"))
    texts = df.select(F.col(key).alias("__of"), F.col(text).alias("__t")).where("__t IS NOT NULL")
    seen = texts.join(F.broadcast(some), F.col("__of") == F.col("__k")).select("__k", F.col("__y").cast("double").alias("__y"), *[c.cast("double").alias(n) for n, c in stats.items()])
    one = seen.groupBy("__k").agg(F.min(F.struct("__y", *stats)).alias("x")).select("__k", "x.*")
    got = one.toPandas().sort_values("__k").reset_index(drop=True)
    return fit_rows({n: got[n].to_numpy() for n in stats}, got["__y"].to_numpy())


def score(df: DataFrame, model: Model, text: str = "text") -> DataFrame:
    """df with the column __score; statistics are computed once a row. A null text scores as an empty one."""
    stats = statistics(F.col(text))
    named = df.select("*", *[c.cast("double").alias(f"__s_{n}") for n, c in stats.items()])
    return named.withColumn("__score", model.score({n: F.col(f"__s_{n}") for n in stats})).drop(*[f"__s_{n}" for n in stats])


def report(df: DataFrame, labels: DataFrame) -> DataFrame:
    """(doc_id, held_out, score, predicted) of every document; repeated rows each give a row, an empty table none."""
    rows = df.select("doc_id", "text")
    scored = score(rows, fit(rows, labels))
    return scored.select("doc_id", F.coalesce(held_out(F.col("doc_id")), F.lit(False)).alias("held_out"), F.col("__score").alias("score"), (F.col("__score") >= THRESHOLD).cast("int").alias("predicted"))
