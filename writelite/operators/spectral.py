"""Discrete Fourier transforms: brute force, standard and write-saving, and an exact modular twin.

A signal is (idx, re, im), or with `by` one signal for each group. The write-saving transform of n = omega * s * t looks at
the signal as columns of omega * s values a time: omega-point transforms by brute force, an inner twiddle, s-point
transforms, an outer twiddle, then t-point transforms of the rows. Two exchanges gather the columns and the rows; all
transposes are index arithmetic, which projections carry for nothing.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from writelite.functions.model import LEDGER

PRIME, GENERATOR = 998_244_353, 3


def split(n: int, omega: int) -> tuple[int, int, int]:
    """(omega, s, t) with n = omega * s * t, s and t powers of two with s = t or s = 2t.

    >>> split(64, 4), split(128, 4), split(8, 16)
    ((4, 4, 4), (4, 8, 4), (1, 4, 2))
    """
    if n < 1 or n & (n - 1) or omega & (omega - 1):
        raise ValueError("n and omega must be powers of two")
    omega = omega if omega < n else 1
    half = (n // omega).bit_length() - 1
    return omega, 1 << (half + 1) // 2, 1 << half // 2


def _base(x: np.ndarray) -> np.ndarray:
    """Transform along the last axis by a matrix, for the sizes below a base case."""
    n = x.shape[-1]
    return x @ np.exp(-2j * np.pi * np.outer(np.arange(n), np.arange(n)) / n)


def transform(x: np.ndarray, omega: int, base: int = 32) -> np.ndarray:
    """The recursion on arrays, along the last axis."""
    n = x.shape[-1]
    if n <= base:
        return _base(x)
    w, s, t = split(n, omega)
    y = np.swapaxes(x.reshape(*x.shape[:-1], w * s, t), -1, -2)  # a row for each residue mod t
    y = _columns(y, w, s, omega, base)
    y = y * np.exp(-2j * np.pi * np.outer(np.arange(t), np.arange(w * s)) / n)
    z = transform(np.swapaxes(y, -1, -2), omega, base)
    return np.swapaxes(z, -1, -2).reshape(x.shape)


def _columns(y: np.ndarray, w: int, s: int, omega: int, base: int) -> np.ndarray:
    """Transforms of length w * s along the last axis: brute force over w, inner twiddle, then length s."""
    v = y.reshape(*y.shape[:-1], w, s)
    brute = np.exp(-2j * np.pi * np.outer(np.arange(w), np.arange(w)) / w)
    v = np.einsum("ab,...bs->...as", brute, v) * np.exp(-2j * np.pi * np.outer(np.arange(w), np.arange(s)) / (w * s))
    v = transform(v, omega, base)
    return np.swapaxes(v, -1, -2).reshape(y.shape)


def fft(sig: DataFrame, n: int, omega: int, base: int = 32, fuse: bool = True) -> DataFrame:
    """Write-saving transform of one long signal (idx, re, im); absent places are zeros.

    With `fuse` the brute-force transforms run where the columns have been gathered, and what they give is not written
    before the transforms of length s; inner and outer transposes are one change of index. Without, the brute force is a
    step of its own, whose values cross the network once more.
    """
    w, s, t = split(n, omega)

    def brute(pdf: pd.DataFrame) -> pd.DataFrame:
        col, b = int(pdf.col.iloc[0]), int(pdf.b.iloc[0])
        x = np.zeros(w, complex)
        np.add.at(x, pdf.a.to_numpy(), pdf.re.to_numpy() + 1j * pdf.im.to_numpy())
        y = _base(x[None, :])[0] * np.exp(-2j * np.pi * b * np.arange(w) / (w * s))
        return pd.DataFrame({"a": np.arange(w), "b": b, "col": col, "re": y.real, "im": y.imag})

    def inner(pdf: pd.DataFrame) -> pd.DataFrame:
        col, a = int(pdf.col.iloc[0]), int(pdf.a.iloc[0])
        x = np.zeros(s, complex)
        x[pdf.b.to_numpy()] = pdf.re.to_numpy() + 1j * pdf.im.to_numpy()
        row = a + w * np.arange(s)
        y = transform(x, omega, base) * np.exp(-2j * np.pi * col * row / n)
        return pd.DataFrame({"row": row, "col": col, "re": y.real, "im": y.imag})

    def columns(pdf: pd.DataFrame) -> pd.DataFrame:
        col = int(pdf.col.iloc[0])
        x = np.zeros(w * s, complex)
        np.add.at(x, pdf.row.to_numpy(), pdf.re.to_numpy() + 1j * pdf.im.to_numpy())
        y = _columns(x[None, :], w, s, omega, base)[0] * np.exp(-2j * np.pi * col * np.arange(w * s) / n)
        return pd.DataFrame({"row": np.arange(w * s), "col": col, "re": y.real, "im": y.imag})

    def rows(pdf: pd.DataFrame) -> pd.DataFrame:
        k = int(pdf.row.iloc[0])
        x = np.zeros(t, complex)
        x[pdf.col.to_numpy()] = pdf.re.to_numpy() + 1j * pdf.im.to_numpy()
        y = transform(x, omega, base)
        return pd.DataFrame({"idx": k + w * s * np.arange(t), "re": y.real, "im": y.imag})

    placed = sig.select(F.floor(F.col("idx") / t).cast("long").alias("row"), (F.col("idx") % t).cast("long").alias("col"), F.col("re").cast("double").alias("re"), F.col("im").cast("double").alias("im"))
    if fuse:
        done = placed.groupBy("col").applyInPandas(columns, "row long, col long, re double, im double")
    else:
        cells = placed.select(F.floor(F.col("row") / s).cast("long").alias("a"), (F.col("row") % s).alias("b"), "col", "re", "im")
        forced = cells.groupBy("col", "b").applyInPandas(brute, "a long, b long, col long, re double, im double")
        done = forced.groupBy("col", "a").applyInPandas(inner, "row long, col long, re double, im double")
    return done.groupBy("row").applyInPandas(rows, "idx long, re double, im double")


def fft_standard(sig: DataFrame, n: int, base: int = 32) -> DataFrame:
    """The square-root split without the brute-force factor."""
    return fft(sig, n, 1, base)


def fft_groups(sig: DataFrame, by: str, n: int, omega: int, base: int = 32) -> DataFrame:
    """A transform for each group, groups of n values being small: one exchange by group."""

    def go(pdf: pd.DataFrame) -> pd.DataFrame:
        x = np.zeros(n, complex)
        x[pdf.idx.to_numpy()] = pdf.re.to_numpy()
        y = transform(x, omega, base)
        return pd.DataFrame({by: pdf[by].iloc[0], "idx": np.arange(n), "re": y.real, "im": y.imag})

    return sig.groupBy(by).applyInPandas(go, f"{by} long, idx long, re double, im double")


def dft_bruteforce(sig: DataFrame, n: int, inverse: bool = False) -> DataFrame:
    """Every output value from all inputs: native, n^2 terms."""
    out = sig.sparkSession.range(n).select(F.col("id").alias("k"))
    a = F.lit((2 if inverse else -2) * np.pi / n) * ((F.col("k") * F.col("idx")) % n)
    c, s = F.cos(a), F.sin(a)
    re, im = F.col("re").cast("double"), F.col("im").cast("double")
    total = sig.crossJoin(F.broadcast(out)).groupBy("k").agg(F.sum(re * c - im * s).alias("re"), F.sum(re * s + im * c).alias("im"))
    scale = n if inverse else 1
    return total.select(F.col("k").alias("idx"), (F.col("re") / scale).alias("re"), (F.col("im") / scale).alias("im"))


def ifft(spec: DataFrame, n: int, omega: int) -> DataFrame:
    """Inverse transform: conjugate, transform, conjugate, divide."""
    back = fft(spec.select("idx", "re", (-F.col("im")).alias("im")), n, omega)
    return back.select("idx", (F.col("re") / n).alias("re"), (-F.col("im") / n).alias("im"))


def energy(sig: DataFrame) -> DataFrame:
    return sig.agg(F.sum(F.col("re") * F.col("re") + F.col("im") * F.col("im")).alias("energy"))


def _powers(root: int, n: int) -> list[int]:
    out = [1] * n
    for i in range(1, n):
        out[i] = out[i - 1] * root % PRIME
    return out


def ntt(sig: DataFrame, n: int) -> DataFrame:
    """Number-theoretic transform (idx, v) modulo PRIME by the same split in two exchanges, in exact integers."""
    if n & (n - 1) or (PRIME - 1) % n:
        raise ValueError("n must be a power of two that divides the prime less one")
    s = 1 << (n.bit_length() - 1 + 1) // 2
    t = n // s
    root = F.array(*[F.lit(x) for x in _powers(pow(GENERATOR, (PRIME - 1) // n, PRIME), n)])
    w = lambda e: root[(e % n).cast("int")].cast("long")
    x = sig.select(F.floor(F.col("idx") / t).cast("long").alias("row"), (F.col("idx") % t).alias("col"), F.pmod("v", F.lit(PRIME)).cast("long").alias("v"))
    k1 = F.explode(F.sequence(F.lit(0), F.lit(s - 1)).cast("array<long>")).alias("k1")
    a = x.select("row", "col", "v", k1).groupBy("col", "k1").agg(F.sum(F.col("v") * w(F.col("row") * F.col("k1") * t) % PRIME).alias("v"))
    a = a.select("col", "k1", ((F.col("v") % PRIME) * w(F.col("col") * F.col("k1")) % PRIME).alias("v"))
    k2 = F.explode(F.sequence(F.lit(0), F.lit(t - 1)).cast("array<long>")).alias("k2")
    b = a.select("col", "k1", "v", k2).groupBy("k1", "k2").agg(F.sum(F.col("v") * w(F.col("col") * F.col("k2") * s) % PRIME).alias("v"))
    return b.select((F.col("k1") + F.col("k2") * s).alias("idx"), (F.col("v") % PRIME).cast("long").alias("v"))


def ledger_rows(n: int, M: int, B: int, omega: int, fuse: bool = False) -> list[tuple]:
    """Ledger of the recursion: at each level the brute-force read of omega scans, and a write of all, of every node.

    fuse merges the two transposes and folds the brute-force write into the first one: two writes a level saved.
    """
    out, level, nodes, size = [], 0, 1, n
    while size > M:
        nb = -(-size // B)
        out.append(("fft", "bruteforce", level, 0, 0, nodes * max(omega, 1) * nb, nodes * (0 if fuse else nb)))
        out.append(("fft", "transpose", level, 0, 0, nodes * (2 if fuse else 3) * nb, nodes * (2 if fuse else 3) * nb))
        w, s, _ = split(size, omega)
        nodes, size, level = nodes * 2 * (size // s), s, level + 1
    out.append(("fft", "base", level, 0, 0, nodes * -(-size // B), nodes * -(-size // B)))
    return out


def ledger(spark, n: int, M: int, B: int, omega: int, fuse: bool = False) -> DataFrame:
    return spark.createDataFrame(ledger_rows(n, M, B, omega, fuse), LEDGER)
