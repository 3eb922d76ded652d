"""Published bounds as integer or float formulas; Big-O ones carry a pinned constant that the tests record."""

from __future__ import annotations

import math

from writelite.functions.model import MachineParams


def blocks(n: int, B: int) -> int:
    return -(-n // B)


def levels(n: int, mp: MachineParams) -> int:
    """Least t >= 1 with (kM/B)^t at least the number of blocks, by integers.

    >>> levels(60_000, MachineParams(256, 16, 8, 1)), levels(60_000, MachineParams(256, 16, 8, 4))
    (3, 2)
    """
    t, reach = 1, mp.fan_out
    while reach < blocks(n, mp.B):
        t, reach = t + 1, reach * mp.fan_out
    return t


def classic_cost(n: int, mp: MachineParams) -> int:
    """Mergesort of fan-out M/B: every level reads and writes all blocks once."""
    return (mp.omega + 1) * blocks(n, mp.B) * levels(n, mp.with_k(1))


def mergesort_cost(n: int, mp: MachineParams) -> int:
    """Write-saving mergesort; k = 1 is the classic algorithm and costs what that costs."""
    return classic_cost(n, mp) if mp.k == 1 else (mp.omega + mp.k + 1) * blocks(n, mp.B) * levels(n, mp)


def mergesort_io(n: int, mp: MachineParams) -> tuple[int, int]:
    lev = levels(n, mp)
    return ((mp.k + 1) if mp.k > 1 else 1) * blocks(n, mp.B) * lev, blocks(n, mp.B) * lev


def merge_io(n: int, mp: MachineParams) -> tuple[int, int]:
    """One merge of kM/B runs of n records in all."""
    return (mp.k + 1) * blocks(n, mp.B), blocks(n, mp.B)


def base_io(n: int, mp: MachineParams) -> tuple[int, int]:
    """Selection sort of n <= kM records in rounds of M."""
    return blocks(n, mp.M) * blocks(n, mp.B), sum(blocks(min(mp.M, n - i), mp.B) for i in range(0, n, mp.M))


def memory(method: str, mp: MachineParams, record_bits: int = 512, n: int = 1 << 40) -> float:
    """Fast memory in records; a pointer is log n bits of a record."""
    alpha = math.log2(max(n, 2)) / record_bits
    return {"merge": mp.M + 2 * mp.B + 2 * alpha * mp.k * mp.M / mp.B, "base": mp.M + mp.B, "sample": mp.M + mp.B + mp.M / mp.B}[method]


def rw_lru_bound(ideal: float, m_ideal: int, m_lru: int, omega: int, B: int) -> float:
    return m_lru / (m_lru - m_ideal) * ideal + (1 + omega) * m_ideal / B


def tall_cache(mp: MachineParams) -> bool:
    return mp.M >= mp.B**2


def parallel_time(writes: float, reads: float, depth_: float, p: int, omega: int) -> float:
    return (omega * writes + reads) / p + depth_


def work_stealing(q1: float, mp: MachineParams) -> float:
    """Private caches: every steal refills a cache, and a write costs omega."""
    return q1 + mp.p * mp.omega * mp.D * mp.M / mp.B


def pdf_shared(q1: float, mp: MachineParams) -> tuple[float, float]:
    """(cost, cache needed) of a depth-first schedule on a shared cache."""
    return q1, mp.M + mp.p * mp.B * mp.D


def pram_sort(n: int, omega: int) -> tuple[float, float, float]:
    """(reads, writes, depth) in words of the write-saving PRAM sort, constant 1."""
    log = math.log2(max(n, 2))
    return n * log, n, omega * log


def pram_sort_matching(n: int, omega: int) -> tuple[float, float, float]:
    """The same of the best deterministic sorts without concurrent writes: their depth matches, but every level writes."""
    log = math.log2(max(n, 2))
    return n * log, n * log, omega * log


def parallel_sample_time(n: int, mp: MachineParams) -> float:
    lev = math.ceil(1 + math.log(max(n / (mp.k * mp.M), 1), mp.fan_out))
    return mp.k * (mp.M / mp.B + math.log2(max(n, 2)) ** 2) * lev


def buffer_tree_insert(n: int, mp: MachineParams) -> tuple[float, float]:
    """Amortised reads and writes of an insertion, constant 1."""
    lev = 1 + math.log(max(n, 2), mp.fan_out)
    return mp.k / mp.B * lev, 1 / mp.B * lev


def oblivious_levels(n: int, M: int, omega: int) -> float:
    return max(1.0, math.log(max(omega * n, 2), omega * M))


def oblivious_sort(n: int, mp: MachineParams) -> tuple[float, float]:
    w = n / mp.B * oblivious_levels(n, mp.M, mp.omega)
    return mp.omega * w, w


def matmul_blocked(n: int, mp: MachineParams) -> tuple[float, float]:
    return n**3 / (mp.B * math.isqrt(mp.M)), n**2 / mp.B


def matmul_recurrence(n: float, M: int, omega: int, first: bool = True) -> tuple[float, float]:
    """Expected (reads, writes) in cells; the first round averages over splits by powers of two."""
    if n <= omega * math.sqrt(M):
        return 2 * omega * n * n, n * n
    if not first:
        r, w = matmul_recurrence(n / omega, M, omega, False)
        return omega**3 * r, omega**3 * w
    b = int(math.log2(omega))
    parts = [(2**i, matmul_recurrence(n / 2**i, M, omega, False)) for i in range(1, b + 1)]
    return sum(f**3 * r for f, (r, _) in parts) / b, sum(f**3 * w for f, (_, w) in parts) / b


def fft_recurrence(n: int, M: int, omega: int) -> tuple[float, float]:
    """(reads, writes) in cells of the write-saving transform; omega 1 is the standard one."""
    if n <= M:
        return n, n
    s = 1 << ((n // omega).bit_length() - 1) // 2
    r, w = fft_recurrence(s, M, omega)
    calls = 2 * n // s
    return calls * r + omega * n, calls * w + n
