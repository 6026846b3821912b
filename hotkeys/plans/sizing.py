"""How many counters, how much memory, and the bounds that follow from them."""

from __future__ import annotations

import math
from fractions import Fraction
from functools import lru_cache

from hotkeys.spec import exact


def counters_any(eps, owners: int = 1) -> int:
    """Counters of an owner for any distribution: 1 / (owners * eps), so 1 / eps in all."""
    return math.ceil(1 / (owners * exact(eps)))


def counters_zipf(eps, owners: int, skew: float) -> int:
    """Counters of an owner under a Zipf distribution of exponent over 1."""
    if skew <= 1:
        raise ValueError("this size holds for exponents over 1")
    return max(1, math.ceil((1 / (owners * float(exact(eps)))) ** (1 / skew) - 1e-9))


def counters_zipf_tight(eps, owners: int, skew: float) -> float:
    """What the counters must exceed, before the simplification to counters_zipf."""
    return (1 / (owners * float(exact(eps))) * (1 - 1 / zeta(skew))) ** (1 / skew)


def total_any(eps) -> int:
    return math.ceil(1 / exact(eps))


def total_zipf(eps, owners: int, skew: float) -> float:
    return owners * (1 / (owners * float(exact(eps)))) ** (1 / skew)


def buffer_counters(owners: int, slots: int) -> int:
    return owners * owners * slots


@lru_cache(maxsize=256)
def zeta(a: float) -> float:
    """Riemann's zeta for a > 1: a head sum and the Euler-Maclaurin tail."""
    if a <= 1:
        raise ValueError("zeta needs an exponent over 1")
    n = 2000
    head = math.fsum(k**-a for k in range(1, n))
    return head + n ** (1 - a) / (a - 1) + 0.5 * n**-a + a * n ** (-a - 1) / 12


@lru_cache(maxsize=256)
def harmonic(u: int, a: float) -> float:
    """Sum of k**-a for k up to u."""
    n = min(u, 20_000)
    head = math.fsum(k**-a for k in range(1, n + 1))
    if u <= n:
        return head

    def integral(x: float) -> float:
        return math.log(x) if a == 1 else x ** (1 - a) / (1 - a)

    return head + integral(u) - integral(n) + 0.5 * (u**-a - n**-a) + a * (n ** (-a - 1) - u ** (-a - 1)) / 12


def fmin_bound(n: int, eps) -> int:
    """Most that the least counter of 1 / eps counters can be."""
    return math.floor(n * exact(eps))


def fmin_bound_split(n: int, eps) -> int:
    """The same for an owner of a split domain, while owners get about equal shares."""
    return fmin_bound(n, eps)


def zipf_expected(n: int, u: int, a: float, r: int) -> float:
    """Expected count of the element of rank r."""
    return n / (r**a * harmonic(u, a))


def fmin_zipf_max(n: int, m: int, u: int, a: float) -> float:
    """Most that the least of m counters can be on n draws: the tail's mass over the counters."""
    return n / m * (harmonic(u, a) - harmonic(min(m, u), a)) / harmonic(u, a)


def zipf_rank(eps, a: float) -> float:
    """Up to this rank elements have a share of eps."""
    return (1 / (float(exact(eps)) * zeta(a))) ** (1 / a)


def zipf_frequent_count(phi, a: float) -> int:
    """How many elements have a share over phi in an endless Zipf stream."""
    return math.floor(zipf_rank(phi, a))


def pending_bound(owners: int, every: int) -> int:
    """Most arrivals of one element that can wait in buffers."""
    return owners * every


def pending_zipf(owners: int, every: int, a: float, r: int) -> float:
    """Arrivals of the element of rank r that wait on average at most."""
    return owners * every / (zeta(a) * r**a)


def guaranteed_rank(n_start: int, owners: int, every: int, phi, a: float) -> float:
    """Below this rank elements are sure to be reported by a query that starts at n_start."""
    return (max(0.0, 1 - owners * every / n_start) / (zeta(a) * float(exact(phi)))) ** (1 / a)


SLOT_BYTES = 32
#: A fit, not a bound: mean bytes of a buffer that the printed totals of 34, 37 and 65.8 MB at 450 threads imply. The
#: bound is buffer_counters(threads, slots) * SLOT_BYTES.
BUFFER_BYTES = 167


def memory_bytes(method: str, eps, threads: int, beta=None, rows: int = 4, buffer_bytes: int = BUFFER_BYTES, slot_bytes: int = SLOT_BYTES) -> float:
    """Bytes of a method's counters by its counter formula."""
    eps = exact(eps)
    beta = exact(beta) if beta is not None else eps * Fraction(9, 10)
    if method == "owner_split":
        return float(slot_bytes / eps + threads * threads * buffer_bytes)
    if method == "merge_collector":
        return float(2 * (threads + 1) / (eps - beta) * slot_bytes)
    if method == "cell_majority":
        return float(rows * threads / eps * slot_bytes)
    if method == "single_summary":
        return float(slot_bytes / eps)
    if method == "local_merge":
        return float(threads * slot_bytes / eps)
    raise ValueError(f"no memory model for {method}")


def counters_of(method: str, eps, threads: int, beta=None, rows: int = 4) -> int:
    return round(memory_bytes(method, eps, threads, beta, rows, buffer_bytes=0, slot_bytes=1))


# --- verdicts on one query of a running stream ---


def interval_ok(f_start: int, pending: int, est: int, f_end: int, eps, n_end: int) -> bool:
    """An estimate lies between what had been handed over at the start and the end's count plus error."""
    return f_start - pending <= est <= f_end + exact(eps) * n_end


def must_report(f_start: int, phi, n_start: int, pending: int) -> bool:
    return f_start > exact(phi) * n_start + pending


def must_not_report(f_end: int, phi, eps, n_start: int, n_end: int) -> bool:
    return f_end < (exact(phi) - exact(eps)) * n_start - exact(eps) * (n_end - n_start)
