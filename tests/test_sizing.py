"""Formulas against printed tables and against each other."""

from __future__ import annotations

import math

import pytest

from hotkeys.plans import sizing
from hotkeys.spec import SupportSpec, exact, exceeds


def test_frequent_elements_of_zipf_streams():
    table = {1.25: [74, 467, 2952], 2.0: [24, 77, 246], 3.0: [9, 20, 43]}
    for a, row in table.items():
        assert [sizing.zipf_frequent_count(p, a) for p in ("0.001", "0.0001", "0.00001")] == row


def test_memory_of_450_threads():
    mb = [sizing.memory_bytes("owner_split", exact(p) / 10, 450) / 1e6 for p in ("0.001", "0.0001", "0.00001")]
    assert mb == pytest.approx([34, 37, 65.8], rel=0.005)
    assert sizing.memory_bytes("merge_collector", "0.000001", 450) == pytest.approx(288.1e9, rel=0.005)
    assert sizing.memory_bytes("cell_majority", "0.000001", 450) == pytest.approx(57e9, rel=0.02)
    with pytest.raises(ValueError):
        sizing.memory_bytes("other", "0.1", 1)


def test_counters():
    assert sizing.counters_any("0.0001", 24) == math.ceil(10000 / 24)
    assert sizing.counters_zipf("0.0001", 1, 2.0) == 100
    assert sizing.counters_zipf_tight("0.0001", 1, 2.0) < 100
    assert sizing.total_any("0.001") == 1000
    assert sizing.total_zipf("0.001", 10, 2.0) == pytest.approx(100)
    assert sizing.buffer_counters(450, 32) == 450 * 450 * 32
    with pytest.raises(ValueError):
        sizing.counters_zipf("0.1", 1, 1.0)


def test_zipf_quantities():
    assert sizing.zeta(2.0) == pytest.approx(math.pi**2 / 6, rel=1e-9)
    assert sizing.harmonic(100_000, 1.0) == pytest.approx(math.fsum(1 / k for k in range(1, 100_001)), rel=1e-9)
    assert sizing.zipf_expected(1000, 10, 1.0, 1) == pytest.approx(1000 / sizing.harmonic(10, 1.0))
    assert sizing.fmin_zipf_max(1000, 10, 10, 1.0) == 0
    limit = sizing.zipf_rank("0.001", 1.5)
    ranks = [sizing.guaranteed_rank(n, 24, 1000, "0.001", 1.5) for n in (24_000, 100_000, 10**7, 10**12)]
    assert ranks == sorted(ranks) and ranks[0] == 0 and ranks[-1] == pytest.approx(limit, rel=1e-6)
    assert sizing.pending_bound(24, 1000) == 24_000
    assert sizing.pending_zipf(24, 1000, 2.0, 1) < 24_000
    assert sizing.fmin_bound(1005, "0.01") == sizing.fmin_bound_split(1005, "0.01") == 10


def test_thresholds_are_exact():
    assert not exceeds(100, exact("0.01"), 10_000) and exceeds(100, exact("0.01"), 10_000, inclusive=True)
    assert exceeds(101, exact(0.01), 10_000)
    spec = SupportSpec("0.001", owners=24)
    assert spec.eps == exact("0.0001") and spec.per_owner() == 417
    for bad in ({"phi": "0"}, {"phi": "0.1", "eps": "0.2"}, {"phi": "0.1", "owners": 0}, {"phi": "0.1", "dist": "x"}):
        with pytest.raises(ValueError):
            SupportSpec(**bad)
