"""Kernels without Spark: heap order, bounds, agreement of the forms, edge streams."""

from __future__ import annotations

from collections import Counter
from fractions import Fraction

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from hotkeys.kernels.buffers import HandoverBuffers
from hotkeys.kernels.minmax import MinMaxSummary, bound_of_query, padded
from hotkeys.kernels.others import BucketListSummary, FrequentSummary, LossyCounting, MinHeapSummary, WeightedFrequent

UPDATES = st.lists(st.tuples(st.integers(0, 30), st.integers(1, 9)), max_size=250)


def fed(kernel, updates):
    for e, w in updates:
        kernel.update(e, w)
    return kernel


def true_counts(updates):
    f = Counter()
    for e, w in updates:
        f[e] += w
    return f


def labelled(kernel):
    return {(e, c) for e, c, _ in kernel.to_rows() if c > kernel.f_min}


@settings(max_examples=150, deadline=None)
@given(UPDATES, st.sampled_from([1, 3, 7, 11, 20, 31]))
def test_minmax_keeps_order_and_bounds(updates, m):
    own, f = MinMaxSummary(m), Counter()
    for e, w in updates:
        own.update(e, w)
        f[e] += w
        own.check_invariant()
    assert own.f_min <= own.n // own.m
    for e, est, over in own.to_rows():
        assert est - over <= f[e] <= est <= f[e] + own.f_min
    for e, c in f.items():
        assert c <= own.f_min or e in own.place
        assert own.estimate(e) >= c


@settings(max_examples=150, deadline=None)
@given(UPDATES, st.sampled_from([3, 7, 11, 31]), st.sampled_from([Fraction(0), Fraction(1, 50), Fraction(1, 7), Fraction(1, 3)]))
def test_query_equals_scan_and_its_cost_is_bounded(updates, m, phi):
    own = fed(MinMaxSummary(m), updates)
    found = own.query(phi)
    assert sorted(found) == sorted((e, c) for e, c, _ in own.to_rows() if c > phi * own.n)
    assert own.stats.comparisons <= bound_of_query(len(found))


@settings(max_examples=100, deadline=None)
@given(UPDATES, st.sampled_from([3, 7, 11]))
def test_forms_agree_above_the_least_count(updates, m):
    assert labelled(fed(MinMaxSummary(m), updates)) == labelled(fed(MinHeapSummary(m), updates))
    unit = [(e, 1) for e, _ in updates]
    a, b, c = (fed(k(m), unit) for k in (MinMaxSummary, MinHeapSummary, BucketListSummary))
    assert labelled(a) == labelled(b) == labelled(c)
    assert a.f_min == b.f_min == c.f_min


@settings(max_examples=100, deadline=None)
@given(UPDATES, st.integers(1, 12))
def test_frequent_and_lossy_counting_are_low_within_their_bounds(updates, m):
    f = true_counts(updates)
    own = fed(WeightedFrequent(m), updates)
    rows = {e: c for e, c, _ in own.to_rows()}
    assert own.offset <= own.n // (m + 1) or not own.n
    for e, c in f.items():
        assert rows.get(e, 0) <= c <= rows.get(e, 0) + own.offset
    unit = [(e, 1) for e, _ in updates]
    lossy, g = fed(LossyCounting(Fraction(1, m)), unit), true_counts(unit)
    kept = {e: c for e, c, _ in lossy.to_rows()}
    for e, c in g.items():
        assert kept.get(e, 0) <= c <= kept.get(e, 0) + Fraction(lossy.n, m)


def test_sizes_are_padded_to_whole_groups():
    assert [padded(m) for m in (1, 3, 4, 7, 8, 100)] == [3, 3, 7, 7, 11, 103]
    assert MinMaxSummary.from_eps("0.01").m == 103


def test_worked_stream_of_seven():
    own = fed(MinMaxSummary(3), [(x, 1) for x in "abacdad"])
    assert labelled(own) == {("a", 3), ("d", 3)} and own.f_min == 1 and own.n == 7
    assert sorted(own.query(Fraction(1, 3))) == [("a", 3), ("d", 3)]


def test_edges():
    empty = MinMaxSummary(7)
    assert empty.query(0) == [] and empty.top_k(3) == [] and empty.f_min == 0
    equal = fed(MinMaxSummary(7), [("x", 2**40)] * 5)
    assert equal.query("0.5") == [("x", 5 * 2**40)]
    spread = fed(MinMaxSummary(7), [(i, 1) for i in range(700)])
    assert spread.f_min == spread.f_max == 100
    with pytest.raises(ValueError):
        spread.update("x", 0)
    with pytest.raises(ValueError):
        BucketListSummary(3).update("x", 2)
    with pytest.raises(ValueError):
        FrequentSummary(3).update("x", 2)


@pytest.mark.parametrize("order", ["random", "ascending", "descending", "round_robin", "tail_first"])
def test_any_order_reports_what_exceeds_the_bound(order):
    f = {i: 200 // (i + 1) for i in range(60)}
    arrivals = [i for i, c in f.items() for _ in range(c)]
    if order == "random":
        import random

        random.Random(1).shuffle(arrivals)
    elif order == "ascending":
        arrivals.sort(key=lambda i: f[i])
    elif order == "round_robin":
        arrivals = sorted(arrivals, key=Counter().__getitem__) and [i for k in range(200) for i, c in f.items() if k < c]
    elif order == "tail_first":
        arrivals = [i for i in arrivals if i >= 10] + [i for i in arrivals if i < 10]
    own = fed(MinMaxSummary(31), [(e, 1) for e in arrivals])
    found = dict(own.query("0.05"))
    assert all(e in found for e, c in f.items() if c > own.n * 0.05)


def test_restored_summary_and_top_k():
    own = fed(MinMaxSummary(15), [(i % 40 if i % 3 else 1, 1 + i % 5) for i in range(900)])
    again = MinMaxSummary.from_rows(15, own.to_rows())
    again.check_invariant()
    assert sorted(again.to_rows()) == sorted(own.to_rows())
    assert [c for _, c in own.top_k(6)] == sorted((c for _, c, _ in own.to_rows()), reverse=True)[:6]


def test_buffers_hand_over_by_age_and_by_slots():
    owner = {"a": 0, "c": 0, "b": 1, "d": 1}
    by_age = HandoverBuffers(2, 3, 4)
    flushed = [by_age.insert(owner[e], e) for e in "aabacd"]
    assert [bool(x) for x in flushed] == [False, False, False, True, False, False]
    assert flushed[3] == [(0, {"a": 3}), (1, {"b": 1})] and by_age.n == 6 and by_age.pending("d") == 1
    by_slots = HandoverBuffers(2, 2, 4)
    assert by_slots.insert(0, "a") == [] and by_slots.insert(0, "c") == [(0, {"a": 1, "c": 1})]
    assert by_slots.insert(1, "b") == [] and by_slots.flush() == [(1, {"b": 1})] and by_slots.flush() == []


def test_dropping_a_hand_over_or_using_the_wrong_minimum_is_noticed():
    f = Counter("aaabbbcccd")
    own = fed(MinMaxSummary(3), [("a", 3), ("b", 3)])  # the hand-over with c was lost
    assert any(c > own.n / 4 and e not in dict(own.query(Fraction(1, 4))) for e, c in f.items())
