"""Mixed runs against plain counts, and the pieces that changed with them."""

from __future__ import annotations

from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from hotkeys import frames, mixed, timing, workloads
from hotkeys.functions import metrics, udfs
from hotkeys.kernels.minmax import MinMaxSummary
from hotkeys.kernels.others import MinHeapSummary, WeightedFrequent
from hotkeys.operators import baselines, sketches
from hotkeys.operators import owner_split as engine
from hotkeys.operators.exact import exact_counts
from hotkeys.shipping import ship
from hotkeys.sources import streams
from hotkeys.spec import SupportSpec, exact

ARRIVALS = [str(x) for x in timing.zipf_list(20_000, 1.0)]


def run(*mixes, marks=(20_000,)):
    return list(mixed.run_all(iter(ARRIVALS), list(mixes), list(marks)))


def test_queries_come_at_their_share_and_change_nothing():
    rows = run(*[mixed.Mix("z", m, 6, "0.01", share, 500, 16) for m in mixed.KINDS for share in (0.0, 0.001, 0.0002)])
    for r in rows:
        assert r["queries"] == {0.0: 0, 0.001: 20, 0.0002: 4}[r["share"]]
    by = {(r["method"], r["share"]): r for r in rows}
    for m in mixed.KINDS:
        assert len({(by[m, s]["pairs"], by[m, s]["handovers"], by[m, s]["n_reported"]) for s in (0.0, 0.001, 0.0002)}) == 1
        assert by[m, 0.0]["critical"] <= by[m, 0.0002]["critical"] <= by[m, 0.001]["critical"]
    # queries alone make the cell matrix stand still, and less so unsynchronised
    assert by["cell_majority", 0.001]["merged"] == 20 * 6 * 4 * 1000 == by["cell_majority_unsynced", 0.001]["merged"]
    assert by["cell_majority", 0.001]["critical"] > by["cell_majority_unsynced", 0.001]["critical"] > by["owner_split", 0.001]["critical"]
    assert by["owner_split_counting", 0.001]["lookups"] > 0 == by["owner_split", 0.001]["lookups"]
    assert by["owner_split", 0.001]["comparisons"] < by["owner_split_minheap", 0.001]["comparisons"]


def test_hand_overs_equal_a_plain_count_and_answers_are_right():
    r = run(mixed.Mix("z", "owner_split", 4, "0.002", 0.0, 500, 501))[0]
    blocks = [(k % 4, k // 4 // 500, e) for k, e in enumerate(ARRIVALS)]
    assert r["pairs"] == len(set(blocks)) and r["handovers"] == len({b[:2] for b in blocks})
    true = {e for e, f in Counter(ARRIVALS).items() if f > 40}
    assert (r["n_true"], r["hits"], r["spurious"], r["low"]) == (len(true), len(true), 0, 0)


def test_splitting_pays_by_the_number_of_owners():
    rows = run(*[mixed.Mix("z", m, t, "0.01", 0.0) for t in (2, 8) for m in ("owner_split", "single_summary")])
    by = {(r["method"], r["owners"]): r["critical"] for r in rows}
    assert by["single_summary", 8] / by["owner_split", 8] > 2 * by["single_summary", 2] / by["owner_split", 2] / 1.5


def test_late_elements_vanish_as_the_stream_doubles():
    rows = run(mixed.Mix("z", "owner_split", 4, "0.01", 0.0, 500, 32), marks=(1_250, 20_000))
    shares = [r["late"] / r["n_true"] for r in rows]
    assert shares[0] > shares[1] and rows[1]["hits"] == rows[1]["n_true"]


def test_grid_runs_apart_and_by_label(spark):
    ship(spark)
    given = {"a": spark.createDataFrame([(k, ARRIVALS[100 * k : 100 * k + 100]) for k in range(50)], "ord long, es array<string>"), "b": spark.createDataFrame([(0, ["x"] * 9)], "ord long, es array<string>")}
    rows = mixed.run_grid(spark, given, [mixed.Mix(x, m, 3, "0.01", 0.01) for x in given for m in ("owner_split", "single_summary")], parts=2).collect()
    assert sorted((r["label"], r["method"], r["arrivals"]) for r in rows) == sorted((x, m, n) for x, ns in (("a", (2500, 5000)), ("b", (4, 9))) for m in ("owner_split", "single_summary") for n in ns)


@pytest.mark.parametrize("kernel", [MinMaxSummary, MinHeapSummary])
def test_bulk_updates_keep_order_and_bounds(kernel):
    r = np.random.default_rng(3)
    for m in (7, 63, 500):
        own, true = kernel(m), Counter()
        for size in (3, 400, 50, 2_000, 5):
            batch = Counter((r.zipf(1.3, size) % 3_000).tolist())
            own.update_batch(batch.keys(), batch.values())
            true.update(batch)
            if kernel is MinMaxSummary:
                own.check_invariant()
        assert own.n == sum(true.values()) == sum(c for _, c, _ in own.to_rows()) and own.f_min <= own.n // own.m
        assert all(est - over <= true[e] <= est for e, est, over in own.to_rows())
        assert all(f <= own.f_min for e, f in true.items() if e not in own.place)
        assert sorted(own.query("0.01")) == sorted((e, c) for e, c, _ in own.to_rows() if c * 100 > own.n)


def test_weighted_frequent_keeps_its_bound():
    r = np.random.default_rng(4)
    own, true = WeightedFrequent(20), Counter()
    for e, w in zip((r.zipf(1.2, 5_000) % 400).tolist(), r.integers(1, 9, 5_000).tolist(), strict=True):
        own.update(e, w)
        true[e] += w
    assert own.offset <= own.n / 21 and len(own.raw) <= 20
    assert all(c <= true[e] <= c + low for e, c, low in own.to_rows()) and all(f <= own.offset for e, f in true.items() if e not in own.raw)


def test_majority_matrix_is_never_high():
    own, true = baselines.MajorityMatrix(4, 50), Counter()
    r = np.random.default_rng(5)
    for _ in range(20):
        batch = Counter((r.zipf(1.4, 300) % 500).tolist())
        h = np.array([mixed.hash_of(e) - (1 << 63) for e in batch], np.int64)
        own.add(h, list(batch), np.array(list(batch.values()), np.int64))
        true.update(batch)
    row, cell, elements, count = own.counters()
    assert all(c <= true[e] for e, c in zip(elements, count.tolist(), strict=True))
    assert max(c for e, c in zip(elements, count.tolist(), strict=True) if e == 1) >= true[1] - (sum(true.values()) - true[1])


def test_sketch_candidates_miss_nothing(spark, sf):
    ship(spark)
    words = streams.documents_words(spark, sf)
    spec = SupportSpec("0.005")
    for answer in (sketches.count_min(words, spec, width=2_000), sketches.count_min(words, spec)):
        row = metrics.violations(answer, exact_counts(words), spec.phi, spec.eps).first()
        assert row["missed"] == 0 and row["low"] == 0 and row["n_true"] > 0
    made = sketches.passed(words, 300, 4, share=spec.phi)
    assert made.filter("row >= 0").groupBy(F.spark_partition_id()).count().agg(F.max("count")).first()[0] <= 1_200


def test_groups_are_split_among_owners(spark):
    ship(spark)
    rows = [("big", f"e{k % 50}") for k in range(3_000)] + [("big", "hot")] * 700 + [("small", "only")] * 3 + [(None, "n")] * 2
    stream = spark.createDataFrame([(g, e, 1) for g, e in rows], "g string, e string, w long").repartition(3)
    found = {(r["g"], r["e"], r["est"], r["lower"]) for r in engine.frequent_by(stream, ["g"], "0.1", 100).collect()}
    assert found == {("big", "hot", 700, 700), ("small", "only", 3, 3), (None, "n", 2, 2)}
    pairs = spark.createDataFrame([("g", (k % 3, "x"), 1) for k in range(90)], "g string, e struct<a:int,b:string>, w long")
    assert {(r["e"]["a"], r["est"]) for r in engine.frequent_by(pairs, ["g"], "0.2", 10).collect()} == {(0, 30), (1, 30), (2, 30)}


def test_pending_pairs_complete_the_counts(spark):
    ship(spark)
    stream = spark.createDataFrame([(f"e{k % 7}", 1) for k in range(1_000)], "e string, w long").repartition(2)
    for mode in ("batch", "rows"):
        summary, pending = engine.build_with_pending(stream, SupportSpec("0.01", owners=2, every=300, slots=100), mode=mode)
        n, waits = engine.stream_length(summary).first()["n"], pending.agg(F.sum("w")).first()[0]
        assert 0 < n < 1_000 and n + waits == 1_000
        assert {r["e"]: r["est"] for r in engine.query(summary, "0.01", pending=pending).collect()} == {f"e{k}": 143 if k < 6 else 142 for k in range(7)}
    totals = engine.worker_totals(engine.handover(stream, SupportSpec("0.01", owners=2, every=300, slots=100))).collect()
    assert sum(r["n"] for r in totals) == 1_000 and all(r["handovers"] >= -(-r["n"] // 300) for r in totals)
    half = streams.sampled_by(stream, "e", {"e0": 1.0})
    assert {r["e"] for r in half.collect()} == {"e0"} and half.count() == 143


def test_given_owners_and_ranges_of_order(spark):
    ship(spark)
    stream = spark.createDataFrame([("a", 1), ("b", 1), ("a", 1), ("c", 1)], "e string, w long")
    summary = engine.build_summary(stream, SupportSpec("0.01", owners=3), how="map", bounds=[("a", 2), ("b", 0), ("c", 2)])
    assert {(r["owner"], r["n_seen"]) for r in summary.collect()} == {(2, 3), (0, 1)}
    rows = spark.createDataFrame([(k * 7919 % 500, k) for k in range(500)], "x long, y long").repartition(5)
    got = streams.numbered(rows, ["x"]).orderBy("ord").collect()
    assert [r["ord"] for r in got] == list(range(500)) and [r["x"] for r in got] == list(range(500))
    frames.release()


def test_aggregates_and_table_functions(spark):
    ship(spark)
    stream = spark.createDataFrame([(k % 2, "hot" if k % 3 else f"e{k}") for k in range(300)], "g int, e string")
    agg = udfs.frequent_agg("0.1", "0.01")
    assert {r["g"]: r["f"] for r in stream.groupBy("g").agg(agg("e").alias("f")).collect()} == {0: ["hot=100"], 1: ["hot=100"]}
    upper = udfs.estimate_udf([("hot", 200, 0), ("e3", 2, 1)], 3)
    assert [r["u"] for r in stream.filter("e = 'hot'").limit(1).select(upper("e").alias("u")).collect()] == [200]
    udfs.register(spark)
    stream.createOrReplaceTempView("arrivals")
    found = spark.sql("SELECT e, est FROM frequent_elements(TABLE(SELECT e FROM arrivals) WITH SINGLE PARTITION, 0.1D, 0.01D)").collect()
    assert [tuple(r) for r in found] == [("hot", 200)]


def test_qualitative_report_ranks_as_published(spark, sf):
    ship(spark)
    rows = {(r["method"], r["queries"], r["answer"]): r for r in workloads.qualitative(spark, sf, (1.0, 2.0)).collect()}
    assert len(rows) == 12
    for q in ("few", "many"):
        for a in ("small", "large"):
            assert rows["owner_split", q, a]["recall"] == 1.0 and rows["owner_split", q, a]["mark_bytes"] == "++"
    for a in ("small", "large"):  # few queries are none on so short a stream
        own, mcb, cmj = (rows[m, "many", a] for m in ("owner_split", "merge_collector", "cell_majority"))
        assert cmj["steps_an_arrival"] > own["steps_an_arrival"] and cmj["steps_a_query"] > own["steps_a_query"]
        assert mcb["bytes"] > own["bytes"] and cmj["bytes"] > own["bytes"]


def test_queries_search_the_heaps_as_they_lie():
    """A query of summaries in arrays goes through their own min-max heaps: what it compares follows from how counts lie there."""
    hashes, t, m = mixed.Ranks(), 3, 40
    ids = np.array([int(x) for x in ARRIVALS])
    own = mixed.Slots(t, m)
    for start in range(0, len(ids), 3_000):
        one, w = np.unique(ids[start : start + 3_000], return_counts=True)
        own.take(one, w, (hashes.many(one) % np.uint64(t)).astype(np.int64))
        own.ordered()
        for i in range(2, own.m + 1):  # every heap is one
            odd, up = i.bit_length() % 2 == 0, own.heap[:, i >> 1]
            assert ((own.heap[:, i] >= up) if odd else (own.heap[:, i] <= up)).all()
            assert i < 4 or ((own.heap[:, i] <= own.heap[:, i >> 2]) if odd else (own.heap[:, i] >= own.heap[:, i >> 2])).all()
    assert (own.count[own.at[:, 1:]] == own.heap[:, 1:]).all()
    seen = set()
    for turn in range(2):
        kernels = [MinMaxSummary(m) for _ in range(t)]
        if turn:  # another order of the heaps, as updates one by one leave it
            for e, c in zip(own.element.tolist(), own.count.tolist(), strict=True):
                for part in (c // 2, c - c // 2):
                    kernels[hashes[e] % t].update(e, part) if part else None
            own.heap[:] = [[s[0] for s in k.heap] for k in kernels]
            own.at[:] = [[0, *[int(own.slot.of[s[1]]) for s in k.heap[1:]]] for k in kernels]
        else:
            kernels = [MinMaxSummary.from_rows(m, [(int(own.element[i]), int(own.count[i]), 0) for i in range(k * own.m, (k + 1) * own.m)]) for k in range(t)]
        for phi in ("0.9", "0.05", "0.01", "0.004", "0.0001"):
            at, compared = own.query(exact(phi))
            found = [k.query(phi, own.n) for k in kernels]
            assert dict(zip(own.element[at].tolist(), own.count[at].tolist(), strict=True)) == dict(x for f in found for x in f)
            assert len(at) == len(set(at.tolist())) and compared == sum(k.stats.comparisons for k in kernels)
            seen.add((phi, compared))
    assert len(seen) > 5  # the two orders are not searched with the same steps
