"""The engine on Spark: answers, certificates, hand-over, edge streams, determinism."""

from __future__ import annotations

from collections import Counter

import pytest
from pyspark.sql import functions as F

from hotkeys.functions.metrics import accuracy, violations
from hotkeys.operators import baselines, sketches
from hotkeys.operators import owner_split as engine
from hotkeys.operators.exact import exact_counts, exact_frequent
from hotkeys.plans import planner
from hotkeys.queries import QUERIES
from hotkeys.sim import Setting, Simulation
from hotkeys.sources import streams
from hotkeys.spec import SupportSpec


def stream_of(spark, pairs, kind="string"):
    return spark.createDataFrame(pairs, f"e {kind}, w long")


@pytest.fixture(scope="module")
def zipf(spark):
    return streams.zipf_stream(spark, 20_000, 20_000, 1.25, partitions=4).persist()


def test_batch_and_row_hand_over_carry_the_same_weight(spark, zipf):
    spec = SupportSpec("0.01", owners=5, slots=16, every=300)
    for mode in ("batch", "rows"):
        pairs = engine.handover(zipf, spec, mode)
        got = {r["e"]: r["w"] for r in pairs.groupBy("e").agg(F.sum("w").alias("w")).collect()}
        assert got == {r["e"]: r["f"] for r in exact_counts(zipf).collect()}
        widest = pairs.groupBy("src", "seq", "owner").agg(F.countDistinct("e").alias("d")).agg(F.max("d")).first()[0]
        assert widest <= spec.slots
        assert pairs.groupBy("e").agg(F.countDistinct("owner").alias("o")).agg(F.max("o")).first()[0] == 1


@pytest.mark.parametrize("inner", ["minmax", "minheap", "bucketlist"])
def test_guarantees_hold(zipf, inner):
    spec = SupportSpec("0.005", owners=4)
    row = violations(engine.frequent(zipf, spec, inner=inner), exact_counts(zipf), spec.phi, spec.eps).first()
    assert row["n"] == 20_000 and row["n_true"] > 5
    assert row["missed"] == row["spurious"] == row["low"] == row["high"] == row["bounds"] == 0


def test_answer_doesnt_depend_on_partitions(spark, zipf):
    spec = SupportSpec("0.005", owners=4, counters=50_000)
    first = sorted(engine.frequent(zipf, spec).collect())
    for parts in (1, 7):
        assert sorted(engine.frequent(zipf.repartition(parts), spec).collect()) == first


def test_certificate_needs_balanced_owners(spark):
    even = stream_of(spark, [(f"x{i % 1000}", 1) for i in range(10_000)])
    spec = SupportSpec("0.1", "0.01", owners=4)
    assert engine.certify(engine.build_summary(even, spec), spec).first()["level"] == "full"
    lone = engine.certify(engine.build_summary(even, spec, how="one"), spec).first()
    assert lone["f_min"] > 100 and lone["level"] == "recall"
    answer, level = engine.frequent_certified(even, spec, how="one")
    assert level == "full" and answer.count() == 0
    small = SupportSpec("0.02", "0.01", owners=4, counters=3)
    assert engine.certify(engine.build_summary(even, small, how="one"), small).first()["level"] == "none"


def test_edge_streams(spark):
    spec = SupportSpec("0.1", owners=3)
    assert engine.frequent(stream_of(spark, []), spec).count() == 0
    assert engine.frequent(stream_of(spark, [("a", 1)]), spec).collect() == [("a", 1, 1, 1)]
    nulls = streams.element_stream(spark.createDataFrame([("a",), (None,), ("a",)], "x string"), "x")
    assert engine.frequent(nulls, spec).collect() == [("a", 2, 2, 2)]
    heavy = stream_of(spark, [("a", 2**40), ("b", 1), ("a", 2**40)])
    assert engine.frequent(heavy, spec).collect() == [("a", 2**41, 2**41, 2**41)]
    with pytest.raises(Exception, match="deletions"):
        engine.frequent(stream_of(spark, [("a", -1)]), spec).collect()
    doubles = streams.element_stream(spark.createDataFrame([(0.0,), (-0.0,), (float("nan"),), (float("nan"),)], "x double"), "x")
    assert exact_counts(doubles).count() == 2
    with pytest.raises(TypeError):
        streams.element_stream(spark.createDataFrame([([1],)], "x array<int>"), "x")


def test_struct_elements_come_back_as_structs(spark, sf):
    rows = engine.frequent(streams.flows(spark, sf), SupportSpec("0.0003", owners=4, counters=10_000)).select("e.*", "est").collect()
    assert rows and all(r["est"] >= 2 for r in rows)


def test_pending_pairs_count_without_the_enhancement(spark):
    spec = SupportSpec("0.15", owners=2, counters=7)
    summary = engine.build_summary(stream_of(spark, [("a", 3), ("b", 1)]), spec)
    pending = stream_of(spark, [("c", 1), ("d", 1)])
    assert {r["e"]: r["est"] for r in engine.query(summary, "0.15", n=6).collect()} == {"a": 3, "b": 1}
    assert {r["e"] for r in engine.query(summary, "0.15", pending=pending).collect()} == {"a", "b", "c", "d"}
    assert engine.query(summary, "0.4", n=6).collect() == [("a", 3, 3, 3)]


def test_estimates_of_given_elements_are_bounds(spark, zipf):
    spec = SupportSpec("0.01", owners=4)
    summary = engine.build_summary(zipf, spec)
    true = {r["e"]: r["f"] for r in exact_counts(zipf).collect()}
    asked = spark.createDataFrame([(k,) for k in (1, 2, 50, 19_999, 10**9)], "e long")
    for r in engine.estimate(summary, asked, spec).collect():
        assert r["lower"] <= true.get(r["e"], 0) <= r["upper"]


def test_combined_summaries_bound_both_streams(spark, zipf):
    spec = SupportSpec("0.01", owners=4)
    a, b = zipf.filter("ord < 8000"), zipf.filter("ord >= 8000")
    both = engine.combine(engine.build_summary(a, spec), engine.build_summary(b, spec))
    row = violations(engine.query(both, spec.phi), exact_counts(zipf), spec.phi, 2 * spec.eps).first()
    assert row["missed"] == row["low"] == row["bounds"] == 0
    assert both.agg(F.sum("n_seen")).first()[0] == 20_000


def test_baselines(spark, zipf):
    spec = SupportSpec("0.01", owners=4)
    counts = exact_counts(zipf).persist()
    check = lambda answer: violations(answer, counts, spec.phi, spec.eps).first()
    one = check(engine.query(baselines.single_summary(zipf, spec), spec.phi))
    assert one["missed"] == one["spurious"] == one["low"] == one["high"] == 0
    merged = check(baselines.local_merge(zipf, spec, 3))
    assert merged["missed"] == merged["low"] == merged["bounds"] == 0
    for answer in (baselines.frequent_unit(zipf, spec, 3), baselines.lossy_counting(zipf, spec, 3)):
        row = check(answer)
        assert row["missed"] == row["spurious"] == row["bounds"] == 0
    for answer in (baselines.merge_collector(zipf, spec, tasks=3), baselines.cell_majority(zipf, spec, tasks=3)):
        assert check(answer)["spurious"] == 0
        assert accuracy(answer, counts, spec.phi).first()["recall"] >= 0.8
    assert check(sketches.count_min(zipf, spec))["missed"] == 0
    two = engine.query(baselines.global_cooperative([zipf, zipf], spec), spec.phi)
    assert violations(two, exact_counts(zipf.unionByName(zipf)), spec.phi, spec.eps).first()["missed"] == 0
    assert {r["e"] for r in sketches.sketch_topk(zipf.select("e", "w"), 3, 1 << 16, 4).collect()} == {1, 2, 3}
    width, depth = 1 << 12, 4
    halves = [sketches.sketch(zipf.filter(c), width, depth) for c in ("ord < 9000", "ord >= 9000")]
    assert sketches.merge(*halves).exceptAll(sketches.sketch(zipf, width, depth)).count() == 0


def test_accuracy_of_empty_sets_is_whole(spark, zipf):
    none = zipf.limit(0).select("e", F.lit(1).alias("est"), F.lit(1).alias("lower"), F.lit(1).alias("upper"))
    row = accuracy(none, exact_counts(zipf), "0.9").first()
    assert (row["precision"], row["recall"]) == (1.0, 1.0)
    assert accuracy(none, exact_counts(zipf), "0.1").first()["recall"] == 0.0


def test_zipf_stream_follows_its_law(spark):
    from hotkeys.plans.sizing import zipf_expected

    for a in (0.75, 1.0, 2.0):
        top = {r["e"]: r["count"] for r in streams.zipf_stream(spark, 50_000, 50_000, a).groupBy("e").count().filter("e <= 3").collect()}
        for r in (1, 2, 3):
            assert abs(top[r] - zipf_expected(50_000, 50_000, a, r)) < 6 * zipf_expected(50_000, 50_000, a, r) ** 0.5
    same = streams.zipf_stream(spark, 1000, 1000, 1.0, partitions=3).exceptAll(streams.zipf_stream(spark, 1000, 1000, 1.0, partitions=1))
    assert same.count() == 0


def test_adverse_orders_keep_the_guarantees(spark, zipf):
    # few counters and small hand-overs, so that summaries replace elements and an order is left
    spec = SupportSpec("0.02", "0.005", owners=2, slots=8, every=50)
    small = zipf.filter("ord < 5000")
    for how in ("ascending", "descending", "round_robin", "tail_first"):
        stream = streams.reordered(small, how).orderBy("ord")
        summary = engine.build_summary(stream, spec, deterministic=True)
        assert summary.agg(F.max("f_min")).first()[0] > 0
        row = violations(engine.query(summary, spec.phi), exact_counts(small), spec.phi, spec.eps).first()
        assert row["n_true"] > 0 and row["missed"] == row["spurious"] == row["low"] == row["bounds"] == 0


@pytest.mark.parametrize("seed", range(6))
def test_overlapping_queries_keep_their_bounds(seed):
    import random

    rng = random.Random(seed)
    arrivals = [min(int(rng.paretovariate(1.0)), 400) for _ in range(4_000)]
    setting = Setting(owners=rng.choice([2, 4, 8]), slots=rng.choice([4, 16]), every=rng.choice([10, 80]), phi="0.02", eps="0.002", query_every=70, seed=seed)
    records = Simulation(arrivals, setting).run()
    assert len(records) > 20 and records[-1]["n_end"] == 4_000
    assert all(r["missed"] == r["spurious"] == r["outside"] == r["pending_over"] == 0 for r in records)
    assert any(r["n_end"] > r["n_start"] for r in records)
    off = Simulation(arrivals, Setting(**{**setting.__dict__, "count_buffers": True})).run()
    assert sum(r["lookups"] for r in off) > 0 and all(r["spurious"] == r["outside"] == 0 for r in off)
    mean = lambda rows: sum(r["comparisons"] + r["lookups"] for r in rows) / len(rows)
    assert mean(records) < mean(off)


def test_a_run_takes_the_whole_stream_and_holds_little_of_it():
    import random

    rng, given = random.Random(3), [0]
    setting = Setting(owners=4, slots=8, every=20, phi="0.02", eps="0.002", query_every=70)

    def arrivals():
        for _ in range(20_000):
            given[0] += 1
            yield min(int(rng.paretovariate(1.0)), 400)

    run, most = Simulation(arrivals(), setting), 0
    for record in run.stream():
        most = max(most, given[0] - run.n)
        assert record["missed"] == record["spurious"] == record["outside"] == record["pending_over"] == 0
    assert record["n_end"] == 20_000 and most < 2_000


def test_certified_answers_double_until_the_proof_is_full(spark):
    apart = stream_of(spark, [(f"k{i}", 1) for i in range(2_000)])
    answer, level = engine.frequent_certified(apart, SupportSpec("0.1", owners=2, counters=1))
    assert level == "full" and answer.count() == 0


def test_overlap_queries_see_every_word(spark, sf):
    n = streams.documents_words(spark, sf).count()
    assert n > 4_000
    ends = QUERIES["overlap_records_sim"](spark, sf).groupBy("run_id").agg(F.max("n_end").alias("n")).collect()
    assert {r["n"] for r in ends} == {n} and len(ends) == 4


def test_planner_chooses(spark, zipf):
    few = stream_of(spark, [(f"k{i % 5}", 1) for i in range(100)])
    plan = planner.choose(few, SupportSpec("0.1"), fraction=1.0)
    assert plan.strategy == "exact"
    answer, level = planner.run(few, plan)
    assert level == "full" and answer.count() == 5
    plan = planner.choose(zipf.select("e", "w"), SupportSpec("0.01"), fraction=0.5)
    assert plan.strategy == "owner_split" and plan.skew > 0.8
    found = {r["e"] for r in planner.run(zipf, plan)[0].collect()}
    assert {r["e"] for r in exact_frequent(zipf, "0.01").collect()} <= found


def test_frequent_by_group(spark):
    rows = [("a", "x")] * 6 + [("a", "y")] * 2 + [("b", "y")] * 3
    df = spark.createDataFrame(rows, "g string, e string").withColumn("w", F.lit(1).cast("long"))
    assert Counter(map(tuple, engine.frequent_by(df, ["g"], "0.5", 7).select("g", "e", "est").collect())) == Counter([("a", "x", 6), ("b", "y", 3)])
