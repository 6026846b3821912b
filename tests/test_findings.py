"""Findings of a review: what was wrong once, on small tables that show it."""

from __future__ import annotations

import zlib
from collections import Counter

import duckdb
import numpy as np
import pytest

from hotkeys import mixed, often, queries, same_bytes, sim, workloads
from hotkeys.functions import metrics
from hotkeys.kernels.buffers import HandoverBuffers
from hotkeys.kernels.minmax import MinMaxSummary, padded
from hotkeys.kernels.others import FiledSummary, FrequentSummary, LossyCounting, WeightedFrequent
from hotkeys.operators import baselines, sketches
from hotkeys.operators import owner_split as engine
from hotkeys.operators.exact import exact_counts
from hotkeys.shipping import ship
from hotkeys.sources import streams
from hotkeys.spec import SupportSpec
from tests.test_entry import rows_of


def against_sql(spark, folder, name):
    con = duckdb.connect()
    for path in folder.glob("*.parquet"):
        con.execute(f"CREATE VIEW {path.stem} AS SELECT * FROM '{path}'")
    ship(spark)
    found = rows_of(queries.QUERIES[name](spark, str(folder)).toPandas())
    assert found == rows_of(con.execute(queries.ORACLES[name]).df())
    return found


@pytest.mark.parametrize("suppliers", [5, 300])
def test_cube_has_its_total_without_a_frequent_supplier(spark, tmp_path, suppliers):
    duckdb.execute(f"COPY (SELECT i % {suppliers} AS l_suppkey, CASE WHEN i % 7 > 0 THEN chr(CAST(65 + i % 3 AS INTEGER)) END AS l_returnflag, chr(CAST(70 + i % 2 AS INTEGER)) AS l_linestatus FROM range(600) AS r(i)) TO '{tmp_path}/lineitem.parquet'")
    found = against_sql(spark, tmp_path, "cube_report")
    assert len(found) == (1 if suppliers == 300 else 14 + 1)


@pytest.mark.parametrize("name", ["zipf_table2", "memory_model_450", "memory_by_threads"])
def test_models_follow_the_given_words(spark, tmp_path, name):
    duckdb.execute(f"COPY (SELECT i AS doc_id, 'w' || i AS text FROM range(37) AS r(i)) TO '{tmp_path}/documents.parquet'")
    few = against_sql(spark, tmp_path, name)
    duckdb.execute(f"COPY (SELECT i AS doc_id, 'w' || i || ' w' || (i + 1) AS text FROM range(20000) AS r(i)) TO '{tmp_path}/documents.parquet'")
    spark.catalog.clearCache()
    assert few != against_sql(spark, tmp_path, name)


def test_new_pre_tokens_get_one_state_a_visit():
    import public_tokenizers
    import tiktoken

    from hotkeys.llm import byte_bpe

    ranks = byte_bpe.read_ranks(public_tokenizers.path("byte_bpe_50k.tiktoken"))
    own, given = byte_bpe.Transducer(byte_bpe.Merges(ranks)), tiktoken.Encoding("x", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    for piece in (" zuschenerach", " Éanéöß漢字", " aaaaaaaaaaaaaaaaaaaaaaaab", "ÿĀ" * 9, " ofeshainqqzx"):
        for _ in range(30):
            before = len(own.pending)
            assert own.encode(piece.encode()) == given.encode_ordinary(piece)
            assert len(own.pending) <= before + 1


def test_drawn_ranks_are_the_zipf_streams(spark):
    ship(spark)
    for n, u, a in ((3_000, 500, 1.0), (2_000, 3_000_000, 0.5), (2_000, 3_000_000, 2.0)):
        given = [r["e"] for r in streams.zipf_stream(spark, n, u, a, partitions=3).orderBy("ord").collect()]
        assert np.concatenate(list(streams.zipf_ranks(n, u, a, 700))).tolist() == given


def test_a_grid_shuffles_little_and_no_draws(spark):
    """Text went through the shuffle once for each number of workers and support, and so did draws."""
    ship(spark)
    given = spark.createDataFrame([(k, [f"a long word {x % 50}" for x in range(k, k + 1_000)]) for k in range(40)], "ord long, es array<string>")
    for stream in (given, mixed.Drawn(40_000, 1.0)):
        mixes = [mixed.Mix("x", "owner_split", t, p) for t in (1, 2) for p in ("0.01", "0.001")]
        frame = mixed.run_grid(spark, {"x": stream}, mixes)
        rows = frame.collect()
        assert sorted((r["owners"], r["phi"], r["arrivals"]) for r in rows) == [(t, p, 40_000) for t in (1, 2) for p in ("0.001", "0.01")]
        if isinstance(stream, mixed.Drawn):
            assert "RangePartitioning" not in frame._jdf.queryExecution().toString()
    parts = mixed.packed(given).collect()
    assert sum(len(r["codes"]) for r in parts) < 40_000 and {x for r in parts for x in r["words"]} == {f"a long word {x}" for x in range(50)}


@pytest.mark.parametrize("owners,slots,every", [(1, 32, 1_000), (4, 8, 50), (24, 32, 20), (6, 1_001, 300)])
def test_buffers_hand_over_as_insertions_do(owners, slots, every):
    ids = np.random.default_rng(2).zipf(1.3, 9_000) % 4_000
    own, pairs, handovers, per = mixed.Buffers(owners, slots, every, mixed.Ranks()), Counter(), 0, np.zeros(owners, np.int64)
    plain, expected, count = [HandoverBuffers(owners, slots, every) for _ in range(owners)], Counter(), 0
    of = (mixed.mixed_bits(ids) % np.uint64(owners)).tolist()
    for lo, hi in ((0, 13), (13, 5_000), (5_000, 9_000)):
        for k in range(lo, hi):
            out = plain[k % owners].insert(of[k], int(ids[k]))
            count += bool(out)
            for _, held in out:
                expected.update(held)
        got = own.feed(mixed.Block(ids[lo:hi], lo, mixed.Ranks()))
        handovers += got.handovers
        pairs.update(dict(zip(got.ids.tolist(), got.w.tolist(), strict=True)))
        assert pairs == expected and handovers == count
    rest = own.flush()
    pairs.update(dict(zip(rest.ids.tolist(), rest.w.tolist(), strict=True)))
    assert pairs == Counter(ids.tolist())


def test_slots_keep_bounds():
    r, own, true = np.random.default_rng(3), mixed.Slots(3, 40), Counter()
    for size in (5, 400, 90, 3_000):
        ids, w = np.unique(r.zipf(1.2, size) % 700, return_counts=True)
        own.take(ids, w, ids % 3)
        true.update(dict(zip(ids.tolist(), w.tolist(), strict=True)))
        assert own.n == own.count.sum() == sum(true.values())
        for i in range(3):
            part = slice(i * own.m, (i + 1) * own.m)
            least = own.count[part].min()
            held = {e: c for e, c in zip(own.element[part].tolist(), own.count[part].tolist(), strict=True) if e >= 0}
            assert all(true[e] <= c <= true[e] + least for e, c in held.items()) and all(e % 3 == i and own.slot.of[e] >= 0 for e in held)
            assert all(f <= least for e, f in true.items() if e % 3 == i and e not in held)
    assert mixed.minmax_comparisons(own.m, 5) <= 4 * 5 + 2


def test_workers_step_in_a_random_order_drawn_as_far_as_needed():
    arrivals = [f"w{k * k % 97}" for k in range(6_000)]
    own = sim.Simulation(iter(arrivals), sim.Setting(owners=6, slots=4, every=20, seed=3))
    own.rng.sample = None  # a whole order for each step cost more than the step
    records = own.run()
    assert records and not any(r[x] for r in records for x in ("missed", "spurious", "outside", "pending_over"))
    assert own.true == Counter(arrivals) and sorted(own.order) == list(range(6))


def test_a_single_summary_in_bulk_keeps_the_guarantees(spark):
    ship(spark)
    stream = spark.createDataFrame([(f"e{k % (1 + k % 300)}", 1) for k in range(9_000)], "e string, w long").repartition(3)
    spec = SupportSpec("0.02", "0.01")
    summary = baselines.single_summary(stream, spec, bulk=True)
    row = metrics.violations(engine.query(summary, spec.phi), exact_counts(stream), spec.phi, spec.eps).first()
    assert row["n"] == 9_000 and row["n_true"] > 0 and not any(row[x] for x in ("missed", "spurious", "low", "high", "bounds"))
    assert summary.count() == 1 and summary.first()["f_min"] > 0


def _by_owner(arrivals, mixes, marks):
    numbers = mixed.Numbers()
    ids = [numbers.of(arrivals[k : k + 7_777]) for k in range(0, len(arrivals), 7_777)]
    slots = padded(mixed.OwnerSplitOften.slots_of(mixes[0]))
    rows = list(often.dealt(iter(ids), numbers, mixes, marks))
    return list(often.records((part for i in range(mixes[0].owners) for part in often.owned([row for row in rows if row["owner"] == i], mixes, slots)), mixes, slots))


@pytest.mark.parametrize(("owners", "phi", "every", "slots"), [(24, "0.001", 1_000, 32), (4, "0.01", 500, 16), (3, "0.002", 50, 8), (1, "0.01", 100, 3), (5, "0.05", 300, 4)])
def test_frequent_queries_by_owner_are_those_of_a_run_by_arrival(monkeypatch, owners, phi, every, slots):
    monkeypatch.setattr(often, "CHUNK", 5_000)
    arrivals = [str(x) for x in np.random.default_rng(1).zipf(1.2, 20_000)]
    mixes = [mixed.Mix("z", m, owners, phi, share, every, slots) for m in often.KINDS for share in (0.1, 0.02)]
    marks = [20_000, 10_000, 4_997]
    key = lambda r: (r["arrivals"], r["method"], r["share"])
    plain, made = sorted(mixed.run_all(arrivals, mixes, marks), key=key), sorted(_by_owner(arrivals, mixes, marks), key=key)
    assert len(plain) == len(made) == 12
    for a, b in zip(plain, made, strict=True):
        assert a.pop("are") == pytest.approx(b.pop("are"))
        assert {x: v for x, v in a.items() if "seconds" not in x} == {x: v for x, v in b.items() if "seconds" not in x}


def test_frequent_queries_search_a_summary_only_where_its_answer_may_change(monkeypatch):
    searched = []
    query = MinMaxSummary.query
    monkeypatch.setattr(MinMaxSummary, "query", lambda own, *given: searched.append(own) or query(own, *given))
    arrivals = [str(x) for x in np.random.default_rng(2).zipf(1.3, 30_000)]
    rows = _by_owner(arrivals, [mixed.Mix("z", m, 4, "0.001", 0.1) for m in often.KINDS], [30_000])
    assert [r["queries"] for r in rows] == [3_000, 3_000]
    assert len(searched) < 3_000  # 2 methods x 4 owners x 3,000 when each query searched all


def test_queries_of_counts_each_query_once():
    since, values, t = [1, 4, 4, 35, 90], [5, 7, 1, 0, 3], 3
    for gap in (1, 2, 10):
        total, by = often.queries_of(since, values, 97, gap, t)
        asked = [(n // gap - 1, [v for s, v in zip(since, values, strict=True) if s <= n][-1]) for n in range(gap, 98, gap)]
        assert total == sum(v for _, v in asked) and by.tolist() == [sum(v for q, v in asked if q % t == j) for j in range(t)]


def test_every_query_of_the_enhancement_on_conversations_is_counted_by_owner(spark, tmp_path, monkeypatch):
    """With a null text, an empty one, rows out of order, and more words than the summaries' slots near the threshold."""
    duckdb.execute(f"COPY (SELECT i // 3 AS conv_id, CAST(i % 3 AS INTEGER) AS turn, 'user' AS role, CASE i % 50 WHEN 7 THEN NULL WHEN 8 THEN '' ELSE array_to_string([concat('w', (i * j * j) % 20011 // (1 + j % 40)) for j in range(1, 61)], ' ') END AS text FROM range(600) AS r(i) ORDER BY hash(i)) TO '{tmp_path}/conversations.parquet'")
    dealt = []
    by_owner = mixed._by_owner
    monkeypatch.setattr(mixed, "_by_owner", lambda spark, streams, mixes, marks: dealt.extend(m.method for m in mixes) or by_owner(spark, streams, mixes, marks))
    found = against_sql(spark, tmp_path, "enhancement_ab_conversations")
    assert len(found) == 2 and sorted(dealt) == ["owner_split", "owner_split_counting"]


def test_texts_are_split_once_in_order_and_owners_get_arrivals_in_few_bytes(spark, tmp_path, monkeypatch):
    """Words were counted in a pass of their own and shuffled as arrays, and the pairs handed over went beside the arrivals that make them."""
    duckdb.execute(f"COPY (SELECT i // 3 AS conv_id, CAST(i % 3 AS INTEGER) AS turn, CASE WHEN i % 50 <> 7 THEN concat('  Ab', i, '-c d', i % 5, ' É', ' ' || i % 3) END AS text FROM range(300) AS r(i) ORDER BY hash(i)) TO '{tmp_path}/conversations.parquet'")
    ship(spark)
    texts, arrays = (make(spark, str(tmp_path), "conversations") for make in (workloads.ordered_texts, workloads.word_arrays))
    streamed = [[r["words"][c] for r in sorted(mixed.packed(x).collect(), key=lambda r: (r["part"], r["seq"])) for c in np.frombuffer(zlib.decompress(r["codes"]), np.uint16)] for x in (texts, arrays)]
    assert streamed[0] == streamed[1] and len(streamed[0]) == 294 * 5
    monkeypatch.setattr(type(texts), "first", lambda own: pytest.fail("a pass that only counts"))
    frame = mixed.run_grid(spark, {"conversations": texts}, workloads.enhancement_grid("conversations"))
    assert "split(" not in frame._jdf.queryExecution().optimizedPlan().toString().split("RepartitionByExpression")[-1]
    assert [r["arrivals"] for r in frame.collect()] == [294 * 5] * 2

    ids = np.random.default_rng(3).zipf(1.3, 50_000) % 20_000
    rows = list(often.dealt(iter([ids]), mixed.Ranks(), workloads.enhancement_grid(), None))
    small = list(map(often.shrunk, rows))
    assert sum(len(x) for row in small for x in row.values() if isinstance(x, bytes)) < 6 * len(ids)
    for row, own in zip(rows, small, strict=True):
        back = often.unshrunk(dict.fromkeys(often.ARRAYS) | own)
        assert all(back[x].tolist() == row[x].tolist() if x in row else back[x] is None for x in often.ARRAYS)
    assert sum(row["marked"] for row in rows) == 24 and not list(often.dealt(iter([]), mixed.Ranks(), workloads.enhancement_grid(), None))


@pytest.mark.parametrize("words", [0, 3])
def test_the_enhancement_has_its_rows_without_words_and_without_queries(spark, tmp_path, words):
    for name, key in (("conversations", "1::BIGINT AS conv_id, 0::INTEGER AS turn"), ("documents", "1::BIGINT AS doc_id")):
        duckdb.execute(f"COPY (SELECT {key}, CASE WHEN {words} > 0 THEN repeat('a b', {words} // 3) END AS text UNION ALL SELECT {key.replace('1::', '2::')}, CASE WHEN {words} > 0 THEN 'c' END) TO '{tmp_path}/{name}.parquet'")
    assert len(against_sql(spark, tmp_path, "enhancement_ab_conversations")) == 2
    rows = queries.QUERIES["enhancement_ab_words"](spark, str(tmp_path)).collect()
    assert [(r["arrivals"], r["queries"], r["steps_a_query"]) for r in rows] == [(words, 0, None)] * 2


def test_a_summary_takes_pairs_at_once_as_one_by_one():
    r, one, all_ = np.random.default_rng(4), MinMaxSummary(40), MinMaxSummary(40)
    for low in range(0, 600, 3):
        e, w = (r.zipf(1.3, 9) % 300).tolist(), r.integers(1, 5, 9).tolist()
        passed, lost, told = False, [], []
        for x, y in zip(e, w, strict=True):
            c = one.estimate(x)
            lost += [(one.heap[1][1], x, c)] if x not in one.place and c else []
            one.update(x, y)
            passed |= c <= low < c + y
        assert all_.update_all(e, w, low, lambda *of: told.append(of)) == passed and told == lost
        assert all_.to_rows() == one.to_rows() and all_.n == one.n
    all_.check_invariant()
    with pytest.raises(ValueError):
        all_.update_all([1, 2], [1, 0], 5)


def test_unit_kernels_take_many_arrivals_at_once():
    ids = (np.random.default_rng(5).zipf(1.2, 20_000) % 3_000).tolist()
    true = Counter(ids)
    for m in (7, 63, 400):
        frequent, plain, space, lossy, each = FrequentSummary(m), WeightedFrequent(m), FiledSummary(m), LossyCounting(f"1/{m}"), LossyCounting(f"1/{m}")
        for lo in range(0, 20_000, 777):
            for own in (frequent, space, lossy):
                own.update_many(ids[lo : lo + 777])
        for e in ids:
            plain.update(e)
            each.update(e)
        assert sorted(frequent.to_rows()) == sorted(plain.to_rows()) and frequent.n == plain.n
        assert sorted(lossy.to_rows()) == sorted(each.to_rows()) and (lossy.n, lossy.bucket) == (each.n, each.bucket)
        rows = space.to_rows()
        assert len(rows) == space.m and sum(c for _, c, _ in rows) == space.n == 20_000 and space.f_min <= 20_000 // space.m
        assert all(c - over <= true[e] <= c for e, c, over in rows) and all(f <= space.f_min for e, f in true.items() if e not in space.count)


def test_equal_bytes_are_the_operators_answers_in_one_pass_a_method(spark, tmp_path):
    """Each method and size took the strings of one cached partition again, arrival by arrival."""
    ship(spark)
    ids = np.random.default_rng(6).zipf(1.25, 36_000) % 9_000
    texts = [(k, " ".join(f"W{x}" for x in ids[90 * k : 90 * k + 90])) for k in range(400)]
    spark.createDataFrame([*texts[::-1], (400, None), (401, "")], "doc_id long, text string").repartition(5).write.parquet(f"{tmp_path}/documents.parquet")
    phi, sizes = "0.002", (16_384, 32_768)
    got = {(r["bytes"], r["method"]): r for r in workloads.equal_bytes(spark, str(tmp_path), sizes, phi).collect()}
    assert len(got) == 12
    stream = spark.createDataFrame([(f"w{x}", 1) for x in ids], "e string, w long").coalesce(1).persist()
    counts = exact_counts(stream).persist()
    for size in sizes:
        spec = same_bytes.spec_of(size, phi)
        made = {
            "frequent": baselines.frequent_unit(stream, spec, 1),
            "lossy_counting": baselines.lossy_counting(stream, spec, 1),
            "count_min": sketches.count_min(stream, spec, width=size // 40, depth=5),
            "count_sketch": sketches.count_sketch(stream, spec, size // 40, 5),
        }
        for name, answer in made.items():
            row, own = metrics.accuracy(answer, counts, phi, over="true").first(), got[size, name]
            assert (row["n_true"], row["n_reported"]) == (own["n_true"], own["n_reported"])
            assert [row[x] for x in ("precision", "recall", "are")] == pytest.approx([own[x] for x in ("precision", "recall", "are")])
        assert got[size, "space_saving"]["recall"] == 1.0 and got[size, "cell_majority"]["n_reported"] > 0
    spark.createDataFrame([], "doc_id long, text string").write.parquet(f"{tmp_path}/none/documents.parquet")
    assert {tuple(r)[2:] for r in workloads.equal_bytes(spark, f"{tmp_path}/none", sizes, phi).collect()} == {(0, 0, 1.0, 1.0, 0.0)}


@pytest.mark.parametrize(("t", "phi", "a", "size"), [(1, "0.05", 0.6, 700), (3, "0.05", 0.6, 501), (5, "0.1", 0.3, 64), (2, "0.05", 1.2, 3_000), (4, "0.01", 1.0, 5_000), (2, "0.5", 0.5, 1_000), (3, "0.3", 1.0, 400)])
def test_merge_collector_withholds_as_arrival_by_arrival(t, phi, a, size):
    """counters of all workers in arrays, a block at once; what is sent, and when, is what plain loops send."""
    ids = np.concatenate(list(mixed.Drawn(30_000, a).arrays()))
    own = mixed.MergeCollector(mixed.Mix("z", "merge_collector", t, phi), mixed.Ranks())
    for start in range(0, len(ids), size):
        own.feed(mixed.Block(ids[start : start + size], start, mixed.Ranks()), None)
    beta, m = own.beta, own.local.m
    local, grown, offset, every, pairs, n = [{} for _ in range(t)], [{} for _ in range(t)], [0] * t, WeightedFrequent(m), 0, [0] * t
    for k, e in enumerate(ids.tolist()):
        j = k % t
        n[j] += 1
        if e not in local[j] and len(local[j]) == m:
            offset[j] += 1
            for x in [x for x, c in local[j].items() if c <= offset[j]]:
                del local[j][x], grown[j][x]
            continue
        local[j][e] = local[j].get(e, offset[j]) + 1
        grown[j][e] = grown[j].get(e, 0) + 1
        if grown[j][e] >= beta * n[j]:
            every.update(e, grown[j][e])
            grown[j][e] = 0
            pairs += 1
    assert own.pairs == own.busy[t] == pairs and own.all.raw == every.raw and own.all.offset == every.offset and own.all.n == every.n
    assert own.local.offset.tolist() == offset and own.local.live.tolist() == list(map(len, local))
    for j in range(t):
        keys = np.array(sorted(local[j])) * t + j
        _, slot = own.local.find(keys)
        assert own.local.raw[slot].tolist() == [local[j][x] for x in sorted(local[j])] and own.local.grown[slot].tolist() == [grown[j][x] for x in sorted(local[j])]
    low = (own.phi - own.eps) * len(ids)
    assert own.found() == {x: c - every.offset for x, c in every.raw.items() if c - every.offset > low}


def test_single_arrivals_take_the_least_slots_in_turn():
    """many elements that come once rise together; the counts and who has them are what one after another gives."""
    r = np.random.default_rng(7)
    for k in range(200):
        own = mixed.Slots(1, int(r.integers(3, 60)))
        m = own.m
        one = np.arange(m)
        own.take(one, r.integers(1, int(r.choice([2, 5, 40])) + 1, m), np.zeros(m, np.int64))
        plain = [[int(c), i, i] for i, c in enumerate(own.count)]
        new = 1_000 + np.arange(int(r.integers(1, 4 * m)))
        w = np.where(r.random(len(new)) < 0.1 * (k % 3), r.integers(2, 9, len(new)), 1)
        for e, x in sorted(zip(new.tolist(), w.tolist(), strict=True), key=lambda y: (y[1] > 1, y[0])):
            slot = min(plain)
            slot[0] += x
            slot[2] = e
        own.take(new, w, np.zeros(len(new), np.int64))
        assert sorted(own.count.tolist()) == sorted(c for c, _, _ in plain) and own.count.sum() == own.n
        assert all(own.slot.of[e] == i for i, e in enumerate(own.element.tolist()))
        if len(new) >= m and (w == 1).all():  # then no choice among equal slots is open
            assert [[int(c), i, int(e)] for i, (c, e) in enumerate(zip(own.count, own.element, strict=True))] == plain


@pytest.mark.parametrize("name", ["throughput_by_skew", "throughput_by_threads", "latency_by_skew"])
def test_speeds_make_every_run_once(spark, sf, name):
    """the single summary's steps come from the same records, not from a second go through all runs."""
    plan = queries.QUERIES[name](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("run_numbered") + plan.count("MapInArrow run(") <= (2 if name == "throughput_by_threads" else 1), plan


def test_packed_words_shuffle_in_few_bytes(spark, sf):
    """texts are shuffled as texts, and a copy of their words for a task takes less than half of what it took."""
    texts, arrays = workloads.ordered_texts(spark, sf), workloads.word_arrays(spark, sf)
    small, plain = (sorted(mixed.packed(texts, tightly).collect(), key=lambda r: (r["part"], r["seq"])) for tightly in (True, False))
    words = [mixed.loose_words(r["words"]) for r in small]
    assert words == [r["words"] for r in plain]
    given = [e for r in sorted(arrays.collect(), key=lambda r: r["ord"]) for e in r["es"]]
    assert [w[c] for w, r in zip(words, small, strict=True) for c in mixed.loose(r["codes"])] == given
    size = lambda rows: sum(len(r["codes"]) + len(r["words"]) for r in rows)
    before = sum(len(r["codes"]) + sum(8 + (len(w.encode()) + 7) // 8 * 8 for w in r["words"]) for r in plain)
    assert size(small) < before / 2
    odd = ["", "a\nb", "\ud800", "ß" * 300, "𝒳", "x" * 70_000]
    assert mixed.loose_words(mixed.tight_words(odd)) == odd and mixed.loose_words(mixed.tight_words([])) == []
    for most in (1, 256, 1 << 24, (1 << 32) - 1):
        numbers = np.random.default_rng(1).integers(0, most, 1000)
        assert (mixed.loose(mixed.tight(numbers)) == numbers).all()
