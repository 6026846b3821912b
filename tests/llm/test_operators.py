"""Each operator against brute force on awkward tables and on the small documents."""

from __future__ import annotations

import math
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import public_tokenizers as P
import pytest
import regex
import xxhash
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from hotkeys.llm import best_fit_packing, byte_bpe, chat_format, exact_dedup, minmax_dedup, oracles, pii, quality_rules, registry, repeated_passages, token_counts, url_filter
from hotkeys.shipping import ship
from tests.llm import helpers as h

QUERIES = registry.queries()


@pytest.fixture(scope="module", params=[1, 2])
def rows(request):
    return h.awkward(request.param)


@pytest.fixture(scope="module")
def docs(spark, rows):
    ship(spark)
    return h.frame(spark, rows).persist()


@pytest.fixture(scope="module")
def empty(docs):
    return docs.limit(0)


@pytest.fixture(scope="module")
def small(spark, sf):
    ship(spark)
    return [tuple(r) for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()]


def by_id(frame, key="doc_id"):
    return {r[key]: r for r in frame.collect()}


# --- 1 quality rules ---


def test_quality_measures(rows, docs, empty):
    got = by_id(quality_rules.judge(docs))
    for d, text in rows:
        ws, t, r = h.words(text), text or "", got[d]
        lines = [x for x in t.split("\n") if h.words(x)]
        assert (r["n_words"], r["word_chars"], r["n_repeat_words"]) == (len(ws), sum(map(len, ws)), h.repeat_words(ws))
        assert r["n_symbols"] == sum(c in "#*$%&|<>" for c in t) and r["n_dup_lines"] == len(lines) - len(set(lines))
        assert r["base_failed"] == (len(ws) < 50 or 100 * h.repeat_words(ws) > 50 * len(ws))
        assert not (r["kept"] and r["base_failed"]) and r["kept"] == (not r["base_failed"] and not r["failed_rules"])
    kept = quality_rules.kept_rows(docs)
    assert kept.columns == docs.columns and {r["doc_id"] for r in kept.collect()} == {d for d in got if got[d]["kept"]}
    assert quality_rules.judge(empty).count() == quality_rules.kept_rows(empty).count() == 0


def test_quality_keeps_good_labels_and_drops_bad(spark, sf):
    labels = {r["doc_id"]: r["quality"] for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    got = by_id(QUERIES["op1_quality_rules"](spark, sf))
    judged = [(labels[d], r["kept"]) for d, r in got.items() if d in labels and not r["base_failed"]]
    assert sum(kept for good, kept in judged if good) >= 0.99 * sum(good for good, _ in judged)
    assert not any(kept for good, kept in judged if not good)


# --- 2 repeated passages ---


def test_removed_spans(rows, docs, empty):
    expected = h.removed_bytes(rows)
    for r in repeated_passages.without_repeats(docs).collect():
        got = (r["n_bytes"], r["n_removed"], len(r["spans"]), h.sha(bytes(r["kept"])))
        assert got == expected[r["id"]], r["id"]
        assert all(a["end"] < b["start"] for a, b in zip(r["spans"], r["spans"][1:], strict=False))
    assert repeated_passages.without_repeats(empty).count() == 0


def test_removed_spans_of_documents_and_null_ids(spark, sf, small):
    expected = h.removed_bytes(small)
    got = by_id(QUERIES["op2_suffix_dedup"](spark, sf))
    assert {d: tuple(r[1:5]) for d, r in got.items()} == expected
    text = "passage number one " * 20
    twice = spark.createDataFrame([(None, text), (1, text), (2, None)], "doc_id long, text string")
    left = {r["id"]: r["n_removed"] for r in repeated_passages.without_repeats(twice).collect()}
    assert left[repeated_passages.LAST_ID] == len(text) and left[2] == 0


@settings(max_examples=40, deadline=None)
@given(st.lists(st.binary(min_size=100, max_size=160).map(lambda b: bytes(x % 2 for x in b)), min_size=1, max_size=12), st.integers(0, 5))
def test_refined_buckets_are_equal_strings(cuts, repeats):
    cuts = cuts + cuts[:1] * repeats
    data = np.frombuffer(b"".join(cuts), np.uint8)
    base = np.cumsum([0, *map(len, cuts)])[:-1]
    starts = np.array([b + i for b, c in zip(base, cuts, strict=True) for i in range(len(c) - 99)])
    bucket = repeated_passages.refined(data, starts)
    text = [data[s : s + 100].tobytes() for s in starts]
    names = {}
    for b, t in zip(bucket.tolist(), text, strict=True):
        assert names.setdefault(b, t) == t
    assert len(set(bucket.tolist())) == len(set(text))


def test_crowded_anchors_give_the_same_spans(spark):
    r = random.Random(8)
    line = "licensed under the common terms of this licence text that every page repeats at its foot without any change at all"
    rows = [(i, "".join(r.choice("abcdefgh ") for _ in range(150)) + line + "".join(r.choice("abcdefgh ") for _ in range(r.randrange(120)))) for i in range(40)]
    rows += [(50 + i, rows[i][1][100:] + rows[i + 1][1][:130]) for i in range(10)]
    docs = h.frame(spark, rows)
    want = {r["id"]: r["runs"] and sorted(tuple(x) for x in r["runs"]) for r in repeated_passages.removed_spans(docs).collect()}
    got = {r["id"]: r["spans"] for r in repeated_passages.cut_spans(repeated_passages.removed_spans(docs, crowded=2)).collect()}
    assert got == {r["id"]: r["spans"] for r in repeated_passages.without_repeats(docs).collect()} and any(want.values())


# --- 3 PII ---


def test_pii_base_spans(spark, rows):
    r = random.Random(4)
    bits = ["a", "b.c", "@", "x@y.z", ".", "1", "4111 1111 1111 1111", "+1 (555) 010-9999", "-", " ", "é", "😀", "1.2.3.4", "256", "0", "\n", "+", "("]
    own = [*rows, *[(1000 + i, "".join(r.choice(bits) for _ in range(r.randrange(25)))) for i in range(500)], (9999, "1" * 3000 + " a." * 2000 + "b@c" + ".d" * 4000)]
    docs = h.frame(spark, own)
    got = {x["id"]: x["s"] for x in pii.entities(docs).select("id", pii.spans_text(F.col("spans")).alias("s")).collect()}
    assert got == {d: h.base_spans(t) for d, t in own}
    clean = by_id(pii.sanitised(docs))
    for d, t in own:
        if not got[d]:
            assert clean[d]["text"] == t and clean[d]["n_chars"] == len(t or "")
        else:
            assert not re.search(r"[A-Za-z0-9]@[A-Za-z0-9-]+\.[A-Za-z0-9]", clean[d]["text"]) and clean[d]["n_chars"] == len(clean[d]["text"])
    assert pii.sanitised(docs).columns == docs.columns and pii.all_spans(docs.limit(0)).count() == 0


def test_terms_that_disclose_an_entity_go(spark):
    fill = [f"plain words number{i} of other texts stand here" for i in range(30)]
    near = [f"word{i} ask Zebediah at zeb@mail.example.com about word{i + 50} today" for i in range(4)]
    rows = list(enumerate(fill + near)) + [(90, "Today words of texts stand")]
    docs = spark.createDataFrame([(d, t, len(t)) for d, t in rows], "doc_id long, text string, n_chars long")
    # a name that also stands alone elsewhere is not confined to the address
    elsewhere = docs.union(spark.createDataFrame([(None, "Zebediah", 8)], docs.schema))
    assert not any(s["kind"] == "term" and s["value"] == "Zebediah" for r in pii.all_spans(elsewhere, alpha=1.0).collect() for s in r["spans"])
    found = {r["id"]: [s["value"] for s in r["spans"] if s["kind"] == "term"] for r in pii.all_spans(docs).collect()}
    assert all("Zebediah" in found[30 + i] for i in range(4)) and not any(found[i] for i in range(30))
    clean = by_id(pii.sanitised(docs))
    assert "Zebediah" not in clean[30]["text"] and "[EMAIL]" in clean[30]["text"] and "[REMOVED]" in clean[30]["text"]
    assert clean[90]["text"] == "Today words of texts stand"
    spans = F.array(F.struct(F.lit(0).alias("start"), F.lit(4).alias("rank"), F.lit(4).alias("end"), F.lit("term").alias("kind"), F.lit("Rome").alias("value")))
    labels = F.create_map(F.lit("rome"), F.lit("a city"))
    assert spark.range(1).select(pii.redacted(F.lit("Rome is old"), spans, labels).alias("t")).first()["t"] == "a city is old"


def brute_terms(rows, alpha):
    """(term, entity) -> (pmi, information) of disclosing terms, by counting every pair of the corpus."""
    white = " \t\n\x0b\f\r"
    held_by, holders, near, mentions = {}, {}, {}, {}
    for key in {(d, t or "") for d, t in rows}:
        text = key[1]
        for t in {m.lower() for m in regex.findall(pii.TERM, text)}:
            held_by.setdefault(t, set()).add(key)
        for span in [s.split(":") for s in h.base_spans(text).split(",") if s]:
            start, end = int(span[1]), int(span[2])
            entity = (span[0] + ":" + text[start:end]).lower()
            low, cut = max(start - pii.CONTEXT_CHARS, 0), text[end : end + pii.CONTEXT_CHARS]
            left = text[low:start] if not low else text[low:start].lstrip("".join(set(text) - set(white)))
            left, cut = (left.rstrip("".join(set(text) - set(white)))), (cut if len(cut) < pii.CONTEXT_CHARS else cut.rstrip("".join(set(text) - set(white))))
            around = left + " " + cut.lstrip("".join(set(text) - set(white)))
            context = xxhash.xxh64_intdigest(around.encode(), 42)
            context -= (context >> 63) << 64
            holders.setdefault(entity, set()).add(key)
            mentions.setdefault((entity, key), set()).add(context)
            for t in {m.lower() for m in regex.findall(pii.TERM, around)}:
                near.setdefault((entity, t), set()).add(context)
    n, out = len({(d, t or "") for d, t in rows}), {}
    for entity, keys in holders.items():
        for t in {t for t, where in held_by.items() if where & keys}:
            both = held_by[t] & keys
            evidence = near.get((entity, t), set()) | {min(mentions[entity, k]) for k in both}
            pmi, information = math.log2(n * len(both) / (len(keys) * len(held_by[t]))), math.log2(n / len(keys))
            if len(evidence) >= pii.MIN_CONTEXTS and information > 0 and pmi >= alpha * information - 1e-9:
                out[t, entity] = (pmi, information)
    return out


def test_terms_of_documents_equal_a_count_of_all_pairs(spark, sf):
    larger = sf.replace("0.001", "0.01")
    rows = [tuple(r) for r in spark.read.parquet(f"{larger}/documents.parquet").select("doc_id", "text").collect()]
    frame = spark.createDataFrame(rows, "doc_id long, text string")
    got = {(r["term"], r["entity"]): (r["pmi"], r["information"]) for r in pii.disclosing_terms(frame, pii.entities(frame)).collect()}
    want = brute_terms(rows, pii.ALPHA)
    assert set(got) == set(want) and got
    assert all(abs(got[k][0] - want[k][0]) < 1e-9 and abs(got[k][1] - want[k][1]) < 1e-9 for k in got)
    terms = {t for t, _ in want}
    texts = dict(rows)
    for r in QUERIES["op3_pii"](spark, larger).collect():
        text = texts[r["doc_id"]] or ""
        base = [s for s in h.base_spans(text).split(",") if s]
        cut = [(int(a), int(b)) for _, a, b in (s.split(":") for s in base)]
        spans = [f"term:{m.start()}:{m.end()}" for m in regex.finditer(pii.TERM, text) if m[0].lower() in terms and not any(m.start() < b and a < m.end() for a, b in cut)]
        assert sorted(r["spans"].split(",") if r["spans"] else []) == sorted(base + spans), r["doc_id"]


def test_rows_that_share_an_id_get_their_own_terms(spark):
    fill = [(i, f"plain words number{i} of other texts stand here") for i in range(30)]
    near = [(100 + i, f"word{i} ask Zebediah at zeb@mail.example.com about word{i + 50} today") for i in range(4)]
    twin = (100, "an innocent text under the same id but nothing else")
    docs = spark.createDataFrame([(*r, "own", 7) for r in [*fill, *near, twin, (None, near[0][1])]], "doc_id long, text string, __new string, row int")
    clean = pii.sanitised(docs)
    assert clean.columns == docs.columns
    texts = [r["text"] for r in clean.filter("doc_id = 100").collect()]
    assert twin[1] in texts and sum("[EMAIL]" in t and "Zebediah" not in t for t in texts) == 1
    assert "Zebediah" not in clean.filter("doc_id IS NULL").first()["text"] and clean.filter("__new = 'own' AND row = 7").count() == 36


def test_terms_are_generalised_where_a_broader_one_is_safe(spark):
    names = ["zebediah", "amelia", "bruno", "clara"]
    fill = [(i, f"ask about plain words number{i} of {names[1 + i % 3]} at a word today") for i in range(60)]
    near = [(100 + i, f"word{i} ask Zebediah at zeb@mail.example.com about Quorley word{i + 50} today") for i in range(4)]
    docs = spark.createDataFrame([*fill, *near], "doc_id long, text string")
    taxonomy = spark.createDataFrame([(n, "person") for n in names] + [("quorley", "hamlet"), ("hamlet", "place")], "term string, broader string")
    clean = by_id(pii.sanitised(docs, taxonomy=taxonomy))
    # person covers all names and so says little; hamlet and place cover nothing but the disclosing term
    assert "ask person at [EMAIL] about [REMOVED]" in clean[100]["text"]
    assert clean[5]["text"] == fill[5][1]


def test_terms_far_from_their_entity_are_found(spark):
    gap = " ".join(["plain words of other texts stand here"] * 8)
    fill = [f"plain words number{i} of other texts stand here" for i in range(30)]
    held = [f"word{i} Li and Quorley wrote {gap} to zeb@mail.example.com with Zebediah line{i}" for i in range(3)]
    held.append(f"Zebediah {gap} word9 Li, Quorley {gap} zeb@mail.example.com line9")
    rows = list(enumerate([*fill, *held, "Quorley"]))
    docs = spark.createDataFrame(rows, "doc_id long, text string")

    def terms(alpha):
        return {r["id"]: {s["value"] for s in r["spans"] if s["kind"] == "term"} for r in pii.all_spans(docs, alpha=alpha).collect()}

    strict, loose = terms(1.0), terms(0.5)
    assert all({"Li", "Zebediah"} <= strict[d] and "Quorley" not in strict[d] and "plain" not in strict[d] for d in range(30, 34))
    assert all("Quorley" in loose[d] for d in range(30, 35)) and not any(strict[d] for d in [*range(30), 34])


# --- 4 URLs ---


def brute_url(url):
    host, path = url_filter.host_and_path(url)
    rules = [("net/", "block", "net", "/"), ("example.net/en/", "allow", "example.net", "/en/"), ("example.com/de/", "block", "example.com", "/de/"), ("org/fr/", "allow", "org", "/fr/")]
    fits = [r for r in rules if (host == r[2] or host.endswith("." + r[2])) and path.startswith(r[3])]
    if fits:
        best = max(fits, key=lambda r: len(r[0]))
        return host, path, best[0], best[1]
    bad = re.search(r"(?:^|[^a-z0-9])(?:" + "|".join(url_filter.BLOCK_WORDS) + r")(?:[^a-z0-9]|$)", host)
    return host, path, None, "block" if bad else "allow"


def test_urls(spark):
    urls = [None, "", "no scheme", "http://", "HTTP://Example.NET/en/x", "http://example.net", "http://a.example.net/en", "http://net/", "http://notnet/", "https://x.org/fr/a?b#c", "http://example.com/de/", "http://example.com/DE/", "http://m.casino-win.example.org/", "http://casinos.org/", "http://h?x/en/", "http://a b.net/x", "://x.net/", "http://example.net/en/#a", "http://free-bets.com"] * 2
    pages = spark.createDataFrame([(i, u, "<p>") for i, u in enumerate(urls)], "page_id long, url string, id string")
    got = by_id(url_filter.judge_urls(pages), "page_id")
    assert [tuple(got[i][1:5]) for i in range(len(urls))] == [brute_url(u) for u in urls]
    assert url_filter.judge_urls(pages.limit(0)).count() == 0
    index = url_filter.RuleIndex(url_filter.RULES, {"example": 10**6, "net": 5, "en": 7})
    assert "en" not in index.by_token and "example.net/en/" in {r.name for r, _ in index.by_token["net"]}


def test_rules_come_from_a_table(spark):
    tokens = url_filter.literal_tokens
    assert tokens(r"(?<![a-z0-9])free\-bets(?![a-z0-9])") == ("free", "bets") and tokens(r"\Aads\.[a-z]+\.com\Z") == ("ads", "com")
    assert tokens(r"ads") == tokens(r"(?:ads|pop)\.") == tokens(r"x+ads?\.") == () and tokens(r"\.track\.") == ("track",)
    rows = [("net", "block", "net/", None, None), ("tracker", "block", None, r"(?<![a-z0-9])track[a-z]*\.", None), ("pixel", "block", None, r"\Apixel\.", "/p"), ("ours", "allow", None, r"\.ours\.example\Z", None)]
    rules = spark.createDataFrame(rows, "name string, action string, address string, host_pattern string, path_prefix string")
    urls = ["http://a.net/x", "http://tracking.org/", "http://track.ours.example/", "http://pixel.org/p1", "http://pixel.org/q", "http://plain.org/"]
    pages = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string")
    got = by_id(url_filter.judge_urls(pages, rules), "page_id")
    assert [(got[i]["rule"], got[i]["verdict"]) for i in range(6)] == [("net/", "block"), (None, "block"), (None, "allow"), (None, "block"), (None, "allow"), (None, "allow")]
    assert all(set(word.split("-")) == set(url_filter.word_rule(word).tokens) for word in url_filter.BLOCK_WORDS)


# --- 5 packing ---


def check_packing(rows, got, tokenizer):
    ids = {d: np.array([*tokenizer.encode(t or "", add_special_tokens=False).ids, 1], "<u4") for d, t in rows}
    expected = Counter()
    for d, x in ids.items():
        for k, at in enumerate(range(0, len(x), 4096)):
            expected[(d, k, at, len(x[at : at + 4096]), zlib.crc32(x[at : at + 4096].tobytes()))] += 1
    assert Counter((r["doc_id"], r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in got) == expected
    placed = defaultdict(list)
    for r in got:
        placed[r["sequence_id"]].append((r["offset"], r["length"]))
    for spans in placed.values():
        at = 0
        for offset, length in sorted(spans):
            assert offset == at
            at += length
        assert at <= 4096
    return len(placed), -(-sum(r["length"] for r in got) // 4096)


def test_packing(rows, docs, empty, small, spark, sf):
    from tokenizers import Tokenizer

    path = P.path("word_bpe_49k.json")
    tokenizer = Tokenizer.from_file(path)
    check_packing(rows, best_fit_packing.pack_documents(docs, path).collect(), tokenizer)
    bins, least = check_packing(small, QUERIES["op5_best_fit_packing"](spark, sf).collect(), tokenizer)
    assert bins <= least + 1
    assert best_fit_packing.pack_documents(empty, path).count() == 0


@settings(max_examples=60, deadline=None)
@given(st.dictionaries(st.integers(1, 40), st.integers(1, 5), max_size=10))
def test_plans_use_every_piece_and_beat_best_fit(counts):
    plan, first = best_fit_packing.pack(counts, 40, 2000), best_fit_packing.best_fit(counts, 40)
    for p in (plan, first):
        used = Counter()
        for filling, times in p:
            assert sum(filling) <= 40
            for k in filling:
                used[k] += times
        assert used == Counter(counts)
    bins = lambda p: sum(n for _, n in p)
    assert -(-sum(k * n for k, n in counts.items()) // 40) <= bins(plan) <= bins(first)


def fewest(pieces, capacity):
    """Bins by trying every piece in every bin."""
    pieces = sorted(pieces, reverse=True)
    best = len(pieces)

    def place(i, bins):
        nonlocal best
        if len(bins) >= best:
            return
        if i == len(pieces):
            best = len(bins)
            return
        for b in range(len(bins)):
            if bins[b] >= pieces[i] and bins[b] not in bins[:b]:
                place(i + 1, [*bins[:b], bins[b] - pieces[i], *bins[b + 1 :]])
        place(i + 1, [*bins, capacity - pieces[i]])

    place(0, [])
    return best


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(1, 30), min_size=1, max_size=9))
def test_exact_packing_is_proved_and_best(pieces):
    done = best_fit_packing.packed(Counter(pieces), 30, None, None)
    assert done.proved and done.bins == fewest(pieces, 30) == sum(n for _, n in done.plan) and done.bins >= done.least
    usual = best_fit_packing.packed(Counter(pieces), 30)
    assert usual.bins >= done.bins and (not usual.proved or usual.bins == done.bins)


def test_bin_completion_mends_what_best_fit_wastes():
    counts = {6: 1, 5: 2, 4: 1, 3: 2, 2: 2}  # capacity 10: 6+4, 5+5, 3+3+2+2
    assert sum(n for _, n in best_fit_packing.pack(counts, 10)) == 3


# --- 6 exact dedup ---


def test_exact_copies(rows, docs, empty, spark):
    norm = {d: h.WHITE.sub(" ", t or "") for d, t in rows}
    groups = defaultdict(list)
    for d, t in norm.items():
        groups[t].append(d)
    got = by_id(exact_dedup.classes_of(docs), "id")
    for d, t in norm.items():
        assert (got[d]["keep_id"], got[d]["group_size"], bytes(got[d]["sha"]).hex()) == (min(groups[t]), len(groups[t]), h.sha(t))
    kept = exact_dedup.kept_rows(docs)
    assert kept.columns == docs.columns and sorted(r["doc_id"] for r in kept.collect()) == sorted(min(g) for g in groups.values())
    assert exact_dedup.kept_rows(empty).count() == 0
    tied = spark.createDataFrame([(1, "a  b"), (1, "a b"), (2, "a b"), (None, "c"), (None, "c"), (None, None), (3, "")], "doc_id long, text string")
    assert sorted((r["doc_id"] is None, r["doc_id"]) for r in exact_dedup.kept_rows(tied).collect()) == [(False, 1), (False, 3), (True, None)]


def test_directory_doubles_where_cells_are_crowded(spark):
    cells = {0: 50, 1: 50, 900: 3}  # hashes by their first ten bits
    hashes = [((c << 54) | i) - ((c >> 9) << 64) for c, n in cells.items() for i in range(n)]
    counts = spark.createDataFrame([(x,) for x in hashes], "h64 long")
    got = {r["cell"]: (r["depth"], r["bucket"]) for r in exact_dedup.directory(counts, 10, 60).collect()}
    assert sorted(got) == list(range(1024))
    assert got[0] == (10, 0) and got[1] == (10, 1) and got[900] == (1, 512) and got[2] == (9, 2) and got[3] == (9, 2)
    shared = Counter(got.values())
    assert all(n == 1 << (10 - depth) for (depth, _), n in shared.items())
    alone = exact_dedup.directory(counts.limit(3), 0, 60).collect()
    assert [tuple(r) for r in alone] == [(0, 0, 0)]


def test_rows_find_their_copies_through_the_directory(spark, monkeypatch):
    rows = [(i, f"text {i % 40}") for i in range(120)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    found = {r["id"]: r for r in exact_dedup.build_index(docs, capacity=4).collect()}
    assert all(found[i]["keep_id"] == i % 40 and found[i]["group_size"] == 3 for i in found)
    assert len({r["bucket"] for r in found.values()}) > 5
    # a directory that sends each row to two buckets finds every copy twice: rows go where it says
    wrong = spark.createDataFrame([(0, 0, 0), (0, 0, 1)], "cell int, depth int, bucket int")
    assert sorted(exact_dedup.build_index(docs, cells=wrong, depth=0).groupBy("bucket").count().collect()) == [(0, 120), (1, 120)]
    # hot hashes are combined before they are shuffled, and found by whole text or by digest
    monkeypatch.setattr(exact_dedup, "HOT_ROWS", 3)
    for most in (8_000_000, 0):
        monkeypatch.setattr(exact_dedup, "MOST_BROADCAST_BYTES", most)
        hot = {r["id"]: r for r in exact_dedup.build_index(docs, capacity=4).collect()}
        assert all(hot[i]["keep_id"] == i % 40 and hot[i]["group_size"] == 3 and hot[i]["sha"] == found[i]["sha"] for i in range(120))
        assert sorted(r["doc_id"] for r in exact_dedup.kept_rows(docs).collect()) == list(range(40))


def test_inner_names_do_not_clash_with_columns(spark):
    docs = spark.createDataFrame([(1, "a  b", 5, "x", 7), (2, "a b", 6, "y", 8), (3, None, 7, "z", 9)], "doc_id long, text string, row int, h64 string, bucket int")
    kept = exact_dedup.kept_rows(docs)
    assert kept.columns == docs.columns and sorted(r["row"] for r in kept.collect()) == [5, 7]


# --- 7 byte-level BPE ---


@pytest.fixture(scope="module")
def bpe():
    import tiktoken

    ranks = byte_bpe.read_ranks(P.path("byte_bpe_50k.tiktoken"))
    return byte_bpe.Encoder(ranks, P.PATTERN), tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})


def test_bpe_equals_the_library(bpe, small, rows):
    own, library = bpe
    for _ in range(3):  # new words, and moves that are there already
        for _, text in [*small, *rows]:
            assert own.encode(text or "") == library.encode_ordinary(text or "")
        own.known.clear()
    for text in ("a" * 3000, "ab" * 2000, "=" * 777, "".join(random.Random(1).choice("abcdefgh") for _ in range(3000))):
        assert own.encode(text) == library.encode_ordinary(text)


def test_bpe_query_equals_the_library(bpe, small, spark, sf):
    _, library = bpe
    got = by_id(QUERIES["op7_byte_bpe"](spark, sf))
    for d, text in small:
        ids = library.encode_ordinary(text or "")
        assert tuple(got[d])[1:4] == (len(ids), h.sha(np.array(ids, "<u4").tobytes()), h.sha((text or "").encode()))


@settings(max_examples=300, deadline=None)
@given(st.text(max_size=60) | st.text("abest' \n\t01é😀漢<|>", max_size=60))
def test_bpe_of_any_text(bpe, text):
    own, library = bpe
    ids = own.encode(text)
    assert ids == library.encode_ordinary(text)
    by_id = own.transducer.merges.by_id
    for chunk in (1, 2, 7):
        stream = byte_bpe.StreamDecoder(by_id)
        parts = [stream.feed(ids[at : at + chunk]) for at in range(0, len(ids), chunk)]
        assert "".join(parts) + stream.close() == text and all("�" not in p or "�" in text for p in parts)


@settings(max_examples=200, deadline=None)
@given(st.binary(max_size=12))
def test_utf8_machine_agrees_with_the_codec(data):
    state = byte_bpe.Utf8Machine.START
    for b in data:
        state = state and byte_bpe.Utf8Machine.step(state, b)
    try:
        data.decode()
        valid = True
    except UnicodeDecodeError:
        valid = False
    assert valid == (state == byte_bpe.Utf8Machine.START)


def test_bpe_on_tables(rows, docs, empty, bpe):
    how = (P.path("byte_bpe_50k.tiktoken"), P.PATTERN)
    for r in byte_bpe.round_trip(docs, *how).collect():
        text = dict(rows)[r["doc_id"]] or ""
        assert np.frombuffer(bytes(r["ids"]), "<u4").tolist() == bpe[1].encode_ordinary(text) and r["decoded"] == text and r["n_tokens"] == len(r["ids"]) // 4
    decoded = byte_bpe.decode_documents(byte_bpe.encode_documents(docs, *how), *how)
    assert {r["doc_id"]: r["decoded"] for r in decoded.collect()} == {d: t or "" for d, t in rows}
    assert byte_bpe.round_trip(empty, *how).count() == 0


# --- 8 token counts ---


def test_token_counts(rows, docs, empty, small, spark, sf):
    import sentencepiece

    model = P.path("piece_bpe_32k.model")
    library = sentencepiece.SentencePieceProcessor(model_file=model)
    for own, got in ((rows, token_counts.token_counts(docs, model)), (small, QUERIES["op8_token_counts"](spark, sf))):
        got = by_id(got)
        for d, text in own:
            n = len(library.encode(text or ""))
            assert tuple(got[d])[1:] == (len((text or "").encode()), n, n > 4096)
    assert token_counts.token_counts(empty, model).count() == 0


@settings(max_examples=300, deadline=None)
@given(st.lists(st.text("ab▁ \n<s>é漢\x00", max_size=30), max_size=8))
def test_token_counts_of_any_text(texts):
    import pyarrow as pa

    own = token_counts.counter(P.path("piece_bpe_32k.model"))
    assert own.splits and own.count(pa.array(texts, pa.string())).tolist() == [own.whole(t) for t in texts]


# --- 9 near-dedup ---


@pytest.mark.parametrize("k", [4, 5])
def test_near_copies(rows, docs, empty, k):
    expected = h.near_components(rows, k)
    got = {r["id"]: (r["n_shingles"], r["component"]) for r in minmax_dedup.near_duplicates(docs, k).collect()}
    assert got == expected
    kept = minmax_dedup.kept_rows(docs, k)
    assert kept.columns == docs.columns and {r["doc_id"] for r in kept.collect()} == {d for d, (_, c) in expected.items() if c == d}
    assert minmax_dedup.kept_rows(empty).count() == 0


def test_near_copies_of_documents(spark, sf, small):
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in QUERIES["op9_minmax_dedup"](spark, sf).collect()}
    assert got == h.near_components(small, 4)


def test_large_classes_and_null_ids_are_labelled(spark, monkeypatch):
    monkeypatch.setattr(minmax_dedup, "HOT_ROWS", 5)
    rows = [(10 + i, "one two three four five six seven") for i in range(8)] + [(3, "a b c d e f g"), (40, "a b c d e f g"), (50, None), (51, " ")]
    docs = spark.createDataFrame([*rows, (None, "a b c d e f g")], "doc_id long, text string")
    found = minmax_dedup.near_duplicates(docs).collect()
    assert len(found) == 13 and {x["id"]: x["component"] for x in found} == {**{10 + i: 10 for i in range(8)}, 3: 3, 40: 3, 50: 50, 51: 51, None: None}
    assert sorted(str(r["doc_id"]) for r in minmax_dedup.kept_rows(docs).collect()) == ["10", "3", "50", "51", "None"]


def test_chains_and_crowded_buckets_lose_no_link(spark, monkeypatch):
    monkeypatch.setattr(minmax_dedup, "BLOCK", 10)
    r = random.Random(2)
    base = [f"w{r.randrange(10**6)}" for _ in range(120)]
    rows = []
    for i in range(50):  # each differs from the one before in one word, so far ends are unlike
        base[(7 * i) % 120] = f"new{i}"
        rows.append((i * 3 + 1, " ".join(base)))
    shared = [f"s{r.randrange(10**6)}" for _ in range(90)]
    rows += [(1000 + i, " ".join(shared + [f"own{i}x{j}" for j in range(40)])) for i in range(40)]  # alike but not linked
    got = {x["id"]: (x["n_shingles"], x["component"]) for x in minmax_dedup.near_duplicates(h.frame(spark, rows), 4).collect()}
    assert got == h.near_components(rows, 4)


def test_min_max_values_estimate_similarity():
    r = random.Random(3)
    for share in (0.5, 0.8, 0.95):
        common = int(2000 * share)
        a = np.unique(np.array([r.getrandbits(64) for _ in range(2000)], np.uint64))
        b = np.unique(np.concatenate([a[r.sample(range(len(a)), common)], np.array([r.getrandbits(64) for _ in range(2000 - common)], np.uint64)]))
        sa, sb = minmax_dedup.signatures([a, b])
        true = len(np.intersect1d(a, b)) / len(np.union1d(a, b))
        assert abs((sa == sb).mean() - true) < 5 * (true * (1 - true) / 252) ** 0.5


# --- 10 chat ---


def test_chat_round_trip(spark):
    r = random.Random(5)
    bits = ["a", "\\", "<", "|", "</s>", "<s>", "[INST]", "[/INST]", "\n", "<|", ">", "[", "\\<|", "é", "😀", "[\\N]", " "]
    rows = []
    for c in range(60):
        for t in range(r.randrange(1, 6)):
            text = lambda: None if r.random() < 0.05 else "".join(r.choice(bits) for _ in range(r.randrange(12)))
            rows.append((c, t if r.random() < 0.9 else None, r.choice(["user", "assistant", "system", None, text()]), text()))
    rows += rows[:5]
    given_ = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").repartition(3)
    out = chat_format.parse(chat_format.format_conversations(chat_format.events_of(given_))).collect()
    expected = defaultdict(list)
    for c, t, role, text in rows:
        expected[c].append(((t is not None, t or 0), role or "", text or ""))
    assert len(out) == len(expected)
    for o in out:
        turns = [x[1:] for x in sorted(expected[o["conv_id"]])]
        assert [tuple(t) for t in o["turns"]] == turns
        assert o["loss_texts"] == [t for role, t in turns if role == "assistant"]
    assert chat_format.format_conversations(chat_format.events_of(given_.limit(0))).count() == 0


def test_event_log_folds_deltas_edits_and_regenerations(spark):
    log = [
        (1, 1, "message", None, "user", "Hi"),
        (1, 2, "delta", None, None, " there"),
        (1, 3, "message", None, "assistant", "He"),
        (1, 4, "delta", None, None, "llo"),
        (1, 5, "regenerate", None, None, ""),
        (1, 6, "delta", None, None, "Good "),
        (1, 7, "delta", None, None, "day"),
        (1, 8, "edit", 1, None, "Hey"),
        (1, 9, "delta", 1, None, "!"),
        (2, 1, "message", None, "user", None),
    ]
    events = spark.createDataFrame(log, "conv_id long, seq long, kind string, target long, role string, text string").repartition(4)
    got = sorted(tuple(r) for r in chat_format.fold(events).collect())
    assert got == [(1, 1, "user", "Hey!"), (1, 2, "assistant", "Good day"), (2, 1, "user", "")]


# --- all queries ---


@pytest.mark.parametrize("name", sorted(oracles.ORACLES))
def test_query_equals_its_sql(name, spark, sf, duck):
    got = QUERIES[name](spark, sf).toPandas()
    expected = duck.execute(oracles.ORACLES[name]).df()
    assert sorted(got.columns) == sorted(expected.columns)
    clean = lambda f: sorted(map(repr, f[sorted(f.columns)].astype(object).where(f[sorted(f.columns)].notna(), None).values.tolist()))
    assert clean(got) == clean(expected)


def test_native_operators_run_no_python(spark, sf):
    for name in ("op1_quality_rules", "op3_pii", "op6_exact_dedup", "op10_chat_format"):
        plan = QUERIES[name](spark, sf)._jdf.queryExecution().executedPlan().toString()
        assert not re.search("Python|Arrow|Pandas", plan), name


def test_one_query_for_each_operator():
    assert sorted(int(re.match(r"op(\d+)_", q)[1]) for q in QUERIES) == list(range(1, 11))
