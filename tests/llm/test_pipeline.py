"""The pipeline's stages on awkward documents, stage by stage against brute force."""

from __future__ import annotations

import public_tokenizers as P
from tokenizers import Tokenizer

import corpus_pipeline
from hotkeys.llm import common, quality_rules
from hotkeys.shipping import ship
from tests.llm import helpers as h
from tests.llm.test_operators import check_packing


def test_stages(spark, sf):
    ship(spark)
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text", "lang", "source", "n_chars")
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality", "exact", "near", "sanitise", "pack"]
    stage = dict(corpus_pipeline.STAGES)
    start = {r["doc_id"]: r["text"] for r in docs.collect()}
    judged = {r["doc_id"]: r["kept"] for r in quality_rules.judge(docs).collect()}

    kept = stage["quality"](spark, docs, sf).persist()
    assert kept.columns == docs.columns and {r["doc_id"] for r in kept.collect()} == {d for d, ok in judged.items() if ok}

    unique = stage["exact"](spark, kept, sf).persist()
    first = {}
    for d in sorted(d for d, ok in judged.items() if ok):
        first.setdefault(h.WHITE.sub(" ", start[d] or ""), d)
    assert {r["doc_id"] for r in unique.collect()} == set(first.values())

    apart = stage["near"](spark, unique, sf).persist()
    components = h.near_components([(r["doc_id"], r["text"]) for r in unique.collect()], 5)
    assert {r["doc_id"] for r in apart.collect()} == {d for d, (_, c) in components.items() if c == d}

    clean = stage["sanitise"](spark, apart, sf).persist()
    assert clean.columns == docs.columns and clean.count() == apart.count()
    for r in clean.collect():
        assert not h.base_spans(r["text"]) or h.base_spans(start[r["doc_id"]])
        if not h.base_spans(start[r["doc_id"]]) and "[REMOVED]" not in r["text"]:
            assert r["text"] == start[r["doc_id"]]

    packed = stage["pack"](spark, clean, sf).collect()
    bins, least = check_packing([(r["doc_id"], r["text"]) for r in clean.collect()], packed, Tokenizer.from_file(P.path("word_bpe_49k.json")))
    assert bins <= least + 1
    whole = corpus_pipeline.run(spark, sf).collect()
    columns = ["doc_id", "piece", "start", "length", "ids_crc32"]
    assert sorted(tuple(r[c] for c in columns) for r in whole) == sorted(tuple(r[c] for c in columns) for r in packed)


def test_empty_table_goes_through(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").limit(0)
    for _, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, sf)
    assert docs.count() == 0


def test_clashing_columns_and_nulls_go_through_and_tables_are_cleared(spark, tmp_path):
    ship(spark)
    words = " ".join(f"the word{i} and of{i}" for i in range(40))
    rows = [(1, words, "en", "web", 5, "a", 1, "x"), (2, words.replace(" ", "  "), None, None, None, "b", 2, None), (3, None, "en", "web", 5, "c", 3, "y"), (None, words + " more", "en", "web", 5, "d", 4, "z")]
    folder = str(tmp_path)
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, __h64 string, row int, id string").write.parquet(f"{folder}/documents.parquet")
    found = corpus_pipeline.run(spark, folder).collect()
    assert {r["doc_id"] for r in found} <= {1, None} and found
    assert common.clear(spark) > 0 and common.clear(spark) == 0
