"""Suffix-array dedup: removes every byte of a 100-byte string that also starts earlier.

A full suffix array of a corpus is many times its size. Here the suffixes are first thinned without
losing a match. In each 100-byte window the least-hashed 40-gram is its anchor; equal windows have
their anchors at the same place, so only windows of one anchor can be equal, and a run of windows
with one anchor is one row: (anchor hash, context hash, document, place). Rows of one anchor and
context are copies of one another, and all but the earliest are repeats; each batch combines
its copies before the shuffle, so that a passage in every document is no hot key.

What is left is anchors with different contexts, at the ends of repeats. Their contexts' windows are
suffix-sorted by bucket-pointer refinement: buckets of 8-grams are refined by the bucket pointers at
offset 8, the result by its own pointers at 16, and so on to depth 100. A refinement touches only
buckets that still have several suffixes, and reads the pointers that the last one updated. Windows
that end in one bucket are equal; all but the first are repeats.

Order is by document id and then start. Defined results: null text counts as empty; texts under 100
bytes keep all; a null id counts as after all others, with at most one such row; rows that repeat an
id are one document, so they don't make each other repeats; other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hotkeys.llm.common import sized_broadcast, table, text_of, written

WINDOW = 100
GRAM = 40
CHUNK_BYTES = 131_072
#: Bytes of contexts that are suffix-sorted at once; whole anchors only.
SORT_BYTES = 4_000_000
#: Contexts of one anchor from which on its windows are dealt over all tasks.
CROWDED = 1_000
LAST_ID = (1 << 63) - 1

_RANDOM = np.random.Generator(np.random.PCG64(7_2024))
_GRAM_BYTES = _RANDOM.integers(0, 1 << 64, 256, np.uint64)
_CONTEXT_BYTES = _RANDOM.integers(0, 1 << 64, 256, np.uint64)
_BASE = np.uint64(0xD1342543DE82EF95)
_MIX = np.uint64(0x9E3779B97F4A7C15)
_OTHER_BASE = np.uint64(0xC2B2AE3D27D4EB4F)


def _powers(base: np.uint64, n: int) -> np.ndarray:
    out = np.full(n, base, np.uint64)
    out[0] = 1
    return np.multiply.accumulate(out)


_INVERSE = np.uint64(pow(int(_BASE), -1, 1 << 64))


def _mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(32))) * _MIX
    x = (x ^ (x >> np.uint64(29))) * _BASE
    return x ^ (x >> np.uint64(32))


def gram_hashes(data: np.ndarray) -> np.ndarray:
    """Hash of the 40-gram at every place, by doubling."""
    h, size, kept = _GRAM_BYTES[data], 1, {}
    while True:
        if size == 8:
            kept[8] = h
        if size == 32:
            break
        factor = np.uint64(pow(int(_BASE), size, 1 << 64))
        h = h[:-size] * factor + h[size:]
        size *= 2
    n = len(data) - GRAM + 1
    factor = np.uint64(pow(int(_BASE), 8, 1 << 64))
    return _mixed(h[:n] * factor + kept[8][32 : 32 + n])


def anchors_of_windows(h: np.ndarray) -> np.ndarray:
    """For every window start the place of its anchor: the leftmost of the least hashes."""
    width = WINDOW - GRAM + 1
    least, at, size = h, np.arange(len(h), dtype=np.int32), 1
    while 2 * size <= width:
        left, right = least[:-size], least[size:]
        later = right < left
        least, at = np.where(later, right, left), np.where(later, at[size:], at[:-size])
        size *= 2
    shift = width - size
    left, right = least[: len(least) - shift], least[shift:]
    return np.where(right < left, at[shift:], at[: len(at) - shift])


def chunk_runs(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, ...]:
    """Runs of windows with one anchor in the documents data[start:end].

    Returns row (document), a (first window's start in it), span (windows - 1), off (anchor - a), the
    anchor's hash and the context's hash.
    """
    empty = np.empty(0, np.int64)
    if len(data) < WINDOW:
        return empty, empty, empty, empty, empty, empty
    h = gram_hashes(data)
    at = anchors_of_windows(h)
    valid = np.zeros(len(at), bool)
    for s, e in zip(starts.tolist(), ends.tolist(), strict=True):
        if e - s >= WINDOW:
            valid[s : e - WINDOW + 1] = True
    windows = np.flatnonzero(valid)
    if not len(windows):
        return empty, empty, empty, empty, empty, empty
    anchor = at[windows]
    new = np.empty(len(windows), bool)
    new[0] = True
    new[1:] = (anchor[1:] != anchor[:-1]) | (windows[1:] != windows[:-1] + 1)
    first = np.flatnonzero(new)
    last = np.append(first[1:], len(windows)) - 1
    a, b, place = windows[first], windows[last], anchor[first].astype(np.int64)
    sums = np.zeros(len(data) + 1, np.uint64)
    np.cumsum(_CONTEXT_BYTES[data] * _powers(_BASE, len(data)), out=sums[1:])
    span, off = b - a, place - a
    content = (sums[b + WINDOW] - sums[a]) * _powers(_INVERSE, len(data))[a]
    context = _mixed(content + (span * 64 + off).astype(np.uint64) * _MIX)
    row = np.searchsorted(starts, a, side="right") - 1
    return row, a - starts[row], span, off, h[place].view(np.int64), context.view(np.int64)


def _packed(a: np.ndarray, span: np.ndarray, off: np.ndarray, repeat: np.ndarray) -> np.ndarray:
    return (a << 17) | (repeat.astype(np.int64) << 16) | (span << 8) | off


def batch_rows(ids: np.ndarray, texts: list[bytes]) -> tuple[np.ndarray, ...]:
    """anchor, context, id and place of every run of a batch; copies within the batch are marked."""
    order = np.argsort(ids, kind="stable")
    parts, at = [], 0
    while at < len(order):
        end, size = at, 0
        while end < len(order) and (size < CHUNK_BYTES or end == at):
            size += len(texts[order[end]])
            end += 1
        own = order[at:end]
        data = np.frombuffer(b"".join([texts[i] for i in own]), np.uint8)
        bounds = np.cumsum([0, *[len(texts[i]) for i in own]])
        row, *rest = chunk_runs(data, bounds[:-1], bounds[1:])
        parts.append((ids[own][row] if len(row) else np.empty(0, np.int64), *rest))
        at = end
    doc, a, span, off, anchor, context = (np.concatenate([p[i] for p in parts]) if parts else np.empty(0, np.int64) for i in range(6))
    return marked(anchor, context, doc, a, span, off)


def marked(anchor: np.ndarray, context: np.ndarray, doc: np.ndarray, a: np.ndarray, span: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, ...]:
    """anchor, context, id and place of rows given in order of id and start; all but the first of equal ones are marked.

    Rows are equal if both hashes, 128 bits, are. Marked rows need no further look and are spread over all tasks.
    """
    by_key = np.lexsort((context, anchor))  # stable, so each key's first is its earliest
    sorted_anchor, sorted_context, sorted_doc, sorted_a = anchor[by_key], context[by_key], doc[by_key], a[by_key]
    head = np.ones(len(anchor), bool)
    head[1:] = (sorted_anchor[1:] != sorted_anchor[:-1]) | (sorted_context[1:] != sorted_context[:-1])
    lead = np.flatnonzero(head)[np.cumsum(head) - 1] if len(anchor) else by_key
    repeat = np.zeros(len(anchor), bool)
    repeat[by_key] = ~head & ((sorted_doc != sorted_doc[lead]) | (sorted_a != sorted_a[lead]))
    spread = np.where(repeat, _mixed(anchor.view(np.uint64) + np.arange(len(anchor), dtype=np.uint64)).view(np.int64), anchor)
    return spread, context, doc, _packed(a, span, off, repeat)


def runs(texts: DataFrame) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            column = batch.column("text").cast(pa.binary())
            arrays = batch_rows(batch.column("id").to_numpy(), column.to_pylist())
            for at in range(0, len(arrays[0]), 100_000):
                yield pa.RecordBatch.from_arrays([pa.array(x[at : at + 100_000]) for x in arrays], ["anchor", "context", "id", "place"])

    return texts.mapInArrow(run, "anchor long, context long, id long, place long")


def settled(found: DataFrame) -> DataFrame:
    """Runs (id, a, b) that are repeats, and with their anchor those whose windows must be sorted."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["anchor", "id", "a", "b", "off", "open"]
        last: tuple[int, int, int, int] | None = None  # anchor, context, id and a of the latest context's first run
        waiting: tuple[int, int, int, int, int] | None = None  # an anchor's first run, open if another context follows

        def out(anchor, doc, a, b, off, is_open) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(np.asarray(x, np.int64)) for x in (anchor, doc, a, b, off)] + [pa.array(np.asarray(is_open, bool))], names)

        for batch in batches:
            anchor, context, doc, place = (c.to_numpy() for c in batch.columns)
            a, span, off, marked = place >> 17, (place >> 8) & 0xFF, place & 0xFF, (place >> 16 & 1).astype(bool)
            if marked.any():
                k = np.flatnonzero(marked)
                yield out(anchor[k], doc[k], a[k], a[k] + span[k], off[k], np.zeros(len(k), bool))
                keep = np.flatnonzero(~marked)
                anchor, context, doc, a, span, off = (x[keep] for x in (anchor, context, doc, a, span, off))
            n = len(anchor)
            if not n:
                continue
            before = last or (None, None, 0, 0)
            new_anchor, new_context = np.ones(n, bool), np.ones(n, bool)
            new_anchor[1:] = anchor[1:] != anchor[:-1]
            new_context[1:] = new_anchor[1:] | (context[1:] != context[:-1])
            if last:
                new_anchor[0] = anchor[0] != last[0]
                new_context[0] = new_anchor[0] or context[0] != last[1]
            heads = np.flatnonzero(new_context)
            group = np.cumsum(new_context) - 1  # -1: goes on from the batch before
            head_doc, head_a = np.append(doc[heads], before[2]), np.append(a[heads], before[3])
            repeat = np.flatnonzero(~new_context & ((doc != head_doc[group]) | (a != head_a[group])))
            if len(repeat):
                yield out(anchor[repeat], doc[repeat], a[repeat], a[repeat] + span[repeat], off[repeat], np.zeros(len(repeat), bool))
            if len(heads):
                fresh = new_anchor[heads]
                if waiting and not fresh[0]:
                    yield out(*[[x] for x in waiting], [True])
                followed = np.append(~fresh[1:], False)
                is_open = np.flatnonzero(~fresh | followed)
                if len(is_open):
                    k = heads[is_open]
                    yield out(anchor[k], doc[k], a[k], a[k] + span[k], off[k], np.ones(len(k), bool))
                k = heads[-1]
                waiting = tuple(int(x[k]) for x in (anchor, doc, a, a + span, off)) if fresh[-1] else None
                last = (int(anchor[k]), int(context[k]), int(doc[k]), int(a[k]))

    dealt = found.repartition("anchor").sortWithinPartitions("anchor", "context", "id", "place")
    return dealt.mapInArrow(run, "anchor long, id long, a long, b long, off long, open boolean")


def contexts(texts: DataFrame, opened: DataFrame) -> DataFrame:
    """The bytes of every open run: (anchor, id, a, bytes)."""
    lists = opened.groupBy("id").agg(F.collect_list(F.struct("anchor", "a", "b")).alias("open_runs"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 200):
                part = batch.slice(at, 200)
                anchors, ids, starts, cuts = [], [], [], []
                for doc, text, open_runs in zip(part.column("id").to_pylist(), part.column("text").cast(pa.binary()).to_pylist(), part.column("open_runs").to_pylist(), strict=True):
                    for r in open_runs:
                        if r["b"] + WINDOW <= len(text):
                            anchors.append(r["anchor"])
                            ids.append(doc)
                            starts.append(r["a"])
                            cuts.append(text[r["a"] : r["b"] + WINDOW])
                long = lambda x: pa.array(x, pa.int64())
                yield pa.RecordBatch.from_arrays([long(anchors), long(ids), long(starts), pa.array(cuts, pa.binary())], ["anchor", "id", "a", "bytes"])

    return texts.join(lists, "id").select("id", "text", "open_runs").mapInArrow(run, "anchor long, id long, a long, bytes binary")


def _ranks(first: np.ndarray, second: np.ndarray) -> np.ndarray:
    """Bucket pointers of pairs of bucket pointers."""
    key = first.astype(np.uint64) << np.uint64(32) | second.astype(np.uint64)
    return np.unique(key, return_inverse=True)[1]


def refined(data: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """Bucket pointers at depth 100 of the suffixes at starts, by bucket-pointer refinement.

    Every start has 100 bytes. Suffixes have equal pointers exactly if their first 100 bytes are equal.
    """
    n = len(data)
    gram = np.zeros(n, np.uint64)
    padded = np.append(data, np.zeros(8, np.uint8)).astype(np.uint64)
    for k in range(8):
        gram = gram << np.uint64(8) | padded[k : n + k]
    pointer = np.unique(gram, return_inverse=True)[1].astype(np.int64)
    depth = 8
    while depth < 64:
        count = np.bincount(pointer)
        active = np.flatnonzero(count[pointer] > 1)
        active = active[active + 2 * depth <= n]
        fine = _ranks(pointer[active], pointer[active + depth])
        # a refined bucket gets pointers behind all old ones; suffixes alone in theirs keep them
        pointer = pointer.copy()
        pointer[active] = fine + len(count)
        pointer = np.unique(pointer, return_inverse=True)[1].astype(np.int64)
        depth *= 2
    return _ranks(pointer[starts], pointer[starts + WINDOW - depth])


def repeats_among(anchor: np.ndarray, doc: np.ndarray, a: np.ndarray, cuts: list[bytes]) -> tuple[np.ndarray, ...]:
    """Runs (id, first, last start) of repeated windows; rows come by anchor, id and a."""
    data = np.frombuffer(b"".join(cuts), np.uint8)
    sizes = np.array([len(c) for c in cuts])
    base = np.cumsum(sizes) - sizes
    windows = sizes - WINDOW + 1
    row = np.repeat(np.arange(len(cuts)), windows)
    inside = np.arange(len(row)) - np.repeat(np.cumsum(windows) - windows, windows)
    starts = base[row] + inside
    bucket = refined(data, starts)
    order = np.argsort(bucket, kind="stable")
    head = np.ones(len(order), bool)
    head[1:] = bucket[order][1:] != bucket[order][:-1]
    lead = order[np.flatnonzero(head)[np.cumsum(head) - 1]]
    repeat = np.zeros(len(order), bool)
    repeat[order] = ~head & ((doc[row[order]] != doc[row[lead]]) | (a[row[order]] + inside[order] != a[row[lead]] + inside[lead]))
    hit = np.flatnonzero(repeat)
    if not len(hit):
        empty = np.empty(0, np.int64)
        return empty, empty, empty
    new = np.ones(len(hit), bool)
    new[1:] = (hit[1:] != hit[:-1] + 1) | (row[hit[1:]] != row[hit[:-1]])
    first = hit[new]
    last = hit[np.append(np.flatnonzero(new)[1:], len(hit)) - 1]
    return doc[row[first]], a[row[first]] + inside[first], a[row[last]] + inside[last]


def sorted_repeats(found: DataFrame) -> DataFrame:
    """Repeats (id, a, b) among the contexts of each anchor."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        size = 0

        def solve(rows: pa.Table) -> pa.RecordBatch:
            columns = [rows.column(c).to_numpy() for c in ("anchor", "id", "a")]
            parts = repeats_among(*columns, rows.column("bytes").to_pylist())
            return pa.RecordBatch.from_arrays([pa.array(p.astype(np.int64)) for p in parts], ["id", "a", "b"])

        for batch in batches:
            for at in range(0, batch.num_rows, 2_000):
                part = batch.slice(at, 2_000)
                held.append(part)
                size += part.column("bytes").nbytes
                if size > SORT_BYTES:
                    rows = pa.Table.from_batches(held)
                    anchor = rows.column("anchor").to_numpy()
                    cut = int(np.searchsorted(anchor, anchor[-1]))  # the last anchor may go on
                    if cut:
                        yield solve(rows.slice(0, cut))
                        held = rows.slice(cut).combine_chunks().to_batches()
                        size = sum(b.column("bytes").nbytes for b in held)
        if held and sum(b.num_rows for b in held):
            yield solve(pa.Table.from_batches(held))

    dealt = found.repartition("anchor").sortWithinPartitions("anchor", "id", "a")
    return dealt.mapInArrow(run, "id long, a long, b long")


def window_pointers(data: np.ndarray, base: np.uint64, start: np.ndarray) -> np.ndarray:
    """Bucket pointers at depth 100 of the windows at start, named by hashes, so that tasks can make them apart.

    As in the refinement, a pointer at twice the depth is made of two pointers: that of the place and that of the place behind it.
    """
    pointer, depth = _CONTEXT_BYTES[data] * base, 1
    while 2 * depth <= WINDOW:
        pointer = _mixed(pointer[:-depth] * base + pointer[depth:])
        depth *= 2
    return _mixed(pointer[start] * base + pointer[start + WINDOW - depth] * _MIX).view(np.int64)


def pointed_repeats(found: DataFrame) -> DataFrame:
    """Repeats (id, a, b) among the contexts of crowded anchors, window by window over all tasks.

    A batch marks what repeats in it; of the rest each window goes to the task of its pointers.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 2_000):
                part = batch.slice(at, 2_000)
                order = np.lexsort((part.column("a").to_numpy(), part.column("id").to_numpy()))
                cuts = part.column("bytes").take(pa.array(order)).to_pylist()
                doc, first = part.column("id").to_numpy()[order], part.column("a").to_numpy()[order]
                sizes = np.array([len(c) for c in cuts])
                windows = sizes - WINDOW + 1
                row = np.repeat(np.arange(len(cuts)), windows)
                inside = np.arange(len(row)) - np.repeat(np.cumsum(windows) - windows, windows)
                start = (np.cumsum(sizes) - sizes)[row] + inside
                data = np.frombuffer(b"".join(cuts), np.uint8)
                none = np.zeros(len(row), np.int64)
                arrays = marked(window_pointers(data, _BASE, start), window_pointers(data, _OTHER_BASE, start), doc[row], first[row] + inside, none, none)
                for lo in range(0, len(row), 100_000):
                    yield pa.RecordBatch.from_arrays([pa.array(x[lo : lo + 100_000]) for x in arrays], ["anchor", "context", "id", "place"])

    return settled(found.select("id", "a", "bytes").mapInArrow(run, "anchor long, context long, id long, place long")).filter("NOT open").select("id", "a", "b")


def removed_spans(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", crowded: int = CROWDED) -> DataFrame:
    """id, text and runs: the repeated windows' first and last starts, null where there is none."""
    spark = docs.sparkSession
    texts = docs.select(F.coalesce(F.col(f"`{id_col}`").cast("long"), F.lit(LAST_ID)).alias("id"), text_of(text_col).alias("text"))
    known = written(spark, settled(runs(texts)), "repeat-runs")
    dealt = texts.repartition("id")  # both joins read this exchange
    opened = known.filter("open").select("id", "anchor", "a", "b")
    spans = known.filter("NOT open").select("id", "a", "b")
    # anchors with so many contexts are few: at most one for each `crowded` open runs
    busy = written(spark, opened.groupBy("anchor").agg(F.count("*").alias("n")).filter(F.col("n") > crowded).select("anchor"), "crowded-anchors")
    n_busy = busy.count()
    found = contexts(dealt, opened)
    if n_busy:
        few = sized_broadcast(busy, n_busy, 500_000)
        found = written(spark, found, "contexts")
        spans = spans.union(pointed_repeats(found.join(few, "anchor", "left_semi")))
        found = found.join(few, "anchor", "left_anti")
    spans = spans.union(sorted_repeats(found))
    return dealt.join(spans.groupBy("id").agg(F.collect_list(F.struct("a", "b")).alias("runs")), "id", "left").select("id", "text", "runs")


def cut_spans(found: DataFrame) -> DataFrame:
    """id, spans (array of start and end in bytes), n_bytes, n_removed and kept (the bytes left)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        span_type = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))
        for batch in batches:
            for at in range(0, batch.num_rows, 200):
                part = batch.slice(at, 200)
                texts = part.column("text").cast(pa.binary()).to_pylist()
                spans, removed, kept = [], [], []
                for text, own in zip(texts, part.column("runs").to_pylist(), strict=True):
                    merged: list[list[int]] = []
                    for a, b in sorted((r["a"], r["b"] + WINDOW) for r in own or ()):
                        if merged and a <= merged[-1][1]:
                            merged[-1][1] = max(merged[-1][1], b)
                        else:
                            merged.append([a, b])
                    edges = [0, *[x for m in merged for x in m], len(text)]
                    spans.append([{"start": a, "end": b} for a, b in merged])
                    removed.append(sum(b - a for a, b in merged))
                    kept.append(b"".join([text[a:b] for a, b in zip(edges[::2], edges[1::2], strict=True)]))
                yield pa.RecordBatch.from_arrays(
                    [part.column("id"), pa.array(spans, span_type), pa.array([len(t) for t in texts], pa.int64()), pa.array(removed, pa.int64()), pa.array(kept, pa.binary())], ["id", "spans", "n_bytes", "n_removed", "kept"]
                )

    return found.mapInArrow(run, "id long, spans array<struct<start:long,end:long>>, n_bytes long, n_removed long, kept binary")


def without_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The spans that each document loses and the bytes that it keeps."""
    return cut_spans(removed_spans(docs, id_col, text_col))


def op2_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = without_repeats(table(spark, sf_dir, "documents"))
    doc_id = F.when(F.col("id") < LAST_ID, F.col("id")).alias("doc_id")
    return found.select(doc_id, "n_bytes", "n_removed", F.size("spans").cast("long").alias("n_spans"), F.sha2("kept", 256).alias("kept_sha256"))
