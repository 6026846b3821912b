"""Hashed-counter sketches: Count-Min, Count Sketch, and either with candidates that are kept beside them.

Tasks fill matrices of a fixed size from their arrivals; what is shuffled is the matrices' cells and few candidates,
whatever the number of distinct elements.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from hotkeys.frames import keep
from hotkeys.operators import owner_split as engine
from hotkeys.operators.exact import over_threshold
from hotkeys.spec import SupportSpec, exact


def width_of(eps) -> int:
    return math.ceil(math.e / float(eps))


def depth_of(delta: float) -> int:
    return math.ceil(math.log(1 / delta))


def _at(width: int, depth: int, seed: int, signed: bool) -> list:
    """An element's cell in each row, counted from 1; its sign is the counter's."""
    cells = [F.pmod(F.xxhash64("e", F.lit(seed + r)), F.lit(width)) + 1 for r in range(depth)]
    signs = [F.pmod(F.xxhash64("e", F.lit(seed + 7919 + r)), F.lit(2)) * 2 - 1 for r in range(depth)]
    return [(c * s if signed else c).alias(f"at{r}") for r, (c, s) in enumerate(zip(cells, signs, strict=True))]


def _hashed(elements: DataFrame, width: int, depth: int, seed: int, signed: bool) -> DataFrame:
    cells = elements.select("e", F.posexplode(F.array(*_at(width, depth, seed, signed))).alias("row", "at"))
    return cells.select("e", "row", (F.abs("at") - 1).alias("cell"), F.signum("at").cast("long").alias("sign"))


def passed(stream: DataFrame, width: int, depth: int, seed: int = 42, signed: bool = False, share=None) -> DataFrame:
    """One pass of every task over its arrivals: (row, cell, c) of its matrix, and with a share its candidates as (-1, e).

    A task holds width * depth counters whatever it reads. Its candidates are the elements whose estimate was over
    the share of its arrivals when they last came; at 4 / share of them, and at twice as many as stayed the last time, those
    that have fallen under it go. What is frequent in the stream is so in some task, so none is missing where estimates are not low.
    """
    share = exact(share) if share is not None else None
    given = stream.select("e", F.col("w").cast("long").alias("w"), F.xxhash64("e", F.lit(seed - 1)).alias("h"), *_at(width, depth, seed, signed))
    schema = T.StructType([T.StructField("row", T.IntegerType()), T.StructField("cell", T.LongType()), T.StructField("c", T.LongType()), T.StructField("e", stream.schema["e"].dataType)])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        matrix, n, kind = np.zeros((depth, width), np.int64), 0, None
        known: dict = {}  # candidate -> its cells
        most = 4 / share if share else math.inf

        def estimate(at: np.ndarray) -> np.ndarray:
            found = np.stack([matrix[r, np.abs(at[r]) - 1] * np.sign(at[r]) for r in range(depth)])
            return np.median(found, axis=0) if signed else found.min(axis=0)

        for batch in batches:
            kind = batch.column("e").type
            _, first, place = np.unique(batch.column("h").to_numpy(), return_index=True, return_inverse=True)
            if not len(first):
                continue
            w = np.zeros(len(first), np.int64)
            np.add.at(w, place, batch.column("w").to_numpy())
            n += int(w.sum())
            at = np.stack([batch.column(f"at{r}").to_numpy()[first] for r in range(depth)])
            for r in range(depth):
                np.add.at(matrix[r], np.abs(at[r]) - 1, w * np.sign(at[r]))
            if share is not None:
                over = np.flatnonzero(estimate(at) * share.denominator >= share.numerator * n)
                known.update(zip(engine.keys(batch.column("e").take(pa.array(first[over]))), at[:, over].T, strict=True))
                if len(known) > most:
                    still = estimate(np.stack(list(known.values())).T) * share.denominator >= share.numerator * n
                    known = {e: x for (e, x), stays in zip(known.items(), still, strict=True) if stays}
                    most = max(most, 2 * len(known))
        row, cell = np.nonzero(matrix)
        if len(row):
            yield pa.RecordBatch.from_arrays([pa.array(row, pa.int32()), pa.array(cell), pa.array(matrix[row, cell]), pa.nulls(len(row), kind)], ["row", "cell", "c", "e"])
        if known:
            k = len(known)
            yield pa.RecordBatch.from_arrays([pa.array([-1] * k, pa.int32()), pa.nulls(k, pa.int64()), pa.nulls(k, pa.int64()), engine.restored(list(known), kind)], ["row", "cell", "c", "e"])

    return given.mapInArrow(run, schema)


def _matrix(made: DataFrame) -> DataFrame:
    return made.filter("row >= 0").groupBy("row", "cell").agg(F.sum("c").alias("c"))


def sketch(stream: DataFrame, width: int, depth: int, seed: int = 42, signed: bool = False) -> DataFrame:
    """(row, cell, c): at most width * depth counters; sketches of one seed and size add up."""
    return _matrix(passed(stream, width, depth, seed, signed))


def merge(left: DataFrame, right: DataFrame) -> DataFrame:
    return left.unionByName(right).groupBy("row", "cell").agg(F.sum("c").alias("c"))


def estimates(counters: DataFrame, elements: DataFrame, width: int, depth: int, seed: int = 42, signed: bool = False) -> DataFrame:
    """(e, est): the least counter of an element, or for a signed sketch the median."""
    found = _hashed(elements.select("e"), width, depth, seed, signed).join(counters, ["row", "cell"], "left")
    value = F.coalesce(F.col("c") * F.col("sign"), F.lit(0))
    if signed:
        return found.groupBy("e").agg(F.sort_array(F.collect_list(value)).alias("v")).select("e", F.expr("cast(floor((v[cast((size(v) - 1) div 2 as int)] + v[cast(size(v) div 2 as int)]) / 2) as bigint)").alias("est"))
    return found.groupBy("e").agg(F.min(value).alias("est"))


def count_min(stream: DataFrame, spec: SupportSpec, delta: float = 0.01, seed: int = 42, width: int | None = None, depth: int | None = None) -> DataFrame:
    """Frequent elements by Count-Min estimates, which are never low, of the candidates that the tasks keep."""
    width, depth = width or width_of(spec.eps), depth or depth_of(delta)
    made = keep(passed(stream, width, depth, seed, share=spec.phi))
    found = estimates(_matrix(made), made.filter("row = -1").select("e").distinct(), width, depth, seed)
    return _over(found, stream, spec, low=False)


def count_sketch(stream: DataFrame, spec: SupportSpec, width: int | None = None, depth: int = 5, seed: int = 42) -> DataFrame:
    """Frequent elements by Count Sketch estimates, which may be high or low; candidates from phi - eps on."""
    width = width or width_of(spec.eps)
    made = keep(passed(stream, width, depth, seed, True, share=spec.phi - spec.eps))
    found = estimates(_matrix(made), made.filter("row = -1").select("e").distinct(), width, depth, seed, True)
    return _over(found, stream, spec, low=True)


def _over(found: DataFrame, stream: DataFrame, spec: SupportSpec, low: bool) -> DataFrame:
    n = stream.agg(F.coalesce(F.sum("w"), F.lit(0)).alias("n"))
    slack = F.ceil(F.col("n") * F.lit(float(spec.eps))).cast("long")
    kept = found.crossJoin(F.broadcast(n)).filter(over_threshold("est", "n", spec.phi))
    return kept.select("e", "est", F.greatest(F.col("est") - slack, F.lit(0)).alias("lower"), (F.col("est") + slack if low else F.col("est")).alias("upper"))


def candidates(stream: DataFrame, k: int) -> DataFrame:
    """Elements that one task counts among its k most frequent: the heap kept beside a sketch."""
    given = stream.select("e", F.col("w").cast("long").alias("w"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from hotkeys.kernels.minmax import MinMaxSummary

        own, kind = MinMaxSummary(max(1_000, 20 * k)), None
        for batch in batches:
            kind = batch.column("e").type
            for e, w in zip(engine.keys(batch.column("e")), batch.column("w").to_pylist(), strict=True):
                own.update(e, w)
        if kind is not None:
            yield pa.RecordBatch.from_arrays([engine.restored([e for e, _ in own.top_k(2 * k)], kind)], ["e"])

    return given.mapInArrow(run, T.StructType([stream.schema["e"]])).distinct()


def sketch_topk(stream: DataFrame, k: int, width: int, depth: int, seed: int = 42, signed: bool = False) -> DataFrame:
    """(e, est) of the k greatest sketch estimates among the tasks' candidates."""
    found = estimates(sketch(stream, width, depth, seed, signed), candidates(stream, k), width, depth, seed, signed)
    return found.orderBy(F.desc("est"), "e").limit(k)


def builtin_topk(stream: DataFrame, k: int, most_items: int = 10_000) -> DataFrame:
    """(e, est) by Spark's own approximate top-k aggregate, as a further reference."""
    rows = stream.select(F.explode(F.array_repeat("e", F.col("w").cast("int"))).alias("e"))
    found = rows.agg(F.expr(f"approx_top_k(e, {k}, {most_items})").alias("t"))
    return found.select(F.explode("t").alias("x")).select(F.col("x.item").alias("e"), F.col("x.count").alias("est"))


def builtin_topk_merged(stream: DataFrame, by: str, k: int, most_items: int = 10_000) -> DataFrame:
    """(e, est) by the same aggregate in parts: one state for each value of by, combined, then asked."""
    parts = stream.groupBy(by).agg(F.expr(f"approx_top_k_accumulate(e, {most_items})").alias("state"))
    found = parts.agg(F.expr(f"approx_top_k_combine(state, {most_items})").alias("state")).select(F.expr(f"approx_top_k_estimate(state, {k})").alias("t"))
    return found.select(F.explode("t").alias("x")).select(F.col("x.item").alias("e"), F.col("x.count").alias("est"))


def builtin_count_min_bytes(stream: DataFrame, spec: SupportSpec, delta: float = 0.01, seed: int = 42) -> DataFrame:
    """One row: bytes of Spark's own Count-Min sketch of the same size, whatever the stream's length."""
    return stream.agg(F.octet_length(F.count_min_sketch("e", F.lit(float(spec.eps)), F.lit(1 - delta), F.lit(seed))).cast("long").alias("sketch_bytes"))


def builtin_frequent_items(stream: DataFrame, support: float) -> DataFrame:
    """(e) by Spark's own freqItems: a superset of the elements above the support."""
    return stream.stat.freqItems(["e"], support).select(F.explode("e_freqItems").alias("e"))
