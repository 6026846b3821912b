"""The methods that the owner-split engine is compared with.

Every one of them gives (e, est, lower, upper), so that the measures take any of them.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import replace
from functools import reduce
from typing import Any

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from hotkeys.frames import keep
from hotkeys.kernels.minmax import MinMaxSummary
from hotkeys.kernels.others import FrequentSummary, LossyCounting, WeightedFrequent
from hotkeys.operators import owner_split as engine
from hotkeys.operators.exact import over_threshold
from hotkeys.spec import SupportSpec, exact


def length_of(stream: DataFrame) -> DataFrame:
    return stream.agg(F.coalesce(F.sum("w"), F.lit(0)).alias("n"))


def single_summary(stream: DataFrame, spec: SupportSpec, inner: str = "minmax", bulk: bool = False) -> DataFrame:
    """One summary fed with every arrival by one task: what speed-ups are measured against.

    With bulk the task combines arrivals by element, engine.ABSORB_ROWS at a time, before the summary takes them.
    """
    one = replace(spec, owners=1, counters=spec.counters or replace(spec, owners=1).per_owner())
    pairs = stream.select(F.lit(0).alias("owner"), F.lit(0).alias("src"), F.lit(0).cast("long").alias("seq"), "e", F.col("w").cast("long").alias("w"))
    return keep(engine.absorb(engine.route(pairs, 1), stream, one.per_owner(), inner, bulk=bulk))


def global_cooperative(streams: list[DataFrame], spec: SupportSpec, inner: str = "minmax") -> DataFrame:
    """One shared summary that map tasks feed with combined pairs, for one stream or several."""
    whole = reduce(DataFrame.unionByName, [s.select("e", "w") for s in streams])
    one = replace(spec, owners=1, counters=spec.counters or replace(spec, owners=1).per_owner())
    return engine.build_summary(whole, one, inner)


def local_rows(stream: DataFrame, make, tasks: int | None = None) -> DataFrame:
    """(src, e, est, over, f_min, n) of a kernel run in each task over the task's own arrivals."""
    schema = T.StructType([T.StructField("src", T.IntegerType()), stream.schema["e"], *[T.StructField(c, T.LongType()) for c in ("est", "over", "f_min", "n")]])
    given = (stream.repartition(tasks) if tasks else stream).select(F.spark_partition_id().alias("src"), "e", F.col("w").cast("long").alias("w"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, kind, src = make(), None, 0
        for batch in batches:
            if not batch.num_rows:
                continue
            kind, src = batch.column("e").type, batch.column("src")[0].as_py()
            for e, w in zip(engine.keys(batch.column("e")), batch.column("w").to_pylist(), strict=True):
                if getattr(own, "weighted", True):
                    own.update(e, w)
                else:
                    for _ in range(w):
                        own.update(e)
        rows = own.to_rows()
        if rows:
            n = len(rows)
            least = getattr(own, "f_min", 0)
            yield pa.RecordBatch.from_arrays(
                [pa.array([src] * n, pa.int32()), engine.restored([r[0] for r in rows], kind), pa.array([r[1] for r in rows], pa.int64()), pa.array([r[2] for r in rows], pa.int64()), pa.array([least] * n, pa.int64()), pa.array([own.n] * n, pa.int64())], ["src", "e", "est", "over", "f_min", "n"]
            )

    return given.mapInArrow(run, schema)


def local_merge(stream: DataFrame, spec: SupportSpec, tasks: int = 8) -> DataFrame:
    """Space-Saving in each task, merged when asked: estimates add up, an absent task adds its f_min."""
    m = replace(spec, owners=1).per_owner()
    rows = keep(local_rows(stream, lambda: MinMaxSummary(m), tasks))
    per_task = rows.groupBy("src").agg(F.max("f_min").alias("f_min"), F.max("n").alias("n"))
    sums = per_task.agg(F.coalesce(F.sum("f_min"), F.lit(0)).alias("floor"), F.coalesce(F.sum("n"), F.lit(0)).alias("n"))
    merged = rows.groupBy("e").agg(F.sum("est").alias("est"), F.sum("over").alias("over"), F.sum("f_min").alias("own"))
    both = merged.crossJoin(F.broadcast(sums)).withColumn("absent", F.col("floor") - F.col("own"))
    top = both.withColumn("est", F.col("est") + F.col("absent")).withColumn("over", F.col("over") + F.col("absent"))
    return top.filter(over_threshold("est", "n", spec.phi)).select("e", "est", (F.col("est") - F.col("over")).alias("lower"), F.col("est").alias("upper"))


def merge_collector(stream: DataFrame, spec: SupportSpec, beta=None, tasks: int = 8, shared_slots: int = 4096) -> DataFrame:
    """Local weighted Frequent instances whose grown counters one collecting instance merges.

    A task withholds a counter's growth until it reaches beta * n of its own arrivals so far. What
    is withheld at the end stays unseen, for only the collector is queried, so the answer may lack
    elements. The collector is one task by design; it is the bottleneck that the method has.
    """
    eps = spec.eps
    beta = exact(beta) if beta is not None else eps * 9 / 10
    m = math.ceil(1 / (eps - beta))
    p, q = beta.numerator, beta.denominator
    sent_schema = T.StructType([stream.schema["e"], T.StructField("w", T.LongType())])
    given = stream.repartition(tasks).select("e", F.col("w").cast("long").alias("w"))

    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = WeightedFrequent(m)
        grown: dict[Any, int] = {}
        sent: list[tuple[Any, int]] = []
        kind = None

        def out() -> pa.RecordBatch:
            made = pa.RecordBatch.from_arrays([engine.restored([e for e, _ in sent], kind), pa.array([w for _, w in sent], pa.int64())], ["e", "w"])
            sent.clear()
            return made

        for batch in batches:
            kind = batch.column("e").type
            for e, w in zip(engine.keys(batch.column("e")), batch.column("w").to_pylist(), strict=True):
                own.update(e, w)
                if e in own.raw:
                    grown[e] = grown.get(e, 0) + w
                    if grown[e] * q >= p * own.n:
                        sent.append((e, grown.pop(e)))
                        if len(sent) >= shared_slots:
                            yield out()
                else:
                    grown.pop(e, None)
                if len(grown) > 2 * m:
                    grown = {k: v for k, v in grown.items() if k in own.raw}
        if sent:
            yield out()

    def collect(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, kind = WeightedFrequent(m), None
        for batch in batches:
            kind = batch.column("e").type
            for e, w in zip(engine.keys(batch.column("e")), batch.column("w").to_pylist(), strict=True):
                own.update(e, w)
        rows = own.to_rows()
        if rows:
            yield pa.RecordBatch.from_arrays([engine.restored([r[0] for r in rows], kind), pa.array([r[1] for r in rows], pa.int64()), pa.array([r[2] for r in rows], pa.int64())], ["e", "est", "low"])

    schema = T.StructType([stream.schema["e"], T.StructField("est", T.LongType()), T.StructField("low", T.LongType())])
    merged = given.mapInArrow(local, sent_schema).repartition(1).mapInArrow(collect, schema)  # the local ones run apart
    found = merged.crossJoin(F.broadcast(length_of(stream)))
    # estimates are low by eps * n at most, so what may exceed phi * n is reported from (phi - eps) * n on
    kept = found.filter(over_threshold("est", "n", spec.phi - spec.eps))
    return kept.select("e", "est", F.col("est").alias("lower"), (F.col("est") + F.col("low")).alias("upper"))


#: Odd multipliers of a public 64-bit mixing function.
_MIX = (np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB))


def cells_of(h: np.ndarray, row: int, cells: int) -> np.ndarray:
    """A row's cell of each hash."""
    x = (h.view(np.uint64) + np.uint64((row + 1) * int(_MIX[1]) % (1 << 64))) * _MIX[0]
    x = (x ^ (x >> np.uint64(31))) * _MIX[1]
    return ((x ^ (x >> np.uint64(29))) % np.uint64(cells)).astype(np.int64)


class MajorityMatrix:
    """rows x cells of one Frequent counter each: the element that holds a cell loses what others bring to it."""

    def __init__(self, rows: int, cells: int):
        self.rows, self.cells = rows, cells
        self.hash = np.zeros((rows, cells), np.int64)
        self.count = np.zeros((rows, cells), np.int64)
        self.held = np.empty((rows, cells), object)

    def add(self, h: np.ndarray, elements: list[Any], w: np.ndarray) -> None:
        """Weighted arrivals of distinct elements; those of one cell one after another, all cells at once."""
        names = np.empty(len(elements), object)
        names[:] = elements
        for row in range(self.rows):
            cell = cells_of(h, row, self.cells)
            order = np.argsort(cell.astype(np.uint16) if self.cells <= 1 << 16 else cell, kind="stable")  # small numbers are sorted by digits
            of = cell[order]
            first = np.flatnonzero(np.append(True, of[1:] != of[:-1]))
            turn = np.arange(len(of)) - np.repeat(first, np.diff(np.append(first, len(of))))
            by_turn = np.argsort(turn.astype(np.uint16) if len(turn) <= 1 << 16 else turn, kind="stable")
            for part in np.split(order[by_turn], np.cumsum(np.bincount(turn))[:-1]):
                at, hashes, weights = cell[part], h[part], w[part]
                now = self.count[row, at]
                left = np.where((now > 0) & (self.hash[row, at] == hashes), now + weights, now - weights)
                taken = left < 0
                self.count[row, at] = np.abs(left)
                self.hash[row, at[taken]] = hashes[taken]
                self.held[row, at[taken]] = names[part[taken]]

    def counters(self) -> tuple[np.ndarray, np.ndarray, list[Any], np.ndarray]:
        """row, cell, element and count of the cells that hold something."""
        row, cell = np.nonzero(self.count)
        return row, cell, self.held[row, cell].tolist(), self.count[row, cell]


def cell_majority(stream: DataFrame, spec: SupportSpec, rows: int = 4, tasks: int = 8, cells: int | None = None) -> DataFrame:
    """A matrix of rows x 1/eps cells, each with one Frequent counter; one matrix per task, merged when asked.

    A cell's candidate loses what others in the cell bring; merging adds the counters of equal candidates
    and keeps the greatest. An element's estimate is its greatest one over the rows; it is never high. A task
    combines each batch of arrivals by element before they go to the matrix.
    """
    cells = cells or math.ceil(1 / spec.eps)
    given = stream.repartition(tasks).select("e", F.col("w").cast("long").alias("w"), F.xxhash64("e", F.lit(spec.seed)).alias("h"))
    schema = T.StructType([T.StructField("row", T.IntegerType()), T.StructField("cell", T.IntegerType()), stream.schema["e"], T.StructField("c", T.LongType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        matrix, kind = MajorityMatrix(rows, cells), None
        for batch in batches:
            kind = batch.column("e").type
            h, first, place = np.unique(batch.column("h").to_numpy(), return_index=True, return_inverse=True)
            w = np.zeros(len(h), np.int64)
            np.add.at(w, place, batch.column("w").to_numpy())
            if len(h):
                matrix.add(h, engine.keys(batch.column("e").take(pa.array(first))), w)
        row, cell, elements, count = matrix.counters()
        if len(row):
            yield pa.RecordBatch.from_arrays([pa.array(row, pa.int32()), pa.array(cell, pa.int32()), engine.restored(elements, kind), pa.array(count)], ["row", "cell", "e", "c"])

    local = given.mapInArrow(run, schema)
    by_candidate = local.groupBy("row", "cell", "e").agg(F.sum("c").alias("c"))
    merged = by_candidate.groupBy("row", "cell").agg(F.max_by("e", F.struct("c", "e")).alias("e"), F.max("c").alias("c"))
    found = merged.groupBy("e").agg(F.max("c").alias("est")).crossJoin(F.broadcast(length_of(stream)))
    kept = found.filter(over_threshold("est", "n", spec.phi - spec.eps))
    slack = F.ceil(F.col("n") * F.lit(float(spec.eps))).cast("long")
    return kept.select("e", "est", F.col("est").alias("lower"), (F.col("est") + slack).alias("upper"))


def _sum_of_locals(rows: DataFrame, spec: SupportSpec, slack) -> DataFrame:
    """Under-estimates from tasks add up to one for the stream, low by the slack at most."""
    n = rows.groupBy("src").agg(F.max("n").alias("n")).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"))
    found = rows.groupBy("e").agg(F.sum("est").alias("est")).crossJoin(F.broadcast(n))
    kept = found.filter(over_threshold("est", "n", spec.phi - spec.eps))
    return kept.select("e", "est", F.col("est").alias("lower"), (F.col("est") + slack).alias("upper"))


def frequent_unit(stream: DataFrame, spec: SupportSpec, tasks: int = 8) -> DataFrame:
    """Frequent with 1 / eps counters in each task; the tasks' counters add up."""
    m = math.ceil(1 / spec.eps)
    rows = keep(local_rows(stream, lambda: FrequentSummary(m), tasks))
    return _sum_of_locals(rows, spec, F.floor(F.col("n") / F.lit(m + 1)).cast("long"))


def lossy_counting(stream: DataFrame, spec: SupportSpec, tasks: int = 8) -> DataFrame:
    eps = spec.eps
    rows = keep(local_rows(stream, lambda: LossyCounting(eps), tasks))
    return _sum_of_locals(rows, spec, F.ceil(F.col("n") * F.lit(float(eps))).cast("long"))
