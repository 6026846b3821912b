"""Counter- and sketch-based methods that hold the same bytes, over one packed stream.

The methods are the operators' (baselines, sketches) as one task runs them, in the order of the stream: summaries take arrival by
arrival, sketches and majority cells BATCH arrivals at once, as many as an Arrow batch has. Here elements are numbers, so that a
task decodes the stream once for its methods and their sizes, and answers are held against exact counts where they are made. Which of the least counts
Space-Saving replaces is left open by it, and not what the heaps choose.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from fractions import Fraction
from itertools import groupby

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from hotkeys import mixed
from hotkeys.kernels.others import FiledSummary, FrequentSummary, LossyCounting
from hotkeys.operators.baselines import MajorityMatrix
from hotkeys.spec import SupportSpec, exact

#: Arrivals that a matrix takes at once.
BATCH = 10_000
#: Rows of a sketch and of a majority matrix, and the seed of a sketch's hashes.
DEPTH, ROWS, SEED = 5, 4, 42
#: Methods that share a task, which take about as long together; one of each asks for hashes. More tasks would shuffle more copies.
TASKS = (("space_saving", "count_sketch"), ("frequent", "count_min"), ("lossy_counting", "cell_majority"))


def spec_of(size: int, phi: str) -> SupportSpec:
    eps = Fraction(24, size)
    return SupportSpec(phi, eps=eps if eps <= exact(phi) else phi, owners=1, counters=size // 32)


def seeds_of(method: str, phi: str) -> list[int]:
    """Seeds of the hashes of elements that a method asks for."""
    cells = [SEED + r for r in range(DEPTH)]
    return {"count_min": cells, "count_sketch": cells + [SEED + 7919 + r for r in range(DEPTH)], "cell_majority": [SupportSpec(phi).seed]}.get(method, [])


class Batch:
    """Consecutive arrivals and, when asked for, their distinct elements with their numbers of arrivals."""

    def __init__(self, ids: np.ndarray):
        self.ids = ids
        self.known: tuple[np.ndarray, np.ndarray] | None = None

    def counted(self) -> tuple[np.ndarray, np.ndarray]:
        if self.known is None:
            self.known = np.unique(self.ids, return_counts=True)
        return self.known


class Counters:
    """A counter-based summary, which reports what is over a share: its estimates are never low, or low by eps N at most."""

    def __init__(self, method: str, spec: SupportSpec):
        m = -(-spec.eps.denominator // spec.eps.numerator)
        self.own = {"space_saving": lambda: FiledSummary(spec.per_owner()), "frequent": lambda: FrequentSummary(m), "lossy_counting": lambda: LossyCounting(spec.eps)}[method]()
        self.share = spec.phi if method == "space_saving" else spec.phi - spec.eps

    def take(self, batch: Batch, hashes: list[np.ndarray]) -> None:
        self.own.update_many(batch.ids.tolist())

    def found(self, n: int, hashes: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        rows = [(e, c) for e, c, _ in self.own.to_rows() if c * self.share.denominator > self.share.numerator * n]
        return np.array([e for e, _ in rows], np.int64), np.array([c for _, c in rows], np.int64)


class Sketch:
    """Count-Min, or Count Sketch when signed, and its candidates as in sketches.passed."""

    def __init__(self, method: str, spec: SupportSpec, width: int):
        self.signed, self.width, self.phi = method == "count_sketch", width, spec.phi
        self.share = spec.phi - spec.eps if self.signed else spec.phi
        self.matrix = np.zeros(DEPTH * width, np.int64)
        self.candidate = mixed.Grown(False, bool)
        self.held = self.n = 0
        self.most = 4 / self.share if self.share else float("inf")

    def _at(self, ids: np.ndarray, hashes: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray | int]:
        cells = np.stack([hashes[r][ids] % self.width + r * self.width for r in range(DEPTH)])
        return cells, np.stack([hashes[DEPTH + r][ids] % 2 * 2 - 1 for r in range(DEPTH)]) if self.signed else 1

    def _estimates(self, cells: np.ndarray, signs: np.ndarray | int) -> np.ndarray:
        found = self.matrix[cells] * signs
        return np.sort(found, axis=0)[DEPTH // 2] if self.signed else found.min(axis=0)

    def _over(self, est: np.ndarray) -> np.ndarray:
        return est * self.share.denominator >= self.share.numerator * self.n

    def take(self, batch: Batch, hashes: list[np.ndarray]) -> None:
        ids, w = batch.counted()
        self.n += len(batch.ids)
        cells, signs = self._at(ids, hashes)
        np.add.at(self.matrix, cells.ravel(), np.broadcast_to(w * signs, cells.shape).ravel())  # shapes alike: add.at misreads others
        over = ids[self._over(self._estimates(cells, signs))]
        candidate = self.candidate.reach(int(ids[-1]))
        self.held += int(np.count_nonzero(~candidate[over]))
        candidate[over] = True
        if self.held > self.most:
            held = np.flatnonzero(candidate)
            candidate[held] = self._over(self._estimates(*self._at(held, hashes)))
            self.held = int(np.count_nonzero(candidate))
            self.most = max(self.most, 2 * self.held)

    def found(self, n: int, hashes: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        held = np.flatnonzero(self.candidate.of)
        est = self._estimates(*self._at(held, hashes)) if len(held) else np.zeros(0, np.int64)
        over = est * self.phi.denominator > self.phi.numerator * n
        return held[over], est[over]


class Majority:
    """A matrix of majority cells; an element's estimate is its greatest count, low by eps N."""

    def __init__(self, spec: SupportSpec, cells: int):
        self.own, self.share = MajorityMatrix(ROWS, cells), spec.phi - spec.eps

    def take(self, batch: Batch, hashes: list[np.ndarray]) -> None:
        ids, w = batch.counted()
        order = np.argsort(hashes[0][ids])
        self.own.add(hashes[0][ids][order], ids[order].tolist(), w[order])

    def found(self, n: int, hashes: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        _, _, elements, count = self.own.counters()
        ids, place = np.unique(np.array(elements, np.int64), return_inverse=True)
        est = np.zeros(len(ids), np.int64)
        np.maximum.at(est, place, count)
        over = est * self.share.denominator > self.share.numerator * n
        return ids[over], est[over]


def made(method: str, size: int, phi: str) -> Counters | Sketch | Majority:
    """A method in so many bytes: slots of 32, entries of 24, cells of 8 in 5 rows or of 16 in 4."""
    spec = spec_of(size, phi)
    if method in ("count_min", "count_sketch"):
        return Sketch(method, spec, size // 40)
    return Majority(spec, size // 64) if method == "cell_majority" else Counters(method, spec)


def batched(arrays: Iterable[np.ndarray]) -> Iterator[np.ndarray]:
    """The same arrivals, BATCH at a time."""
    left = np.zeros(0, np.int64)
    for ids in arrays:
        ids = np.concatenate([left, ids])
        whole = len(ids) // BATCH * BATCH
        yield from ids[:whole].reshape(-1, BATCH)
        left = ids[whole:]
    if len(left):
        yield left


def measured(found: np.ndarray, est: np.ndarray, truth: np.ndarray, phi: str) -> dict:
    """n_true, n_reported, precision, recall and the relative error of frequent elements, an unreported one estimated 0."""
    share = exact(phi)
    due = np.flatnonzero(truth * share.denominator > share.numerator * int(truth.sum()))
    of = np.zeros(len(truth), np.int64)
    of[found] = est
    hits = len(np.intersect1d(due, found, assume_unique=True))
    part = lambda whole: hits / whole if whole else 1.0 if not len(due) and not len(found) else 0.0
    return {"n_true": len(due), "n_reported": len(found), "precision": part(len(found)), "recall": part(len(due)), "are": float(np.mean(np.abs(of[due] - truth[due]) / truth[due])) if len(due) else 0.0}


def run(rows: Iterable[tuple[list[str] | None, bytes | None, np.ndarray | None]], methods: tuple[str, ...], sizes: Iterable[int], phi: str) -> Iterator[dict]:
    """What a task's methods find in each size, for packed rows with the hashes of their words, one row of numbers for each word."""
    numbers, own = mixed.Numbers(), {(m, size): made(m, size, phi) for m in methods for size in sizes}
    table = [mixed.Grown(0) for m in methods for _ in seeds_of(m, phi)]

    def arrivals() -> Iterator[np.ndarray]:
        for words, codes, hashes in rows:
            if codes is not None:
                if table:
                    at = numbers.of(words)
                    for x, h in zip(table, hashes.T, strict=True):
                        x.reach(int(at.max()))[at] = h
                yield from mixed.unpacked([(words, codes)], numbers)

    truth, n = mixed.Grown(0), 0
    for ids in batched(arrivals()):
        batch = Batch(ids)
        n += len(ids)
        np.add.at(truth.reach(int(ids.max())), ids, np.ones(len(ids), np.int64))
        for x in own.values():
            x.take(batch, [h.of for h in table])
    for (method, size), x in own.items():
        yield {"bytes": size, "method": method} | measured(*x.found(n, [h.of for h in table]), truth.of, phi)


FIELDS = "bytes int, method string, n_true long, n_reported long, precision double, recall double, are double"


def _hashed(seeds: list[int]) -> Column:
    return F.transform("words", lambda w: F.array(*[F.xxhash64(w, F.lit(s)) for s in seeds]))


def compare(spark: SparkSession, stream: DataFrame, sizes: tuple[int, ...], phi: str) -> DataFrame:
    """All methods in all sizes on a stream (ord, es): a task for each of TASKS; words are hashed where they have arrived."""
    asked = spark.createDataFrame([(k,) for k in range(len(TASKS))], "run int")
    hashes = F.lit(None).cast("array<array<bigint>>")
    for k, methods in enumerate(TASKS):
        hashes = F.when(F.col("run") == k, _hashed([s for m in methods for s in seeds_of(m, phi)])).otherwise(hashes)
    every = mixed.packed(stream).crossJoin(F.broadcast(asked)).select("run", "part", "seq", "words", "codes")
    one = asked.select("run", F.lit(-1).alias("part"), F.lit(0).cast("long").alias("seq"), F.lit(None).cast("array<string>").alias("words"), F.lit(None).cast("binary").alias("codes"))
    given = every.unionByName(one).repartitionById(len(TASKS), F.col("run")).sortWithinPartitions("run", "part", "seq").select("run", "words", "codes", hashes.alias("hashes"))

    def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def rows() -> Iterator[tuple]:
            for b in batches:
                for i, k in enumerate(b.column("run").to_pylist()):
                    h = b.column("hashes")[i]
                    words = b.column("words")[i].as_py()
                    yield k, words, b.column("codes")[i].as_py(), h.values.flatten().to_numpy().reshape(len(words), -1) if h.is_valid else None

        for k, mine in groupby(rows(), key=lambda row: row[0]):
            found = list(run((row[1:] for row in mine), TASKS[k], sizes, phi))
            yield pa.RecordBatch.from_pydict({name: pa.array([r[name] for r in found], mixed.ARROW[kind]) for name, kind in (x.split() for x in FIELDS.split(", "))})

    return given.mapInArrow(measure, FIELDS)
