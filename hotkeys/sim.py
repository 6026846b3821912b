"""A seeded model of the engine's concurrency: workers, hand-overs, drains and overlapping queries.

Shared memory has no counterpart among Spark tasks, so overlap is studied here: one random worker at a time
takes one step (insert an arrival, drain one handed-over buffer, or visit one owner for a query), and each
query's bounds are checked against the true counts at its start and end. A run takes its arrivals from
an iterator and keeps no copy of the counts for a query, only what has changed since the query began, so it
can go through a whole stream. Each run is one pass of one task, as every step depends on the last.
"""

from __future__ import annotations

import random
from collections import Counter, deque
from collections.abc import Hashable, Iterable, Iterator
from dataclasses import dataclass, field
from itertools import groupby

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hotkeys.kernels.buffers import HandoverBuffers
from hotkeys.kernels.minmax import MinMaxSummary
from hotkeys.kernels.others import MinHeapSummary
from hotkeys.plans.sizing import counters_any, interval_ok, must_not_report, must_report, pending_bound
from hotkeys.spec import exact


@dataclass
class _Query:
    left: list[int]
    n_start: int
    due: dict[Hashable, int]  # true counts at the start of the elements over the threshold
    most_pending: int
    came: Counter = field(default_factory=Counter)  # arrivals since the start
    drained: Counter = field(default_factory=Counter)  # what owners have taken in since
    found: dict[Hashable, int] = field(default_factory=dict)
    comparisons: int = 0
    lookups: int = 0


@dataclass
class Setting:
    owners: int = 4
    slots: int = 8
    every: int = 50
    phi: str = "0.01"
    eps: str = "0.001"
    query_every: int = 100
    count_buffers: bool = False
    inner: str = "minmax"
    counters: int | None = None
    seed: int = 0


_END = object()


class Simulation:
    def __init__(self, arrivals: Iterable[Hashable], setting: Setting):
        self.s = setting
        self.phi, self.eps = exact(setting.phi), exact(setting.eps)
        self.p, self.q = self.phi.numerator, self.phi.denominator
        self.rng = random.Random(setting.seed)
        t = setting.owners
        self.order = list(range(t))
        self.owners: dict[Hashable, int] = {}
        self.source = iter(arrivals)
        self.dealt = 0
        self.todo: list[deque] = [deque() for _ in range(t)]
        self.buffers = [HandoverBuffers(t, setting.slots, setting.every) for _ in range(t)]
        self.lists: list[deque] = [deque() for _ in range(t)]  # pushed buffers by owner: (worker, pairs)
        self.unflushed = [0] * t
        kernel = {"minmax": MinMaxSummary, "minheap": MinHeapSummary}[setting.inner]
        self.inner = [kernel(setting.counters or counters_any(setting.eps, t)) for _ in range(t)]
        self.true: Counter = Counter()
        self.n = 0
        self.heavy: set[Hashable] = set()  # all elements over the threshold, and some that were
        self.waiting: Counter = Counter()
        self.levels: Counter = Counter()  # how many elements wait with each count
        self.top = 0
        self.query: dict[int, _Query] = {}
        self.since_query = 0
        self.records: deque[dict] = deque()
        self.n_queries = 0
        self.peak_waiting = 0

    def owner(self, e: Hashable) -> int:
        known = self.owners.get(e)
        if known is None:
            known = self.owners[e] = self._owner(e)
        return known

    def _owner(self, e: Hashable) -> int:
        return hash((e, 0x9E37)) % self.s.owners if isinstance(e, int) else sum(map(ord, str(e))) % self.s.owners

    def _has(self, j: int) -> bool:
        """Whether worker j has an arrival left; they are dealt in turn, no sooner than asked for."""
        while not self.todo[j]:
            e = next(self.source, _END)
            if e is _END:
                return False
            self.todo[self.dealt % self.s.owners].append(e)
            self.dealt += 1
        return True

    def _wait(self, e: Hashable, w: int) -> None:
        before = self.waiting.get(e, 0)
        now = before + w
        if before:
            self.levels[before] -= 1
        if now:
            self.waiting[e] = now
            self.levels[now] += 1
        else:
            self.waiting.pop(e, None)
        if now > self.top:
            self.top = now
        while self.top and not self.levels[self.top]:
            self.top -= 1

    def _insert(self, j: int) -> None:
        e = self.todo[j].popleft()
        self.n += 1
        self.true[e] += 1
        if self.true[e] * self.q > self.p * self.n:
            self.heavy.add(e)
        self._wait(e, 1)
        for q in self.query.values():
            q.came[e] += 1
        if self.waiting[e] > self.peak_waiting:
            self.peak_waiting = self.waiting[e]
        for i, pairs in self.buffers[j].insert(self.owner(e), e):
            self.lists[i].append((j, pairs))
            self.unflushed[j] += 1
        self.since_query += 1

    def _drain(self, i: int) -> bool:
        """Owner i takes one buffer off its list, if there is one. A query's visit is one step, so none is drained within it."""
        if not self.lists[i]:
            return False
        j, pairs = self.lists[i].popleft()
        for e, w in pairs.items():
            self.inner[i].update(e, w)
            self._wait(e, -w)
            for q in self.query.values():
                q.drained[e] += w
        self.unflushed[j] -= 1
        return True

    def _visit(self, j: int) -> None:
        q = self.query[j]
        i = q.left.pop(self.rng.randrange(len(q.left)))
        phi = self.phi
        if self.s.count_buffers:
            extra: Counter = Counter()
            for b in self.buffers:
                extra.update(b.held[i])
                q.lookups += len(b.held[i])
            for _, pairs in self.lists[i]:
                extra.update(pairs)
                q.lookups += len(pairs)
            # waiting counts can lift what is below the threshold by the most that waits, so the summary is searched down to there
            low = max(0, phi * q.n_start - max(extra.values(), default=0))
            held = dict(self.inner[i].query(low, 1))
            q.comparisons += self.inner[i].stats.comparisons
            for e in {*held, *extra}:
                est = self.inner[i].estimate(e) if e in self.inner[i].place else 0
                if est + extra[e] > phi * q.n_start:
                    q.found[e] = est + extra[e]
        else:
            q.found.update(self.inner[i].query(phi, q.n_start))
            q.comparisons += self.inner[i].stats.comparisons
        if not q.left:
            self._finish(self.query.pop(j))

    def _finish(self, q: _Query) -> None:
        s, phi, eps, n_end = self.s, self.phi, self.eps, self.n
        start = lambda e: self.true[e] - q.came[e]
        slack = lambda e: 0 if s.count_buffers else self.waiting[e] - q.came[e] + q.drained[e]
        missed = sum(1 for e, f in q.due.items() if e not in q.found and must_report(f, phi, q.n_start, slack(e)))
        spurious = sum(1 for e in q.found if must_not_report(self.true[e], phi, eps, q.n_start, n_end))
        outside = sum(1 for e, est in q.found.items() if not interval_ok(start(e), slack(e), est, self.true[e], eps, n_end))
        self.records.append(
            {
                "query_id": self.n_queries,
                "n_start": q.n_start,
                "n_end": n_end,
                "n_reported": len(q.found),
                "missed": missed,
                "spurious": spurious,
                "outside": outside,
                "most_pending": q.most_pending,
                "pending_over": int(self.peak_waiting > pending_bound(s.owners, s.every)),
                "late": sum(1 for e in q.due if e not in q.found),
                "comparisons": q.comparisons,
                "lookups": q.lookups,
            }
        )
        self.n_queries += 1

    def _begin(self, j: int) -> None:
        self.since_query = 0
        # a count over the threshold was over it when it last grew, so heavy lacks none
        self.heavy = {e for e in self.heavy if self.true[e] * self.q > self.p * self.n}
        self.query[j] = _Query(list(range(self.s.owners)), self.n, {e: self.true[e] for e in self.heavy}, self.top)

    def step(self) -> bool:
        """One step of one random worker that can take one; False when all is done."""
        order, draw = self.order, self.rng.random
        for left in range(self.s.owners, 0, -1):  # workers in a random order, drawn no further than one that can take a step
            at = int(draw() * left)
            j = order[at]
            order[at] = order[left - 1]
            order[left - 1] = j
            if j in self.query:
                self._visit(j)
                return True
            if self.unflushed[j]:
                if self._drain(j):
                    return True
                # others hold this worker's buffers; they are drained by their owners
                continue
            if self._has(j):
                if self.since_query >= self.s.query_every:
                    self._begin(j)
                else:
                    self._insert(j)
                return True
            if self._drain(j):
                return True
        return False

    def stream(self) -> Iterator[dict]:
        """The records, each as soon as its query is done."""
        while self.step():
            while self.records:
                yield self.records.popleft()
        self._begin(0)
        while self.query:
            self._visit(0)
        yield from self.records

    def run(self) -> list[dict]:
        return list(self.stream())


RECORD = "query_id long, n_start long, n_end long, n_reported long, missed long, spurious long, outside long, most_pending long, pending_over long, late long, comparisons long, lookups long"
#: Records in a batch that a run gives back.
BATCH = 10_000


def simulate(arrivals: DataFrame, settings: list[Setting], spark: SparkSession) -> DataFrame:
    """run_id and a record for each query of each run over all arrivals.

    arrivals (ord, es): arrays of elements, in the order of ord. A task takes one run's rows in that order, in
    Arrow batches, and holds no more of them than a batch.
    """
    grid = spark.createDataFrame([(k,) for k in range(len(settings))], "run_id int")
    none = grid.limit(1).select(F.lit(None).cast(arrivals.schema["ord"].dataType).alias("ord"), F.lit(None).cast(arrivals.schema["es"].dataType).alias("es"))
    given = arrivals.select("ord", "es").unionByName(none).crossJoin(F.broadcast(grid))
    names = ["run_id", *[x.split()[0] for x in RECORD.split(", ")]]
    schema = pa.schema([(x, pa.int32() if x == "run_id" else pa.int64()) for x in names])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = (row for b in batches for row in zip(b.column("run_id").to_pylist(), b.column("es"), strict=True))
        for run_id, own in groupby(rows, key=lambda row: row[0]):
            made = []
            for record in Simulation((e for _, es in own for e in es.as_py() or ()), settings[run_id]).stream():
                made.append({"run_id": run_id, **record})
                if len(made) >= BATCH:
                    yield pa.RecordBatch.from_pylist(made, schema)
                    made = []
            yield pa.RecordBatch.from_pylist(made, schema)

    dealt = given.repartitionById(len(settings), F.col("run_id")).sortWithinPartitions("run_id", "ord", "es")
    return dealt.select("run_id", "es").mapInArrow(run, "run_id int, " + RECORD)
