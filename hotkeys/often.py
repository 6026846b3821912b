"""Mixed runs that ask after every few arrivals: the owner-split engine dealt out by owner, every query counted.

What workers hand over depends on their arrivals only, and what an owner's summary holds on what is handed to it. So one task
goes through the buffers of all workers for where they hand over. Each owner has a task of its own, which gets its arrivals and those
places, makes its pairs of them, and its summary takes these arrival by arrival as before.

A query's cost in a min-max heap follows from the places that are over the threshold. A count that grows changes them only when it
passes the threshold: one that is over already changes places with others that are over, and one that stays under with others
under. So a summary is searched where a count passes the threshold or the threshold rises, and every query until the next such
arrival costs the same steps; its time is taken to be that of the search.
"""

from __future__ import annotations

import json
import time
from collections.abc import Iterable, Iterator
from fractions import Fraction

import numpy as np

from hotkeys.kernels.minmax import MinMaxSummary
from hotkeys.spec import exact

#: Arrivals that are handed to the owners' tasks at a time.
CHUNK = 1 << 20

#: What an owner's task gets of a chunk: its arrivals (number and element), the last arrival before each hand-over of a worker, where
#: the threshold of what is handed over rises and to what; at a marked length, when all that waits is handed over, the sums of all owners.
FIELDS = "run int, owner int, seq long, n long, marked boolean, at binary, come binary, done binary, rise_at binary, rise binary, sums string"
#: Fields that hold numbers of arrivals, and the other arrays.
NUMBERED, ARRAYS = ("at", "done", "rise_at"), ("at", "done", "rise_at", "come", "rise")


def shrunk(row: dict) -> dict:
    """A row whose arrays are bytes of the narrowest kind, numbers of arrivals as the gaps that lead to the row's last."""
    out = dict(row)
    for x in ARRAYS:
        if x in row:
            of = np.diff(np.append(row[x], row["n"])) if x in NUMBERED else row[x]
            most = int(of.max(initial=0))
            kind = next(k for k in ("u1", "u2", "u4", "i8") if k == "i8" or most >> 8 * int(k[1]) == 0)
            out[x] = kind.encode() + of.astype(kind).tobytes()
    return out


def unshrunk(row: dict) -> dict:
    out = dict(row)
    for x in ARRAYS:
        if row[x] is not None:
            of = np.frombuffer(row[x], row[x][:2].decode(), offset=2).astype(np.int64)
            out[x] = row["n"] - np.cumsum(of[::-1])[::-1] if x in NUMBERED else of
    return out


def queries_of(since: list[int], values: list, upto: int, gap: int, t: int) -> tuple[float, np.ndarray]:
    """The sum over all queries, one each gap arrivals up to upto, of values that hold from arrival since on; and by worker, who ask in turns."""
    first = (np.array([*since, upto + 1], np.int64) - 1) // gap
    v, times = np.array(values), np.diff(first)
    turns = np.zeros(2 * t, v.dtype)
    np.add.at(turns, first[:-1] % t, v)
    np.add.at(turns, first[:-1] % t + times % t, -v)
    turns = np.cumsum(turns)
    return (v * times).sum().item(), turns[:t] + turns[t:] + (v * (times // t)).sum()


class Workers:
    """The buffers of all workers, HandoverBuffers for a chunk of arrivals at once, and what is counted of all owners together."""

    def __init__(self, t: int, slots: int, every: int, phi: Fraction, gaps: list[int], hashes):
        self.t, self.slots, self.every, self.phi, self.hashes = t, slots, every, phi, hashes
        self.held = [np.zeros(0, np.int64) for _ in range(t)]  # arrivals since a worker's last hand-over
        self.n = self.handed = self.waiting = self.handovers = 0
        self.lookups = dict.fromkeys(gaps, 0)
        self.paid = {gap: np.zeros(t, np.int64) for gap in gaps}

    def owners(self, ids: np.ndarray) -> np.ndarray:
        return (self.hashes.many(ids) % np.uint64(self.t)).astype(np.int16 if self.t < 1 << 15 else np.int64)

    def _ends(self, before: np.ndarray, owners: np.ndarray) -> list[int]:
        """Where a worker's hand-overs end, before being each arrival's last equal one."""
        start, size, ends = 0, len(before), []
        while start < size:
            first = np.flatnonzero(before[start : start + self.every] < start)
            own = owners[start + first]
            full = np.flatnonzero(np.bincount(own) >= self.slots)
            if len(full):
                start += min(int(first[np.flatnonzero(own == i)[self.slots - 1]]) for i in full) + 1
            elif start + self.every <= size:
                start += self.every
            else:
                break
            ends.append(start)
        return ends

    def feed(self, ids: np.ndarray) -> dict[int, dict[str, np.ndarray]]:
        """What each owner gets of the arrivals."""
        t, n, size = self.t, self.n, len(ids)
        change = np.zeros(size, np.int64)  # of the pairs that wait
        over = []
        for j in range(t):
            at = (j - n) % t
            old = len(self.held[j])
            mine = np.concatenate([self.held[j], ids[at::t]])
            if len(mine) == old:
                continue
            bits = len(mine).bit_length()
            key = np.sort((mine << bits) + np.arange(len(mine)))
            order, key = key & ((1 << bits) - 1), key >> bits
            same = np.flatnonzero(key[1:] == key[:-1])
            before = np.full(len(mine), -1, np.int64)
            before[order[same + 1]] = order[same]
            ends = np.array(self._ends(before, self.owners(mine)), np.int64)
            starts = np.append(0, ends)
            fresh = (before < np.repeat(starts, np.diff(np.append(starts, len(mine))))).astype(np.int64)
            change[at::t] += fresh[old:]
            last = int(starts[-1])
            self.held[j] = mine[last:]
            if last:
                done = n + 1 + at + (ends - 1 - old) * t
                change[done - n - 1] -= np.add.reduceat(fresh[:last], starts[:-1])
                over.append((done, np.diff(starts)))
        self._asked(change)
        done, rise_at, rise = self._risen(over)
        by = self.owners(ids)
        come = np.argsort(by, kind="stable")
        last = np.cumsum(np.bincount(by, minlength=t))
        self.n += size
        parts = [come[(last[i - 1] if i else 0) : last[i]] for i in range(t)]
        return {i: {"at": x + n + 1, "come": ids[x], "done": done, "rise_at": rise_at, "rise": rise} for i, x in enumerate(parts)}

    def _asked(self, change: np.ndarray) -> None:
        """Count what queries look up: every pair that waits."""
        waiting = self.waiting + np.cumsum(change)
        for gap in self.paid:
            seen = waiting[gap - 1 - self.n % gap :: gap]
            self.lookups[gap] += int(seen.sum())
            np.add.at(self.paid[gap], (self.n // gap + np.arange(len(seen))) % self.t, seen)
        self.waiting = int(waiting[-1])

    def _risen(self, over: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """The hand-overs, those with which the threshold rises, and what counts must exceed from then on."""
        at, size = map(np.concatenate, zip(*over, strict=True)) if over else [np.zeros(0, np.int64)] * 2
        order = np.argsort(at)
        low = [self.phi.numerator * x // self.phi.denominator for x in (self.handed + np.append(0, np.cumsum(size[order]))).tolist()]
        self.handed += int(size.sum())
        self.handovers += len(at)
        up = np.flatnonzero(np.diff(np.array(low, np.int64)))
        return at[order], at[order][up], np.array(low, np.int64)[1:][up]

    def flush(self) -> None:
        """All that waits is handed over."""
        self.handovers += sum(len(held) > 0 for held in self.held)
        self.held = [np.zeros(0, np.int64) for _ in range(self.t)]
        self.handed, self.waiting = self.n, 0

    def sums(self, method: str, gap: int) -> dict:
        """What owners do not count themselves: they add their pairs."""
        busy = (self.n - np.arange(self.t) + self.t - 1) // self.t
        looks = method == "owner_split_counting" and gap
        return {"arrivals": self.n, "queries": self.n // gap if gap else 0, "handovers": self.handovers, "lookups": self.lookups[gap] if looks else 0, "busy": (busy + self.paid[gap] if looks else busy).tolist()}


class Pairs:
    """What workers hand over to one owner, from its arrivals and the places of all hand-overs."""

    def __init__(self, t: int):
        self.t, self.n = t, 0
        self.at = self.e = np.zeros(0, np.int64)  # arrivals that wait
        self.seconds = 0.0

    def feed(self, row: dict) -> dict[str, np.ndarray]:
        """Pairs by hand-over: the last arrival before it, element, weight."""
        at, e = np.append(self.at, row["at"]), np.append(self.e, row["come"])
        span = row["n"] + 1
        worker = (at - 1) % self.t
        ends = np.append(np.sort((row["done"] - 1) % self.t * span + row["done"]), self.t * span)  # by worker, and one of none
        due = ends[np.searchsorted(ends, worker * span + at)]  # an arrival's next of any worker
        gone = due // span == worker
        self.at, self.e = at[~gone], e[~gone]
        return self._combined(due[gone] % span, at[gone], e[gone])

    def flush(self) -> dict[str, np.ndarray]:
        """The same of all that waits, worker by worker."""
        at, e = self.at, self.e
        self.at = self.e = np.zeros(0, np.int64)
        return self._combined((at - 1) % self.t, at, e)

    def _combined(self, turn: np.ndarray, at: np.ndarray, e: np.ndarray) -> dict[str, np.ndarray]:
        """Each turn's elements once, in the order of their first arrivals."""
        if not len(at):
            return {"t": turn, "e": e, "w": e}
        key = (turn - turn.min()) * (e.max() + 1) + e
        order = np.argsort(key, kind="stable")
        head = np.flatnonzero(np.append(True, np.diff(key[order]) != 0))
        w, one = np.diff(np.append(head, len(order))), order[head]
        self.n += len(one)
        put = np.argsort((turn[one] - turn.min()) * (at[-1] - at[0] + 1) + at[one] - at[0])
        one = one[put]
        return {"t": turn[one], "e": e[one], "w": w[put]}


class Ignoring:
    """One owner's summary, asked for what exceeds the support among all that was handed over."""

    def __init__(self, mixes: list, m: int):
        self.mixes, self.t = mixes, mixes[0].owners
        phi = exact(mixes[0].phi)
        self.p, self.q = phi.numerator, phi.denominator
        self.own = MinMaxSummary(m)
        self.low = 0  # what a count must exceed
        self.seconds = self.searching = 0.0
        self.cost: list[tuple[int, int, float]] = []  # from which arrival on, comparisons and seconds of a query
        self.answers: list[tuple[int, int]] = []
        self.total = [{"comparisons": 0, "answers": 0, "query_seconds": 0.0, "busy": np.zeros(self.t, np.int64)} for _ in mixes]
        self.search(1)

    def search(self, n: int) -> None:
        start = time.perf_counter()
        found = self.own.query(self.low, 1)
        spent = time.perf_counter() - start
        self.cost.append((n, self.own.stats.comparisons, spent))
        self.searching += spent
        self.answered(n, len(found))

    def answered(self, n: int, answers: int) -> None:
        self.answers.append((n, answers))

    def take(self, e: list[int], w: list[int]) -> bool:
        """Whether a count has passed the threshold."""
        return self.own.update_all(e, w, self.low)

    def feed(self, row: dict) -> None:
        rise = dict(zip(row["rise_at"].tolist(), row["rise"].tolist(), strict=True))
        for n, e, w in handed(row, row["rise_at"]):
            passed = self.take(e, w)
            if n in rise:
                self.low = rise[n]
            if passed or n in rise:
                self.search(n)

    def found(self) -> dict[int, int]:
        return dict(self.own.query(self.low, 1))

    def flush(self, row: dict) -> None:
        self.take(row["e"].tolist(), row["w"].tolist())
        self.low = self.p * row["n"] // self.q
        self.search(row["n"] + 1)

    def asked(self, n: int) -> None:
        """Add up the queries to arrival n, and keep what the next ones cost."""
        since, steps, spent = zip(*self.cost, strict=True)
        since_a, answers = zip(*self.answers, strict=True)
        for mix, total in zip(self.mixes, self.total, strict=True):
            if mix.gap:
                compared, busy = queries_of(since, steps, n, mix.gap, self.t)
                total["comparisons"] += compared
                total["busy"] += busy
                total["query_seconds"] += queries_of(since, spent, n, mix.gap, self.t)[0]
                total["answers"] += queries_of(since_a, answers, n, mix.gap, self.t)[0]
        self.cost, self.answers = [(n + 1, steps[-1], spent[-1])], [(n + 1, answers[-1])]


class Counting(Ignoring):
    """The same, asked for what exceeds the support among all arrivals, what waits counted as well."""

    def __init__(self, mixes: list, m: int):
        self.all: dict[int, int] = {}  # estimate and what waits
        self.over: set[int] = set()  # the elements for which that exceeds the threshold
        super().__init__(mixes, m)

    def answered(self, n: int, answers: int) -> None:
        """The summary's own answers are not the query's."""
        self.answers.append((n, len(self.over)))

    def take(self, e: list[int], w: list[int]) -> bool:
        return self.own.update_all(e, w, self.low, self.replaced)

    def replaced(self, gone: int, e: int, c: int) -> None:
        both, over = self.all, self.over
        left = both[gone] - c
        if left:
            both[gone] = left
        else:
            del both[gone]
        if left <= self.low:
            over.discard(gone)
        both[e] += c
        if both[e] > self.low:
            over.add(e)

    def feed(self, row: dict) -> None:
        both, over, come, at = self.all, self.over, row["come"].tolist(), row["at"].tolist()
        low = self.p * row["before"] // self.q
        rises = np.array([-(-v * self.q // self.p) for v in range(low + 1, self.p * row["n"] // self.q + 1)], np.int64)
        risen = set(rises.tolist())
        done, above, low = 0, self.low + 1, self.low
        for n, e, w in handed(row, np.append(rises, row["n"])):
            while done < len(at) and at[done] <= n:
                x = come[done]
                c = both[x] = both.get(x, 0) + 1
                if c == above:
                    over.add(x)
                    self.answers.append((at[done], len(over)))
                done += 1
            if n in risen:
                self.low = low = self.p * n // self.q
                above = low + 1
                gone = [x for x in over if both[x] <= low]
                over.difference_update(gone)
            before = len(over)
            if (e and self.take(e, w)) or n in risen:
                self.search(n)
            elif len(over) != before:
                self.answers.append((n, len(over)))

    def found(self) -> dict[int, int]:
        return {x: self.all[x] for x in self.over}


def handed(row: dict, more: np.ndarray) -> Iterator[tuple[int, list[int], list[int]]]:
    """Hand-overs in order, elements and weights of each, and further arrivals without any."""
    e, w = row["e"].tolist(), row["w"].tolist()
    times = np.union1d(row["t"], more)
    ends = np.searchsorted(row["t"], times, side="right").tolist()
    start = 0
    for n, end in zip(times.tolist(), ends, strict=True):
        yield n, e[start:end], w[start:end]
        start = end


KINDS = {"owner_split": Ignoring, "owner_split_counting": Counting}


def dealt(arrivals: Iterable[np.ndarray], hashes, mixes: list, marks: list[int] | None) -> Iterator[dict]:
    """Rows of a run for its owners' tasks: runs of one stream that differ in the method and the queries. Without marks its end is marked."""
    mix = mixes[0]
    own = Workers(mix.owners, mix.slots, mix.every, exact(mix.phi), sorted({x.gap for x in mixes} - {0}), hashes)
    left, seq, spent = sorted(set(marks or ()) - {0}), 0, 0.0

    def marked() -> Iterator[dict]:
        own.flush()
        sums = json.dumps([own.sums(x.method, x.gap) | {"seconds": spent} for x in mixes])
        for i in range(own.t):
            yield {"owner": i, "seq": seq, "n": own.n, "marked": True, "sums": None if i else sums}

    for part in arrivals:
        at = 0
        while at < len(part):
            start = time.perf_counter()
            size = min([len(part) - at, CHUNK, *[k - own.n for k in left[:1]]])
            rows = own.feed(part[at : at + size])
            at += size
            spent += time.perf_counter() - start
            for i, row in rows.items():
                yield {"owner": i, "seq": seq, "n": own.n, "marked": False, "sums": None} | row
            seq += 1
            if left and own.n == left[0]:
                left.pop(0)
                yield from marked()
                seq += 1
    if marks is None and own.n:
        yield from marked()


def owned(rows: Iterable[dict], mixes: list, m: int) -> Iterator[tuple[int, int, dict]]:
    """(marked length, setting, sums) of one owner's rows, in order."""
    alike: dict[str, list[int]] = {}
    for k, mix in enumerate(mixes):
        alike.setdefault(mix.method, []).append(k)
    runs = [(KINDS[method]([mixes[k] for k in ks], m), ks) for method, ks in alike.items()]
    phi = exact(mixes[0].phi)
    truth: dict[int, int] = {}
    pairs, before = Pairs(mixes[0].owners), 0
    for row in rows:
        n = row["n"]
        if not row["marked"]:
            for x, c in zip(*[y.tolist() for y in np.unique(row["come"], return_counts=True)], strict=True):
                truth[x] = truth.get(x, 0) + c
            start = time.perf_counter()
            row = row | pairs.feed(row) | {"before": before}
            pairs.seconds += time.perf_counter() - start
            for run, _ in runs:
                start, searched = time.perf_counter(), run.searching
                run.feed(row)
                run.seconds += time.perf_counter() - start - (run.searching - searched)
                run.asked(n)
            before = n
            continue
        if row["sums"]:
            for k, sums in enumerate(json.loads(row["sums"])):
                yield n, k, sums
        due = {x for x, c in truth.items() if c * phi.denominator > phi.numerator * n}
        floor = (phi - phi / 10) * n
        row = row | pairs.flush()
        for run, ks in runs:
            early = run.found()
            run.flush(row)
            found = run.found()
            hits = [x for x in found if x in due]
            seen = {"n_true": len(due), "n_reported": len(found), "hits": len(hits), "late": sum(x not in early for x in due), "spurious": sum(truth[x] < floor for x in found), "low": sum(c < truth[x] for x, c in found.items()), "are": sum(abs(found[x] - truth[x]) / truth[x] for x in hits)}
            for k, total in zip(ks, run.total, strict=True):
                busy = total["busy"].tolist()
                busy[row["owner"]] += pairs.n
                yield n, k, total | seen | {"pairs": pairs.n, "busy": busy, "seconds": pairs.seconds + run.seconds}


def fixed(mix, m: int) -> dict:
    """What a setting's records have in common."""
    return {"label": mix.label, "method": mix.method, "owners": mix.owners, "phi": mix.phi, "share": mix.share, "merged": 0, "counters": mix.owners * m + mix.owners * mix.owners * mix.slots}


def records(parts: Iterable[tuple[int, int, dict]], mixes: list, m: int) -> Iterator[dict]:
    """The settings' records at each marked length, of what their owners add up to."""
    sums: dict[tuple[int, int], dict] = {}
    for n, k, part in parts:
        own = sums.setdefault((n, k), {})
        for name, x in part.items():
            own[name] = np.add(own[name], x) if name in own else x
    for (_, k), own in sorted(sums.items()):
        own["critical"] = max(own.pop("busy"))
        own["are"] = own["are"] / max(1, own["hits"])
        yield fixed(mixes[k], m) | {name: x.item() if isinstance(x, np.generic) else x for name, x in own.items()}
