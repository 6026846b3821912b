"""The other counter-based summaries: two more forms of Space-Saving, Frequent and Lossy Counting."""

from __future__ import annotations

import heapq
import math
from collections.abc import Hashable, Iterable, Sequence

from hotkeys.kernels.minmax import QueryStats, padded
from hotkeys.spec import exact, exceeds


class MinHeapSummary:
    """Space-Saving on a min-heap: the least count is at the top, a query looks at every counter.

    Slots are lists [count, element, over, place] that move as a whole, as in the min-max heap.
    """

    weighted = True

    def __init__(self, m: int):
        self.m = padded(m)
        self.heap: list[list] = []
        self.place: dict[Hashable, list] = {}
        self.n = 0
        self.stats = QueryStats()

    @property
    def f_min(self) -> int:
        return self.heap[0][0] if len(self.heap) == self.m else 0

    def _up(self, i: int, slot: list) -> None:
        heap, c = self.heap, slot[0]
        while i and heap[(i - 1) >> 1][0] > c:
            above = heap[(i - 1) >> 1]
            heap[i] = above
            above[3] = i
            i = (i - 1) >> 1
        heap[i] = slot
        slot[3] = i

    def _down(self, i: int, slot: list) -> None:
        heap, size, c = self.heap, len(self.heap), slot[0]
        k = 2 * i + 1
        while k < size:
            below = heap[k]
            if k + 1 < size and heap[k + 1][0] < below[0]:
                k += 1
                below = heap[k]
            if below[0] >= c:
                break
            heap[i] = below
            below[3] = i
            i, k = k, 2 * k + 1
        heap[i] = slot
        slot[3] = i

    def update(self, e: Hashable, w: int = 1) -> None:
        if w <= 0:
            raise ValueError("weights are positive: deletions are not supported")
        self.n += w
        slot = self.place.get(e)
        if slot is not None:
            slot[0] += w
            self._down(slot[3], slot)
        elif len(self.heap) < self.m:
            slot = self.place[e] = [w, e, 0, len(self.heap)]
            self.heap.append(slot)
            self._up(slot[3], slot)
        else:
            slot = self.heap[0]
            del self.place[slot[1]]
            slot[1], slot[2] = e, slot[0]
            slot[0] += w
            self.place[e] = slot
            self._down(0, slot)

    def update_batch(self, elements: Iterable[Hashable], weights: Iterable[int]) -> None:
        """Register already combined pairs, tracked elements first."""
        place, rest, changed = self.place, [], False
        for e, w in zip(elements, weights, strict=True):
            slot = place.get(e)
            if slot is None:
                rest.append((e, w))
            else:
                slot[0] += w
                self.n += w
                changed = True
        if changed:  # in ascending order every heap is one
            self.heap.sort(key=lambda s: s[0])
            for i, slot in enumerate(self.heap):
                slot[3] = i
        for e, w in rest:
            self.update(e, w)

    def query(self, phi, n: int | None = None) -> list[tuple[Hashable, int]]:
        phi, n = exact(phi), self.n if n is None else n
        self.stats = QueryStats(len(self.heap))
        p, q = phi.numerator * n, phi.denominator
        return [(x[1], x[0]) for x in self.heap if x[0] * q > p]

    def estimate(self, e: Hashable) -> int:
        slot = self.place.get(e)
        return self.f_min if slot is None else slot[0]

    def to_rows(self) -> list[tuple[Hashable, int, int]]:
        return [(x[1], x[0], x[2]) for x in self.heap]


class BucketListSummary:
    """Space-Saving on buckets of equal counts, linked by count: unit updates in constant time."""

    weighted = False

    def __init__(self, m: int):
        self.m = padded(m)
        self.buckets: dict[int, dict[Hashable, int]] = {}  # count -> element -> over, in order of arrival
        self.above: dict[int, int | None] = {}
        self.below: dict[int, int | None] = {}
        self.of: dict[Hashable, int] = {}
        self.low: int | None = None
        self.high: int | None = None
        self.n = 0
        self.stats = QueryStats()

    @property
    def f_min(self) -> int:
        return self.low if len(self.of) == self.m and self.low is not None else 0

    def _link(self, count: int, under: int | None) -> None:
        """A bucket for count, right above the bucket `under` or lowest."""
        over = self.above[under] if under is not None else self.low
        self.buckets[count] = {}
        self.below[count], self.above[count] = under, over
        if under is None:
            self.low = count
        else:
            self.above[under] = count
        if over is None:
            self.high = count
        else:
            self.below[over] = count

    def _unlink(self, count: int) -> None:
        under, over = self.below.pop(count), self.above.pop(count)
        del self.buckets[count]
        if under is None:
            self.low = over
        else:
            self.above[under] = over
        if over is None:
            self.high = under
        else:
            self.below[over] = under

    def _put(self, e: Hashable, count: int, over: int, under: int | None) -> None:
        if count not in self.buckets:
            self._link(count, under)
        self.buckets[count][e] = over
        self.of[e] = count

    def update(self, e: Hashable, w: int = 1) -> None:
        if w != 1:
            raise ValueError("the bucket list takes unit updates only")
        self.n += 1
        count = self.of.get(e)
        if count is None:
            if len(self.of) < self.m:
                self._put(e, 1, 0, None)
                return
            count = self.low
            gone = next(iter(self.buckets[count]))
            del self.buckets[count][gone], self.of[gone]
            over = count
        else:
            over = self.buckets[count].pop(e)
        self._put(e, count + 1, over, count)
        if not self.buckets[count]:
            self._unlink(count)

    def query(self, phi, n: int | None = None) -> list[tuple[Hashable, int]]:
        """From the highest bucket down; stops at the first one that fails."""
        phi, n = exact(phi), self.n if n is None else n
        out: list[tuple[Hashable, int]] = []
        self.stats = QueryStats()
        at = self.high
        while at is not None:
            self.stats.comparisons += 1
            if not exceeds(at, phi, n):
                break
            out += [(e, at) for e in self.buckets[at]]
            at = self.below[at]
        return out

    def estimate(self, e: Hashable) -> int:
        return self.of.get(e, self.f_min)

    def to_rows(self) -> list[tuple[Hashable, int, int]]:
        return [(e, count, over) for count, bucket in self.buckets.items() for e, over in bucket.items()]


class WeightedFrequent:
    """Frequent with weights: when full, what clears the least counter is taken from all and from w.

    Subtractions are kept as one offset, and counters leave when the offset reaches them. Estimates
    are low by `offset`, which is at most n / (m + 1). The least counter is at the top of a heap of counts
    as they were when pushed; one that has grown since is pushed again when it comes up.
    """

    weighted = True

    def __init__(self, m: int):
        self.m = m
        self.raw: dict[Hashable, int] = {}
        self.queue: list[tuple[int, int, Hashable]] = []
        self.pushed = 0
        self.offset = 0
        self.n = 0

    def _least(self) -> tuple[int, int, Hashable]:
        """The top of the heap, once it is as large as the counter that it stands for."""
        queue, raw = self.queue, self.raw
        while True:
            c, k, e = queue[0]
            now = raw[e]
            if now == c:
                return queue[0]
            heapq.heapreplace(queue, (now, k, e))

    def update(self, e: Hashable, w: int = 1) -> None:
        if w <= 0:
            raise ValueError("weights are positive: deletions are not supported")
        self.n += w
        raw = self.raw
        if e in raw:
            raw[e] += w
            return
        while len(raw) >= self.m:
            least = self._least()[0] - self.offset
            taken = min(least, w)
            self.offset += taken
            w -= taken
            while raw and self._least()[0] <= self.offset:
                del raw[heapq.heappop(self.queue)[2]]
            if not w:
                return
        raw[e] = self.offset + w
        self.pushed += 1
        heapq.heappush(self.queue, (raw[e], self.pushed, e))

    def to_rows(self) -> list[tuple[Hashable, int, int]]:
        """(element, estimate, how much it may be low)."""
        return [(e, v - self.offset, self.offset) for e, v in self.raw.items()]


class FrequentSummary(WeightedFrequent):
    """Frequent with unit updates: the offset grows by one, so elements are filed by the offset that they were last seen to leave at."""

    weighted = False

    def __init__(self, m: int):
        super().__init__(m)
        self.filed: dict[int, list[Hashable]] = {}

    def update(self, e: Hashable, w: int = 1) -> None:
        if w != 1:
            raise ValueError("Frequent takes unit updates; WeightedFrequent takes weights")
        self.update_many((e,))

    def update_many(self, elements: Sequence[Hashable]) -> None:
        """Register an arrival of each element."""
        raw, filed, m, offset = self.raw, self.filed, self.m, self.offset
        self.n += len(elements)
        for e in elements:
            if e in raw:
                raw[e] += 1
            elif len(raw) < m:
                raw[e] = offset + 1
                filed.setdefault(offset + 1, []).append(e)
            else:
                offset += 1
                for x in filed.pop(offset, ()):
                    if raw[x] == offset:
                        del raw[x]
                    else:
                        filed.setdefault(raw[x], []).append(x)
        self.offset = offset


class FiledSummary:
    """Space-Saving with unit updates and no queries between them: slots are filed by the count that they were last seen to have,
    and looked at again when that is the least one."""

    weighted = False

    def __init__(self, m: int):
        self.m = padded(m)
        self.count: dict[Hashable, int] = {}
        self.over: dict[Hashable, int] = {}
        self.filed: dict[int, list[Hashable]] = {}
        self.low = 1  # no count is less
        self.n = 0

    @property
    def f_min(self) -> int:
        return min(self.count.values()) if len(self.count) == self.m else 0

    def update_many(self, elements: Sequence[Hashable]) -> None:
        """Register an arrival of each element."""
        count, over, filed, m, low = self.count, self.over, self.filed, self.m, self.low
        self.n += len(elements)
        for e in elements:
            if e in count:
                count[e] += 1
                continue
            if len(count) < m:
                least = 0
            else:
                while True:
                    some = filed.get(low)
                    if not some:
                        filed.pop(low, None)
                        low += 1
                        continue
                    gone = some.pop()
                    now = count[gone]
                    if now == low:
                        break
                    filed.setdefault(now, []).append(gone)
                del count[gone], over[gone]
                least = low
            count[e], over[e] = least + 1, least
            filed.setdefault(least + 1, []).append(e)
        self.low = low

    def to_rows(self) -> list[tuple[Hashable, int, int]]:
        return [(e, c, self.over[e]) for e, c in self.count.items()]


class LossyCounting:
    """Counts with pruning at the ends of buckets of ceil(1 / eps) arrivals; low by at most eps * n."""

    weighted = True

    def __init__(self, eps):
        self.width = math.ceil(1 / exact(eps))
        self.entries: dict[Hashable, list[int]] = {}  # element -> [count, most it may be low]
        self.n = 0
        self.bucket = 1

    def update(self, e: Hashable, w: int = 1) -> None:
        self.n += w
        entry = self.entries.get(e)
        if entry is None:
            self.entries[e] = [w, self.bucket - 1]
        else:
            entry[0] += w
        now = -(-self.n // self.width)
        if now > self.bucket or self.n % self.width == 0:
            done = self.n // self.width
            self.entries = {k: v for k, v in self.entries.items() if v[0] + v[1] > done}
            self.bucket = done + 1

    def update_many(self, elements: Sequence[Hashable]) -> None:
        """Register an arrival of each element, up to the end of a bucket at a time."""
        at = 0
        while at < len(elements):
            entries, low = self.entries, self.bucket - 1
            part = elements[at : at + self.width - self.n % self.width]
            for e in part:
                if e in entries:
                    entries[e][0] += 1
                else:
                    entries[e] = [1, low]
            at += len(part)
            self.n += len(part)
            if self.n % self.width == 0:
                done = self.n // self.width
                self.entries = {k: v for k, v in entries.items() if v[0] + v[1] > done}
                self.bucket = done + 1

    def to_rows(self) -> list[tuple[Hashable, int, int]]:
        return [(e, c, low) for e, (c, low) in self.entries.items()]
