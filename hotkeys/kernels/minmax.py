"""Space-Saving counters in a min-max heap: the least and the greatest count are both at the top.

Slots are numbered from 1; a slot's level is the position of its number's highest bit. Counts on
even levels are least in their subtree, on odd levels greatest. A query goes down the odd levels
while counts pass, then up the even levels from where it came out, in waves.
"""

from __future__ import annotations

import heapq
import math
from collections.abc import Callable, Hashable, Iterable
from dataclasses import dataclass

from hotkeys.spec import exact


@dataclass
class QueryStats:
    comparisons: int = 0


def padded(m: int) -> int:
    """The least number of slots not under m, nor under 3, in which every group of four grandchildren is whole."""
    return 4 * (m // 4) + 3


class MinMaxSummary:
    """Estimates are never low and at most f_min high; over is each slot's own bound on that.

    A slot is a list [count, element, over, place] that moves through the heap as a whole, so the map from
    elements to slots stays as it is when order is restored.
    """

    weighted = True

    def __init__(self, m: int):
        if m < 1:
            raise ValueError("a summary needs a counter")
        self.m = padded(m)
        self.heap: list[list] = [[0, None, 0, i] for i in range(self.m + 1)]  # the first is not used
        self.place: dict[Hashable, list] = {}
        self.n = 0
        self.stats = QueryStats()

    @classmethod
    def from_eps(cls, eps) -> MinMaxSummary:
        return cls(math.ceil(1 / exact(eps)))

    @property
    def f_min(self) -> int:
        return self.heap[1][0]

    @property
    def f_max(self) -> int:
        return max(self.heap[2][0], self.heap[3][0])

    def __len__(self) -> int:
        return len(self.place)

    # --- heap order ---

    def _lift(self, i: int, slot: list) -> None:
        """Put a grown slot at the odd level of place i, over the smaller odd-level ancestors."""
        heap, c = self.heap, slot[0]
        while i > 3 and c > heap[i >> 2][0]:
            above = heap[i >> 2]
            heap[i] = above
            above[3] = i
            i >>= 2
        heap[i] = slot
        slot[3] = i

    def _sink(self, i: int, slot: list) -> None:
        """Put a grown slot at the even level of place i, under the smaller descendants.

        A place has four grandchildren or none, and those are never above their parents.
        """
        heap, m, c = self.heap, self.m, slot[0]
        k = 4 * i
        while k + 3 <= m:
            least, other, third, fourth = heap[k : k + 4]
            if other[0] < least[0]:
                least = other
            if fourth[0] < third[0]:
                third = fourth
            if third[0] < least[0]:
                least = third
            if least[0] >= c:
                heap[i] = slot
                slot[3] = i
                return
            j = least[3]
            heap[i] = least
            least[3] = i
            up = heap[j >> 1]
            if c > up[0]:
                heap[j >> 1] = slot
                slot[3] = j >> 1
                slot, c = up, up[0]
            i, k = j, 4 * j
        if 2 * i + 1 <= m:
            least = heap[2 * i] if heap[2 * i][0] <= heap[2 * i + 1][0] else heap[2 * i + 1]
            if least[0] < c:
                j = least[3]
                heap[i] = least
                least[3] = i
                i = j
        heap[i] = slot
        slot[3] = i

    def _ordered(self) -> None:
        """Restore the order of all slots at once: descending counts, dealt to odd levels from the top and even ones from below.

        Sorted by level, odd levels downwards hold ever smaller counts and even levels upwards as well, so a slot on
        an odd level is at least all below it, and one on an even level at most.
        """
        heap = self.heap
        slots = sorted(heap[1:], key=lambda s: -s[0])
        at, top = 0, self.m.bit_length()
        levels = [x for x in range(2, top + 1) if not x & 1] + [x for x in range(top, 0, -1) if x & 1]
        for level in levels:
            for i in range(1 << (level - 1), min(1 << level, self.m + 1)):
                heap[i] = slots[at]
                slots[at][3] = i
                at += 1

    def check_invariant(self) -> None:
        count = [s[0] for s in self.heap]
        for i in range(2, self.m + 1):
            up, odd = i >> 1, i.bit_length() % 2 == 0
            assert count[i] >= count[up] if odd else count[i] <= count[up], (i, up)
            if i > 3:
                assert count[i] <= count[i >> 2] if odd else count[i] >= count[i >> 2], i
        assert all(s[3] == i for i, s in enumerate(self.heap[1:], 1))
        assert all(s[1] == e and self.heap[s[3]] is s for e, s in self.place.items())
        assert sum(count) == self.n

    # --- updates ---

    def update(self, e: Hashable, w: int = 1) -> None:
        """Register w arrivals of e."""
        if w <= 0:
            raise ValueError("weights are positive: deletions are not supported")
        self.n += w
        slot = self.place.get(e)
        if slot is None:
            slot = self.heap[1]
            if slot[1] is not None:
                del self.place[slot[1]]
            slot[1], slot[2] = e, slot[0]
            self.place[e] = slot
            slot[0] += w
            self._sink(1, slot)
            return
        slot[0] += w
        i = slot[3]
        if i.bit_length() & 1:
            if i > 1:
                up = self.heap[i >> 1]
                if slot[0] > up[0]:
                    self._lift(i >> 1, slot)
                    slot = up
            self._sink(i, slot)
        elif i > 3 and slot[0] > self.heap[i >> 2][0]:
            self._lift(i, slot)

    def update_all(self, elements: list[Hashable], weights: list[int], low: int, replaced: Callable[[Hashable, Hashable, int], None] | None = None) -> bool:
        """Register pairs one by one, in plain loops; whether a count has passed low.

        replaced is told who loses a slot, who takes it, and the count that is taken over.
        """
        if min(weights, default=1) <= 0:
            raise ValueError("weights are positive: deletions are not supported")
        heap, place, passed = self.heap, self.place, False
        for e, w in zip(elements, weights, strict=True):
            slot = place.get(e)
            if slot is None:
                slot = heap[1]
                c, gone = slot[0], slot[1]
                if gone is not None:
                    del place[gone]
                    if replaced:
                        replaced(gone, e, c)
                slot[0], slot[1], slot[2] = c + w, e, c
                place[e] = slot
                self._sink(1, slot)
            else:
                c, i = slot[0], slot[3]
                slot[0] = c + w
                if i.bit_length() & 1:
                    up = heap[i >> 1]
                    if i > 1 and c + w > up[0]:
                        self._lift(i >> 1, slot)
                        slot = up
                    self._sink(i, slot)
                elif i > 3 and c + w > heap[i >> 2][0]:
                    self._lift(i, slot)
            if c <= low < c + w:
                passed = True
        self.n += sum(weights)
        return passed

    def update_batch(self, elements: Iterable[Hashable], weights: Iterable[int]) -> None:
        """Register already combined pairs, tracked elements first so that fewer are thrown out.

        Counts of tracked elements, and of new ones while slots are free, are added up without a look at the order,
        which is restored once; only what must replace a slot goes one by one.
        """
        place, tracked, rest = self.place, [], []
        for e, w in zip(elements, weights, strict=True):
            if w <= 0:
                raise ValueError("weights are positive: deletions are not supported")
            (rest if e not in place else tracked).append((e, w))
        free = self.m - len(place)
        if 8 * (len(tracked) + min(free, len(rest))) < self.m:  # few changes are cheaper one by one
            rest = tracked + rest
        else:
            for e, w in tracked:
                place[e][0] += w
                self.n += w
            if free:
                new, rest = rest[:free], rest[free:]
                for slot, (e, w) in zip([s for s in self.heap[1:] if s[1] is None], new, strict=False):
                    slot[:2] = w, e
                    place[e] = slot
                    self.n += w
            self._ordered()
        for e, w in rest:
            self.update(e, w)

    # --- reads ---

    def _above(self, slots: Iterable[int], p: int, q: int) -> list[int]:
        """Those of the slots whose count times q exceeds p; counts the comparisons."""
        slots = list(slots)
        self.stats.comparisons += len(slots)
        heap = self.heap
        return [i for i in slots if heap[i][0] * q > p]

    def query(self, phi, n: int | None = None) -> list[tuple[Hashable, int]]:
        """(element, estimate) of every slot above phi * n, n being the summary's own total unless given."""
        phi = exact(phi)
        p, q = phi.numerator * (self.n if n is None else n), phi.denominator
        self.stats = QueryStats()
        found, feet = [], set()
        wave = self._above((2, 3), p, q)
        while wave:  # down the odd levels
            found += wave
            ahead = []
            for i in wave:
                if 4 * i + 3 <= self.m:
                    ahead += range(4 * i, 4 * i + 4)
                else:
                    feet |= {2 * i, 2 * i + 1} if 2 * i + 1 <= self.m else {i >> 1}
            wave = self._above(ahead, p, q)
        seen = set(feet)
        wave = self._above(feet, p, q)
        while wave:  # up the even levels
            found += wave
            up = {i >> 2 for i in wave if i > 3} - seen
            seen |= up
            wave = self._above(up, p, q)
        return [(self.heap[i][1], self.heap[i][0]) for i in found if self.heap[i][1] is not None]

    def top_k(self, k: int) -> list[tuple[Hashable, int]]:
        """The k largest estimates, best first, without a look at most slots."""
        queue = [(-self.heap[i][0], i) for i in (2, 3)]
        heapq.heapify(queue)
        out: list[tuple[Hashable, int]] = []
        seen = {2, 3}
        while queue and len(out) < k:
            c, i = heapq.heappop(queue)
            if self.heap[i][1] is not None:
                out.append((self.heap[i][1], -c))
            if i.bit_length() % 2 == 0:
                down = range(4 * i, 4 * i + 4) if 4 * i + 3 <= self.m else ((2 * i, 2 * i + 1) if 2 * i + 1 <= self.m else (i >> 1,))
            else:
                down = (i >> 2,) if i > 3 else ()
            for j in down:
                if j not in seen:
                    seen.add(j)
                    heapq.heappush(queue, (-self.heap[j][0], j))
        return out

    def estimate(self, e: Hashable) -> int:
        """An upper bound of e's count: its estimate, or f_min where it has no slot."""
        slot = self.place.get(e)
        return self.f_min if slot is None else slot[0]

    def to_rows(self) -> list[tuple[Hashable, int, int]]:
        """(element, estimate, over) in slot order, empty slots left out."""
        return [(e, c, over) for c, e, over, _ in self.heap[1:] if e is not None]

    @classmethod
    def from_rows(cls, m: int, rows: Iterable[tuple[Hashable, int, int]]) -> MinMaxSummary:
        out = cls(m)
        for slot, (e, est, over) in zip(out.heap[1:], rows, strict=False):
            slot[:3] = est, e, over
            out.place[e] = slot
            out.n += est
        out._ordered()
        return out


def bound_of_query(answers: int) -> int:
    """Most comparisons that a query with so many answers makes: two at the top, four for each answer."""
    return 4 * answers + 2
