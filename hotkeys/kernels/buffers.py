"""A worker's bounded buffers, one for each owner, with both reasons for handing them over."""

from __future__ import annotations

from collections.abc import Hashable

Batch = list[tuple[int, dict[Hashable, int]]]


class HandoverBuffers:
    """insert() returns nothing, or every nonempty buffer when one has `slots` distinct elements or
    `every` updates have come since the last time."""

    def __init__(self, owners: int, slots: int, every: int):
        self.slots, self.every = slots, every
        self.held: list[dict[Hashable, int]] = [{} for _ in range(owners)]
        self.since = 0
        self.n = 0

    def insert(self, owner: int, e: Hashable, w: int = 1) -> Batch:
        held = self.held[owner]
        held[e] = held.get(e, 0) + w
        self.since += 1
        self.n += w
        return self.flush() if len(held) >= self.slots or self.since >= self.every else []

    def flush(self) -> Batch:
        out = [(i, b) for i, b in enumerate(self.held) if b]
        self.held = [{} for _ in self.held]
        self.since = 0
        return out

    def pending(self, e: Hashable) -> int:
        return sum(b.get(e, 0) for b in self.held)
