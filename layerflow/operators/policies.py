"""Which partial sums leave the resident store when it is full.

Each policy knows the residents and gives up k of them, lowest rank first.  Ranks are pairs, so that ties break by
position; a lazily cleaned heap keeps the cost of a step logarithmic, except for the bucket queue, whose steps are O(1).
"""

from __future__ import annotations

import heapq
import random


class BucketQueue:
    """Residents by pending count: one linked list a count, insert, move and remove in constant time."""

    def __init__(self, max_pending: int):
        self.head: list[int] = [-1] * (max_pending + 1)
        self.next: dict[int, int] = {}
        self.prev: dict[int, int] = {}
        self.at: dict[int, int] = {}

    def __len__(self) -> int:
        return len(self.at)

    def __contains__(self, v: int) -> bool:
        return v in self.at

    def insert(self, v: int, pending: int) -> None:
        first = self.head[pending]
        self.next[v], self.prev[v], self.at[v] = first, -1, pending
        if first != -1:
            self.prev[first] = v
        self.head[pending] = v

    def remove(self, v: int) -> int:
        pending, before, after = self.at.pop(v), self.prev.pop(v), self.next.pop(v)
        if before == -1:
            self.head[pending] = after
        else:
            self.next[before] = after
        if after != -1:
            self.prev[after] = before
        return pending

    def decrease(self, v: int, by: int) -> None:
        self.insert(v, self.remove(v) - by)

    def lowest(self):
        """Residents from the lowest count up; of one count by id."""
        for first in self.head:
            bucket, v = [], first
            while v != -1:
                bucket.append(v)
                v = self.next[v]
            yield from sorted(bucket)


class Policy:
    """Ranks change as messages come; ``note(v, pending, slice, next_use)`` tells of each."""

    def __init__(self, seed: int = 0):
        self.rank: dict[int, tuple] = {}
        self.heap: list[tuple] = []

    def order(self, v: int, pending: int, step: int, next_use: int) -> float:
        raise NotImplementedError

    def note(self, v: int, pending: int, step: int, next_use: int = 0) -> None:
        r = (self.order(v, pending, step, next_use), v)
        if self.rank.get(v) != r:
            self.rank[v] = r
            heapq.heappush(self.heap, r)

    def forget(self, v: int) -> None:
        self.rank.pop(v, None)

    def victims(self, k: int, pinned: set[int]) -> list[int]:
        found, aside = [], []
        while len(found) < k and self.heap:
            r = heapq.heappop(self.heap)
            if self.rank.get(r[1]) != r:
                continue
            (aside if r[1] in pinned else found).append(r[1])
        for v in aside:
            heapq.heappush(self.heap, self.rank[v])
        for v in found:
            self.forget(v)
        return found


class FewestPending(Policy):
    """Those with the fewest messages to come: they cost one reload at most a message left."""

    def order(self, v, pending, step, next_use):
        return pending


class MostPending(Policy):
    def order(self, v, pending, step, next_use):
        return -pending


class LeastRecent(Policy):
    def order(self, v, pending, step, next_use):
        return step


class Fifo(Policy):
    def order(self, v, pending, step, next_use):
        return self.rank[v][0] if v in self.rank else step


class RandomVictim(Policy):
    def __init__(self, seed: int = 0):
        super().__init__(seed)
        self.rng = random.Random(seed)

    def order(self, v, pending, step, next_use):
        return self.rank[v][0] if v in self.rank else self.rng.random()


class FarthestNext(Policy):
    """Belady's choice: those used again latest."""

    def order(self, v, pending, step, next_use):
        return -next_use


POLICIES: dict[str, type[Policy]] = {"fewest": FewestPending, "most": MostPending, "lru": LeastRecent, "fifo": Fifo, "random": RandomVictim, "farthest": FarthestNext}
