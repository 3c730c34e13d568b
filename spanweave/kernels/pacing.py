"""Steady emission: a buffer between the search and its consumer, driven by the search's events alone.

Warm-up holds the first n solutions (n even).  The inner nodes that are open then are the spine; below it every subtree is
paced by itself, with depths counted from its root.  One buffered solution goes out when an inner node of even depth is met
first, or one of odd depth is finished; a leaf's solution goes out at once if the buffer is full (3n/2) or if its parent had
two leaves before, and is kept otherwise; a spine node of odd depth gives one when finished.  What is left goes out at the
end.
"""

from __future__ import annotations

from collections import deque
from collections.abc import Iterable, Iterator

from .branching import Event


class Pacer:
    def __init__(self, warmup: int) -> None:
        self.n = max(2, warmup + warmup % 2)
        self.held: deque[Event] = deque()
        self.underflow = self.most_held = self.longest_gap = self.steps = 0

    def _give(self) -> Iterator[Event]:
        if self.held:
            self.longest_gap, self.steps = max(self.longest_gap, self.steps), 0
            yield self.held.popleft()
        else:
            self.underflow += 1

    def _keep(self, e: Event) -> None:
        self.held.append(e)
        self.most_held = max(self.most_held, len(self.held))

    def __call__(self, events: Iterable[Event]) -> Iterator[Event]:
        """The leaf events, in paced order."""
        warm, spine = True, -1
        for e in events:
            if warm:
                if e.kind == "leaf":
                    self._keep(e)
                    if len(self.held) == self.n:
                        warm, spine = False, e.depth - 1
                continue
            self.steps += 1
            if e.kind == "leaf":
                if len(self.held) >= 3 * self.n // 2 or e.sibling >= 2:
                    self.longest_gap, self.steps = max(self.longest_gap, self.steps), 0
                    yield e
                else:
                    self._keep(e)
            elif e.kind == "enter":
                if (e.depth - spine - 1) % 2 == 0:
                    yield from self._give()
            elif e.depth <= spine:
                if e.depth % 2:
                    yield from self._give()
                spine = e.depth - 1
            elif (e.depth - spine - 1) % 2:
                yield from self._give()
        while self.held:
            yield self.held.popleft()
