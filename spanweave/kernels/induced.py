"""Minimal vertex sets that induce a connection of the terminals, in graphs without claws, and neighbours between such sets.

Vertex sets are integers used as bit sets.
"""

from __future__ import annotations

from collections.abc import Iterator


def masks(n: int, ends: list[tuple[int, int]]) -> list[int]:
    near = [0] * n
    for a, b in ends:
        if a != b:
            near[a] |= 1 << b
            near[b] |= 1 << a
    return near


def members(mask: int) -> list[int]:
    out = []
    while mask:
        low = mask & -mask
        out.append(low.bit_length() - 1)
        mask ^= low
    return out


def part(near: list[int], start: int, allowed: int) -> int:
    """The component of vertex ``start`` within ``allowed``."""
    seen = todo = 1 << start
    while todo:
        v = (todo & -todo).bit_length() - 1
        todo &= todo - 1
        new = near[v] & allowed & ~seen
        seen |= new
        todo |= new
    return seen


def around(near: list[int], mask: int) -> int:
    out = 0
    for v in members(mask):
        out |= near[v]
    return out


def shrink(near: list[int], universe: int, keep: int) -> int | None:
    """``universe`` without the vertices that ``keep``'s connection does not need, tried in ascending order; None if it is not connected."""
    anchor = (keep & -keep).bit_length() - 1
    now = part(near, anchor, universe)
    if keep & ~now:
        return None
    for u in members(now & ~keep):
        if now >> u & 1:
            rest = part(near, anchor, now & ~(1 << u))
            if not keep & ~rest:
                now = rest
    return now


def swap_neighbours(near: list[int], solution: int, terminals: int, everything: int) -> Iterator[tuple[int, int, int]]:
    """(solution, v, w): v leaves a solution, which falls into two sides; w joins one side, and a shortest path reconnects the sides.

    The path leaves the grown side at w only: its other vertices stay clear of that side and of what is next to it, and of v.
    """
    for v in members(solution & ~terminals):
        rest = solution & ~(1 << v)
        one = part(near, (rest & -rest).bit_length() - 1, rest)
        for side, other in ((one, rest & ~one), (rest & ~one, one)):
            if not side or not other:
                continue
            for w in members(around(near, side) & ~solution & everything):
                grown = shrink(near, side | 1 << w, side & terminals | 1 << w)
                rear = shrink(near, other, other & terminals) if other & terminals else None
                if grown is None or rear is None:
                    continue
                core = grown & ~(1 << w)
                barred = (core | around(near, core) | 1 << v) & ~(1 << w)
                found = _bridge(near, w, rear, everything & ~barred)
                if found is None:
                    continue
                result = shrink(near, grown | rear | found, terminals)
                if result is not None and not result >> v & 1:
                    yield result, v, w


def _bridge(near: list[int], start: int, goal: int, allowed: int) -> int | None:
    """Vertices of a shortest path from ``start`` into ``goal`` through allowed vertices."""
    came, todo = {start: -1}, [start]
    for x in todo:
        if goal >> x & 1:
            out = 0
            while x >= 0:
                out |= 1 << x
                x = came[x]
            return out
        for y in members(near[x] & (allowed | goal)):
            if y not in came:
                came[y] = x
                todo.append(y)
    return None


def is_minimal(near: list[int], mask: int, terminals: int) -> bool:
    """Connected, with all terminals, and no proper subset of it connects them.  One vertex at a time suffices: whatever smaller set connects them, some vertex beyond it can go while the terminals stay connected."""
    anchor = (terminals & -terminals).bit_length() - 1
    if terminals & ~mask or part(near, anchor, mask) != mask:
        return False
    return all(terminals & ~part(near, anchor, mask & ~(1 << v)) for v in members(mask & ~terminals))


def traverse(near: list[int], terminals: int, everything: int) -> Iterator[int]:
    """All solutions reachable from the greedy one, within one process (graphs without claws: all there are)."""
    first = shrink(near, everything, terminals)
    if first is None:
        return
    met, todo = {first}, [first]
    for x in todo:
        yield x
        for y, _, _ in swap_neighbours(near, x, terminals, everything):
            if y not in met:
                met.add(y)
                todo.append(y)
