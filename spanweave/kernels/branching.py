"""One branching driver for all problems whose solutions grow by attaching paths.

A node of the search holds a partial solution.  Its problem either names a target, for which every way to attach it becomes
a child, or says that the partial solution has one completion, which is emitted.  With ``improved`` branching a target has
at least two attachments, so inner nodes are fewer than leaves; with ``simple`` branching the first missing target is taken.
"""

from __future__ import annotations

from collections.abc import Iterator
from typing import NamedTuple

from .paths import WHOLE, PathSearch, Rest


class Event(NamedTuple):
    """``kind``: enter, leaf or leave; ``solution`` (edge positions) with leaves; ``sibling``: how many leaf children its parent had before; ``work``: arcs looked at so far."""

    kind: str
    depth: int
    solution: tuple[int, ...] | None = None
    sibling: int = 0
    work: int = 0


class Continuation(NamedTuple):
    """An unfinished node: the attached paths, and what is left of the search for its children."""

    attached: tuple[tuple[int, ...], ...]
    rest: Rest


ROOT = Continuation((), WHOLE)


class Level:
    """A live inner node: its target's path search and how many of its children were leaves."""

    __slots__ = ("leaves", "paths", "search")

    def __init__(self, search: PathSearch) -> None:
        self.search, self.paths, self.leaves = search, iter(search), 0


class Enumeration:
    """Solutions below one continuation.  ``events`` walks the search; ``unfinished`` writes down what is left of it."""

    def __init__(self, problem, start: Continuation = ROOT) -> None:
        self.problem, self.start, self.levels, self.peak = problem, start, [], 0
        for path in start.attached:
            problem.push(list(path))

    def events(self) -> Iterator[Event]:
        p, g = self.problem, self.problem.g
        base = len(self.start.attached)

        def visit(rest: Rest = WHOLE) -> tuple[int, ...] | None:
            target, solution = p.choose()
            if target is None:
                return solution
            self.levels.append(Level(p.attachments(target, rest)))
            return None

        if not p.feasible:
            return
        solution = visit(self.start.rest)
        if solution is not None:
            yield Event("leaf", base, solution, 0, g.work)
            return
        yield Event("enter", base, work=g.work)
        while self.levels:
            level = self.levels[-1]
            path = next(level.paths, None)
            depth = base + len(self.levels)
            if path is None:
                self.levels.pop()
                yield Event("leave", depth - 1, work=g.work)
                if self.levels:
                    p.pop()
                continue
            p.push(path[0])
            self.peak = max(self.peak, p.size() + sum(len(x.search.edges) for x in self.levels))
            solution = visit()
            if solution is not None:
                p.pop()
                level.leaves += 1
                yield Event("leaf", depth, solution, level.leaves - 1, g.work)
            else:
                yield Event("enter", depth, work=g.work)

    def unfinished(self) -> list[Continuation]:
        """The rest of the search as rows that do not overlap; the search is over for this object."""
        out, attached = [], list(self.problem.attached[: len(self.start.attached)])
        for k, level in enumerate(self.levels):
            rests, late = level.search.split()
            out += [Continuation(tuple(attached), r) for r in rests]
            out += [Continuation((*attached, tuple(edges)), WHOLE) for edges, _ in late]
            where = len(self.start.attached) + k
            if where < len(self.problem.attached):
                attached.append(self.problem.attached[where])
        self.levels = []
        return out


class AttachProblem:
    """What the problems share: terminals by position, the attached paths, and whether there can be a solution at all."""

    def __init__(self, g, improved: bool = True, alternate: bool = True) -> None:
        self.g, self.improved, self.alternate = g, improved, alternate
        self.attached: list[tuple[int, ...]] = []
        self.edges: list[int] = []
        self.feasible = True

    def size(self) -> int:
        return len(self.edges)

    def push(self, path: list[int]) -> None:
        self.attached.append(tuple(path))
        self.edges += path
        self.grow(path)

    def pop(self) -> None:
        path = self.attached.pop()
        del self.edges[len(self.edges) - len(path) :]
        self.shrink(path)

    def done(self) -> tuple[None, tuple[int, ...]]:
        return None, tuple(self.edges)
