"""Minimal Steiner trees, directed, undirected and with terminals as leaves only, as problems of the branching driver."""

from __future__ import annotations

from .branching import AttachProblem
from .graph import Graph, bridges, reached
from .paths import WHOLE, PathSearch, Rest


class _Grown(AttachProblem):
    """A partial solution that is one tree: vertices in it, in order of arrival."""

    def __init__(self, g: Graph, improved: bool, alternate: bool) -> None:
        super().__init__(g, improved, alternate)
        self.inside = bytearray(g.n)
        self.vertices: list[int] = []
        self.marks: list[int] = []

    def _enter(self, v: int) -> None:
        if not self.inside[v]:
            self.inside[v] = 1
            self.vertices.append(v)

    def grow(self, path) -> None:
        self.marks.append(len(self.vertices))
        for k in path:
            for v in self.g.ends[k]:
                self._enter(v)

    def shrink(self, path) -> None:
        size = self.marks.pop()
        for v in self.vertices[size:]:
            self.inside[v] = 0
        del self.vertices[size:]

    def missing(self) -> list[int]:
        return [w for w in self.terminals if not self.inside[w]]

    def _leaving(self, allowed=None) -> list[tuple[int, int]]:
        arcs = [(k, w) for v in self.vertices for k, w in self.g.out[v] if not self.inside[w] and (allowed is None or allowed[w])]
        self.g.work += sum(len(self.g.out[v]) for v in self.vertices)
        return sorted(arcs)

    def _search(self, first, target: int, blocked: bytearray, rest: Rest) -> PathSearch:
        return PathSearch(self.g, first, target, blocked, alternate=self.alternate, start=rest)


class TreeProblem(_Grown):
    """Trees of an undirected graph that hold all terminals and no other leaf."""

    def __init__(self, g: Graph, terminals: list[int], improved: bool = True, alternate: bool = True) -> None:
        super().__init__(g, improved, alternate)
        self.terminals = sorted(set(terminals))
        self._enter(self.terminals[0])
        seen = reached(g.out, self.terminals[:1])
        self.feasible = all(seen[w] for w in self.terminals)
        self.bridge = bridges(g.n, g.ends) if improved else None

    def choose(self):
        """Improved: grow a spanning tree from the partial one and keep what leads to terminals; an edge of it that is no bridge has a terminal with a choice below it."""
        missing = self.missing()
        if not missing:
            return self.done()
        if not self.improved:
            return missing[0], None
        came: dict[int, tuple[int, int]] = {}
        todo = list(self.vertices)
        for v in todo:
            self.g.work += len(self.g.out[v])
            for k, w in self.g.out[v]:
                if not self.inside[w] and w not in came:
                    came[w] = (k, v)
                    todo.append(w)
        used, extra = set(), []
        for w in missing:
            v = w
            while not self.inside[v] and v not in used:
                used.add(v)
                k, up = came[v]
                if not self.bridge[k]:
                    return w, None
                extra.append(k)
                v = up
        return None, (*self.edges, *extra)

    def attachments(self, target: int, rest: Rest = WHOLE) -> PathSearch:
        return self._search(self._leaving(), target, self.inside, rest)


class DirectedProblem(_Grown):
    """Out-trees from a root that reach all terminals and have no other leaf."""

    def __init__(self, g: Graph, root: int, terminals: list[int], improved: bool = True, alternate: bool = True) -> None:
        super().__init__(g, improved, alternate)
        self.terminals, self.root = sorted(set(terminals)), root
        self._enter(root)
        seen = reached(g.out, [root])
        self.feasible = all(seen[w] for w in self.terminals)

    def choose(self):
        """Improved: a depth-first tree off the partial solution, kept to what leads to terminals.  Going through it in falling
        post-order, a vertex that reaches another tree vertex by other arcs than the tree's gives that one a second way in;
        what was searched in vain need not be searched again."""
        missing = self.missing()
        if not missing:
            return self.done()
        if not self.improved:
            return missing[0], None
        out, inside = self.g.out, self.inside
        came: dict[int, tuple[int, int]] = {}
        order: list[int] = []
        for source in self.vertices:
            stack = [(source, iter(out[source]))]
            while stack:
                v, rest = stack[-1]
                for k, w in rest:
                    self.g.work += 1
                    if not inside[w] and w not in came:
                        came[w] = (k, v)
                        stack.append((w, iter(out[w])))
                        break
                else:
                    stack.pop()
                    if not inside[v]:
                        order.append(v)
        kept, arcs, below = set(), [], {}
        for w in missing:
            v = w
            while not inside[v] and v not in kept:
                kept.add(v)
                below[v] = w
                arcs.append(came[v][0])
                v = came[v][1]
        tree, gone = set(arcs), bytearray(inside)
        # The contracted partial solution finishes last, so it is searched first.
        for start in [-1, *(v for v in reversed(order) if v in kept)]:
            todo = list(self.vertices) if start < 0 else [start]
            if start >= 0:
                if gone[start]:
                    continue
                gone[start] = 1
            for v in todo:
                for k, w in out[v]:
                    self.g.work += 1
                    if k in tree or gone[w]:
                        continue
                    if w in kept:
                        return below[w], None
                    gone[w] = 1
                    todo.append(w)
        return None, (*self.edges, *arcs)

    def attachments(self, target: int, rest: Rest = WHOLE) -> PathSearch:
        return self._search(self._leaving(), target, self.inside, rest)


class TerminalProblem(_Grown):
    """Trees within one admissible component (no terminal in it, every terminal next to it) whose leaves are all the terminals.

    ``g`` has no terminal-terminal edges.  For two terminals see ``st_paths``; this is for three or more.
    """

    def __init__(self, g: Graph, terminals: list[int], component: bytearray, improved: bool = True, alternate: bool = True) -> None:
        super().__init__(g, improved, alternate)
        self.terminals, self.component = sorted(set(terminals)), component
        self.outside = bytearray(1 - c for c in component)
        if improved:
            inner = [k for k, (a, b) in enumerate(g.ends) if component[a] and component[b]]
            cut = bridges(g.n, [g.ends[k] for k in inner])
            self.bridge = {k: bool(b) for k, b in zip(inner, cut, strict=True)}

    def choose(self):
        """A terminal has one attachment only if it has one edge into the component and all that leads there is bridges of the component; paths never pass another terminal."""
        missing = self.missing()
        if not missing:
            return self.done()
        if not self.improved or not self.vertices:
            return missing[0], None
        came: dict[int, tuple[int, int]] = {}
        todo = [v for v in self.vertices if self.component[v]]
        for v in todo:
            self.g.work += len(self.g.out[v])
            for k, w in self.g.out[v]:
                if self.component[w] and not self.inside[w] and w not in came:
                    came[w] = (k, v)
                    todo.append(w)
        used, extra = set(), []
        for w in missing:
            doors = [(k, v) for k, v in self.g.out[w] if self.component[v]]
            if len(doors) > 1:
                return w, None
            k, v = doors[0]
            extra.append(k)
            while not self.inside[v] and v not in used:
                used.add(v)
                k, up = came[v]
                if not self.bridge[k]:
                    return w, None
                extra.append(k)
                v = up
        return None, (*self.edges, *extra)

    def attachments(self, target: int, rest: Rest = WHOLE) -> PathSearch:
        blocked = bytearray(self.outside)
        blocked[target] = 0
        if self.vertices:
            for v in self.vertices:
                blocked[v] = 1
            first = [(k, w) for k, w in self._leaving(self.component) if w != target]
            doors = [(k, target) for k, v in self.g.out[target] if self.component[v] and self.inside[v]]
            return self._search(sorted([(k, w) for k, w in first] + doors), target, blocked, rest)
        start = next(w for w in self.terminals if w != target)
        return self._search([(k, w) for k, w in self.g.out[start] if self.component[w]], target, blocked, rest)

    def _leaving(self, allowed=None) -> list[tuple[int, int]]:
        arcs = [(k, w) for v in self.vertices if self.component[v] for k, w in self.g.out[v] if self.component[w] and not self.inside[w]]
        self.g.work += sum(len(self.g.out[v]) for v in self.vertices)
        return sorted(arcs)


def without_terminal_edges(g: Graph, terminals: set[int]) -> Graph:
    """A copy without the edges between two terminals; vertex positions stay."""
    names = g.names
    return Graph([(e, names[a], names[b]) for e, (a, b) in zip(g.edge_ids, g.ends, strict=True) if not (a in terminals and b in terminals)], False, names)


def admissible_components(g: Graph, terminals: set[int]) -> list[bytearray]:
    """Components of the graph without the terminals that every terminal is next to."""
    blocked = bytearray(1 if v in terminals else 0 for v in range(g.n))
    found, met = [], bytearray(blocked)
    for v in range(g.n):
        if not met[v]:
            part = reached(g.out, [v], blocked)
            for w in range(g.n):
                met[w] |= part[w]
            if all(any(part[u] for _, u in g.out[w]) for w in terminals):
                found.append(part)
    return found
