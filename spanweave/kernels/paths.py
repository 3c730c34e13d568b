"""All simple paths to a target, each once, by leaving known paths.

A node of the search stands for the paths that share a prefix and do not go on by one forbidden arc.  It walks through one
representative path for every first arc that leads on; each representative is emitted, and every inner position from which
another way to the target exists becomes a child node: prefix up to there, the representative's arc forbidden.  Nodes of
even depth emit before their children, those of odd depth after, so that at most two nodes in a row emit nothing.

A node's whole memory is its prefix length, the forbidden arc and the last first arc used, as the search for the next
representative is deterministic; so an unfinished search can be written down as a few rows and resumed elsewhere.
"""

from __future__ import annotations

from collections.abc import Iterator
from typing import NamedTuple

from .graph import Graph


class Rest(NamedTuple):
    """What is left of a node: edges of the prefix, the forbidden edge (-1: none), first arcs up to ``floor`` done, depth."""

    prefix: tuple[int, ...]
    banned: int
    floor: int
    depth: int


WHOLE = Rest((), -1, -1, 0)


class _Node:
    __slots__ = ("at", "banned", "depth", "floor", "late", "live", "piece", "scan", "size")

    def __init__(self, size: int, at: int, banned: int, floor: int, depth: int) -> None:
        self.size, self.at, self.banned, self.floor, self.depth = size, at, banned, floor, depth
        self.piece: list[tuple[int, int]] | None = None  # the representative beyond the prefix: (edge, vertex)
        self.scan, self.late = 0, False
        self.live: bytearray | None = None


class PathSearch:
    """Paths from one vertex, or from a set by its leaving arcs, to ``target``, off the vertices in ``blocked``.

    ``keep_marks``: keep each node's reachability marks while its children run instead of finding them anew afterwards.
    """

    def __init__(self, g: Graph, first: list[tuple[int, int]], target: int, blocked: bytearray, *, alternate: bool = True, keep_marks: bool = False, start: Rest = WHOLE, out=None, inn=None) -> None:
        self.g, self.first, self.target, self.alternate, self.keep_marks = g, first, target, alternate, keep_marks
        self.out, self.inn = out or g.out, inn or g.inn
        self.on = bytearray(blocked)
        self.edges: list[int] = []
        self.vertices: list[int] = []
        self.stack: list[_Node] = []
        self.nodes = 0
        at = -1
        for e in start.prefix:
            at = next(w for k, w in self._arcs(at) if k == e)
            self._extend(e, at)
        self._open(_Node(len(self.edges), at, start.banned, start.floor, start.depth))

    def _arcs(self, v: int) -> list[tuple[int, int]]:
        return self.first if v < 0 else self.out[v]

    def _extend(self, edge: int, vertex: int) -> None:
        self.edges.append(edge)
        self.vertices.append(vertex)
        self.on[vertex] = 1

    def _cut(self, size: int) -> None:
        for v in self.vertices[size:]:
            self.on[v] = 0
        del self.edges[size:], self.vertices[size:]

    def _open(self, node: _Node) -> None:
        self.nodes += 1
        self.stack.append(node)

    def _ways_in(self, live: bytearray, todo: list[int], step: dict[int, tuple[int, int]] | None = None) -> None:
        """Mark what reaches the marked vertices in ``todo`` off the present path; ``step`` gets each vertex's next arc."""
        on, inn = self.on, self.inn
        for v in todo:
            self.g.work += len(inn[v])
            for k, w in inn[v]:
                if not live[w] and not on[w]:
                    live[w] = 1
                    if step is not None:
                        step[w] = (k, v)
                    todo.append(w)

    def _next(self, node: _Node) -> list[tuple[int, int]] | None:
        """The representative with the smallest first arc beyond the floor."""
        live, step = bytearray(len(self.out)), {}
        live[self.target] = 1
        self._ways_in(live, [self.target], step)
        for position, (k, w) in enumerate(self._arcs(node.at)):
            self.g.work += 1
            if position > node.floor and k != node.banned and live[w] and not self.on[w]:
                node.floor, piece = position, [(k, w)]
                while w != self.target:
                    k, w = step[w]
                    piece.append((k, w))
                return piece
        return None

    def _marks(self, node: _Node) -> bytearray:
        """Marks for position ``node.scan`` of its representative: what reaches the target off everything up to there."""
        self._cut(node.size)
        for k, w in node.piece[: node.scan]:
            self._extend(k, w)
        live = bytearray(len(self.out))
        live[self.target] = 1
        todo = [self.target]
        self._ways_in(live, todo)
        return live

    def _child(self, node: _Node) -> _Node | None:
        """The next inner position, going backwards, from which another way exists; marks only ever turn on meanwhile."""
        while node.scan > 0:
            i, at = node.scan, node.piece[node.scan - 1][1]
            if node.live is None:
                node.live = self._marks(node)
            banned = node.piece[i][0]
            self.g.work += len(self.out[at])
            other = any(k != banned and node.live[w] and not self.on[w] for k, w in self.out[at])
            if other:
                child = _Node(node.size + i, at, banned, -1, node.depth + 1)
            # One step back: the vertex is free again, and it reaches the target by the representative.
            self._cut(node.size + i - 1)
            node.scan -= 1
            node.live[at] = 1
            self._ways_in(node.live, [at])
            if other:
                if not self.keep_marks:
                    node.live = None
                # the child's prefix holds the vertex that was just freed
                for k, w in node.piece[i - 1 : i]:
                    self._extend(k, w)
                return child
        return None

    def __iter__(self) -> Iterator[tuple[list[int], list[int]]]:
        """(edges, vertices beyond the start) of each path; lists of their own."""
        while self.stack:
            node = self.stack[-1]
            if node.piece is None:
                self._cut(node.size)
                piece = self._next(node)
                if piece is None:
                    self.stack.pop()
                    continue
                node.piece, node.scan, node.live = piece, len(piece) - 1, None
                node.late = self.alternate and node.depth % 2 == 1
                if not node.late:
                    yield self._whole(node)
                continue
            self._cut(node.size + node.scan)
            child = self._child(node)
            if child is not None:
                self._open(child)
                continue
            piece, late = node.piece, node.late
            result = self._whole(node) if late else None
            node.piece = node.live = None
            if late:
                yield result

    def _whole(self, node: _Node) -> tuple[list[int], list[int]]:
        return self.edges[: node.size] + [k for k, _ in node.piece], self.vertices[: node.size] + [w for _, w in node.piece]

    def split(self) -> tuple[list[Rest], list[tuple[list[int], list[int]]]]:
        """Stop: what is left as rows that do not overlap, and the late paths that were still to be emitted."""
        rest, late = [], []
        path = list(self.edges)
        for node in self.stack:
            prefix = tuple(path[: node.size])
            rest.append(Rest(prefix, node.banned, node.floor, node.depth))
            if node.piece is None:
                continue
            whole = [*prefix, *(k for k, _ in node.piece)]
            if node.late:
                late.append((whole, self.vertices[: node.size] + [w for _, w in node.piece]))
            rest += [Rest(tuple(whole[: node.size + i]), node.piece[i][0], -1, node.depth + 1) for i in range(node.scan, 0, -1)]
            path = whole
        self.stack = []
        return rest, late


def st_paths(g: Graph, s: int, t: int, **options) -> Iterator[list[int]]:
    """Edge positions of every simple path from vertex position s to t; the trivial path if they are equal."""
    if s == t:
        yield []
        return
    blocked = bytearray(g.n)
    blocked[s] = 1
    for edges, _ in PathSearch(g, g.out[s], t, blocked, **options):
        yield edges


def set_paths(g: Graph, sources: set[int], targets: set[int]) -> Iterator[list[int]]:
    """Paths from ``sources`` to ``targets`` with all inner vertices outside both; a common vertex is a trivial path."""
    for v in sorted(sources & targets):
        yield []
    a, b = sources - targets, targets - sources
    # One more vertex stands for all targets: arcs into a target lead there, and nothing leaves a target or enters a source.
    goal = g.n
    out = [[(k, goal if w in targets else w) for k, w in arcs if w not in sources] if v not in targets else [] for v, arcs in enumerate(g.out)] + [[]]
    inn: list[list[tuple[int, int]]] = [[] for _ in range(g.n + 1)]
    for v, arcs in enumerate(out):
        for k, w in arcs:
            inn[w].append((k, v))
    blocked = bytearray(g.n + 1)
    for v in sources:
        blocked[v] = 1
    first = sorted((k, w) for v in a for k, w in out[v])
    if first and b:
        for edges, _ in PathSearch(g, first, goal, blocked, out=out, inn=inn):
            yield edges


def shortest_path(out: list[list[tuple[int, int]]], starts: list[int], goals: set[int], allowed) -> list[int] | None:
    """Vertices of a shortest path through allowed vertices, ties by adjacency order."""
    came: dict[int, int] = dict.fromkeys(starts, -1)
    todo = list(starts)
    for v in todo:
        if v in goals:
            path = [v]
            while came[path[-1]] >= 0:
                path.append(came[path[-1]])
            return path[::-1]
        for _, w in out[v]:
            if w not in came and allowed(w):
                came[w] = v
                todo.append(w)
    return None
