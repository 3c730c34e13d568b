"""Adjacency for kernels: vertices and edges by position, arcs in ascending edge order, and a counter of the arcs looked at."""

from __future__ import annotations

from collections.abc import Iterable


class Graph:
    """A multigraph.  ``edges`` are (edge_id, src, dst); self-loops are dropped and counted.  Undirected edges are two arcs with one position."""

    def __init__(self, edges: Iterable[tuple[int, int, int]], directed: bool = False, vertices: Iterable[int] = ()) -> None:
        kept, self.loops = [], 0
        for e, a, b in edges:
            if a == b:
                self.loops += 1
            else:
                kept.append((e, a, b))
        kept.sort()
        names = sorted({v for _, a, b in kept for v in (a, b)} | set(vertices))
        self.directed, self.names, self.index = directed, names, {v: k for k, v in enumerate(names)}
        self.edge_ids = [e for e, _, _ in kept]
        self.ends = [(self.index[a], self.index[b]) for _, a, b in kept]
        self.n, self.m, self.work = len(names), len(kept), 0
        self.out: list[list[tuple[int, int]]] = [[] for _ in names]
        self.inn: list[list[tuple[int, int]]] = [[] for _ in names] if directed else self.out
        for k, (a, b) in enumerate(self.ends):
            self.out[a].append((k, b))
            self.inn[b].append((k, a))

    def named(self, edges: Iterable[int]) -> list[int]:
        return sorted(self.edge_ids[k] for k in edges)


def reached(out: list[list[tuple[int, int]]], starts: Iterable[int], blocked: bytearray | None = None) -> bytearray:
    """Vertices reachable from ``starts`` without entering blocked ones."""
    seen = bytearray(len(out))
    todo = [s for s in starts if not (blocked and blocked[s])]
    for s in todo:
        seen[s] = 1
    while todo:
        v = todo.pop()
        for _, w in out[v]:
            if not seen[w] and not (blocked and blocked[w]):
                seen[w] = 1
                todo.append(w)
    return seen


def bridges(n: int, ends: list[tuple[int, int]]) -> bytearray:
    """1 for each edge whose removal disconnects its ends.  Edges are told apart by position, so parallel ones are no bridges; self-loops never are."""
    near: list[list[tuple[int, int]]] = [[] for _ in range(n)]
    for k, (a, b) in enumerate(ends):
        if a != b:
            near[a].append((k, b))
            near[b].append((k, a))
    met, low, found, clock = [0] * n, [0] * n, bytearray(len(ends)), 0
    for root in range(n):
        if met[root]:
            continue
        clock += 1
        met[root] = low[root] = clock
        stack = [(root, -1, iter(near[root]))]
        while stack:
            v, came, rest = stack[-1]
            for k, w in rest:
                if k == came:
                    continue
                if met[w]:
                    low[v] = min(low[v], met[w])
                else:
                    clock += 1
                    met[w] = low[w] = clock
                    stack.append((w, k, iter(near[w])))
                    break
            else:
                stack.pop()
                if stack:
                    up = stack[-1][0]
                    low[up] = min(low[up], low[v])
                    if low[v] > met[up]:
                        found[came] = 1
    return found


def two_connected_blocks(n: int, ends: list[tuple[int, int]]) -> list[list[int]]:
    """Edge positions of each block (maximal part without a cut vertex)."""
    near: list[list[tuple[int, int]]] = [[] for _ in range(n)]
    for k, (a, b) in enumerate(ends):
        if a != b:
            near[a].append((k, b))
            near[b].append((k, a))
    met, low, clock, waiting, out = [0] * n, [0] * n, 0, [], []
    for root in range(n):
        if met[root]:
            continue
        clock += 1
        met[root] = low[root] = clock
        stack = [(root, -1, iter(near[root]))]
        while stack:
            v, came, rest = stack[-1]
            for k, w in rest:
                if k == came:
                    continue
                if not met[w]:
                    clock += 1
                    met[w] = low[w] = clock
                    waiting.append(k)
                    stack.append((w, k, iter(near[w])))
                    break
                if met[w] < met[v]:
                    waiting.append(k)
                    low[v] = min(low[v], met[w])
            else:
                stack.pop()
                if stack:
                    up = stack[-1][0]
                    low[up] = min(low[up], low[v])
                    if low[v] >= met[up]:
                        block = []
                        while True:
                            block.append(waiting.pop())
                            if block[-1] == came:
                                break
                        out.append(block)
    return out


class UnionFind:
    def __init__(self, n: int) -> None:
        self.up = list(range(n))

    def find(self, x: int) -> int:
        while self.up[x] != x:
            self.up[x] = x = self.up[self.up[x]]
        return x

    def union(self, x: int, y: int) -> bool:
        x, y = self.find(x), self.find(y)
        if x != y:
            self.up[max(x, y)] = min(x, y)
        return x != y


class LcaIndex:
    """Lowest common ancestors in a rooted forest, by an Euler tour and a sparse table of its depths."""

    def __init__(self, n: int, children: list[list[int]], roots: list[int]) -> None:
        self.depth, self.first, tour = [0] * n, [0] * n, []
        for root in roots:
            stack = [(root, 0)]
            while stack:
                v, k = stack.pop()
                if not k:
                    self.first[v] = len(tour)
                tour.append(v)
                if k < len(children[v]):
                    stack.append((v, k + 1))
                    self.depth[children[v][k]] = self.depth[v] + 1
                    stack.append((children[v][k], 0))
        self.table, width = [tour], 1
        while 2 * width <= len(tour):
            last = self.table[-1]
            self.table.append([a if self.depth[a] <= self.depth[b] else b for a, b in zip(last, last[width:], strict=False)])
            width *= 2

    def of(self, a: int, b: int) -> int:
        lo, hi = sorted((self.first[a], self.first[b]))
        level = (hi - lo + 1).bit_length() - 1
        x, y = self.table[level][lo], self.table[level][hi + 1 - (1 << level)]
        return x if self.depth[x] <= self.depth[y] else y
