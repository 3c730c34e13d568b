"""Minimal Steiner forests as a problem of the branching driver: pairs that must be connected, attached in the contracted graph."""

from __future__ import annotations

from .branching import AttachProblem
from .graph import Graph, LcaIndex, UnionFind, bridges
from .paths import WHOLE, PathSearch, Rest


def pairs_of_sets(sets: list[list[int]]) -> list[tuple[int, int]]:
    """Each set's smallest member with every other one; sets of fewer than two ask for nothing."""
    return sorted({(min(s), v) for s in map(set, sets) for v in s if v != min(s)})


class ForestProblem(AttachProblem):
    def __init__(self, g: Graph, pairs: list[tuple[int, int]], improved: bool = True, alternate: bool = True, completion: str = "lca") -> None:
        super().__init__(g, improved, alternate)
        whole = UnionFind(g.n)
        for a, b in g.ends:
            whole.union(a, b)
        self.feasible = all(whole.find(a) == whole.find(b) for a, b in pairs)
        self.pairs, self.complete = pairs, {"lca": self._by_ancestors, "naive": self._by_paths}[completion]

    def grow(self, path) -> None:
        pass

    shrink = grow

    def _classes(self) -> UnionFind:
        classes = UnionFind(self.g.n)
        for k in self.edges:
            classes.union(*self.g.ends[k])
        return classes

    def choose(self):
        """Improved: a pair has one way only if its classes coincide once the bridges of the contracted graph are contracted too."""
        classes = self._classes()
        open_pairs = [p for p in self.pairs if classes.find(p[0]) != classes.find(p[1])]
        if not open_pairs:
            return self.done()
        if not self.improved:
            return open_pairs[0], None
        self.g.work += self.g.m + self.g.n
        cut = bridges(self.g.n, [(classes.find(a), classes.find(b)) for a, b in self.g.ends])
        joined = UnionFind(self.g.n)
        forced = [*self.edges, *(k for k in range(self.g.m) if cut[k])]
        for k in forced:
            joined.union(*self.g.ends[k])
        for p in open_pairs:
            if joined.find(p[0]) != joined.find(p[1]):
                return p, None
        return None, tuple(self.complete(forced))

    def attachments(self, target: tuple[int, int], rest: Rest = WHOLE) -> PathSearch:
        classes = self._classes()
        out: list[list[tuple[int, int]]] = [[] for _ in range(self.g.n)]
        for k, (a, b) in enumerate(self.g.ends):
            a, b = classes.find(a), classes.find(b)
            if a != b:  # an edge within a class would close a cycle
                out[a].append((k, b))
                out[b].append((k, a))
        self.g.work += self.g.m
        s, t = (classes.find(v) for v in target)
        blocked = bytearray(self.g.n)
        blocked[s] = 1
        return PathSearch(self.g, out[s], t, blocked, alternate=self.alternate, start=rest, out=out, inn=out)

    def _rooted(self, forest: list[int]) -> tuple[list[tuple[int, int] | None], list[list[int]], list[int]]:
        near: dict[int, list[tuple[int, int]]] = {}
        for k in forest:
            a, b = self.g.ends[k]
            near.setdefault(a, []).append((k, b))
            near.setdefault(b, []).append((k, a))
        up: list[tuple[int, int] | None] = [None] * self.g.n
        children: list[list[int]] = [[] for _ in range(self.g.n)]
        met, roots = bytearray(self.g.n), []
        for root in sorted(near):
            if met[root]:
                continue
            met[root] = 1
            roots.append(root)
            todo = [root]
            for v in todo:
                for k, w in near[v]:
                    if not met[w]:
                        met[w] = 1
                        up[w] = (k, v)
                        children[v].append(w)
                        todo.append(w)
        return up, children, roots

    def _by_ancestors(self, forest: list[int]) -> list[int]:
        """Edges on pairs' paths.  Pairs whose lowest common ancestor is nearest a root come first; a climb ends at an edge that is already marked, as all above it up to its ancestor is marked too."""
        up, children, roots = self._rooted(forest)
        tree = LcaIndex(self.g.n, children, roots)
        meetings: list[list[tuple[int, int]]] = [[] for _ in range(max(tree.depth, default=0) + 1)]
        for a, b in self.pairs:
            top = tree.of(a, b)
            meetings[tree.depth[top]].extend([(a, top), (b, top)])
        marked: dict[int, None] = {}
        for v, top in (x for level in meetings for x in level):
            while v != top and up[v][0] not in marked:
                marked[up[v][0]] = None
                v = up[v][1]
        return list(marked)

    def _by_paths(self, forest: list[int]) -> list[int]:
        """The same by one whole path per pair."""
        up, _, _ = self._rooted(forest)

        def climb(v: int) -> list[tuple[int, int]]:
            out = [(-1, v)]
            while up[v] is not None:
                out.append(up[v])
                v = up[v][1]
            return out

        marked: dict[int, None] = {}
        for a, b in self.pairs:
            x, y = climb(a), climb(b)
            while len(x) > 1 and len(y) > 1 and x[-2][1] == y[-2][1]:
                x.pop()
                y.pop()
            marked |= dict.fromkeys(k for k, _ in x[1:] + y[1:])
        return list(marked)
