"""Kernels against brute force on small random graphs, and the invariants that the bounds rest on."""

import random
from itertools import combinations, permutations

import pytest

from spanweave.kernels.branching import ROOT, Enumeration, Event
from spanweave.kernels.forests import ForestProblem, pairs_of_sets
from spanweave.kernels.graph import Graph, LcaIndex, UnionFind, bridges, reached, two_connected_blocks
from spanweave.kernels.hard import has_claw, internal_trees, is_dual, minimal_transversals, minimum_trees
from spanweave.kernels.induced import is_minimal, masks, part, traverse
from spanweave.kernels.pacing import Pacer
from spanweave.kernels.paths import WHOLE, PathSearch, set_paths, shortest_path, st_paths
from spanweave.kernels.solve import Options, path_solutions, solutions, traced
from spanweave.kernels.trees import DirectedProblem, TerminalProblem, TreeProblem, admissible_components, without_terminal_edges


def graph(r, n, m, directed=False):
    return Graph([(k, r.randrange(n), r.randrange(n)) for k in range(m)], directed, range(n))


def all_paths(g, s, t):
    out = []

    def go(v, seen, edges):
        if v == t:
            out.append(tuple(edges))
            return
        for k, w in g.out[v]:
            if w not in seen:
                go(w, seen | {w}, [*edges, k])

    go(s, {s}, [])
    return sorted(out)


def found(make):
    events = list(Enumeration(make()).events())
    out = sorted(tuple(sorted(e.solution)) for e in events if e.kind == "leaf")
    assert len(set(out)) == len(out)
    return out, events


def in_pieces(make, r):
    """The same search, interrupted again and again."""
    out, todo = [], [ROOT]
    while todo:
        run, stop = Enumeration(make(), todo.pop()), r.randint(1, 6)
        for n, e in enumerate(run.events()):
            if e.kind == "leaf":
                out.append(tuple(sorted(e.solution)))
            if n + 1 >= stop:
                todo += run.unfinished()
                break
    return sorted(out)


def is_forest(g, edges):
    joined = UnionFind(g.n)
    return all(joined.union(*g.ends[k]) for k in edges)


def subsets(g):
    return (c for size in range(g.m + 1) for c in combinations(range(g.m), size))


def trees(g, w):
    out = []
    for edges in subsets(g):
        vertices = {v for k in edges for v in g.ends[k]} | (set(w) if len(w) == 1 else set())
        if set(w) <= vertices and len(edges) == len(vertices) - 1 and is_forest(g, edges):
            degree = {v: sum(v in g.ends[k] for k in edges) for v in vertices}
            if all(v in w for v in vertices if degree[v] <= 1):
                out.append(edges)
    return sorted(out)


def forests(g, pairs):
    def joins(edges):
        u = UnionFind(g.n)
        for k in edges:
            u.union(*g.ends[k])
        return all(u.find(a) == u.find(b) for a, b in pairs)

    return sorted(e for e in subsets(g) if joins(e) and not any(joins(e[:i] + e[i + 1 :]) for i in range(len(e))))


def out_trees(g, root, w):
    out = []
    for edges in subsets(g):
        vertices = {v for k in edges for v in g.ends[k]} | {root}
        heads = [g.ends[k][1] for k in edges]
        if len(edges) != len(vertices) - 1 or not set(w) <= vertices or len(set(heads)) != len(heads) or root in heads:
            continue
        below = [[] for _ in range(g.n)]
        for k in edges:
            below[g.ends[k][0]].append((k, g.ends[k][1]))
        if sum(reached(below, [root])) == len(vertices) and all(below[v] or v in w for v in vertices):
            out.append(edges)
    return sorted(out)


@pytest.mark.parametrize("seed", range(8))
def test_paths(seed):
    r = random.Random(seed)
    for _ in range(60):
        n = r.randint(2, 7)
        g = graph(r, n, r.randint(1, 12), r.random() < 0.5)
        s, t = r.sample(range(n), 2)
        want = all_paths(g, s, t)
        for alternate in (True, False):
            for keep in (True, False):
                assert sorted(map(tuple, st_paths(g, s, t, alternate=alternate, keep_marks=keep))) == want
        blocked = bytearray(g.n)
        blocked[s] = 1
        got, todo = [], [WHOLE]
        while todo:
            search, stop = PathSearch(g, g.out[s], t, blocked, start=todo.pop()), r.randint(0, 2)
            for k, (edges, _) in enumerate(search):
                got.append(tuple(edges))
                if k >= stop:
                    rest, late = search.split()
                    todo += rest
                    got += [tuple(e) for e, _ in late]
                    break
        assert sorted(got) == want
        a, b = (set(r.sample(range(n), r.randint(1, min(3, n)))) for _ in range(2))
        inner = [p for x in a - b for y in b - a for p in all_paths(g, x, y)]
        inner = [p for p in inner if not {v for k in p for v in g.ends[k]} - ends_of(g, p) & (a | b)]
        assert sorted(map(tuple, set_paths(g, a, b))) == sorted(inner + [()] * len(a & b))


def ends_of(g, path):
    """The two ends of a path, by degree within it."""
    degree = {}
    for k in path:
        for v in g.ends[k]:
            degree[v] = degree.get(v, 0) + 1
    return {v for v, d in degree.items() if d == 1}


def test_paths_emit_at_least_every_third_node():
    n = 6
    g = Graph([(k, a, b) for k, (a, b) in enumerate(combinations(range(n), 2))], False)
    blocked = bytearray(g.n)
    blocked[0] = 1
    search = PathSearch(g, g.out[0], n - 1, blocked)
    before = 0
    for _ in search:
        assert search.nodes - before <= 3
        before = search.nodes


@pytest.mark.parametrize("n", [2, 3, 4, 5, 6])
def test_complete_graphs(n):
    edges = [(k, a, b) for k, (a, b) in enumerate(combinations(range(n), 2))]
    assert len(list(path_solutions(edges, [0], [n - 1], False))) == sum(len(list(permutations(range(n - 2), k))) for k in range(n - 1))
    arcs = [(k, a, b) for k, (a, b) in enumerate(permutations(range(n), 2))]
    assert len(list(solutions(arcs, [list(range(1, n))], 0, Options(flavour="directed")))) == n ** (n - 2)
    assert len(list(solutions(edges, [list(range(n))]))) == n ** (n - 2)


@pytest.mark.parametrize("seed", range(8))
def test_all_flavours(seed):
    r = random.Random(100 + seed)
    for _ in range(30):
        n = r.randint(2, 6)
        g = graph(r, n, r.randint(1, 9))
        w = r.sample(range(n), r.randint(1, min(4, n)))
        want = trees(g, w)
        for improved in (True, False):
            got, events = found(lambda: TreeProblem(g, w, improved))
            assert got == want == in_pieces(lambda: TreeProblem(g, w, improved), r)
            if improved:
                inner, leaves = (sum(e.kind == k for e in events) for k in ("enter", "leaf"))
                assert inner < leaves or (inner, leaves) in ((0, 0), (0, 1))
        pacer = Pacer(g.n)
        assert sorted(tuple(sorted(e.solution)) for e in pacer(Enumeration(TreeProblem(g, w)).events())) == want
        assert pacer.underflow == 0 and pacer.longest_gap <= 20 and pacer.most_held <= 3 * pacer.n // 2 + 1
        if len(w) >= 3:
            leaves_only = sorted(e for e in want if all(sum(x in g.ends[k] for k in e) == 1 for x in w))
            h = without_terminal_edges(g, set(w))
            back = [g.edge_ids.index(e) for e in h.edge_ids]
            for improved in (True, False):
                parts = [found(lambda c=c: TerminalProblem(h, w, c, improved))[0] for c in admissible_components(h, set(w))]  # noqa: B023
                assert sorted(tuple(sorted(back[k] for k in s)) for p in parts for s in p) == leaves_only
        pairs = pairs_of_sets([r.sample(range(n), r.randint(1, min(3, n))) for _ in range(r.randint(1, 3))])
        want = forests(g, pairs)
        for improved, completion in ((False, "lca"), (True, "lca"), (True, "naive")):
            make = lambda: ForestProblem(g, pairs, improved, completion=completion)  # noqa: E731, B023
            assert found(make)[0] == want == in_pieces(make, r)
        d = graph(r, n, r.randint(1, 9), True)
        root, *ends = r.sample(range(n), min(n, r.randint(2, 4)))
        want = out_trees(d, root, ends)
        for improved in (True, False):
            make = lambda: DirectedProblem(d, root, ends, improved)  # noqa: E731, B023
            assert found(make)[0] == want == in_pieces(make, r)


@pytest.mark.parametrize("seed", range(6))
def test_pacer_on_synthetic_trees(seed):
    """Trees whose inner nodes have two or more children, without any graph."""
    r = random.Random(seed)

    def grow(depth, sibling=0):
        if depth > r.randint(2, 7):
            yield Event("leaf", depth, (), sibling)
            return
        yield Event("enter", depth)
        leaves = 0
        for _ in range(r.choice([2, 2, 3, 5])):
            child = list(grow(depth + 1, leaves))
            leaves += child[0].kind == "leaf"
            yield from child
        yield Event("leave", depth)

    events = list(grow(0))
    n = sum(e.kind == "enter" for e in events)
    for warmup in (4, 7, max(2, n // 3), n):
        pacer = Pacer(warmup)
        assert len(list(pacer(events))) == sum(e.kind == "leaf" for e in events)
        assert pacer.most_held <= max(pacer.n, 3 * pacer.n // 2)
        assert pacer.longest_gap <= 20


@pytest.mark.parametrize("seed", range(6))
def test_claw_free_connections_are_all_reached(seed):
    r = random.Random(seed)
    for k in range(120):
        n = r.randint(2, 8)
        if k % 2:
            x = [r.random() * 4 for _ in range(n)]
            edges = [(a, b) for a, b in combinations(range(n), 2) if abs(x[a] - x[b]) <= 1]
        else:
            p = r.choice([0.5, 0.7, 0.85])
            edges = [e for e in combinations(range(n), 2) if r.random() < p]
        near, w = masks(n, edges), sum(1 << v for v in r.sample(range(n), r.randint(1, min(4, n))))
        if has_claw(near):
            continue
        anchor = (w & -w).bit_length() - 1
        connected = [s for s in range(1 << n) if s & w == w and part(near, anchor, s) == s]
        want = sorted(s for s in connected if not any(t != s and t & s == t for t in connected))
        assert sorted(traverse(near, w, (1 << n) - 1)) == want == [s for s in connected if is_minimal(near, s, w)]


@pytest.mark.parametrize("seed", range(4))
def test_hard_problems(seed):
    r = random.Random(seed)
    for _ in range(60):
        n = r.randint(1, 7)
        sets = [r.randrange(1, 1 << n) for _ in range(r.randint(1, 6))]
        hits = [s for s in range(1 << n) if all(s & h for h in sets)]
        want = sorted(s for s in hits if not any(t != s and t & s == t for t in hits))
        assert sorted(minimal_transversals(sets)) == want and is_dual(sets, want)
        assert len(want) < 2 or not is_dual(sets, want[1:])
        g = graph(r, n, r.randint(1, 8))
        w = r.sample(range(n), r.randint(1, min(3, n)))
        connected = [e for e in subsets(g) if is_forest(g, e) and (not e or len(e) == len({v for k in e for v in g.ends[k]}) - 1)]
        inside = [e for e in connected if e and all(sum(x in g.ends[k] for k in e) >= 2 for x in w)]
        assert sorted(internal_trees(g, w)) == sorted(inside)
        holding = [e for e in connected if set(w) <= {v for k in e for v in g.ends[k]} or (not e and len(w) == 1)]
        least = min(map(len, holding), default=0)
        assert sorted(minimum_trees(g, w)) == sorted(e for e in holding if len(e) == least)


@pytest.mark.parametrize("seed", range(4))
def test_bridges_blocks_and_ancestors(seed):
    r = random.Random(seed)
    for _ in range(80):
        n = r.randint(2, 7)
        g = graph(r, n, r.randint(1, 10))
        cut = bridges(g.n, g.ends)
        for k, (a, b) in enumerate(g.ends):
            others = [[(j, w) for j, w in arcs if j != k] for arcs in g.out]
            assert bool(cut[k]) == (not reached(others, [a])[b])
        blocks = two_connected_blocks(g.n, g.ends)
        assert sorted(k for b in blocks for k in b) == list(range(g.m))
        assert {b[0] for b in blocks if len(b) == 1} == {k for k in range(g.m) if cut[k]}
        up = [-1] + [r.randrange(v) for v in range(1, n)]
        children = [[w for w in range(n) if up[w] == v] for v in range(n)]
        tree = LcaIndex(n, children, [0])

        def line(v, up=up):
            return [v, *line(up[v])] if v else [0]

        for a in range(n):
            for b in range(n):
                assert tree.of(a, b) == next(x for x in line(a) if x in line(b))


# Worked examples on a square with one diagonal.

SQUARE = [(0, 1, 2), (1, 2, 3), (2, 3, 4), (3, 4, 1), (4, 1, 3)]


def keys(*args, **options):
    root = options.pop("root", None)
    return sorted(s.key for s in solutions(*args, root, Options(**options)))


def test_square():
    assert keys(SQUARE, [[1, 3, 4]]) == sorted(["3-4", "2-4", "0-1-3", "0-1-2", "2-3"])
    assert len(keys(SQUARE, [[1, 3], [2, 4]], flavour="forest")) == 8
    assert keys(SQUARE, [[2, 4]], flavour="terminal") == sorted(["0-3", "1-2", "0-2-4", "1-3-4"])
    assert keys(SQUARE, [[1, 3, 4]], flavour="terminal") == []
    arcs = [(2 * k + d, *((a, b) if d else (b, a))) for k, a, b in SQUARE for d in (0, 1)]
    assert len(keys(arcs, [[3]], flavour="directed", root=1)) == 3
    events = list(traced([*SQUARE, (5, 3, 5)], [[3, 5]], None, Options()))
    assert [e[0] for e in events] == ["leaf", "emit", "end"]


def test_contract_of_special_cases():
    assert keys(SQUARE, [[2]]) == ["v2"] and keys([], [[7]]) == ["v7"]
    assert keys(SQUARE, [[2]], flavour="terminal") == [] and keys(SQUARE, [[2]], flavour="terminal", allow_trivial=True) == ["v2"]
    assert keys(SQUARE, [[1, 99]]) == [] and keys(SQUARE, [[1, 1, 2, 2]]) == keys(SQUARE, [[1, 2]])
    assert keys(SQUARE, [[1], []], flavour="forest") == ["empty"]
    assert keys([*SQUARE, (9, 2, 2)], [[1, 3]]) == keys(SQUARE, [[1, 3]])
    assert keys([(0, 1, 2), (1, 1, 2)], [[1, 2]]) == ["0", "1"]
    for bad in (lambda: keys(SQUARE, [[]]), lambda: keys(SQUARE, [[1, 2]], flavour="directed", root=1), lambda: keys(SQUARE, [[1]], flavour="directed")):
        with pytest.raises(ValueError):
            bad()
    assert len(list(solutions(SQUARE, [[1, 3]], None, Options(limit=2)))) == 2


def test_terminals_are_never_passed():
    """Terminal y has two ways into the component {a, b}; z is forced all the same."""
    a, b, x, y, z = range(5)
    edges = [(0, a, b), (1, x, a), (2, y, a), (3, y, b), (4, z, b)]
    want = ["0-1-2-4", "0-1-3-4"]
    for branching in ("simple", "improved"):
        assert keys(edges, [[x, y, z]], flavour="terminal", branching=branching) == want


def test_ancestors_nearest_the_root_first():
    edges = [(0, 0, 1), (1, 1, 2), (2, 2, 3)]
    assert keys(edges, [[0, 2], [1, 3]], flavour="forest") == ["0-1-2"]


def test_star_with_a_single_member():
    star = [(1, -1, 1), (2, -1, 2), (3, -1, 3)]
    assert keys(star, [[1, 2], [2, 3]], flavour="group") == ["1-3", "v2"]


def test_long_chain_needs_no_recursion():
    n = 5000
    chain = [(k, k, k + 1) for k in range(n)]
    assert len(next(solutions(chain, [[0, n]])).edges) == n
    assert len(next(iter(path_solutions(chain, [0], [n], False)))) == n
    assert len(next(solutions(chain, [[0, n], [1, 7]], None, Options(flavour="forest"))).edges) == n
    assert len(next(solutions(chain, [[n]], 0, Options(flavour="directed"))).edges) == n


def test_shortest_path():
    g = Graph(SQUARE)
    assert [g.names[v] for v in shortest_path(g.out, [g.index[2]], {g.index[4]}, lambda v: True)] in ([2, 1, 4], [2, 3, 4])
    assert shortest_path(g.out, [g.index[2]], {g.index[4]}, lambda v: v == g.index[2]) is None
