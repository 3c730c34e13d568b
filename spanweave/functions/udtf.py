"""Enumeration for SQL: SELECT ... FROM steiner_trees(TABLE(edges) PARTITION BY (graph_id), '9,11,7')."""

from __future__ import annotations

from pyspark.sql import Row, SparkSession
from pyspark.sql.functions import udtf

from ..kernels.solve import Options, path_solutions, solutions

RETURNS = "graph_id bigint, solution_key string, n_edges int, edges array<bigint>"


def _ids(text: str) -> list[int]:
    return [int(x) for x in text.split(",") if x.strip()]


class _Trees:
    flavour = "tree"

    def __init__(self) -> None:
        self.graph, self.edges, self.wanted, self.root = None, [], "", None

    def eval(self, row: Row, terminals: str, root: int | None = None):
        self.graph, self.wanted, self.root = row["graph_id"], terminals, root
        self.edges.append((row["edge_id"], row["src"], row["dst"]))

    def terminate(self):
        if self.edges:
            for s in solutions(self.edges, [_ids(self.wanted)], self.root, Options(flavour=self.flavour)):
                yield self.graph, s.key, len(s.edges), s.edges


class _TerminalTrees(_Trees):
    flavour = "terminal"


class _DirectedTrees(_Trees):
    flavour = "directed"


class _Paths(_Trees):
    def eval(self, row: Row, source: int, target: int):
        self.graph, self.wanted = row["graph_id"], (source, target)
        self.edges.append((row["edge_id"], row["src"], row["dst"]))

    def terminate(self):
        if self.edges:
            for p in path_solutions(self.edges, [self.wanted[0]], [self.wanted[1]], False):
                yield self.graph, "-".join(map(str, p)) or "trivial", len(p), p


def register(spark: SparkSession) -> None:
    """steiner_trees(edges, terminals), terminal_steiner_trees(edges, terminals), directed_steiner_trees(edges, terminals, root) and st_paths(edges, s, t)."""
    for name, handler in (("steiner_trees", _Trees), ("terminal_steiner_trees", _TerminalTrees), ("directed_steiner_trees", _DirectedTrees), ("st_paths", _Paths)):
        spark.udtf.register(name, udtf(handler, returnType=RETURNS))
