"""Enumeration of minimal connecting subgraphs as DataFrame operators.

Modes.  ``auto`` (the default) asks ``plans.planner``, which looks at counts.  ``fleet``: many instances, each with a graph that one task can hold; an instance is one row with its edges nested,
and a generator streams its solutions out in batches.  ``shard``: few instances with long searches; see ``shards``.
Solutions need no de-duplication, as searches never produce one twice.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import replace

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import model
from ..kernels.solve import Options, completed, path_solutions, solutions, traced
from ..plans.planner import choose_mode
from ..plans.spread import beside

BATCH = 2000
#: Flavours whose searches branch by attachments and can be split over tasks.
SPLITTABLE = frozenset(("tree", "forest", "terminal", "directed"))


def packed_instances(instances: DataFrame, terminals: DataFrame, edges: DataFrame) -> DataFrame:
    """(instance_id, root, edges, sets): one row an instance.  Edges meet instances by graph, terminals are nested by set; instances that share a graph are spread."""
    have = [F.col(c) if c in instances.columns else F.lit(0 if c == "graph_id" else None).cast("bigint").alias(c) for c in ("instance_id", "graph_id", "root")]
    jobs = model.need(instances.select(*have), "instance_id", "graph_id", "root")
    if "set_id" not in terminals.columns:
        terminals = terminals.withColumn("set_id", F.lit(0))
    sets = terminals.groupBy("instance_id", "set_id").agg(F.sort_array(F.collect_set("vertex_id")).alias("members"))
    sets = sets.groupBy("instance_id").agg(F.sort_array(F.collect_list(F.struct("set_id", "members"))).alias("sets"))
    graphs = model.checked_edges(edges).groupBy("graph_id").agg(F.sort_array(F.collect_list(F.struct("edge_id", "src", "dst"))).alias("edges"))
    return beside(jobs.join(sets, "instance_id", "left"), graphs, "graph_id", how="left").select("instance_id", "root", F.coalesce("edges", F.array().cast("array<struct<edge_id:bigint,src:bigint,dst:bigint>>")).alias("edges"), F.transform("sets", lambda s: s["members"]).alias("sets"))


def _plain(row) -> tuple[list[tuple[int, int, int]], list[list[int]], int | None]:
    edges = [(e["edge_id"], e["src"], e["dst"]) for e in row.edges]
    return edges, [[int(v) for v in s] for s in row.sets] if row.sets is not None else [], None if pd.isna(row.root) else int(row.root)


def over_instances(packed: DataFrame, work: Callable[..., Iterator[tuple]], schema: str) -> DataFrame:
    """``work(instance_id, edges, sets, root)`` for every row, its rows streamed out in batches."""
    names = [c.split()[0] for c in schema.split(", ")]

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            held: list[tuple] = []
            for row in frame.itertuples(index=False):
                for out in work(int(row.instance_id), *_plain(row)):
                    held.append(out)
                    if len(held) >= BATCH:
                        yield pd.DataFrame(held, columns=names)
                        held = []
            if held:
                yield pd.DataFrame(held, columns=names)

    return packed.mapInPandas(run, schema)


def enumerated(instances: DataFrame, terminals: DataFrame, edges: DataFrame, options: Options) -> DataFrame:
    """Solutions of all instances in fleet mode."""

    def work(who, graph, sets, root):
        for n, s in enumerate(solutions(graph, sets, root, options)):
            yield who, s.key, len(s.edges), len(s.vertices), s.edges, s.vertices, f"{who}", n

    return over_instances(packed_instances(instances, terminals, edges), work, model.SOLUTIONS)


def trace(instances: DataFrame, terminals: DataFrame, edges: DataFrame, options: Options) -> DataFrame:
    """Every event of the searches, with the arcs looked at so far: what the measures are made from."""

    def work(who, graph, sets, root):
        for n, (kind, depth, sibling, done, size) in enumerate(traced(graph, sets, root, options)):
            yield who, n, kind, depth, sibling, done, size

    return over_instances(packed_instances(instances, terminals, edges), work, model.TRACE)


def _enumerator(flavour: str, doc: str) -> Callable[..., DataFrame]:
    def operator(instances: DataFrame, terminals: DataFrame, edges: DataFrame, *, mode: str = "auto", work_budget: int = 200_000, **options) -> DataFrame:
        o = Options(flavour=flavour, **options)
        if mode == "auto":
            mode = choose_mode(instances, model.checked_edges(edges))
            if mode == "relational":
                raise ValueError("the largest graph does not fit a task: prune it (operators.graph_tests) or use plans.relational")
            if o.pacing == "buffered" or o.flavour not in SPLITTABLE:
                mode = "fleet"
        if mode not in ("fleet", "shard"):
            raise ValueError(f"unknown mode {mode!r}")
        if mode == "shard":
            from .shards import sharded

            return sharded(instances, terminals, edges, o, work_budget=work_budget)
        return enumerated(instances, terminals, edges, o)

    operator.__doc__ = doc
    operator.__name__ = f"{flavour}_solutions"
    return operator


steiner_trees = _enumerator("tree", "Minimal Steiner trees: instances(instance_id, graph_id), terminals(instance_id, vertex_id), edges(graph_id, edge_id, src, dst).")
steiner_forests = _enumerator("forest", "Minimal Steiner forests: terminals carry a set_id; every set is to be connected.")
terminal_steiner_trees = _enumerator("terminal", "Minimal trees whose leaves are exactly the terminals.")
directed_steiner_trees = _enumerator("directed", "Minimal out-trees from instances.root that reach all terminals.")
group_steiner_trees = _enumerator("group", "Minimal trees that touch every set; a set whose only row has a null vertex_id has no members, so no tree touches it; max_choices guards the number of representatives' choices.")
internal_steiner_trees = _enumerator("internal", "All trees with every terminal inside; exhaustive, guarded by max_vertices.")
minimum_steiner_trees = _enumerator("minimum", "All Steiner trees with fewest edges.")


def st_paths(edges: DataFrame, endpoints: DataFrame, *, directed: bool = False, limit: int | None = None, alternate: bool = True, state: str = "compact") -> DataFrame:
    """(instance_id, solution_key, n_edges, path): simple paths for endpoints(instance_id, s, t[, graph_id]); key in path order, "trivial" for s = t.

    ``state``: "compact" finds reachability marks anew after a child search, "copied" keeps them at every level.
    """
    o = Options(limit=limit, alternate=alternate, keep_marks=state == "copied")
    return _paths(edges, endpoints.withColumn("a", F.array("s")).withColumn("b", F.array("t")), directed, o)


def set_paths(edges: DataFrame, endpoints: DataFrame, *, directed: bool = False, limit: int | None = None) -> DataFrame:
    """Like ``st_paths`` for endpoints(instance_id, sources, targets): from a source to a target, inner vertices outside both."""
    return _paths(edges, endpoints.withColumn("a", F.col("sources")).withColumn("b", F.col("targets")), directed, replace(Options(), limit=limit))


def _paths(edges: DataFrame, endpoints: DataFrame, directed: bool, o: Options) -> DataFrame:
    graph = F.col("graph_id") if "graph_id" in endpoints.columns else F.lit(0).cast("bigint").alias("graph_id")
    jobs = endpoints.select("instance_id", graph, F.lit(None).cast("bigint").alias("root"), F.array("a", "b").alias("sets"))
    graphs = model.checked_edges(edges).groupBy("graph_id").agg(F.sort_array(F.collect_list(F.struct("edge_id", "src", "dst"))).alias("edges"))
    packed = beside(jobs, graphs, "graph_id").select("instance_id", "root", "edges", "sets")

    def work(who, graph, sets, root):
        for p in path_solutions(graph, sets[0], sets[1], directed, o):
            yield who, "-".join(map(str, p)) or "trivial", len(p), p

    return over_instances(packed, work, "instance_id bigint, solution_key string, n_edges int, path array<bigint>")


def hamiltonian_paths(edges: DataFrame, endpoints: DataFrame, *, directed: bool = False) -> DataFrame:
    """Paths that visit every vertex of the graph."""
    sizes = model.checked_edges(edges).select(F.explode(F.array("src", "dst")).alias("v")).agg(F.count_distinct("v").alias("n"))
    return st_paths(edges, endpoints, directed=directed).crossJoin(F.broadcast(sizes)).where("n_edges = n - 1").drop("n")  # one row on the right


def complete_tree(instances: DataFrame, terminals: DataFrame, edges: DataFrame, partial: DataFrame | None = None, *, flavour: str = "tree") -> DataFrame:
    """(instance_id, solution_key, n_edges, edges): one minimal solution for each instance that holds all edges of its partial(instance_id, edge_id).

    A spanning structure is grown around the partial edges and what hangs loose without a terminal is taken away again, in
    time linear in the graph; nothing is enumerated.  ``flavour``: tree, forest or directed.  A partial solution must be part of some minimal
    one: acyclic, its leaves terminals, and for trees connected.  No row where there is no solution.
    """
    packed = packed_instances(instances, terminals, edges)
    if partial is None:
        partial = instances.sparkSession.createDataFrame([], "instance_id bigint, edge_id bigint")
    kept = partial.groupBy("instance_id").agg(F.collect_set("edge_id").alias("kept"))
    rows = packed.join(kept, "instance_id", "left")

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            out = []
            for row in frame.itertuples(index=False):
                found = completed(*_plain(row)[:2], [] if row.kept is None else [int(e) for e in row.kept], _plain(row)[2], flavour)
                if found is not None:
                    out.append((int(row.instance_id), found.key, len(found.edges), found.edges))
            yield pd.DataFrame(out, columns=["instance_id", "solution_key", "n_edges", "edges"])

    return rows.mapInPandas(run, "instance_id bigint, solution_key string, n_edges int, edges array<bigint>")
