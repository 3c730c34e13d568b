"""Transversals, the star reduction and induced connections as DataFrame operators."""

from __future__ import annotations

from collections.abc import Iterator
from itertools import islice

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..kernels.graph import Graph
from ..kernels.hard import has_claw, is_dual
from ..kernels.hard import minimal_transversals as kernel_transversals
from ..kernels.hard import streamed_transversals
from ..kernels.induced import is_minimal as is_minimal_induced
from ..kernels.induced import masks, members, shrink, swap_neighbours
from ..kernels.solve import minimal_forest
from ..plans.spread import beside
from ..plans.workspace import settle
from .enumerate import over_instances, packed_instances


def minimal_transversals(hyperedges: DataFrame, *, limit: int | None = None) -> DataFrame:
    """(instance_id, solution_key, n): inclusion-minimal sets that hit every hyperedge(instance_id, hyperedge_id, element); a key is the elements in ascending order.

    With a ``limit`` they are found one after the other and the search ends there.
    """
    nested = hyperedges.groupBy("instance_id", "hyperedge_id").agg(F.collect_set("element").alias("members")).groupBy("instance_id").agg(F.collect_set(F.array_sort("members")).alias("sets"))

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            for who, sets in zip(frame["instance_id"], frame["sets"], strict=True):
                names = sorted({int(v) for s in sets for v in s})
                at = {v: k for k, v in enumerate(names)}
                masks_of = [sum(1 << at[int(v)] for v in s) for s in sets]
                found = kernel_transversals(masks_of) if limit is None else list(islice(streamed_transversals(masks_of), limit))
                keys = [[names[k] for k in members(m)] for m in found]
                yield pd.DataFrame({"instance_id": who, "solution_key": ["-".join(map(str, k)) for k in keys], "n": [len(k) for k in keys]})

    return nested.mapInPandas(run, "instance_id bigint, solution_key string, n int")


def check_dual(hyperedges: DataFrame, transversals: DataFrame) -> DataFrame:
    """(instance_id, dual): whether transversals(instance_id, solution_key) are exactly the minimal ones, by the recursive duality test."""
    sets = hyperedges.groupBy("instance_id", "hyperedge_id").agg(F.collect_set("element").alias("members")).groupBy("instance_id").agg(F.collect_set(F.array_sort("members")).alias("sets"))
    keys = transversals.groupBy("instance_id").agg(F.collect_list("solution_key").alias("keys"))

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            out = []
            for who, sets, keys in zip(frame["instance_id"], frame["sets"], frame["keys"], strict=True):
                at = {v: k for k, v in enumerate(sorted({int(v) for s in sets for v in s}))}
                mask = lambda vs: sum(1 << at[int(v)] for v in vs)  # noqa: B023, E731
                out.append((who, is_dual([mask(s) for s in sets], [mask(k.split("-")) for k in ([] if keys is None else keys)])))
            yield pd.DataFrame(out, columns=["instance_id", "dual"])

    return sets.join(keys, "instance_id", "left").mapInPandas(run, "instance_id bigint, dual boolean")


def hypergraph_to_star(hyperedges: DataFrame, centre: int = -1) -> tuple[DataFrame, DataFrame]:
    """(edges, groups): one leaf for each element around a centre, and a group for each hyperedge.

    A transversal of several elements is a group tree of its leaves and the centre, one of a single element is that leaf.
    """
    leaves = hyperedges.select(F.col("element")).distinct()
    edges = leaves.select(F.lit(0).cast("bigint").alias("graph_id"), F.col("element").alias("edge_id"), F.lit(centre).cast("bigint").alias("src"), F.col("element").alias("dst"))
    groups = hyperedges.select("instance_id", F.col("hyperedge_id").cast("int").alias("set_id"), F.col("element").alias("vertex_id")).distinct()
    return edges, groups


def induced_steiner_subgraphs(instances: DataFrame, terminals: DataFrame, edges: DataFrame, *, require_claw_free: bool = True, max_rounds: int | None = None) -> DataFrame:
    """(instance_id, solution_key, n_vertices, round): minimal vertex sets that induce a connection of the terminals.

    A breadth-first walk over solutions: each round expands the new ones in parallel, keeps what was not met before (an
    anti join with all solutions so far) and settles it.  In a graph without claws every solution is reached; otherwise the
    operator raises an error unless ``require_claw_free`` is False, and then gives what it reaches.
    """
    packed = settle(packed_instances(instances, terminals, edges))

    def first(who, graph, sets, root):
        g, near, wanted, everything = _masks(graph, sets)
        if require_claw_free and has_claw(near):
            raise ValueError(f"instance {who}: the graph has a claw")
        found = shrink(near, everything, wanted)
        if found is not None:
            yield who, *_named(g, found)

    schema = "instance_id bigint, solution_key string, vertices array<bigint>"
    new = settle(over_instances(packed, first, schema).withColumn("round", F.lit(0)))
    met, rounds = new, 0
    while (max_rounds is None or rounds < max_rounds) and not new.isEmpty():
        rounds += 1
        step = beside(new, packed, "instance_id").mapInPandas(_expanded, schema).dropDuplicates(["instance_id", "solution_key"])
        new = settle(step.join(met.select("instance_id", "solution_key"), ["instance_id", "solution_key"], "left_anti").withColumn("round", F.lit(rounds)))
        met = met.unionByName(new)
    return met.select("instance_id", "solution_key", F.size("vertices").alias("n_vertices"), "round")


def _masks(graph, sets) -> tuple[Graph, list[int], int, int]:
    g = Graph(graph, False, {v for s in sets for v in s})
    return g, masks(g.n, g.ends), sum(1 << g.index[v] for v in {v for s in sets for v in s}), (1 << g.n) - 1


def _named(g: Graph, mask: int) -> tuple[str, list[int]]:
    vertices = [g.names[k] for k in members(mask)]
    return "-".join(map(str, vertices)), vertices


def _expanded(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    from .enumerate import _plain

    for frame in frames:
        rows = []
        for row in frame.itertuples(index=False):
            graph, sets, _ = _plain(row)
            g, near, wanted, everything = _masks(graph, sets)
            now = sum(1 << g.index[int(v)] for v in row.vertices)
            found = {y for y, _, _ in swap_neighbours(near, now, wanted, everything)}
            rows += [(row.instance_id, *_named(g, y)) for y in found]
        yield pd.DataFrame(rows, columns=["instance_id", "solution_key", "vertices"])


def solution_arcs(solutions: DataFrame, instances: DataFrame, terminals: DataFrame, edges: DataFrame) -> DataFrame:
    """(instance_id, source, target): which solution leads to which in one step of the walk, for solutions(instance_id, solution_key)."""
    packed = packed_instances(instances, terminals, edges)
    vertices = F.transform(F.regexp_extract_all("solution_key", F.lit(r"(?<![0-9])-?[0-9]+"), F.lit(0)), lambda v: v.cast("bigint"))
    rows = solutions.select("instance_id", F.col("solution_key").alias("source"), vertices.alias("vertices"))
    rows = beside(rows, packed, "instance_id")

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            for k in range(len(frame)):
                one = frame.iloc[k : k + 1]
                for out in _expanded(iter([one])):
                    yield out[["instance_id", "solution_key"]].rename(columns={"solution_key": "target"}).assign(source=one["source"].iloc[0])[["instance_id", "source", "target"]]

    return rows.mapInPandas(run, "instance_id bigint, source string, target string")


def check_minimal(solutions: DataFrame, instances: DataFrame, terminals: DataFrame, edges: DataFrame, flavour: str) -> DataFrame:
    """(instance_id, solution_key, minimal) for forests, solutions(instance_id, solution_key, edges), and induced connections, solutions(instance_id, solution_key, vertices).

    A forest is minimal if it has no cycle, connects every set, and each edge lies between two members of a set; a vertex set
    if it induces a connection of the terminals and none of its other vertices can go.
    """
    column = {"forest": "edges", "induced": "vertices"}[flavour]
    packed = packed_instances(instances, terminals, edges)
    rows = beside(solutions.select("instance_id", "solution_key", F.col(column).alias("members")), packed, "instance_id")

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from .enumerate import _plain

        for frame in frames:
            out = []
            for row in frame.itertuples(index=False):
                graph, sets, _ = _plain(row)
                own = [int(x) for x in row.members]
                out.append((row.instance_id, row.solution_key, minimal_forest(graph, sets, own) if flavour == "forest" else _minimal_induced(graph, sets, own)))
            yield pd.DataFrame(out, columns=["instance_id", "solution_key", "minimal"])

    return rows.mapInPandas(run, "instance_id bigint, solution_key string, minimal boolean")


def _minimal_induced(graph, sets, vertices: list[int]) -> bool:
    g, near, wanted, _ = _masks(graph, sets)
    if not all(v in g.index for v in vertices):
        return False
    own = sum(1 << g.index[v] for v in set(vertices))
    return is_minimal_induced(near, own, wanted)


def solution_distance(a, b):
    """How many members of one solution the other lacks; zero if and only if two minimal solutions are equal."""
    return F.size(F.array_except(a, b))


def smallest(solutions: DataFrame, size: str) -> DataFrame:
    """The solutions of each instance with the least ``size``."""
    from pyspark.sql import Window

    place = F.rank().over(Window.partitionBy("instance_id").orderBy(size))
    return solutions.withColumn("place", place).where("place = 1").drop("place")


def from_line_graph(solutions: DataFrame) -> DataFrame:
    """Vertex sets of a line graph back to trees: the edge ids are the members that are not negative."""
    ids = F.filter(F.transform(F.regexp_extract_all("solution_key", F.lit(r"(?<![0-9])-?[0-9]+"), F.lit(0)), lambda s: s.cast("bigint")), lambda v: v >= 0)
    return solutions.select("instance_id", F.array_join(F.transform(F.array_sort(ids), lambda e: e.cast("string")), "-").alias("solution_key"), F.size(ids).alias("n_edges"))
