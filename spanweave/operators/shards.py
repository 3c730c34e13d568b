"""Searches that are split over tasks: unfinished nodes are rows.

A round gives every row a budget of arcs to look at; what is finished comes out as solutions, what is not as new rows,
which the next round deals out evenly.  Rows of a round are disjoint parts of the search, so nothing is found twice, a lost
task is repeated from its rows, and the set of solutions depends on neither the budget nor the number of tasks.  Rounds
start with a small budget, to spread, and raise it.

The graphs travel nested beside their rows; an instance's graph must fit a task.  An instance with many rows has a copy of its
graph at as many places as there are tasks, so its rows are spread whatever the join.

A split search hands solutions out as its parts find them: ``pacing="buffered"`` needs one task and is refused.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..kernels.branching import ROOT, Continuation
from ..kernels.graph import Graph
from ..kernels.paths import Rest
from ..kernels.solve import Options, _solution, problems, resumed
from ..plans.spread import beside
from ..plans.workspace import settle
from .enumerate import BATCH, SPLITTABLE, _plain, enumerated, packed_instances

ROWS = "instance_id bigint, part int, attached array<array<bigint>>, prefix array<bigint>, banned bigint, floor bigint, depth int"
FOUND = "instance_id bigint, solution_key string, n_edges int, n_vertices int, edges array<bigint>, vertices array<bigint>, shard string, emit_seq bigint, more boolean, part int, attached array<array<bigint>>, prefix array<bigint>, banned bigint, floor bigint, depth int"


def sharded(instances: DataFrame, terminals: DataFrame, edges: DataFrame, options: Options, *, work_budget: int = 200_000, first_budget: int = 2_000) -> DataFrame:
    """Solutions in shard mode.  ``limit`` is per instance and stops after the round in which it is reached."""
    if options.flavour not in SPLITTABLE:
        return enumerated(instances, terminals, edges, options)
    if options.pacing == "buffered":
        raise ValueError("a split search cannot pace its solutions: use mode='fleet'")
    packed = settle(packed_instances(instances, terminals, edges))
    todo = packed.select("instance_id", F.lit(-1).alias("part"), F.array().cast("array<array<bigint>>").alias("attached"), F.array().cast("array<bigint>").alias("prefix"), F.lit(-1).cast("bigint").alias("banned"), F.lit(-1).cast("bigint").alias("floor"), F.lit(0).alias("depth"))
    done: list[DataFrame] = []
    budget = min(first_budget, work_budget)
    while True:
        rows = beside(todo, packed, "instance_id")
        result = settle(rows.mapInPandas(_round(options, budget), FOUND))
        done.append(result.where("not more"))
        todo = result.where("more").select(*(c.split()[0] for c in ROWS.split(", ")))
        if todo.isEmpty() or (options.limit and _enough(done, options.limit)):
            break
        budget = min(work_budget, budget * 4)
    out = done[0]
    for d in done[1:]:
        out = out.unionByName(d)
    out = out.select("instance_id", "solution_key", "n_edges", "n_vertices", "edges", "vertices", "shard", "emit_seq")
    if options.limit:
        from pyspark.sql import Window

        first = F.row_number().over(Window.partitionBy("instance_id").orderBy("shard", "emit_seq"))
        out = out.withColumn("first", first).where(F.col("first") <= options.limit).drop("first")
    return out


def _enough(done: list[DataFrame], limit: int) -> bool:
    every = done[0].select("instance_id")
    for d in done[1:]:
        every = every.unionByName(d.select("instance_id"))
    return every.groupBy("instance_id").count().where(F.col("count") < limit).isEmpty()


def _round(options: Options, budget: int):
    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        columns = [c.split()[0] for c in FOUND.split(", ")]
        for frame in frames:
            held: list[tuple] = []
            for row in frame.itertuples(index=False):
                for out in _one(row, options, budget):
                    held.append(out)
                    if len(held) >= BATCH:
                        yield pd.DataFrame(held, columns=columns)
                        held = []
            if held:
                yield pd.DataFrame(held, columns=columns)

    return run


def _one(row, options: Options, budget: int) -> Iterator[tuple]:
    edges, sets, root = _plain(row)
    who = int(row.instance_id)
    if row.part < 0:
        # Cases that no search covers (one terminal, two leaf terminals, nothing to connect) are done at once.
        terminals = {v for s in sets for v in s}
        if len(terminals) < 2 or (options.flavour == "terminal" and len(terminals) == 2) or (options.flavour == "forest" and not any(len(s) > 1 for s in sets)):
            if options.flavour != "directed":
                from ..kernels.solve import solutions

                for n, s in enumerate(solutions(edges, sets, root, options)):
                    yield (who, s.key, len(s.edges), len(s.vertices), s.edges, s.vertices, "0", n, False, None, None, None, None, None, None)
                return
    g = Graph(edges, options.flavour == "directed", {v for s in sets for v in s} | ({root} - {None}))
    makers = problems(g, sets, root, options)
    start = Continuation(tuple(tuple(map(int, a)) for a in row.attached), Rest(tuple(map(int, row.prefix)), int(row.banned), int(row.floor), int(row.depth)))
    name = "/".join("-".join(map(str, a)) for a in start.attached) + f"|{'-'.join(map(str, start.rest.prefix))}|{start.rest.banned}|{start.rest.floor}"
    for part in range(len(makers)) if row.part < 0 else [int(row.part)]:
        p = makers[part]()
        seq = 0
        for item in resumed(g, makers[part], start if row.part >= 0 else ROOT, budget):
            if isinstance(item, list):
                for c in item:
                    yield (who, None, None, None, None, None, None, None, True, part, [list(a) for a in c.attached], list(c.rest.prefix), c.rest.banned, c.rest.floor, c.rest.depth)
            else:
                s = _solution(p.g, item, sets[0][:1])
                yield (who, s.key, len(s.edges), len(s.vertices), s.edges, s.vertices, f"{part}:{name}", seq, False, None, None, None, None, None, None)
                seq += 1
