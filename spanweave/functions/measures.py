"""Cost and accuracy measures, as DataFrame plans over solutions and traces.

A trace has one row an event: enter, leaf and leave of the search, and emit when a solution is handed out; ``work`` counts
the arcs looked at so far.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.window import WindowSpec

def by_seq() -> WindowSpec:
    return Window.partitionBy("instance_id").orderBy("seq")


def delays(trace: DataFrame) -> DataFrame:
    """(instance_id, seq, delay, passed): work and events since the emission before; the last row runs to the end."""
    out = trace.where("kind in ('emit', 'end')").withColumn("delay", F.col("work") - F.coalesce(F.lag("work").over(by_seq()), F.lit(0)))
    return out.select("instance_id", "seq", "kind", "work", "delay")


def delay_report(trace: DataFrame) -> DataFrame:
    """Per instance: solutions, greatest and median delay, work before the first solution."""
    d = delays(trace)
    return d.groupBy("instance_id").agg(
        F.count(F.when(F.col("kind") == "emit", 1)).alias("n_solutions"), F.max("delay").alias("max_delay"), F.percentile_approx("delay", 0.5, 10_000).alias("median_delay"),
        F.min(F.when(F.col("kind") == "emit", F.col("work"))).alias("first_work"),
    )


def amortized_report(trace: DataFrame) -> DataFrame:
    """Per instance: all work, and work for each solution."""
    out = trace.groupBy("instance_id").agg(F.max("work").alias("work"), F.count(F.when(F.col("kind") == "emit", 1)).alias("n_solutions"))
    return out.withColumn("work_per_solution", F.col("work") / F.greatest(F.col("n_solutions"), F.lit(1)))


def incremental_cost(trace: DataFrame, n: int) -> DataFrame:
    """(instance_id, i, delay, ratio): the work between solution i - 1 and solution i, and that over n + i, for a graph of ``n`` vertices."""
    place = F.row_number().over(by_seq())
    out = delays(trace).where("kind = 'emit'").select("instance_id", place.alias("i"), "delay")
    return out.withColumn("ratio", F.col("delay") / (F.lit(n) + F.col("i")))


def space(trace: DataFrame) -> DataFrame:
    """Per instance: the most ids that the search held (attached paths and open path searches), and the most that lay in found but not yet emitted solutions."""
    ids = F.when(F.col("kind") == "leaf", F.col("n_edges")).when(F.col("kind") == "emit", -F.col("n_edges")).otherwise(0)
    held = trace.withColumn("held", F.sum(ids).over(by_seq().rowsBetween(Window.unboundedPreceding, 0)))
    return held.groupBy("instance_id").agg(F.max(F.when(F.col("kind") == "end", F.col("n_edges"))).alias("search_ids"), F.max("held").alias("buffered_ids"))


def tree_shape(trace: DataFrame) -> DataFrame:
    """Per instance: inner nodes, leaves, height, and inner nodes with one child."""
    nodes = trace.where("kind in ('enter', 'leaf')")
    # A node's parent is the last inner node one level up that was entered before it.
    by_depth = Window.partitionBy("instance_id", "depth").orderBy("seq")
    inner = trace.where("kind = 'enter'").select("instance_id", F.col("depth").alias("up"), F.col("seq").alias("from"), F.lead("seq").over(by_depth).alias("to"))
    joined = nodes.join(inner, "instance_id").where("depth = up + 1 and seq > from and (to is null or seq < to)").groupBy("instance_id", "up", "from").agg(F.count("*").alias("children"))
    single = joined.groupBy("instance_id").agg(F.count(F.when(F.col("children") == 1, 1)).alias("one_child"))
    shape = nodes.groupBy("instance_id").agg(F.count(F.when(F.col("kind") == "enter", 1)).alias("inner"), F.count(F.when(F.col("kind") == "leaf", 1)).alias("leaves"), F.max("depth").alias("height"))
    return shape.join(single, "instance_id", "left").select("instance_id", "inner", "leaves", "height", F.coalesce("one_child", F.lit(0)).alias("one_child"))


def buffer_report(trace: DataFrame) -> DataFrame:
    """Per instance: the most solutions held back at a time, the fewest between the first emission and the last one found, and the most search events between two emissions.

    Solutions are held when found; one that goes out at once counts for that event.  ``least_held`` below 1 would mean that an
    emission was due and none was there.
    """
    held = F.sum(F.when(F.col("kind") == "leaf", 1).when(F.col("kind") == "emit", -1).otherwise(0)).over(by_seq().rowsBetween(Window.unboundedPreceding, 0))
    steps = F.sum(F.when(F.col("kind").isin("enter", "leaf", "leave"), 1).otherwise(0)).over(by_seq().rowsBetween(Window.unboundedPreceding, 0))
    counted = trace.withColumn("held", held).withColumn("steps", steps)
    gaps = counted.where("kind = 'emit'").withColumn("gap", F.col("steps") - F.lag("steps").over(by_seq()))
    bounds = counted.groupBy("instance_id").agg(F.min(F.when(F.col("kind") == "emit", F.col("seq"))).alias("first_emit"), F.max(F.when(F.col("kind") == "leaf", F.col("seq"))).alias("last_leaf"))
    inside = (F.col("seq") >= F.col("first_emit")) & (F.col("seq") < F.col("last_leaf")) & (F.col("kind") == "emit")
    held_by = counted.join(bounds, "instance_id").groupBy("instance_id").agg(F.max("held").alias("most_held"), F.min(F.when(inside, F.col("held") + 1)).alias("least_held"))
    return held_by.join(gaps.groupBy("instance_id").agg(F.max("gap").alias("longest_gap")), "instance_id", "left")


def published_bound(solutions: DataFrame, m: int, *, factor: int = 1) -> DataFrame:
    """(instance_id, solution_key, bound): the delay bound of earlier work, edges of the graph times the sizes of a solution and of the one before (by size, then key), times ``factor``."""
    order = Window.partitionBy("instance_id").orderBy("n_edges", "solution_key")
    return solutions.select("instance_id", "solution_key", (F.lit(m * factor).cast("bigint") * (F.col("n_edges") + F.coalesce(F.lag("n_edges").over(order), F.lit(0)))).alias("bound"))


def output_size(solutions: DataFrame) -> DataFrame:
    """Per instance: number, total, least, greatest and mean size."""
    return solutions.groupBy("instance_id").agg(F.count("*").alias("n"), F.sum("n_edges").alias("total"), F.min("n_edges").alias("least"), F.max("n_edges").alias("most"), F.avg("n_edges").alias("mean"))


def compare_solutions(actual: DataFrame, expected: DataFrame) -> DataFrame:
    """One row: solutions missing, spurious and repeated, by instance and key."""
    keys = ["instance_id", "solution_key"]
    a = actual.groupBy(*keys).agg(F.count("*").alias("times"))
    both = a.join(expected.select(*keys).distinct().withColumn("wanted", F.lit(1)), keys, "full_outer")
    return both.agg(F.count(F.when(F.col("times").isNull(), 1)).alias("missing"), F.count(F.when(F.col("wanted").isNull(), 1)).alias("spurious"), F.count(F.when(F.col("times") > 1, 1)).alias("repeated"))


def leaf_degrees(solutions: DataFrame, edges: DataFrame) -> DataFrame:
    """(instance_id, solution_key, vertex, degree) within each solution."""
    long = solutions.select("instance_id", "solution_key", F.explode("edges").alias("edge_id"))
    return long.join(edges.select("edge_id", "src", "dst"), "edge_id").select("instance_id", "solution_key", F.explode(F.array("src", "dst")).alias("vertex")).groupBy("instance_id", "solution_key", "vertex").agg(F.count("*").alias("degree"))


def is_minimal(solutions: DataFrame, terminals: DataFrame, edges: DataFrame, flavour: str = "tree") -> DataFrame:
    """(instance_id, solution_key, minimal) for trees: as many edges as vertices less one, and leaves that are terminals.

    ``terminal`` asks besides that all terminals are leaves; ``directed`` that no vertex is entered twice and the leaves, those that nothing leaves, are terminals.
    """
    keys = ["instance_id", "solution_key"]
    w = terminals.select("instance_id", F.col("vertex_id").alias("vertex"), F.lit(1).alias("t")).distinct()
    if flavour == "directed":
        arcs = solutions.select(*keys, F.explode("edges").alias("edge_id")).join(edges.select("edge_id", "src", "dst"), "edge_id")
        ends = arcs.select(*keys, F.col("dst").alias("vertex"), F.lit(1).alias("into"), F.lit(0).alias("out")).union(arcs.select(*keys, "src", F.lit(0), F.lit(1)))
        d = ends.groupBy(*keys, "vertex").agg(F.sum("into").alias("into"), F.sum("out").alias("out"))
        bad = (F.col("into") > 1) | ((F.col("out") == 0) & F.col("t").isNull())
    else:
        d = leaf_degrees(solutions, edges)
        bad = (F.col("degree") == 1) & F.col("t").isNull()
        if flavour == "terminal":
            bad = bad | ((F.col("degree") > 1) & F.col("t").isNotNull())
    found = d.join(w, ["instance_id", "vertex"], "left").groupBy(*keys).agg(F.count("*").alias("n"), F.max(bad.cast("int")).alias("bad"))
    out = solutions.select(*keys, "n_edges").join(found, keys, "left")
    return out.select(*keys, ((F.col("n_edges") == 0) | ((F.col("bad") == 0) & (F.col("n") == F.col("n_edges") + 1))).alias("minimal"))


def size_cube(solutions: DataFrame, *columns: str) -> DataFrame:
    """Counts over all combinations of the columns, totals included."""
    return solutions.cube(*columns).agg(F.count("*").alias("n"))


def mask_of(bits: Column) -> Column:
    """bigint with the bits of an array of positions set."""
    return F.aggregate(bits, F.lit(0).cast("bigint"), lambda m, b: m.bitwiseOR(F.call_function("shiftleft", F.lit(1).cast("bigint"), b.cast("int"))))
