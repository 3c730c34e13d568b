"""What keeps plans spread and answers whole: hot instances and graphs, long paths, numbering, completions, minimality, measures."""

import itertools
import random
from collections import Counter

import pytest
from pyspark.sql import functions as F

from spanweave.functions import measures
from spanweave.kernels.graph import Graph
from spanweave.kernels.hard import minimal_transversals, streamed_transversals
from spanweave.kernels.solve import Options, _choices, solutions, traced
from spanweave.operators import enumerate as enum
from spanweave.operators import graph_tests, hard
from spanweave.operators.keyword import explain_fragments
from spanweave.plans import relational
from spanweave.plans.spread import beside, ranked
from spanweave.plans.workspace import workspace
from spanweave.sources import graphs


@pytest.fixture
def no_broadcast(spark):
    old = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    yield
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", old)


def most_in_a_partition(df):
    counts = [r["n"] for r in df.groupBy(F.spark_partition_id().alias("p")).agg(F.count("*").alias("n")).collect()]
    return max(counts) / sum(counts), len(counts)


def test_rows_of_one_key_are_spread(spark, no_broadcast):
    rows = spark.range(4000).select(F.lit(7).cast("bigint").alias("instance_id"), "id").unionByName(spark.range(20).select(F.col("id").alias("instance_id"), "id"))
    large = spark.range(100).select(F.col("id").alias("instance_id"), F.array_repeat(F.lit(1), 50).alias("edges"))
    out = beside(rows, large, "instance_id", slots=16)
    share, parts = most_in_a_partition(out)
    assert share < 0.3 and parts >= 12
    assert out.count() == 4020 and out.select("id", "instance_id").distinct().count() == 4019
    left = beside(spark.range(3).select(F.col("id").alias("graph_id")), spark.range(2).select(F.col("id").alias("graph_id"), F.lit(1).alias("x")), "graph_id", how="left")
    assert sorted((r["graph_id"], r["x"]) for r in left.collect()) == [(0, 1), (1, 1), (2, None)]


def test_instances_of_one_graph_are_spread(spark, no_broadcast):
    edges = spark.createDataFrame([(3, k, k, k + 1) for k in range(30)], "graph_id bigint, edge_id bigint, src bigint, dst bigint")
    jobs = spark.range(1000).select(F.col("id").alias("instance_id"), F.lit(3).cast("bigint").alias("graph_id"))
    terminals = jobs.select("instance_id", F.explode(F.array(F.lit(0).cast("bigint"), 1 + F.col("instance_id") % 30)).alias("vertex_id"))
    share, parts = most_in_a_partition(enum.packed_instances(jobs, terminals, edges))
    assert share < 0.3 and parts >= 8
    assert enum.steiner_trees(jobs, terminals, edges, mode="fleet").count() == 1000


def test_frontier_of_one_instance_is_spread(spark, no_broadcast):
    packed = spark.createDataFrame([(0, None, [(0, 0, 1)], [[0, 1]])], "instance_id bigint, root bigint, edges array<struct<edge_id:bigint,src:bigint,dst:bigint>>, sets array<array<bigint>>")
    frontier = spark.range(1000).select(F.lit(0).cast("bigint").alias("instance_id"), F.col("id").cast("string").alias("solution_key"), F.array("id").alias("vertices"))
    share, parts = most_in_a_partition(beside(frontier, packed, "instance_id"))
    assert share < 0.3 and parts >= 8


def test_shards_refuse_pacing_and_auto_is_the_default(spark):
    g = graphs.labelled_graph([(k, k, k + 1) for k in range(3)], spark)
    one, w = graphs.one_instance(spark), spark.createDataFrame([(0, 0), (0, 3)], "instance_id bigint, vertex_id bigint")
    with pytest.raises(ValueError, match="pace"):
        enum.steiner_trees(one, w, g, mode="shard", pacing="buffered")
    assert enum.steiner_trees(one, w, g).count() == enum.steiner_trees(one, w, g, pacing="buffered").count() == 1


def test_a_path_of_a_hundred_edges(spark):
    g = graphs.labelled_graph([(k, k, k + 1) for k in range(100)], spark)
    ends = spark.createDataFrame([(0,)], "s bigint"), spark.createDataFrame([(100,)], "t bigint")
    assert [len(r["edges"]) for r in relational.paths(g, *ends).collect()] == [100]
    with pytest.raises(ValueError, match="64"):
        relational.paths(g, *ends, max_hops=64)


def test_numbering(spark):
    df = spark.range(1000).select((F.col("id") * 7919 % 1000).alias("v"), "id").repartition(5)
    assert [(r["n"], r["v"]) for r in ranked(df, "n", F.desc("v")).orderBy("n").collect()] == [(k, 999 - k) for k in range(1000)]
    assert ranked(df.limit(0), "n", "v").count() == 0


def test_several_graphs_are_refused(spark):
    two = spark.createDataFrame([(0, 0, 1, 2), (1, 1, 2, 3)], "graph_id bigint, edge_id bigint, src bigint, dst bigint")
    w = spark.createDataFrame([(0, 1)], "instance_id bigint, vertex_id bigint")
    for call in (lambda: graph_tests.claws(two), lambda: graph_tests.line_graph(two), lambda: graph_tests.strip_leaves(two, w), lambda: graph_tests.relevant_blocks(two, w), lambda: graph_tests.compress_chains(two, w), lambda: graph_tests.admissible_components(two, w), lambda: graph_tests.distances(two, w.select(F.col("vertex_id").alias("vertex")))):
        with pytest.raises(ValueError, match="several graphs"):
            call()


def random_graph(r, n, p):
    return [(k, a, b) for k, (a, b) in enumerate((a, b) for a in range(n) for b in range(a + 1, n) if r.random() < p)]


def way(edges, a, b):
    """Edge ids of the path from a to b in a tree."""
    came, todo = {a: []}, [a]
    for v in todo:
        for k, x, y in edges:
            u = y if x == v else x if y == v else None
            if u is not None and u not in came:
                came[u] = [*came[v], k]
                todo.append(u)
    return came[b]


def test_completions_are_solutions_that_hold_the_partial_one(spark):
    r = random.Random(4)
    rows, jobs, wanted, partial, every = [], [], [], {}, {}
    for i in range(20):
        edges, w = random_graph(r, 6, 0.5), r.sample(range(6), 3)
        found = list(solutions(edges, [w]))
        every[i] = {s.key for s in found}
        rows += [(i, *e) for e in edges]
        jobs.append((i, i))
        wanted += [(i, v) for v in w]
        if found:
            one = set(r.choice(found).edges)
            partial[i] = way([e for e in edges if e[0] in one], w[0], w[1])
    edges = spark.createDataFrame(rows, "graph_id bigint, edge_id bigint, src bigint, dst bigint")
    begun = spark.createDataFrame([(i, e) for i, path in partial.items() for e in path], "instance_id bigint, edge_id bigint")
    out = enum.complete_tree(spark.createDataFrame(jobs, "instance_id bigint, graph_id bigint"), spark.createDataFrame(wanted, "instance_id bigint, vertex_id bigint"), edges, begun).collect()
    assert {row["instance_id"] for row in out} == {i for i, keys in every.items() if keys}
    for row in out:
        assert row["solution_key"] in every[row["instance_id"]] and set(partial[row["instance_id"]]) <= set(row["edges"])


@pytest.mark.parametrize("flavour", ["forest", "directed"])
def test_completion_of_nothing_is_a_solution(flavour):
    from spanweave.kernels.solve import completed

    r = random.Random(5)
    for _ in range(60):
        edges = random_graph(r, 6, 0.5)
        if flavour == "directed":
            edges += [(100 + k, b, a) for k, a, b in edges if r.random() < 0.5]
            sets, root = [r.sample(range(1, 6), 2)], 0
        else:
            sets, root = [r.sample(range(6), 2), r.sample(range(6), 2)], None
        keys = {s.key for s in solutions(edges, sets, root, Options(flavour=flavour))}
        one = completed(edges, sets, [], root, flavour)
        assert (one is None) == (not keys) and (one is None or one.key in keys)


def test_minimality_of_forests_and_induced_sets(spark):
    g = graphs.labelled_graph([(0, 0, 1), (1, 1, 2), (2, 2, 3), (3, 0, 3), (4, 4, 5)], spark)
    one = graphs.one_instance(spark)
    w = spark.createDataFrame([(0, 0, 0), (0, 0, 1), (0, 1, 4), (0, 1, 5)], "instance_id bigint, set_id int, vertex_id bigint")
    tried = spark.createDataFrame([(0, "0-4", [0, 4]), (0, "0", [0]), (0, "0-1-4", [0, 1, 4]), (0, "1-2-3-4", [1, 2, 3, 4]), (0, "0-1-2-3-4", [0, 1, 2, 3, 4]), (0, "9", [9])], "instance_id bigint, solution_key string, edges array<bigint>")
    got = {r["solution_key"]: r["minimal"] for r in hard.check_minimal(tried, one, w, g, "forest").collect()}
    assert got == {"0-4": True, "0": False, "0-1-4": False, "1-2-3-4": True, "0-1-2-3-4": False, "9": False}
    w = spark.createDataFrame([(0, 0), (0, 2)], "instance_id bigint, vertex_id bigint")
    tried = spark.createDataFrame([(0, "a", [0, 1, 2]), (0, "b", [0, 2, 3]), (0, "c", [0, 1, 2, 3]), (0, "d", [0, 2])], "instance_id bigint, solution_key string, vertices array<bigint>")
    assert {r["solution_key"]: r["minimal"] for r in hard.check_minimal(tried, one, w, g, "induced").collect()} == {"a": True, "b": True, "c": False, "d": False}


def test_streamed_transversals_are_all():
    r = random.Random(6)
    for _ in range(200):
        sets = [sum(1 << v for v in r.sample(range(7), r.randrange(1, 5))) for _ in range(r.randrange(1, 7))]
        found = list(streamed_transversals(sets))
        assert len(found) == len(set(found)) and sorted(found) == sorted(minimal_transversals(sets))
    many = [3 << 2 * k for k in range(200)]  # 2^200 of them
    assert len(list(itertools.islice(streamed_transversals(many), 50))) == 50


def test_choices_of_group_members_reach_every_minimal_tree():
    r = random.Random(7)
    for _ in range(40):
        edges = random_graph(r, 6, 0.45)
        groups = [r.sample(range(6), r.randrange(1, 4)) for _ in range(3)]
        got = {s.key for s in solutions(edges, groups, None, Options(flavour="group"))}
        want = set()
        for choice in itertools.product(*groups):
            for s in solutions(edges, [sorted(set(choice))]):
                degree = Counter(v for k in s.edges for v in next(e[1:] for e in edges if e[0] == k))
                members = set(degree) or set(choice)
                if all(any(members & set(q) == {v} for q in groups) for v, d in degree.items() if d == 1):
                    want.add(s.key)
        assert got == want
        assert all(all(set(c) & set(q) for q in groups) for c in _choices([set(q) for q in groups]))


def test_masks_equal_the_kernels(spark):
    r = random.Random(8)
    for _ in range(3):
        edges = random_graph(r, 6, 0.6)
        g = graphs.labelled_graph(edges, spark)
        w = sorted({v for _, a, b in edges for v in (a, b)})[:3]
        assert sorted(x["solution_key"] for x in relational.exhaustive_trees(g, w).collect()) == sorted(s.key for s in solutions(edges, [w]))
        near = {v: {b if a == v else a for _, a, b in edges if v in (a, b)} for _, x, y in edges for v in (x, y)}

        def joined(s, near=near):
            seen, todo = {min(s)}, [min(s)]
            for v in todo:
                for u in near[v] & s - seen:
                    seen.add(u)
                    todo.append(u)
            return seen == s

        good = [set(s) for k in range(len(near) + 1) for s in itertools.combinations(sorted(near), k) if set(w) <= set(s) and joined(set(s))]
        least = ["-".join(map(str, sorted(s))) for s in good if not any(t < s for t in good)]
        assert sorted(x["solution_key"] for x in relational.exhaustive_induced(g, w).collect()) == sorted(least)


def test_measures_equal_a_recount(spark):
    """Every measure again, from the search's events in plain Python."""
    r = random.Random(9)
    edges, w = random_graph(r, 7, 0.6), [0, 3, 6]
    g, one = graphs.labelled_graph(edges, spark), graphs.one_instance(spark)
    terminals = spark.createDataFrame([(0, v) for v in w], "instance_id bigint, vertex_id bigint")
    for options in (Options(), Options(branching="simple"), Options(pacing="buffered")):
        trace = enum.trace(one, terminals, g, options).cache()
        events = list(traced(edges, [w], None, options))
        emits = [work for kind, _, _, work, _ in events if kind == "emit"]
        gaps = [b - a for a, b in zip([0, *emits], emits, strict=False)]
        report = measures.delay_report(trace).first()
        assert report["n_solutions"] == len(emits) == len(list(solutions(edges, [w])))
        assert report["max_delay"] == max([*gaps, events[-1][3] - emits[-1]]) and report["first_work"] == emits[0]
        assert [(x["i"], x["delay"], round(x["ratio"], 9)) for x in measures.incremental_cost(trace, 7).orderBy("i").collect()] == [(i, d, round(d / (7 + i), 9)) for i, d in enumerate(gaps, 1)]
        held = ids = most = most_ids = steps = 0
        least, due, between, last = None, [], [], None
        leaves = max(k for k, e in enumerate(events) if e[0] == "leaf")
        for k, (kind, *_, size) in enumerate(events):
            held, ids = (held + 1, ids + size) if kind == "leaf" else (held - 1, ids - size) if kind == "emit" else (held, ids)
            most, most_ids = max(most, held), max(most_ids, ids)
            steps += kind in ("enter", "leaf", "leave")
            if kind == "emit":
                if k < leaves:
                    due.append(held + 1)
                if last is not None:
                    between.append(steps - last)
                last = steps
        least = min(due, default=None)
        b = measures.buffer_report(trace).first()
        assert (b["most_held"], b["least_held"], b["longest_gap"]) == (most, least, max(between, default=None))
        assert least is None or least >= 1  # something was there whenever an emission was due
        s = measures.space(trace).first()
        assert (s["search_ids"], s["buffered_ids"]) == (events[-1][4], most_ids) and s["search_ids"] <= 8 * len(edges)


def test_each_inner_node_has_a_leaf_of_its_own():
    """Improved branching: inner nodes can be matched with different leaves below them, never a third or later leaf among siblings."""
    r = random.Random(10)
    for _ in range(30):
        edges = random_graph(r, 7, 0.5)
        w = sorted({v for _, a, b in edges for v in (a, b)})[:4]
        path, inner, leaves = [], {}, []
        for k, (kind, _, sibling, _, _) in enumerate(traced(edges, [w], None, Options())):
            if kind == "enter":
                path.append(k)
                inner[k] = []
            elif kind == "leave":
                path.pop()
            elif kind == "leaf" and path and sibling < 2:
                for node in path:
                    inner[node].append(len(leaves))
                leaves.append(k)
        owner: dict[int, int] = {}

        def placed(node, tried, owner=owner, inner=inner):
            for leaf in inner[node]:
                if leaf not in tried:
                    tried.add(leaf)
                    if leaf not in owner or placed(owner[leaf], tried):
                        owner[leaf] = node
                        return True
            return False

        assert all(placed(node, set()) for node in inner)


def test_fragments_in_words(spark):
    g = graphs.labelled_graph([(0, 1, 2), (1, 2, 3)], spark)
    found = spark.createDataFrame([(0, "0-1", [0, 1])], "instance_id bigint, solution_key string, edges array<bigint>")
    names = spark.createDataFrame([(1, "one"), (2, "two")], "vertex_id bigint, label string")
    assert sorted((r["src_label"], r["dst_label"]) for r in explain_fragments(found, names, g).collect()) == [("one", "two"), ("two", "3")]


def test_workspace_is_marked_for_deletion(spark):
    path = workspace(spark)
    assert f"/spanweave/{spark.sparkContext.applicationId}/" in path and workspace(spark) != path


def test_trees_at_the_end_of_a_window(spark, tmp_path):
    from spanweave.streaming import transitions

    rows = [(k, f"2024-01-01 00:{k:02d}:00", k % 2, t, 0.0, "{}") for k, t in enumerate(["signup", "signup", "view", "purchase", "purchase", "click"])]
    rows += [(2, "2024-01-01 00:02:00", 0, "view", 0.0, "{}"), (99, "2024-01-03 00:00:00", 0, "view", 0.0, "{}")]
    for n, part in enumerate((rows[3:7], rows[:3], rows[7:])):
        df = spark.createDataFrame(part, "event_id bigint, ts string, user_id bigint, event_type string, value double, props string")
        df.withColumn("ts", F.to_timestamp("ts")).coalesce(1).write.parquet(str(tmp_path / "in" / f"p={n}"))
    stream = spark.readStream.schema(transitions.EVENTS).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(str(tmp_path / "in"))
    out = transitions.trees_at_window_end(stream, width="1 day")
    q = out.writeStream.format("memory").queryName("at_end").option("checkpointLocation", str(tmp_path / "cp")).outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination(120)
    got = sorted(r["solution_key"] for r in spark.table("at_end").collect())
    # signup to view to purchase of user 0, signup to purchase of user 1: arcs 5 s + t by alphabetical place.
    edges = [(3, 4), (4, 2), (3, 2), (2, 0)]
    assert got == sorted(s.key for s in solutions([(5 * a + b, a, b) for a, b in edges], [[2]], 3, Options(flavour="directed")))
    assert transitions.late_rows(q) >= 0
    assert Graph([(0, 0, 1)]).n == 2
