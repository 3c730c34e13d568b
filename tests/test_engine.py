"""DataFrame operators: modes agree, reductions keep the solutions, streams equal their batch twins, errors are clear."""

import random
from itertools import combinations

import pytest
from pyspark.sql import functions as F

from spanweave.functions import measures, udtf
from spanweave.functions.acyclic import is_acyclic
from spanweave.kernels.solve import Options
from spanweave.operators import enumerate as enum
from spanweave.operators import graph_tests, hard
from spanweave.operators.components import connected_components
from spanweave.operators.keyword import k_fragments
from spanweave.plans import planner, relational
from spanweave.sources import graphs
from spanweave.streaming import transitions

SF = "/root/testdata/sf0.001"


def edges_of(spark, rows, graph_id=0):
    return spark.createDataFrame([(graph_id, *r) for r in rows], "graph_id bigint, edge_id bigint, src bigint, dst bigint")


def terminals_of(spark, *sets):
    return spark.createDataFrame([(0, k, v) for k, s in enumerate(sets) for v in s], "instance_id bigint, set_id int, vertex_id bigint")


def keys(df):
    return sorted(r["solution_key"] for r in df.collect())


def rows_of(seed, n=7, m=13):
    r = random.Random(seed)
    return [(k, *r.sample(range(n), 2)) for k in range(m)]


@pytest.mark.parametrize("budget", [250, 10_000])
def test_shards_find_the_same(spark, budget):
    g, one = edges_of(spark, rows_of(1)), graphs.one_instance(spark)
    w = terminals_of(spark, [0, 1, 2, 3])
    for operator, sets in ((enum.steiner_trees, w), (enum.terminal_steiner_trees, terminals_of(spark, [0, 1, 2])), (enum.terminal_steiner_trees, terminals_of(spark, [0, 1])), (enum.steiner_forests, terminals_of(spark, [0, 1], [2, 3], [4]))):
        want = keys(operator(one, sets, g))
        assert keys(operator(one, sets, g, mode="shard", work_budget=budget)) == want
        assert len(set(want)) == len(want)
    rooted = graphs.one_instance(spark, 6)
    assert keys(enum.directed_steiner_trees(rooted, w, g, mode="shard", work_budget=budget)) == keys(enum.directed_steiner_trees(rooted, w, g))


def test_limits_and_modes(spark):
    g, one, w = edges_of(spark, rows_of(2)), graphs.one_instance(spark), terminals_of(spark, [0, 1, 2])
    every = keys(enum.steiner_trees(one, w, g))
    for options in ({}, {"mode": "shard", "work_budget": 30}):
        some = keys(enum.steiner_trees(one, w, g, limit=3, **options))
        assert len(some) == 3 and set(some) <= set(every)
    assert keys(enum.steiner_trees(one, w, g, mode="auto")) == every
    assert planner.explain_mode(one, g, fleet_edges=3).first()["mode"] == "relational"
    assert keys(enum.complete_tree(one, w, g))[0] in every
    with pytest.raises(ValueError, match="unknown mode"):
        enum.steiner_trees(one, w, g, mode="x")
    with pytest.raises(ValueError, match="missing columns"):
        enum.steiner_trees(one, w, g.drop("dst"))
    with pytest.raises(Exception, match="null src"):
        enum.steiner_trees(one, w, edges_of(spark, [(0, None, 1)])).collect()


def test_no_rows(spark):
    g, one, w = edges_of(spark, rows_of(2)), graphs.one_instance(spark), terminals_of(spark, [0, 1, 2])
    assert enum.steiner_trees(one.limit(0), w, g).count() == 0
    assert enum.steiner_trees(one, w, g.limit(0)).count() == 0
    assert connected_components(g.limit(0)).count() == 0
    assert graph_tests.bridges(g.limit(0)).count() == 0 and graph_tests.claws(g.limit(0)).count() == 0
    assert hard.minimal_transversals(spark.createDataFrame([], "instance_id bigint, hyperedge_id bigint, element bigint")).count() == 0


def test_fleet_of_graphs(spark):
    """Two graphs, three instances; parallel edges and self-loops."""
    g = edges_of(spark, [(0, 1, 2), (1, 1, 2), (2, 2, 2)]).union(edges_of(spark, [(0, 1, 3), (1, 3, 2)], 5))
    jobs = spark.createDataFrame([(10, 0, None), (11, 5, None), (12, 5, None)], "instance_id bigint, graph_id bigint, root bigint")
    w = spark.createDataFrame([(10, 1), (10, 2), (11, 1), (11, 2), (12, 3), (12, 3)], "instance_id bigint, vertex_id bigint")
    out = sorted((r["instance_id"], r["solution_key"]) for r in enum.steiner_trees(jobs, w, g).collect())
    assert out == [(10, "0"), (10, "1"), (11, "0-1"), (12, "v3")]


@pytest.mark.parametrize("seed", range(3))
def test_reductions_keep_solutions(spark, seed):
    rows = rows_of(seed, 9, 12)
    g, one, w = edges_of(spark, rows), graphs.one_instance(spark), terminals_of(spark, [0, 1, 2])
    want = keys(enum.steiner_trees(one, w, g))
    assert keys(enum.steiner_trees(one, w, graph_tests.strip_leaves(g, w))) == want
    assert keys(enum.steiner_trees(one, w, graph_tests.relevant_blocks(g, w))) == want
    assert keys(enum.steiner_trees(one, w, graph_tests.terminal_component(g, w))) == want
    short = graph_tests.compress_chains(g, w)
    chains = {r["edge_id"]: r["chain"] for r in short.collect()}
    found = [r["edges"] for r in enum.steiner_trees(one, w, short.drop("chain")).collect()]
    assert sorted("-".join(map(str, sorted(e for k in edges for e in chains[k]))) or "v0" for edges in found) == want


@pytest.mark.parametrize("seed", range(3))
def test_graph_operators(spark, seed):
    rows = rows_of(seed, 8, 9)
    g = edges_of(spark, rows)
    near = {}
    for _, a, b in rows:
        near.setdefault(a, set()).add(b)
        near.setdefault(b, set()).add(a)

    def reach(v, skip=None):
        seen, todo = {v}, [v]
        for x in todo:
            for e, a, b in rows:
                if e != skip and x in (a, b) and (y := a + b - x) not in seen:
                    seen.add(y)
                    todo.append(y)
        return seen

    assert {(r["vertex"], r["component"]) for r in connected_components(g).collect()} == {(v, min(reach(v))) for v in near}
    assert {r["edge_id"] for r in graph_tests.bridges(g.repartition(3)).collect()} == {e for e, a, b in rows if b not in reach(a, e)}
    claws = {(c, *t) for c, n in near.items() for t in combinations(sorted(n), 3) if all(y not in near[x] for x, y in combinations(t, 2))}
    assert {tuple(r) for r in graph_tests.claws(g).collect()} == claws
    if claws:
        with pytest.raises(Exception, match="claw"):
            hard.induced_steiner_subgraphs(graphs.one_instance(spark), terminals_of(spark, [0, 1]), g).collect()


def test_three_terminals_in_an_interval_graph(spark):
    sizes = [2, 5, 8, 11, 19, 28, 29, 37, 38, 41, 42, 43, 46, 50]
    pairs = [(a, b) for a, b in combinations(range(14), 2) if sizes[b] - sizes[a] <= 9]
    g = edges_of(spark, [(k, a, b) for k, (a, b) in enumerate(pairs)])
    near = [{b for a, b in pairs if a == v} | {a for a, b in pairs if b == v} for v in range(14)]

    def connected(s):
        seen, todo = {min(s)}, [min(s)]
        for v in todo:
            for u in near[v] & s - seen:
                seen.add(u)
                todo.append(u)
        return seen == s

    for w in ([0, 9], [0, 6, 13], [3]):
        sets = [set(c) | set(w) for k in range(12) for c in combinations(sorted(set(range(14)) - set(w)), k)]
        joined = [s for s in sets if connected(s)]
        want = sorted("-".join(map(str, sorted(s))) for s in joined if not any(t < s for t in joined))
        assert keys(hard.induced_steiner_subgraphs(graphs.one_instance(spark), terminals_of(spark, w), g)) == want


def test_measures(spark):
    g, one, w = edges_of(spark, rows_of(5)), graphs.one_instance(spark), terminals_of(spark, [0, 1, 2])
    found = enum.steiner_trees(one, w, g)
    n = found.count()
    trace = enum.trace(one, w, g, Options(pacing="buffered"))
    assert measures.delay_report(trace).first()["n_solutions"] == n
    assert measures.amortized_report(trace).first()["work_per_solution"] > 0
    shape = measures.tree_shape(enum.trace(one, w, g, Options())).first()
    assert shape["leaves"] == n and shape["inner"] < n and shape["one_child"] == 0
    assert measures.buffer_report(trace).first()["most_held"] <= n
    assert measures.output_size(found).first()["n"] == n
    assert measures.is_minimal(found, w, g).where("not minimal").count() == 0
    broken = found.withColumn("edges", F.slice("edges", 1, F.size("edges") - 1)).withColumn("n_edges", F.col("n_edges") - 1).where("n_edges > 0")
    assert measures.is_minimal(broken, w, g).where("minimal").count() < broken.count()
    assert tuple(measures.compare_solutions(found, found.limit(n - 1)).first()) == (0, 1, 0)


def test_similarity_and_bench_graphs(spark):
    g = graphs.similarity(spark, SF, 40)
    assert g.count() >= 40 * 3 / 2 and graphs.co_occurrence(spark, SF, 30).count() == 30
    assert graphs.benchmark_tokens(spark, SF, 2).count() > 0
    found = enum.steiner_trees(graphs.one_instance(spark), terminals_of(spark, [0, 7, 20]), g, limit=50)
    assert measures.is_minimal(found, terminals_of(spark, [0, 7, 20]), g).where("not minimal").count() == 0


def test_sources_and_sinks(spark, tmp_path):
    g = graphs.topk_pairs(spark, SF).cache()
    g.select("edge_id", "src", "dst").write.option("header", True).csv(str(tmp_path / "c"))
    g.select("edge_id", "src", "dst").write.json(str(tmp_path / "j"))
    for again in (graphs.edges_from_csv(spark, str(tmp_path / "c")), graphs.edges_from_json(spark, str(tmp_path / "j"))):
        assert sorted(map(tuple, again.select("edge_id", "src", "dst").collect())) == sorted(map(tuple, g.select("edge_id", "src", "dst").collect()))
    a, b = (r["vertex"] for r in graphs.by_degree(g).orderBy("place").limit(2).collect())
    found = enum.steiner_trees(graphs.one_instance(spark), terminals_of(spark, [a, b]), g)
    graphs.write_solutions(found, str(tmp_path / "s"))
    assert spark.read.parquet(str(tmp_path / "s")).count() == found.count()


def test_sql_surface(spark):
    udtf.register(spark)
    edges_of(spark, [(0, 1, 2), (1, 2, 3), (2, 3, 4), (3, 4, 1), (4, 1, 3)]).createOrReplaceTempView("square")
    assert spark.sql("SELECT * FROM steiner_trees(TABLE(square) PARTITION BY (graph_id), '1,3,4')").count() == 5
    assert spark.sql("SELECT * FROM terminal_steiner_trees(TABLE(square) PARTITION BY (graph_id), '2,4')").count() == 4
    assert spark.sql("SELECT * FROM directed_steiner_trees(TABLE(square) PARTITION BY (graph_id), '3', 1)").count() == 2
    assert spark.sql("SELECT * FROM st_paths(TABLE(square) PARTITION BY (graph_id), 1, 3)").count() == 3


def test_recursive_sql_paths(spark):
    edges_of(spark, [(0, 1, 2), (1, 2, 3), (2, 1, 3)]).createOrReplaceTempView("little")
    out = spark.sql(relational.recursive_paths_sql("little", "1")).where("t = 3").collect()
    assert sorted(r["edges"] for r in out) == [[0, 1], [2]]


def test_streams_equal_batches(spark, tmp_path):
    events = spark.read.parquet(f"{SF}/events.parquet").select(*(c.split()[0] for c in transitions.EVENTS.split(", ")))
    folder = str(tmp_path / "events")
    events.union(events.limit(20)).repartitionByRange(4, "ts").sortWithinPartitions("ts").write.parquet(folder)
    far = spark.createDataFrame([(10**9, "2030-01-01 00:00:00", 10**6, "view", 0.0, "{}")], "event_id bigint, ts string, user_id bigint, event_type string, value double, props string").withColumn("ts", F.to_timestamp("ts"))
    far.coalesce(1).write.mode("append").parquet(folder)

    def watched(df, name, mode):
        q = df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", str(tmp_path / name)).trigger(availableNow=True).start()
        try:
            assert q.awaitTermination(120)
        finally:
            q.stop()
        return spark.table(name)

    assert watched(transitions.without_repeats(transitions.event_stream(spark, folder, 100), "400 days"), "once", "append").count() == events.count() + 1
    out = str(tmp_path / "trees")
    q = transitions.trees_per_window(transitions.event_stream(spark, folder, 100).dropDuplicates(["event_id"]), out, late="0 seconds").option("checkpointLocation", str(tmp_path / "c1")).trigger(availableNow=True).start()
    q.awaitTermination(120)
    from spanweave.queries import QUERIES

    want = {(r["window_start"], r["solution_key"]) for r in QUERIES["window_event_fragments"](spark, SF).collect()}
    assert {(r["window_start"], r["solution_key"]) for r in spark.read.parquet(out).collect()} == want

    running = watched(transitions.running_transitions(transitions.event_stream(spark, folder, 100)), "running", "update")
    got = {(r["src_type"], r["dst_type"]): r["n"] for r in running.groupBy("src_type", "dst_type").agg(F.sum("n").alias("n")).collect()}
    from pyspark.sql import Window

    after = F.lead("event_type").over(Window.partitionBy("user_id").orderBy("ts", "event_id"))
    batch = events.withColumn("after", after).where("after <> event_type").groupBy("event_type", "after").count()
    assert got == {(r[0], r[1]): r[2] for r in batch.collect()}


def test_window_counts_and_sessions(spark):
    events = spark.read.parquet(f"{SF}/events.parquet")
    assert transitions.window_counts(events, "7 days").agg(F.sum("n")).first()[0] == events.count()
    assert transitions.window_counts(events, "2 days", "1 day").agg(F.sum("n")).first()[0] == 2 * events.count()
    assert transitions.sessions(events).agg(F.sum("n")).first()[0] == events.count()


def test_k_fragments(spark):
    edges = spark.createDataFrame([(0, 1, 2), (1, 2, 3), (2, 3, 4), (3, 4, 1), (4, 1, 3)], "edge_id bigint, src bigint, dst bigint")
    holders = spark.createDataFrame([("red", 2), ("red", 2), ("blue", 4), ("green", 1)], "keyword string, vertex bigint")
    assert k_fragments(edges, holders, ["red", "blue"]).count() == 4 == k_fragments(edges, holders, ["red", "blue"], kind="strong").count()
    assert k_fragments(edges, holders, ["red", "nothing"]).count() == 0
    assert k_fragments(edges, holders, ["red", "blue"], limit=1).count() == 1
    roots = {r["instance_id"] for r in k_fragments(edges, holders, ["red", "blue"], kind="directed").collect()}
    assert roots == {1, 2, 3, 4}


def test_acyclic_aggregate(spark):
    df = spark.createDataFrame([(0, 1, 2), (0, 2, 3), (1, 1, 2), (1, 2, 1), (2, 5, 6)], "k int, src bigint, dst bigint")
    assert {r["k"]: r["ok"] for r in df.groupBy("k").agg(is_acyclic("src", "dst").alias("ok")).collect()} == {0: True, 1: False, 2: True}
