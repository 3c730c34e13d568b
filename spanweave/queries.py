"""The registered queries: methods, variants, baselines and measures over graphs made from the given tables.

Terminals come from the data: the vertices of a graph by falling degree, then id; the first is A, the second B, and so on.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .functions import measures
from .kernels.solve import Options, solutions
from .operators import enumerate as enum
from .operators import graph_tests, hard
from .operators.components import connected_components
from .operators.keyword import explain_fragments
from .operators.temporal import asof_join
from .plans import relational
from .plans.workspace import settle
from .sources import graphs

A, B, C, D = 1, 2, 3, 4
SIGNUP, PURCHASE, ERROR, VIEW, CLICK = (graphs.EVENT_TYPES.index(t) for t in ("signup", "purchase", "error", "view", "click"))

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}


def query(f):
    QUERIES[f.__name__] = f
    return f


def variant(name: str, f: Callable, *args, **kwargs) -> None:
    QUERIES[name] = lambda spark, sf_dir: f(spark, sf_dir, *args, **kwargs)


def keys(solutions: DataFrame, *more: str) -> DataFrame:
    return solutions.select(*more, "solution_key", F.col("n_edges").cast("bigint").alias("n_edges"))


def trade(spark: SparkSession, sf_dir: str, k: int = 20) -> DataFrame:
    return settle(graphs.topk_pairs(spark, sf_dir, k))


def places(edges: DataFrame, *wanted: int) -> list[int]:
    """Vertices at the given places by degree: as many rows as places."""
    first = graph_tests.degrees(edges).orderBy(F.desc("degree"), "vertex").limit(max(wanted)).collect()
    return [first[p - 1]["vertex"] for p in wanted]


def terminal_rows(spark: SparkSession, *sets: list[int], instance_id: int = 0) -> DataFrame:
    rows = [(instance_id, k, int(v)) for k, s in enumerate(sets) for v in s]
    return spark.createDataFrame(rows, "instance_id bigint, set_id int, vertex_id bigint")


def events_graph(spark: SparkSession, sf_dir: str) -> DataFrame:
    return settle(graphs.event_digraph(spark, sf_dir))


# Paths.


@query
def st_paths_trade(spark, sf_dir, **options):
    g = trade(spark, sf_dir)
    s, t = places(g, A, B)
    return keys(enum.st_paths(g, spark.createDataFrame([(0, s, t)], "instance_id bigint, s bigint, t bigint"), **options))


variant("st_paths_trade_copied_state", st_paths_trade, state="copied")
variant("st_paths_trade_in_order", st_paths_trade, alternate=False)


@query
def st_paths_trade_relational(spark, sf_dir):
    g = trade(spark, sf_dir)
    s, t = places(g, A, B)
    found = relational.paths(g, spark.createDataFrame([(s,)], "s bigint"), spark.createDataFrame([(t,)], "t bigint"))
    return found.select(F.array_join(F.col("edges").cast("array<string>"), "-").alias("solution_key"), F.size("edges").cast("bigint").alias("n_edges"))


@query
def st_paths_events_directed(spark, sf_dir):
    return keys(enum.st_paths(events_graph(spark, sf_dir), spark.createDataFrame([(0, SIGNUP, PURCHASE)], "instance_id bigint, s bigint, t bigint"), directed=True))


@query
def st_path_lengths(spark, sf_dir):
    """How many paths of each length lead from each vertex to each: one instance a pair."""
    g = trade(spark, sf_dir)
    v = graphs.by_degree(g).select("vertex")
    pairs = v.select(F.col("vertex").alias("s")).crossJoin(v.select(F.col("vertex").alias("t")))  # pairs of at most forty vertices
    ends = pairs.select((F.col("s") * 1000 + F.col("t")).alias("instance_id"), "s", "t")
    found = enum.st_paths(g, ends).groupBy("instance_id", "n_edges").agg(F.count("*").alias("n"))
    return found.select(F.floor(F.col("instance_id") / 1000).cast("bigint").alias("s"), (F.col("instance_id") % 1000).alias("t"), F.col("n_edges").cast("bigint").alias("length"), "n")


@query
def set_paths_trade(spark, sf_dir):
    g = trade(spark, sf_dir)
    a, b, c, d = places(g, A, B, C, D)
    return keys(enum.set_paths(g, spark.createDataFrame([(0, [a, c], [b, d])], "instance_id bigint, sources array<bigint>, targets array<bigint>")))


@query
def hamiltonian_paths(spark, sf_dir):
    """Through all five event types, arcs taken as undirected edges: one edge a pair of types."""
    g = events_graph(spark, sf_dir).where("src < dst")
    return keys(enum.hamiltonian_paths(g, spark.createDataFrame([(0, SIGNUP, PURCHASE)], "instance_id bigint, s bigint, t bigint")))


# Trees.


@query
def steiner_trees_buffered(spark, sf_dir, at=(A, B, C), **options):
    g = trade(spark, sf_dir)
    options = {"branching": "improved", "pacing": "buffered"} | options
    return keys(enum.steiner_trees(graphs.one_instance(spark), terminal_rows(spark, places(g, *at)), g, **options))


variant("steiner_trees_simple", steiner_trees_buffered, branching="simple", pacing="none")
variant("steiner_trees_improved", steiner_trees_buffered, pacing="none")
variant("steiner_trees_sharded", steiner_trees_buffered, pacing="none", mode="shard", work_budget=2000)
variant("steiner_trees_four_terminals", steiner_trees_buffered, at=(A, B, C, D))


@query
def steiner_trees_relational(spark, sf_dir):
    g = trade(spark, sf_dir)
    return relational.trees(g, places(g, A, B, C))


@query
def steiner_trees_forced(spark, sf_dir):
    """A with the two vertices of lowest degree."""
    g = trade(spark, sf_dir)
    n = graph_tests.degrees(g).count()
    return keys(enum.steiner_trees(graphs.one_instance(spark), terminal_rows(spark, places(g, A, n - 1, n)), g, pacing="buffered"))


@query
def steiner_trees_disconnected(spark, sf_dir):
    """One terminal is in no edge."""
    g = trade(spark, sf_dir)
    return keys(enum.steiner_trees(graphs.one_instance(spark), terminal_rows(spark, [*places(g, A, B), 999]), g))


@query
def minimum_trees(spark, sf_dir):
    g = trade(spark, sf_dir)
    return keys(enum.minimum_steiner_trees(graphs.one_instance(spark), terminal_rows(spark, places(g, A, B, C)), g))


@query
def minimum_trees_by_rank(spark, sf_dir):
    g = trade(spark, sf_dir)
    return keys(hard.smallest(enum.steiner_trees(graphs.one_instance(spark), terminal_rows(spark, places(g, A, B, C)), g), "n_edges"))


# Forests.


@query
def steiner_forests_improved(spark, sf_dir, **options):
    g = trade(spark, sf_dir)
    a, b, c, d = places(g, A, B, C, D)
    return keys(enum.steiner_forests(graphs.one_instance(spark), terminal_rows(spark, [a, b], [c, d]), g, **options))


variant("steiner_forests_simple", steiner_forests_improved, branching="simple")
variant("steiner_forests_naive_completion", steiner_forests_improved, completion="naive")
variant("steiner_forests_buffered", steiner_forests_improved, pacing="buffered")
variant("steiner_forests_sharded", steiner_forests_improved, mode="shard", work_budget=2000)


@query
def steiner_forests_relational(spark, sf_dir):
    g = trade(spark, sf_dir)
    a, b, c, d = places(g, A, B, C, D)
    return relational.forests(g, [(a, b), (c, d)])


@query
def forest_of_one_set(spark, sf_dir):
    """One set of three: the trees."""
    g = trade(spark, sf_dir)
    return keys(enum.steiner_forests(graphs.one_instance(spark), terminal_rows(spark, places(g, A, B, C)), g))


# Terminal trees.


@query
def terminal_trees_improved(spark, sf_dir, **options):
    g = trade(spark, sf_dir)
    return keys(enum.terminal_steiner_trees(graphs.one_instance(spark), terminal_rows(spark, places(g, A, B, C)), g, **options))


variant("terminal_trees_simple", terminal_trees_improved, branching="simple")
variant("terminal_trees_buffered", terminal_trees_improved, pacing="buffered")
variant("terminal_trees_sharded", terminal_trees_improved, mode="shard", work_budget=500)


@query
def terminal_trees_two(spark, sf_dir):
    g = trade(spark, sf_dir)
    return keys(enum.terminal_steiner_trees(graphs.one_instance(spark), terminal_rows(spark, places(g, A, B)), g))


# Directed trees.


@query
def directed_trees_improved(spark, sf_dir, wanted=(PURCHASE, ERROR, VIEW), **options):
    g = events_graph(spark, sf_dir)
    return keys(enum.directed_steiner_trees(graphs.one_instance(spark, SIGNUP), terminal_rows(spark, list(wanted)), g, **options))


variant("directed_trees_simple", directed_trees_improved, branching="simple")
variant("directed_trees_buffered", directed_trees_improved, pacing="buffered")
variant("directed_trees_sharded", directed_trees_improved, mode="shard", work_budget=500)
variant("directed_trees_spanning", directed_trees_improved, wanted=(PURCHASE, ERROR, VIEW, CLICK))


@query
def directed_trees_relational(spark, sf_dir):
    return relational.trees(events_graph(spark, sf_dir), [PURCHASE, ERROR, VIEW], directed=True, root=SIGNUP)


@query
def directed_trees_user_fleet(spark, sf_dir):
    """One instance a user: from signup to purchase in the user's own digraph."""
    g = settle(graphs.user_digraphs(spark, sf_dir))
    users = g.select("graph_id").distinct()
    jobs = users.select(F.col("graph_id").alias("instance_id"), "graph_id", F.lit(SIGNUP).cast("bigint").alias("root"))
    wanted = users.select(F.col("graph_id").alias("instance_id"), F.lit(PURCHASE).cast("bigint").alias("vertex_id"))
    return keys(enum.directed_steiner_trees(jobs, wanted, g).withColumnRenamed("instance_id", "user_id"), "user_id")


def _windowed(g: DataFrame) -> DataFrame:
    starts = g.select("graph_id").distinct()
    jobs = starts.select(F.col("graph_id").alias("instance_id"), "graph_id", F.lit(SIGNUP).cast("bigint").alias("root"))
    wanted = starts.select(F.col("graph_id").alias("instance_id"), F.lit(PURCHASE).cast("bigint").alias("vertex_id"))
    return keys(enum.directed_steiner_trees(jobs, wanted, g).withColumnRenamed("instance_id", "window_start"), "window_start")


@query
def window_event_fragments(spark, sf_dir):
    """Tumbling windows of 7 days, trees from signup to purchase in each."""
    return _windowed(settle(graphs.window_digraphs(spark, sf_dir)))


@query
def sliding_event_fragments(spark, sf_dir):
    return _windowed(settle(graphs.window_digraphs(spark, sf_dir, "10 days", "5 days")))


@query
def session_transitions(spark, sf_dir):
    """How many sessions (30 minutes apart) have each transition."""
    return graphs.session_digraphs(spark, sf_dir, "6 hours").groupBy("s", "t").agg(F.count("*").alias("sessions"))


@query
def latest_event_before_order(spark, sf_dir):
    """Each order with the type of the customer's latest event by then."""
    orders = graphs.read(spark, sf_dir, "orders").select(F.col("o_custkey").cast("bigint").alias("user_id"), F.col("o_orderdate").cast("timestamp").alias("ts"), "o_orderkey")
    events = graphs.read(spark, sf_dir, "events").select("user_id", F.col("ts").cast("timestamp").alias("ts"), "event_id", "event_type")
    return asof_join(orders, events, key="user_id", time="ts", values=["event_type", "event_id"], tie="event_id").select("o_orderkey", "event_type")


# Hard variants.


@query
def group_trees_regions(spark, sf_dir):
    """Groups: the nations of the first, third and fourth region that are in the graph; a region without any stays as a group without members."""
    g = trade(spark, sf_dir)
    v = graphs.by_degree(g).select("vertex")
    regions = graphs.read(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("bigint").alias("vertex"), F.col("n_regionkey").cast("int").alias("set_id"))
    groups = spark.createDataFrame([(0,), (2,), (3,)], "set_id int").join(v.join(regions, "vertex"), "set_id", "left")
    return keys(enum.group_steiner_trees(graphs.one_instance(spark), groups.select(F.lit(0).cast("bigint").alias("instance_id"), "set_id", F.col("vertex").alias("vertex_id")), g))


@query
def minimal_transversals(spark, sf_dir):
    """For each customer the minimal sets of regions that have a supplier in every order."""
    found = hard.minimal_transversals(graphs.customer_regions(spark, sf_dir))
    return found.select(F.col("instance_id").alias("customer"), "solution_key", F.col("n").cast("bigint").alias("n"))


@query
def minimal_dominating_sets(spark, sf_dir):
    return hard.minimal_transversals(graphs.neighbourhood_hypergraph(trade(spark, sf_dir))).select("solution_key", F.col("n").cast("bigint").alias("n"))


@query
def vertex_covers_by_masks(spark, sf_dir):
    masks = relational.hitting_masks(_by_place(trade(spark, sf_dir)), 20)
    return masks.select(relational.masked_key(F.col("mask"), 20).alias("solution_key"), F.bit_count("mask").cast("bigint").alias("n"))


@query
def vertex_covers_via_star(spark, sf_dir):
    """Group trees of the star, read back as the elements that are leaves."""
    edges, groups = hard.hypergraph_to_star(_by_place(trade(spark, sf_dir)))
    trees = enum.group_steiner_trees(graphs.one_instance(spark), groups, edges, max_choices=2_000_000)
    leaves = F.filter("vertices", lambda v: v >= 0)
    return trees.select(F.array_join(F.transform(F.array_sort(leaves), lambda v: v.cast("string")), "-").alias("solution_key"), F.size(leaves).cast("bigint").alias("n"))


def _by_place(g: DataFrame) -> DataFrame:
    """The edge hypergraph with vertices numbered by their place in the degree order, from 0."""
    place = graphs.by_degree(g).select(F.col("vertex").alias("element"), (F.col("place") - 1).cast("bigint").alias("p"))
    return graphs.edge_hypergraph(g).join(place, "element").select("instance_id", "hyperedge_id", F.col("p").alias("element"))


@query
def hypergraph_star(spark, sf_dir):
    return hard.hypergraph_to_star(graphs.customer_regions(spark, sf_dir))[0].select("edge_id", "src", "dst")


@query
def internal_trees(spark, sf_dir):
    """All trees of the complete graph on the event types in which purchase and error are inside."""
    g = events_graph(spark, sf_dir).where("src < dst")
    return keys(enum.internal_steiner_trees(graphs.one_instance(spark), terminal_rows(spark, [PURCHASE, ERROR]), g))


# Induced connections.


def _ends(g: DataFrame) -> DataFrame:
    """The smallest and the greatest vertex as terminals."""
    ends = g.agg(F.min("src").alias("a"), F.max("dst").alias("b"))
    return ends.select(F.lit(0).cast("bigint").alias("instance_id"), F.explode(F.array("a", "b")).alias("vertex_id"))


@query
def induced_interval_graph(spark, sf_dir):
    """Minimal ways to connect the smallest part size with the greatest by steps of at most 24."""
    g = settle(graphs.intervals(spark, sf_dir, 24))
    return hard.induced_steiner_subgraphs(graphs.one_instance(spark), _ends(g), g).select("solution_key", F.col("n_vertices").cast("bigint").alias("n"))


@query
def minimum_induced(spark, sf_dir):
    g = settle(graphs.intervals(spark, sf_dir, 24))
    found = hard.induced_steiner_subgraphs(graphs.one_instance(spark), _ends(g), g)
    return hard.smallest(found, "n_vertices").select("solution_key", F.col("n_vertices").cast("bigint").alias("n"))


@query
def induced_line_graph(spark, sf_dir):
    """Induced connections of the augmented line graph, read back as trees."""
    g = trade(spark, sf_dir)
    w = places(g, A, B, C)
    h = settle(graphs.numbered(graph_tests.line_graph(g, terminal_rows(spark, w))))
    found = hard.induced_steiner_subgraphs(graphs.one_instance(spark), terminal_rows(spark, [-1 - v for v in w]), h)
    return keys(hard.from_line_graph(found))


def _solution_arcs(spark, sf_dir) -> tuple[DataFrame, DataFrame, DataFrame]:
    g = settle(graphs.intervals(spark, sf_dir, 24))
    one, w = graphs.one_instance(spark), _ends(g)
    found = settle(hard.induced_steiner_subgraphs(one, w, g))
    return g, found, settle(hard.solution_arcs(found, one, w, g))


@query
def solution_graph_reach(spark, sf_dir):
    """The walk over solutions: how many there are, and how many steps lead to from the last one."""
    _, found, arcs = _solution_arcs(spark, sf_dir)
    last = found.agg(F.max("solution_key").alias("vertex")).where("vertex is not null")
    back = graph_tests.reachable(arcs.select(F.col("source").alias("src"), F.col("target").alias("dst")), last)
    return found.agg(F.count("*").alias("solutions")).crossJoin(back.agg(F.count("*").alias("reached")))  # single rows


@query
def solution_graph_degrees(spark, sf_dir):
    """Steps that lead from a solution, most and on average, and the square of the number of vertices that bounds them."""
    g, _, arcs = _solution_arcs(spark, sf_dir)
    n = graph_tests.degrees(g).agg((F.count("*") * F.count("*")).alias("n_squared"))
    each = arcs.groupBy("source").agg(F.count("*").alias("n")).agg(F.max("n").alias("most"), F.round(F.avg("n"), 3).alias("mean"))
    return each.crossJoin(n)  # single rows


@query
def interval_graph(spark, sf_dir):
    return graphs.intervals(spark, sf_dir).select("src", "dst")


@query
def claws(spark, sf_dir):
    return graph_tests.claws(trade(spark, sf_dir))


@query
def line_graph(spark, sf_dir):
    return graph_tests.line_graph(trade(spark, sf_dir))


# Graph operators.


@query
def trade_pairs(spark, sf_dir):
    return graphs.topk_pairs(spark, sf_dir).select("edge_id", "src", "dst")


@query
def degrees(spark, sf_dir):
    return graphs.by_degree(trade(spark, sf_dir)).select("vertex", "degree", F.col("place").cast("bigint").alias("place"))


@query
def bridges(spark, sf_dir):
    return graph_tests.bridges(trade(spark, sf_dir)).select("edge_id")


@query
def components(spark, sf_dir):
    """Hosts and link targets of all pages, each with the smallest label that it is linked with."""
    links = graphs.host_links(spark, sf_dir).select(F.concat(F.lit("host "), "host").alias("src"), F.concat(F.lit("target "), "target").alias("dst"))
    return connected_components(links)


@query
def reachable(spark, sf_dir):
    """From signup by the six most frequent arcs."""
    g = events_graph(spark, sf_dir).where("edge_id < 6")
    return graph_tests.reachable(g, spark.createDataFrame([(SIGNUP,)], "vertex bigint"))


@query
def admissible_components(spark, sf_dir):
    g = trade(spark, sf_dir)
    return graph_tests.admissible_components(g, terminal_rows(spark, places(g, A, B)))


@query
def strip_leaves(spark, sf_dir):
    """Hosts and the three most linked targets: what leaf stripping keeps, by label."""
    pairs = graphs.host_links(spark, sf_dir, 3)
    edges, names = graphs.bipartite(pairs, "host", "target")
    edges, names = settle(edges), settle(names)
    w = names.where("side = 1").select(F.lit(0).alias("instance_id"), "vertex_id")
    left = graph_tests.strip_leaves(edges, w)
    label = lambda side, c: names.where(F.col("side") == side).select(F.col("vertex_id").alias(c), F.col("label").alias(f"{c}_label"))
    return left.join(label(0, "src"), "src").join(label(1, "dst"), "dst").select(F.col("src_label").alias("host"), F.col("dst_label").alias("target"))


@query
def relevant_blocks(spark, sf_dir):
    g = trade(spark, sf_dir)
    return graph_tests.relevant_blocks(g, terminal_rows(spark, places(g, A, B))).select("edge_id")


@query
def trees_after_pruning(spark, sf_dir):
    """The trees for A, B, C of the graph without idle blocks: the same as without pruning."""
    g = trade(spark, sf_dir)
    w = terminal_rows(spark, places(g, A, B, C))
    return keys(enum.steiner_trees(graphs.one_instance(spark), w, settle(graph_tests.relevant_blocks(g, w))))


@query
def normalize_pairs(spark, sf_dir):
    """Each order's supplier regions as pairs with the smallest, by customer."""
    sets = graphs.customer_regions(spark, sf_dir).select("instance_id", F.col("hyperedge_id").alias("set_id"), F.col("element").alias("vertex_id"))
    return graph_tests.normalize_pairs(sets).select(F.col("instance_id").alias("customer"), "a", "b")


# Keyword search.


def _regions(spark: SparkSession, sf_dir: str, g: DataFrame, n: int) -> list[int]:
    """Vertices of the n smallest region keys that have a nation in the graph (at most five)."""
    found = g.where("dst < 0").select("dst").distinct().orderBy(F.desc("dst")).limit(n).collect()
    return [r["dst"] for r in found]


@query
def kfragments_undirected(spark, sf_dir):
    """Trees that connect two region names through nations that trade."""
    g = settle(graphs.region_graph(spark, sf_dir, trade(spark, sf_dir)))
    return keys(enum.steiner_trees(graphs.one_instance(spark), terminal_rows(spark, _regions(spark, sf_dir, g, 2)), g))


@query
def kfragments_strong(spark, sf_dir):
    """Trees whose leaves are three region names, and no name inside."""
    g = settle(graphs.region_graph(spark, sf_dir, trade(spark, sf_dir)))
    return keys(enum.terminal_steiner_trees(graphs.one_instance(spark), terminal_rows(spark, _regions(spark, sf_dir, g, 3)), g))


@query
def kfragments_directed(spark, sf_dir):
    """Along foreign keys from every lineitem to a market segment and a region name, the smallest of each."""
    segment = graphs.read(spark, sf_dir, "customer").agg(F.min("c_mktsegment")).first()[0]
    region = graphs.read(spark, sf_dir, "region").agg(F.min("r_name")).first()[0]
    nested, words = graphs.tuple_graphs(spark, sf_dir, segment, region)
    wanted = [r["vertex_id"] for r in words.collect()]
    packed = nested.select("instance_id", "root", "edges", F.array(F.array(*map(F.lit, wanted))).alias("sets"))

    def work(who, graph, sets, root):
        for s in solutions(graph, sets, root, Options(flavour="directed")):
            yield who, s.key, len(s.edges)

    return keys(enum.over_instances(packed, work, "line bigint, solution_key string, n_edges int"), "line")


def _order_fragments(operator) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark, sf_dir):
        first = lambda table, column: graphs.read(spark, sf_dir, table).agg(F.min(column)).first()[0]
        g = settle(graphs.order_keyword_graphs(spark, sf_dir, first("part", "p_brand"), first("customer", "c_mktsegment"), first("orders", "o_orderpriority")))
        orders = g.select("graph_id").distinct()
        jobs = orders.select(F.col("graph_id").alias("instance_id"), "graph_id")
        words = orders.select(F.col("graph_id").alias("instance_id"), F.explode(F.array(*[F.lit(graphs.KEYWORD * graphs.KIND + k).cast("bigint") for k in range(3)])).alias("vertex_id"))
        return keys(operator(jobs, words, g).withColumnRenamed("instance_id", "order"), "order")

    return run


#: Trees, and trees with keywords at leaves only, of the tuples of each order that hold the least brand, segment and priority.
QUERIES["kfragments_orders"] = _order_fragments(enum.steiner_trees)
QUERIES["kfragments_orders_strong"] = _order_fragments(enum.terminal_steiner_trees)


@query
def page_link_fragments(spark, sf_dir):
    """Trees that connect the three most linked targets through hosts, by number of edges."""
    edges, names = graphs.bipartite(graphs.host_links(spark, sf_dir, 3), "host", "target")
    w = names.where("side = 1").select(F.lit(0).cast("bigint").alias("instance_id"), "vertex_id")
    edges, w = settle(edges), settle(w)
    found = enum.steiner_trees(graphs.one_instance(spark), w, graph_tests.strip_leaves(edges, w))
    return found.groupBy(F.col("n_edges").cast("bigint").alias("n_edges")).agg(F.count("*").alias("n"))


@query
def conversation_trees(spark, sf_dir):
    """First and last turn of each conversation: the chain itself is the one tree."""
    g = settle(graphs.conversation_chains(spark, sf_dir))
    ends = g.groupBy("graph_id").agg(F.min("src").alias("a"), F.max("dst").alias("b"))
    jobs = ends.select(F.col("graph_id").alias("instance_id"), "graph_id", F.lit(None).cast("bigint").alias("root"))
    wanted = ends.select(F.col("graph_id").alias("instance_id"), F.explode(F.array("a", "b")).alias("vertex_id"))
    return keys(enum.steiner_trees(jobs, wanted, g).withColumnRenamed("instance_id", "conv_id"), "conv_id")


@query
def document_facet_degrees(spark, sf_dir):
    """Languages by number of sources with good documents."""
    edges, names = graphs.document_facets(spark, sf_dir)
    return edges.join(names.select(F.col("vertex_id").alias("src"), "label"), "src").groupBy("label").agg(F.count("*").alias("sources"))


@query
def readable_trees(spark, sf_dir):
    """Minimum trees by nation names."""
    g = trade(spark, sf_dir)
    best = enum.minimum_steiner_trees(graphs.one_instance(spark), terminal_rows(spark, places(g, A, B, C)), g)
    nation = graphs.read(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("bigint").alias("vertex_id"), F.col("n_name").alias("label"))
    return explain_fragments(best, nation, g).select("solution_key", F.concat_ws(" - ", "src_label", "dst_label").alias("edge"))


# Solutions as data.


def _trees(spark, sf_dir, at=(A, B, C)) -> DataFrame:
    g = trade(spark, sf_dir)
    return enum.steiner_trees(graphs.one_instance(spark), terminal_rows(spark, places(g, *at)), g)


@query
def tree_size_histogram(spark, sf_dir):
    return _trees(spark, sf_dir).groupBy(F.col("n_edges").cast("bigint").alias("n_edges")).agg(F.count("*").alias("n"))


@query
def edge_frequency(spark, sf_dir):
    return _trees(spark, sf_dir).select(F.explode("edges").alias("edge_id")).groupBy("edge_id").agg(F.count("*").alias("n"))


@query
def published_bound(spark, sf_dir):
    """The greatest delay that earlier work promises for these solutions."""
    return measures.published_bound(_trees(spark, sf_dir), trade(spark, sf_dir).count()).agg(F.max("bound").alias("bound"))


@query
def running_output(spark, sf_dir):
    """Total size of the trees up to each, by size, then key."""
    order = Window.orderBy("n_edges", "solution_key").rowsBetween(Window.unboundedPreceding, 0)  # a few hundred solutions
    return keys(_trees(spark, sf_dir)).withColumn("total", F.sum("n_edges").over(order)).select("solution_key", "total")


@query
def smallest_trees(spark, sf_dir):
    """The ten smallest trees for A, B, C, D."""
    return keys(_trees(spark, sf_dir, (A, B, C, D))).orderBy("n_edges", "solution_key").limit(10)


@query
def trees_intersect_terminal(spark, sf_dir):
    return steiner_trees_buffered(spark, sf_dir).intersect(terminal_trees_improved(spark, sf_dir))


@query
def trees_except_terminal(spark, sf_dir):
    return steiner_trees_buffered(spark, sf_dir).exceptAll(terminal_trees_improved(spark, sf_dir))


@query
def measure_cube(spark, sf_dir):
    """Counts by flavour and size, with totals."""
    both = steiner_trees_buffered(spark, sf_dir).withColumn("flavour", F.lit("tree")).unionByName(terminal_trees_improved(spark, sf_dir).withColumn("flavour", F.lit("terminal")))
    out = measures.size_cube(both, "flavour", "n_edges")
    return out.select(F.coalesce("flavour", F.lit("all")).alias("flavour"), F.coalesce("n_edges", F.lit(-1)).alias("n_edges"), "n")


@query
def completeness(spark, sf_dir):
    """Kernel against path tuples: missing, spurious and repeated solutions."""
    actual = _trees(spark, sf_dir)
    expected = steiner_trees_relational(spark, sf_dir).withColumn("instance_id", F.lit(0).cast("bigint"))
    return measures.compare_solutions(actual, expected)


@query
def minimality(spark, sf_dir):
    """Solutions of each flavour that fail the leaf test."""
    g = trade(spark, sf_dir)
    w = terminal_rows(spark, places(g, A, B, C))
    e = events_graph(spark, sf_dir)
    ew = terminal_rows(spark, [PURCHASE, ERROR, VIEW])
    one = graphs.one_instance(spark)
    parts = [("tree", enum.steiner_trees(one, w, g), w, g), ("terminal", enum.terminal_steiner_trees(one, w, g), w, g), ("directed", enum.directed_steiner_trees(graphs.one_instance(spark, SIGNUP), ew, e), ew, e)]
    out = None
    for flavour, found, wanted, edges in parts:
        row = measures.is_minimal(found, wanted, edges, flavour).agg(F.count("*").alias("n"), F.count(F.when(~F.col("minimal"), 1)).alias("failed")).select(F.lit(flavour).alias("flavour"), "n", "failed")
        out = row if out is None else out.unionByName(row)
    return out


@query
def solution_distances(spark, sf_dir):
    """How far each minimum tree is from the first."""
    g = trade(spark, sf_dir)
    best = enum.minimum_steiner_trees(graphs.one_instance(spark), terminal_rows(spark, places(g, A, B, C)), g)
    first = best.orderBy("solution_key").limit(1).select(F.col("edges").alias("base"))
    return best.crossJoin(F.broadcast(first)).select("solution_key", hard.solution_distance(F.col("edges"), F.col("base")).cast("bigint").alias("distance"))  # one row on the right


# Measures.


VARIANTS = (("simple", {"branching": "simple"}), ("improved", {}), ("buffered", {"pacing": "buffered"}))


def _traces(spark: SparkSession, sf_dir: str, report: Callable[[DataFrame, int, int], DataFrame]) -> DataFrame:
    """``report(trace, n, m)`` of each variant's search for trees on A, B, C, D, with the graph's vertices and edges and the variant's name."""
    g = trade(spark, sf_dir)
    w = terminal_rows(spark, places(g, A, B, C, D))
    n, m = graph_tests.degrees(g).count(), g.count()
    out = None
    for name, options in VARIANTS:
        rows = report(settle(enum.trace(graphs.one_instance(spark), w, g, Options(flavour="tree", **options))), n, m)
        rows = rows.drop("instance_id").select(F.lit(name).alias("variant"), F.lit(n).cast("bigint").alias("n"), F.lit(m).cast("bigint").alias("m"), "*")
        out = rows if out is None else out.unionByName(rows)
    return out


@query
def search_counts(spark, sf_dir):
    """Leaves of each variant's search and solutions handed out: both are the number of trees."""
    kinds = lambda k: F.count(F.when(F.col("kind") == k, 1))
    return _traces(spark, sf_dir, lambda t, n, m: t.groupBy("instance_id").agg(kinds("leaf").alias("leaves"), kinds("emit").alias("emitted")))


@query
def search_delays(spark, sf_dir):
    """Greatest and median work between two solutions, and work before the first, for a graph of n vertices and m edges."""
    return _traces(spark, sf_dir, lambda t, n, m: measures.delay_report(t).withColumn("delay_per_size", F.round(F.col("max_delay") / (n + m), 3)))


@query
def search_amortized(spark, sf_dir):
    """All work, and work for each solution over the graph's size."""
    return _traces(spark, sf_dir, lambda t, n, m: measures.amortized_report(t).withColumn("per_solution_and_size", F.round(F.col("work_per_solution") / (n + m), 3)).drop("work_per_solution"))


@query
def search_incremental(spark, sf_dir):
    """The greatest delay of the i-th solution over n + i."""
    return _traces(spark, sf_dir, lambda t, n, m: measures.incremental_cost(t, n).groupBy("instance_id").agg(F.round(F.max("ratio"), 3).alias("most_per_n_plus_i")))


@query
def search_space(spark, sf_dir):
    """Ids that the search held at a time, and ids in its buffer."""
    return _traces(spark, sf_dir, lambda t, n, m: measures.space(t))


@query
def search_shapes(spark, sf_dir):
    """Inner nodes, leaves, height and inner nodes with one child."""
    return _traces(spark, sf_dir, lambda t, n, m: measures.tree_shape(t))


@query
def search_buffers(spark, sf_dir):
    """Solutions held back, most and least while any is still to be found, and search steps between two emissions."""
    return _traces(spark, sf_dir, lambda t, n, m: measures.buffer_report(t))


@query
def output_sizes(spark, sf_dir):
    """Number, total and mean size of the solutions: what any enumeration has to write."""
    return measures.output_size(_trees(spark, sf_dir)).select("n", F.col("total").alias("total"), F.col("least").cast("bigint").alias("least"), F.col("most").cast("bigint").alias("most"), F.round("mean", 6).alias("mean"))


@query
def duality(spark, sf_dir):
    """Whether the minimal transversals found for each customer are all there are, by the duality test."""
    h = settle(graphs.customer_regions(spark, sf_dir))
    found = hard.minimal_transversals(h)
    return hard.check_dual(h, found).groupBy("dual").agg(F.count("*").alias("customers"))


# More terminal sets, workloads and baselines.


def _forest(*sets: tuple[int, ...]) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark, sf_dir):
        g = trade(spark, sf_dir)
        return keys(enum.steiner_forests(graphs.one_instance(spark), terminal_rows(spark, *[places(g, *s) for s in sets]), g))

    return run


QUERIES["forests_low_degree"] = _forest((6, C), (7, 5))
QUERIES["forests_mixed"] = _forest((8, C), (D, 5))
QUERIES["forests_overlapping"] = _forest((A, B), (B, C))
QUERIES["forests_singleton"] = _forest((A,), (B, C))


def _terminal(*at: int) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark, sf_dir):
        g = trade(spark, sf_dir)
        return keys(enum.terminal_steiner_trees(graphs.one_instance(spark), terminal_rows(spark, places(g, *at)), g))

    return run


QUERIES["terminal_trees_c_e_b"] = _terminal(C, 5, B)
QUERIES["terminal_trees_d_c_b"] = _terminal(D, C, B)
QUERIES["terminal_trees_f_d_b"] = _terminal(6, D, B)
QUERIES["terminal_trees_f_h_g"] = _terminal(6, 8, 7)
QUERIES["terminal_trees_two_inner"] = _terminal(D, 5)


@query
def terminal_trees_no_component(spark, sf_dir):
    """The last vertex by degree, all its neighbours and one more: no component of the rest is next to the last one."""
    g = trade(spark, sf_dir)
    n = graph_tests.degrees(g).count()
    last = places(g, n)[0]
    near = [r["v"] for r in graph_tests.oriented(g).where(F.col("src") == last).select(F.col("dst").alias("v")).distinct().collect()]  # the neighbours of the vertex with fewest
    third = [v for v in places(g, A, B, C, D) if v not in near and v != last][:1]
    return keys(enum.terminal_steiner_trees(graphs.one_instance(spark), terminal_rows(spark, [last, *near, *third]), g))


@query
def shortest_paths_trade(spark, sf_dir):
    """Edges of a shortest path from A to every vertex, by breadth-first rounds."""
    g = trade(spark, sf_dir)
    return graph_tests.distances(g, spark.createDataFrame([(v,) for v in places(g, A)], "vertex bigint"))


@query
def complete_tree_of_one_edge(spark, sf_dir):
    """Whether one tree for A, B, C that holds the most frequent edge at A is among all trees."""
    g = trade(spark, sf_dir)
    w = places(g, A, B, C)
    first = g.where((F.col("src") == w[0]) | (F.col("dst") == w[0])).agg(F.min("edge_id").alias("edge_id")).select(F.lit(0).cast("bigint").alias("instance_id"), "edge_id")
    one = enum.complete_tree(graphs.one_instance(spark), terminal_rows(spark, w), g, first)
    every = enum.steiner_trees(graphs.one_instance(spark), terminal_rows(spark, w), g).select("solution_key")
    held = one.crossJoin(F.broadcast(first.select("edge_id"))).where(F.array_contains("edges", F.col("edge_id")))  # one row on each side
    return held.join(every, "solution_key", "left_semi").agg(F.count("*").alias("found"))


@query
def trees_by_masks(spark, sf_dir):
    """The trees for A, B, C among all sets of edges."""
    g = trade(spark, sf_dir)
    return relational.exhaustive_trees(g, places(g, A, B, C))


@query
def induced_by_masks(spark, sf_dir):
    """Minimal vertex sets of the trade graph that connect two vertices of low degree, among all sets."""
    g = trade(spark, sf_dir)
    return relational.exhaustive_induced(g, places(g, 8, 5))


@query
def induced_three_by_masks(spark, sf_dir):
    g = trade(spark, sf_dir)
    return relational.exhaustive_induced(g, places(g, 6, 7, 8))


@query
def group_trees_all_regions(spark, sf_dir):
    """Groups: the nations of each region in the graph."""
    g = trade(spark, sf_dir)
    v = graph_tests.degrees(g).select("vertex")
    regions = graphs.read(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("bigint").alias("vertex"), F.col("n_regionkey").cast("int").alias("set_id"))
    found = enum.group_steiner_trees(graphs.one_instance(spark), v.join(regions, "vertex").select(F.lit(0).cast("bigint").alias("instance_id"), "set_id", F.col("vertex").alias("vertex_id")), g)
    return found.groupBy(F.col("n_edges").cast("bigint").alias("n_edges")).agg(F.count("*").alias("n"))


@query
def benchmark_transversals(spark, sf_dir):
    """Minimal sets of words that hold one of the three rarest words of each text, for four texts at a time."""
    found = hard.minimal_transversals(graphs.benchmark_tokens(spark, sf_dir))
    return found.groupBy(F.col("instance_id").alias("texts"), F.col("n").cast("bigint").alias("n")).agg(F.count("*").alias("sets"))


@query
def similarity_graph(spark, sf_dir):
    """Each vector's three nearest by cosine, all vectors."""
    return graphs.similarity(spark, sf_dir).select("src", "dst")


@query
def order_part_components(spark, sf_dir):
    """Components of the graph of all orders, suppliers and parts by their number of vertices."""
    g = graphs.order_parts(spark, sf_dir)
    return connected_components(g).groupBy("component").agg(F.count("*").alias("vertices")).groupBy("vertices").agg(F.count("*").alias("components"))


@query
def event_keys(spark, sf_dir):
    """Events by the number in their properties and by week."""
    rows = graphs.read(spark, sf_dir, "events").select(F.get_json_object("props", "$.k").cast("bigint").alias("k"), F.date_trunc("week", "ts").alias("w"))
    return rows.groupBy("k", F.unix_timestamp("w").alias("week")).agg(F.count("*").alias("n"))


@query
def parts_by_word(spark, sf_dir):
    """How many parts have each word in their name, and of how many brands."""
    words = graphs.read(spark, sf_dir, "part").select("p_brand", F.explode(F.array_distinct(F.split(F.lower("p_name"), "[^a-z0-9]+"))).alias("word")).where("word <> ''")
    return words.groupBy("word").agg(F.count("*").alias("parts"), F.count_distinct("p_brand").alias("brands"))


@query
def minimality_of_sets(spark, sf_dir):
    """Forests and induced connections that fail their minimality test, and how many were tested."""
    g = trade(spark, sf_dir)
    one = graphs.one_instance(spark)
    a, b, c, d = places(g, A, B, C, D)
    w = terminal_rows(spark, [a, b], [c, d])
    forests = hard.check_minimal(enum.steiner_forests(one, w, g), one, w, g, "forest")
    h = settle(graphs.intervals(spark, sf_dir, 24))
    ends = _ends(h)
    sets = hard.induced_steiner_subgraphs(one, ends, h).withColumn("vertices", F.transform(F.split("solution_key", "-"), lambda v: v.cast("bigint")))
    induced = hard.check_minimal(sets, one, ends, h, "induced")
    count = lambda df, name: df.agg(F.count("*").alias("n"), F.count(F.when(~F.col("minimal"), 1)).alias("failed")).select(F.lit(name).alias("flavour"), "n", "failed")
    return count(forests, "forest").unionByName(count(induced, "induced"))
