"""Graphs from tables, as DataFrame plans: edges are (graph_id, edge_id, src, dst), ids bigint."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..plans.spread import ranked

#: Vertex ids of tuples: a code for the kind times this, plus the key.
KIND = 10**12


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def edges_from_csv(spark: SparkSession, path: str) -> DataFrame:
    """edge_id, src, dst with a header line."""
    return spark.read.schema("edge_id bigint, src bigint, dst bigint").option("header", True).csv(path).withColumn("graph_id", F.lit(0).cast("bigint"))


def edges_from_json(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("edge_id bigint, src bigint, dst bigint").json(path).withColumn("graph_id", F.lit(0).cast("bigint"))


def write_solutions(solutions: DataFrame, path: str, buckets: int = 16) -> None:
    """Parquet in folders by a bucket of the instance, so that readers of one instance skip the others."""
    solutions.withColumn("bucket", F.pmod(F.xxhash64("instance_id"), F.lit(buckets)).cast("int")).write.mode("overwrite").partitionBy("bucket").parquet(path)


def _edges(src: Column, dst: Column, edge_id: Column, graph_id: Column | None = None) -> list[Column]:
    return [(F.lit(0) if graph_id is None else graph_id).cast("bigint").alias("graph_id"), edge_id.cast("bigint").alias("edge_id"), src.cast("bigint").alias("src"), dst.cast("bigint").alias("dst")]


def topk_pairs(spark: SparkSession, sf_dir: str, k: int = 20) -> DataFrame:
    """The k pairs of different nations with most lineitems between a customer and a supplier; edge_id is the rank from 0.

    At most one row for each pair of nations reaches the ranking, so its single partition is bounded by the nations.
    """
    lines = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey")
    customers = read(spark, sf_dir, "orders").select("o_orderkey", "o_custkey").join(read(spark, sf_dir, "customer").select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
    joined = lines.join(customers, F.col("l_orderkey") == F.col("o_orderkey")).join(read(spark, sf_dir, "supplier").select("s_suppkey", "s_nationkey"), F.col("l_suppkey") == F.col("s_suppkey"))
    pairs = joined.where("c_nationkey <> s_nationkey").groupBy(F.least("c_nationkey", "s_nationkey").alias("a"), F.greatest("c_nationkey", "s_nationkey").alias("b")).agg(F.count("*").alias("n"))
    best = pairs.orderBy(F.desc("n"), "a", "b").limit(k)
    rank = F.row_number().over(Window.orderBy(F.desc("n"), "a", "b")) - 1
    return best.select(*_edges(F.col("a"), F.col("b"), rank))


def by_degree(edges: DataFrame) -> DataFrame:
    """(vertex, degree, place): vertices by falling degree, then id; place counts from 1."""
    ends = edges.select(F.explode(F.array("src", "dst")).alias("vertex")).groupBy("vertex").agg(F.count("*").alias("degree"))
    return ranked(ends, "place", F.desc("degree"), F.col("vertex")).withColumn("place", F.col("place") + 1)


def terminals_at(edges: DataFrame, places: dict[int, int], instance_id: int = 0) -> DataFrame:
    """terminals of one instance: the vertices at ``places`` (place by degree -> set id)."""
    spark = edges.sparkSession
    wanted = spark.createDataFrame([(int(p), int(s)) for p, s in places.items()], "place int, set_id int")
    return by_degree(edges).join(F.broadcast(wanted), "place").select(F.lit(instance_id).cast("bigint").alias("instance_id"), "set_id", F.col("vertex").alias("vertex_id"))


def one_instance(spark: SparkSession, root: int | None = None, instance_id: int = 0) -> DataFrame:
    return spark.createDataFrame([(instance_id, 0, root)], "instance_id bigint, graph_id bigint, root bigint")


# The event types, in alphabetical order; a vertex id is the position.
EVENT_TYPES = ("click", "error", "purchase", "signup", "view")


def _type_id(column: str) -> Column:
    return (F.array_position(F.array(*map(F.lit, EVENT_TYPES)), F.col(column)) - 1).cast("bigint")


def _transitions(events: DataFrame, *keys: str) -> DataFrame:
    """Rows (keys, s, t): consecutive events of a user that differ in type."""
    after = F.lead("event_type").over(Window.partitionBy(*keys, "user_id") .orderBy("ts", "event_id") if keys else Window.partitionBy("user_id").orderBy("ts", "event_id"))
    return events.withColumn("after", after).where("after <> event_type").withColumn("s", _type_id("event_type")).withColumn("t", _type_id("after"))


def event_digraph(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Arcs between event types; edge_id by falling count, then ends (at most 20 rows)."""
    counts = _transitions(read(spark, sf_dir, "events")).groupBy("s", "t").agg(F.count("*").alias("n"))
    return counts.select(*_edges(F.col("s"), F.col("t"), F.row_number().over(Window.orderBy(F.desc("n"), "s", "t")) - 1))


def user_digraphs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One digraph a user, graph_id being the user; edge_id is 5 s + t."""
    arcs = _transitions(read(spark, sf_dir, "events")).select("user_id", "s", "t").distinct()
    return arcs.select(*_edges(F.col("s"), F.col("t"), F.col("s") * 5 + F.col("t"), F.col("user_id")))


def window_digraphs(spark: SparkSession, sf_dir: str, width: str = "7 days", slide: str | None = None) -> DataFrame:
    """One digraph for each time window over all users' transitions within it; graph_id is the window's start in seconds."""
    events = read(spark, sf_dir, "events").withColumn("w", F.window("ts", width, slide or width)).withColumn("start", F.unix_timestamp(F.col("w.start")))
    arcs = _transitions(events, "start").select("start", "s", "t").distinct()
    return arcs.select(*_edges(F.col("s"), F.col("t"), F.col("s") * 5 + F.col("t"), F.col("start")))


def session_digraphs(spark: SparkSession, sf_dir: str, gap: str = "30 minutes") -> DataFrame:
    """(user_id, start, s, t): transitions within a user's session."""
    events = read(spark, sf_dir, "events")
    wide = Window.partitionBy("user_id").orderBy("ts", "event_id")
    fresh = (F.lag("ts").over(wide) + F.expr(f"interval {gap}") < F.col("ts")).cast("int")
    sessions = events.withColumn("session", F.sum(F.coalesce(fresh, F.lit(0))).over(wide.rowsBetween(Window.unboundedPreceding, 0)))
    return _transitions(sessions, "session").select("user_id", "session", "s", "t").distinct()


def tuple_id(code: int, key: str) -> Column:
    return F.lit(code).cast("bigint") * KIND + F.col(key).cast("bigint")


# Kind codes of tuples; 9 is for keyword nodes, numbered by a hash-free rank of their text.
LINEITEM, ORDERS, CUSTOMER, SUPPLIER, PART, NATION, REGION, KEYWORD = 1, 2, 3, 4, 5, 6, 7, 9


def tuple_graphs(spark: SparkSession, sf_dir: str, segment: str, region: str) -> tuple[DataFrame, DataFrame]:
    """(edges, instances): the foreign-key tree below each lineitem whose customer is in ``segment`` and whose customer or supplier is in ``region``.

    An answer to the two keywords uses only tuples that its root refers to, so every lineitem has a graph of its own, of at
    most ten arcs, made by equi-joins; rows that cannot hold both keywords go before anything is nested.  Keyword nodes hang
    on the tuples that hold them: KEYWORD 0 on the customer, KEYWORD 1 on the region.  edge_id numbers the arcs of a graph.
    """
    nation = read(spark, sf_dir, "nation").join(read(spark, sf_dir, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    side = lambda p: F.broadcast(nation.select(F.col("n_nationkey").alias(f"{p}_nation"), F.col("r_regionkey").alias(f"{p}_region"), (F.col("r_name") == region).alias(f"{p}_in")))  # noqa: E731  (a row a nation)
    customers = read(spark, sf_dir, "customer").where(F.col("c_mktsegment") == segment).select("c_custkey", F.col("c_nationkey").alias("c_nation")).join(side("c"), "c_nation")
    suppliers = read(spark, sf_dir, "supplier").select("s_suppkey", F.col("s_nationkey").alias("s_nation")).join(side("s"), "s_nation")
    orders = read(spark, sf_dir, "orders").select("o_orderkey", "o_custkey").join(customers, F.col("o_custkey") == F.col("c_custkey"))
    lines = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_suppkey")
    rows = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(suppliers, F.col("l_suppkey") == F.col("s_suppkey")).where("c_in or s_in")
    rows = rows.withColumn("line", F.col("l_orderkey") * 8 + F.col("l_linenumber"))
    arc = lambda n, a, b: F.struct(F.lit(n).cast("bigint").alias("edge_id"), a.alias("src"), b.alias("dst"))
    line, order, customer, supplier = tuple_id(LINEITEM, "line"), tuple_id(ORDERS, "l_orderkey"), tuple_id(CUSTOMER, "o_custkey"), tuple_id(SUPPLIER, "l_suppkey")
    word = lambda k: F.lit(KEYWORD * KIND + k).cast("bigint")
    arcs = F.array(
        arc(0, line, order), arc(1, line, supplier), arc(2, order, customer), arc(3, customer, tuple_id(NATION, "c_nation")), arc(4, supplier, tuple_id(NATION, "s_nation")),
        arc(5, tuple_id(NATION, "c_nation"), tuple_id(REGION, "c_region")), arc(6, tuple_id(NATION, "s_nation"), tuple_id(REGION, "s_region")), arc(7, customer, word(0)),
        F.when(F.col("c_in"), arc(8, tuple_id(REGION, "c_region"), word(1))), F.when(F.col("s_in"), arc(9, tuple_id(REGION, "s_region"), word(1))),
    )
    # One nation or region on both sides is one tuple: of arcs with equal ends the first stays.
    distinct = F.filter(arcs, lambda x: x.isNotNull())
    distinct = F.filter(distinct, lambda x: ~F.exists(distinct, lambda y: (y["src"] == x["src"]) & (y["dst"] == x["dst"]) & (y["edge_id"] < x["edge_id"])))
    nested = rows.select(F.col("line").cast("bigint").alias("instance_id"), line.alias("root"), F.array_sort(distinct).alias("edges"))
    return nested, spark.createDataFrame([(segment, KEYWORD * KIND), (region, KEYWORD * KIND + 1)], "keyword string, vertex_id bigint")


def order_keyword_graphs(spark: SparkSession, sf_dir: str, brand: str, segment: str, priority: str) -> DataFrame:
    """Edges of one graph for each order whose tuples hold all three keywords: the order with its customer, its lines and their parts.

    graph_id is the order; keyword nodes are KEYWORD 0 to 2: the brand on parts, the segment on the customer, the priority on the
    order.  Edge 1 leads to the customer, 2 and 3 to segment and priority; a line n has 10 n to itself and 10 n + 1 to its part, and
    a part with the brand 10 n + 2, n being its first line.
    """
    customers = read(spark, sf_dir, "customer").where(F.col("c_mktsegment") == segment).select("c_custkey")
    orders = read(spark, sf_dir, "orders").where(F.col("o_orderpriority") == priority).select("o_orderkey", "o_custkey").join(customers, F.col("o_custkey") == F.col("c_custkey"), "left_semi")
    parts = read(spark, sf_dir, "part").select("p_partkey", (F.col("p_brand") == brand).alias("has_brand"))
    lines = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey").join(parts, F.col("l_partkey") == F.col("p_partkey")).join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    whole = lines.withColumn("holds", F.max("has_brand").over(Window.partitionBy("l_orderkey"))).where("holds").withColumn("first", F.min("l_linenumber").over(Window.partitionBy("l_orderkey", "l_partkey")))
    whole = whole.withColumn("line", F.col("l_orderkey") * 8 + F.col("l_linenumber"))
    word = lambda k: F.lit(KEYWORD * KIND + k).cast("bigint")
    order, customer, line, part = tuple_id(ORDERS, "l_orderkey"), tuple_id(CUSTOMER, "o_custkey"), tuple_id(LINEITEM, "line"), tuple_id(PART, "l_partkey")
    arc = lambda n, a, b: F.struct(n.cast("bigint").alias("edge_id"), a.alias("src"), b.alias("dst"))
    n = F.col("l_linenumber")
    arcs = F.array(arc(F.lit(1), order, customer), arc(F.lit(2), customer, word(1)), arc(F.lit(3), order, word(2)), arc(10 * n, order, line), arc(10 * n + 1, line, part), F.when(F.col("has_brand"), arc(10 * F.col("first") + 2, part, word(0))))
    out = whole.select(F.col("l_orderkey").cast("bigint").alias("graph_id"), F.explode(arcs).alias("e")).where("e is not null")
    return out.select("graph_id", "e.*").distinct()


def numbered(pairs: DataFrame) -> DataFrame:
    """Edges with ids by rank of their ends."""
    return ranked(pairs.select("src", "dst").distinct(), "edge_id", "src", "dst").select(*_edges(F.col("src"), F.col("dst"), F.col("edge_id")))


def region_graph(spark: SparkSession, sf_dir: str, trade: DataFrame) -> DataFrame:
    """The trade graph with an edge from each nation in it to its region, whose node carries the region's name: vertex -1 - region key, edge 1000 + nation key."""
    ends = trade.select(F.explode(F.array("src", "dst")).alias("v")).distinct()
    held = read(spark, sf_dir, "nation").join(ends, F.col("n_nationkey") == F.col("v")).select(*_edges(F.col("v"), -1 - F.col("n_regionkey"), 1000 + F.col("v")))
    return trade.unionByName(held)


def host_links(spark: SparkSession, sf_dir: str, top: int | None = None) -> DataFrame:
    """(host, target): distinct links from a page's host to an href, optionally only of the ``top`` targets with most hosts."""
    pages = read(spark, sf_dir, "pages").select(F.regexp_extract("url", r"^[a-z]+://([^/?#]+)", 1).alias("host"), F.explode(F.regexp_extract_all("html", F.lit(r'href="([^"]*)"'), F.lit(1))).alias("target")).distinct()
    if top is None:
        return pages
    best = pages.groupBy("target").agg(F.count("*").alias("hosts")).orderBy(F.desc("hosts"), "target").limit(top)
    return pages.join(F.broadcast(best.select("target")), "target", "left_semi")


def bipartite(pairs: DataFrame, left: str, right: str) -> tuple[DataFrame, DataFrame]:
    """(edges, names) of two kinds of labels: ids by rank of kind and label."""
    labels = pairs.select(F.lit(0).alias("side"), F.col(left).alias("label")).union(pairs.select(F.lit(1), F.col(right))).distinct()
    names = ranked(labels, "vertex_id", "side", "label")
    a, b = (names.where(F.col("side") == k).select(F.col("label").alias(c), F.col("vertex_id").alias(v)) for k, c, v in ((0, left, "src"), (1, right, "dst")))
    return numbered(pairs.join(a, left).join(b, right).select("src", "dst")), names


def intervals(spark: SparkSession, sf_dir: str, reach: int = 9) -> DataFrame:
    """The sizes of all parts; an edge where two differ by at most ``reach``: a unit interval graph, without claws.

    A band join: each size is put into the bucket of its value and meets its own and the next bucket only.
    """
    p = read(spark, sf_dir, "part").select(F.col("p_size").cast("bigint").alias("v")).where("v is not null").distinct()
    low = p.select(F.col("v").alias("a"), F.explode(F.array(F.floor(F.col("v") / (reach + 1)), F.floor(F.col("v") / (reach + 1)) + 1)).alias("bucket"))
    high = p.select(F.col("v").alias("b"), F.floor(F.col("v") / (reach + 1)).alias("bucket"))
    near = low.join(high, "bucket").where((F.abs(F.col("a") - F.col("b")) <= reach) & (F.col("a") != F.col("b"))).select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst"))
    return numbered(near)


def similarity(spark: SparkSession, sf_dir: str, k: int = 3, block: int = 2000) -> DataFrame:
    """Undirected edges to each vector's k nearest by cosine among all vectors, ties to smaller ids; vectors without a direction have none.

    Every block of vectors meets every other one: a task compares two blocks by one matrix product and keeps k for each row.
    """
    v = read(spark, sf_dir, "embeddings").where("vec_id is not null and embedding is not null").select(F.col("vec_id").cast("bigint").alias("vec_id"), F.col("embedding").cast("array<double>").alias("e"))
    blocks = max(1, -(-v.count() // block))
    dealt = v.withColumn("own", F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int"))
    every = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    left, right = dealt.withColumn("other", every), dealt.withColumnRenamed("own", "other").withColumn("own", every)

    def compare(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        out = []
        if len(a) and len(b):
            x, y = (np.array(f["e"].tolist(), dtype=float) for f in (a, b))
            x, y = (m / np.where(n := np.linalg.norm(m, axis=1, keepdims=True), n, np.nan) for m in (x, y))
            names = b["vec_id"].to_numpy()
            for who, row in zip(a["vec_id"], x @ y.T, strict=True):
                row = np.where((names == who) | np.isnan(row), -np.inf, row)
                near = [j for j in np.lexsort((names, -row))[:k] if row[j] > -np.inf]
                out += [(who, names[j], row[j]) for j in near]
        return pd.DataFrame(out, columns=["a", "b", "c"])

    found = left.groupBy("own", "other").cogroup(right.groupBy("own", "other")).applyInPandas(compare, "a bigint, b bigint, c double")
    near = found.withColumn("r", F.row_number().over(Window.partitionBy("a").orderBy(F.desc("c"), "b"))).where(F.col("r") <= k)
    return numbered(near.select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst")))


def conversation_chains(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Turn to next turn of each conversation; graph_id and the ids are the conversation's, vertices are turns."""
    after = F.lead("turn").over(Window.partitionBy("conv_id").orderBy("turn"))
    return read(spark, sf_dir, "conversations").withColumn("after", after).where("after is not null").select(*_edges(F.col("turn"), F.col("after"), F.col("turn"), F.col("conv_id")))


def document_facets(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """Languages and sources of good labelled documents, joined where some document has both."""
    good = read(spark, sf_dir, "labels").where("quality = 1").select("doc_id")
    pairs = read(spark, sf_dir, "documents").select("doc_id", "lang", "source").join(good, "doc_id", "left_semi").select("lang", "source").distinct()
    return bipartite(pairs, "lang", "source")


def customer_regions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hyperedges: for each customer (instance) the regions of the suppliers of each of the orders (hyperedge)."""
    suppliers = read(spark, sf_dir, "supplier").join(F.broadcast(read(spark, sf_dir, "nation").select("n_nationkey", "n_regionkey")), F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", "n_regionkey")
    lines = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey").join(suppliers, F.col("l_suppkey") == F.col("s_suppkey"))
    orders = read(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    seen = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).select("o_custkey", "l_orderkey", "n_regionkey").distinct()
    return seen.select(F.col("o_custkey").cast("bigint").alias("instance_id"), F.col("l_orderkey").cast("bigint").alias("hyperedge_id"), F.col("n_regionkey").cast("bigint").alias("element"))


def edge_hypergraph(edges: DataFrame) -> DataFrame:
    """Each edge as a hyperedge of its ends: its minimal transversals are the minimal vertex covers."""
    return edges.select(F.lit(0).cast("bigint").alias("instance_id"), F.col("edge_id").alias("hyperedge_id"), F.explode(F.array("src", "dst")).alias("element"))


def neighbourhood_hypergraph(edges: DataFrame) -> DataFrame:
    """Each vertex with its neighbours as a hyperedge: minimal transversals are the minimal dominating sets."""
    both = edges.select("src", "dst").union(edges.select("dst", "src"))
    every = both.union(both.select("src", "src")).distinct()
    return every.select(F.lit(0).cast("bigint").alias("instance_id"), F.col("src").alias("hyperedge_id"), F.col("dst").alias("element"))


def benchmark_tokens(spark: SparkSession, sf_dir: str, k: int = 3, texts: int = 4) -> DataFrame:
    """Hyperedges: the k rarest words of each benchmark text; ``texts`` items are an instance, and elements are ranks of words."""
    words = read(spark, sf_dir, "benchmark").select("item_id", F.explode(F.array_distinct(F.split(F.lower("text"), "[^a-z0-9]+"))).alias("word")).where("word <> ''")
    often = words.groupBy("word").agg(F.count("*").alias("n"))
    rare = words.join(often, "word").withColumn("r", F.row_number().over(Window.partitionBy("item_id").orderBy("n", "word"))).where(F.col("r") <= k)
    ids = ranked(rare.select("word").distinct(), "element", "word")
    return rare.join(ids, "word").select(F.floor(F.col("item_id") / texts).cast("bigint").alias("instance_id"), F.col("item_id").cast("bigint").alias("hyperedge_id"), "element")


def order_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The graph of all orders with the parts and suppliers of their lines: each line joins its order with its part and with its supplier."""
    lines = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey")
    order = tuple_id(ORDERS, "l_orderkey")
    ends = lines.select(order.alias("src"), tuple_id(PART, "l_partkey").alias("dst")).unionByName(lines.select(order.alias("src"), tuple_id(SUPPLIER, "l_suppkey").alias("dst")))
    return numbered(ends)


def co_occurrence(spark: SparkSession, sf_dir: str, k: int = 150) -> DataFrame:
    """The k pairs of brands that most often share an order: a denser graph for the bench."""
    lines = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").join(read(spark, sf_dir, "part").select("p_partkey", F.regexp_extract("p_brand", r"(\d+)$", 1).cast("bigint").alias("brand")), F.col("l_partkey") == F.col("p_partkey"))
    seen = lines.select("l_orderkey", "brand").distinct()
    pairs = seen.alias("x").join(seen.alias("y"), (F.col("x.l_orderkey") == F.col("y.l_orderkey")) & (F.col("x.brand") < F.col("y.brand"))).groupBy(F.col("x.brand").alias("src"), F.col("y.brand").alias("dst")).agg(F.count("*").alias("n"))
    return numbered(pairs.orderBy(F.desc("n"), "src", "dst").limit(k).select("src", "dst"))


def labelled_graph(edges: list[tuple[int, int, int]], spark: SparkSession) -> DataFrame:
    """Edges from a Python list, for hand-made graphs."""
    return spark.createDataFrame([(0, *e) for e in edges], T.StructType([T.StructField(c, T.LongType(), False) for c in ("graph_id", "edge_id", "src", "dst")]))
