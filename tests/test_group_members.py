"""Groups without members: no tree touches them."""

import duckdb
import pytest
from pyspark.sql import functions as F

from spanweave.kernels.solve import Options, solutions
from spanweave.operators import enumerate as enum
from spanweave.oracle import SQL
from spanweave.queries import QUERIES

#: Nation pairs by falling number of lineitems; the nation's number modulo 5 is its region.
LACKING = {"no third region": [(0, 5), (5, 3), (0, 3)], "none of the three": [(1, 6), (6, 4)], "all three": [(0, 5), (5, 3), (0, 2), (2, 3)]}


def test_a_group_without_members_has_no_tree():
    edges = [(0, 0, 1), (1, 1, 2)]
    for sets in ([[0], [], [2]], [[], [0]], [[], []]):
        assert list(solutions(edges, sets, None, Options(flavour="group"))) == []
    with pytest.raises(ValueError):
        list(solutions(edges, [], None, Options(flavour="group")))


def test_a_null_member_stands_for_none(spark):
    edges = spark.createDataFrame([(0, 0, 1, 2), (0, 1, 2, 3)], "graph_id bigint, edge_id bigint, src bigint, dst bigint")
    rows = [(0, 0, 1), (0, 1, None), (1, 0, 1), (1, 1, 3)]
    groups = spark.createDataFrame(rows, "instance_id bigint, set_id int, vertex_id bigint")
    instances = spark.createDataFrame([(0, 0), (1, 0)], "instance_id bigint, graph_id bigint")
    assert [(r["instance_id"], r["solution_key"]) for r in enum.group_steiner_trees(instances, groups, edges).collect()] == [(1, "0-1")]


@pytest.mark.parametrize("case", LACKING)
def test_regions_that_the_graph_lacks(spark, tmp_path, case):
    lines = [(c, s) for n, (c, s) in enumerate(reversed(LACKING[case]), 1) for _ in range(n)]
    tables = {
        "nation": ([(k, k % 5) for k in range(25)], "n_nationkey int, n_regionkey int"),
        "customer": ([(k, k) for k in range(25)], "c_custkey bigint, c_nationkey int"),
        "supplier": ([(k, k) for k in range(25)], "s_suppkey bigint, s_nationkey int"),
        "orders": ([(k, c) for k, (c, _) in enumerate(lines)], "o_orderkey bigint, o_custkey bigint"),
        "lineitem": ([(k, s) for k, (_, s) in enumerate(lines)], "l_orderkey bigint, l_suppkey bigint"),
    }
    con = duckdb.connect()
    for name, (rows, schema) in tables.items():
        spark.createDataFrame(rows, schema).coalesce(1).write.parquet(f"{tmp_path}/{name}.parquet")
        con.execute(f"CREATE VIEW {name} AS SELECT * FROM read_parquet('{tmp_path}/{name}.parquet/*.parquet')")
    got = QUERIES["group_trees_regions"](spark, str(tmp_path)).select("solution_key", F.col("n_edges")).collect()
    want = con.execute(SQL["group_trees_regions"]).fetchall()
    assert sorted(map(tuple, got)) == sorted(want) and bool(want) == (case == "all three")
