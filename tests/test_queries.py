"""Registered queries against DuckDB on the smallest tables."""

import math

import duckdb
import pytest

from seedspread.plans import graph_queries, relational
from seedspread.streaming import stream_queries

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
NAMES = ["sweep_best_geo", "push_aggr_geo", "walk_T5_geo", "heat_taylor_geo", "local_cluster_geo", "ncp_geo", "components_page_path", "join_left_missing", "asof_event_prev", "agg_cube", "stream_edges", "stream_degrees", "heat_walks_md5_geo", "sweep_udtf_geo"]


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return con


def tidy(rows):
    return sorted((tuple(round(float(x), 8) if isinstance(x, float) else x for x in r) for r in rows), key=str)


@pytest.mark.parametrize("name", NAMES)
def test_same_rows(spark, sf, duck, name):
    queries = graph_queries.QUERIES | relational.QUERIES | stream_queries.QUERIES
    oracles = graph_queries.ORACLES | relational.ORACLES | stream_queries.ORACLES
    mine = queries[name](spark, sf)
    columns = sorted(mine.columns)
    theirs = duck.sql(oracles[name])
    assert sorted(theirs.columns) == columns
    want = tidy(duck.sql(f"SELECT {', '.join(chr(34) + c + chr(34) for c in columns)} FROM ({oracles[name]})").fetchall())
    assert tidy(map(tuple, mine.select(*columns).collect())) == want


def test_stream_answers_every_customer_of_the_nation(spark):
    sf = "/root/testdata/sf0.01"
    asked = spark.read.parquet(f"{sf}/customer.parquet").filter("c_nationkey = 0").select("c_custkey")
    answered = stream_queries.QUERIES["stream_cluster_queries"](spark, sf)
    assert sorted(r[0] for r in answered.select("run_id").collect()) == sorted(r[0] for r in asked.collect())


def same_as_sql(duck, df, sql):
    columns = ", ".join(sorted(df.columns))
    assert tidy(map(tuple, df.selectExpr(*sorted(df.columns)).collect())) == tidy(duck.sql(f"SELECT {columns} FROM ({sql})").fetchall())


def test_lists_of_hubs_are_whole(spark, sf, duck, monkeypatch):
    from seedspread.operators import graph

    monkeypatch.setattr(graph, "CHUNK", 3)
    same_as_sql(duck, graph_queries.QUERIES["adjacency_geo"](spark, sf), graph_queries.ORACLES["adjacency_geo"])


def test_equal_balances_give_the_smallest_key(spark, tmp_path):
    rows = [(k, n, float(b)) for k, n, b in [(1, 0, 5), (2, 0, 5), (3, 0, 1), (4, 0, 1), (5, 1, 2), (6, 1, 2)]] + [(7, 0, None), (None, 1, 9.0), (8, 2, None)]
    frame = spark.createDataFrame(rows[::-1], "c_custkey long, c_nationkey int, c_acctbal double")
    frame.write.parquet(f"{tmp_path}/customer.parquet")
    got = {tuple(r) for r in relational.QUERIES["agg_min_by"](spark, str(tmp_path)).collect()}
    assert got == {(0, 3, 1), (1, 5, 5), (2, None, None)}


def test_dearer_parts_are_counted_without_pairs(spark, tmp_path):
    rows = [(k, "a" if k % 2 else "b", "t" if k % 3 else None, float(k % 7) if k % 5 else None) for k in range(200)]
    spark.createDataFrame(rows, "p_partkey long, p_brand string, p_type string, p_retailprice double").write.parquet(f"{tmp_path}/part.parquet")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW part AS SELECT * FROM '{tmp_path}/part.parquet/*.parquet'")
    mine = relational.QUERIES["join_theta_price"](spark, str(tmp_path))
    same_as_sql(con, mine, relational.ORACLES["join_theta_price"])
    joins = [x for x in mine._jdf.queryExecution().optimizedPlan().toString().split("\n") if "Join" in x]
    assert joins and not any("<" in x for x in joins)


def test_poisson_table_is_cumulative(spark, sf, duck, tmp_path):
    want = lambda k: round(math.fsum(math.exp(-5.0) * (5**j / math.factorial(j)) for j in range(k + 1)), 9)
    given = relational.QUERIES["math_poisson_cdf"](spark, sf)
    assert dict(map(tuple, given.collect())) == {k: want(k) for k in range(5)}
    same_as_sql(duck, given, relational.ORACLES["math_poisson_cdf"])
    keys = [7, 0, 2, 7, 4, 12, 30, 500, -1, None]
    spark.createDataFrame([(k,) for k in keys], "r_regionkey int").write.parquet(f"{tmp_path}/region.parquet")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW region AS SELECT * FROM '{tmp_path}/region.parquet/*.parquet'")
    mine = relational.QUERIES["math_poisson_cdf"](spark, str(tmp_path))
    assert dict(map(tuple, mine.collect())) == {k: None if k is None else want(k) for k in keys}
    same_as_sql(con, mine, relational.ORACLES["math_poisson_cdf"])


@pytest.fixture(scope="module")
def thinned(spark, sf, tmp_path_factory):
    """The smallest tables with rows left out, so that a query that ignores them shows."""
    path = tmp_path_factory.mktemp("thinned")
    for name, kept in {"lineitem": "l_orderkey % 6 <> 1 and (l_partkey % 6 <> 2 or l_suppkey % 5 <> 3)", "events": "user_id % 16 <> 5", "orders": "o_orderkey % 3 = 0", "customer": "c_custkey % 2 = 0"}.items():
        spark.read.parquet(f"{sf}/{name}.parquet").filter(kept).coalesce(1).write.parquet(f"{path}/{name}.parquet")
    con = duckdb.connect()
    for name in ("lineitem", "events", "orders", "customer"):
        con.execute(f"CREATE VIEW {name} AS SELECT * FROM '{path}/{name}.parquet/*.parquet'")
    return str(path), con


@pytest.mark.parametrize("name", ["gen_torus_degree", "heat_psi_table", "torus_edges_6", "toy_sweep_profile", "walk_lengths_clamped"])
def test_rows_follow_the_given_tables(spark, thinned, name):
    path, con = thinned
    same_as_sql(con, graph_queries.QUERIES[name](spark, path), graph_queries.ORACLES[name])


def test_id_local_joins_the_given_customers(spark, thinned):
    path, con = thinned
    row = graph_queries.QUERIES["id_local_graph"](spark, path).first()
    assert row["n"] == con.sql("SELECT count(*) FROM customer").fetchall()[0][0] and row["min_deg"] >= 1
    assert row["m"] <= 5 * row["n"]
