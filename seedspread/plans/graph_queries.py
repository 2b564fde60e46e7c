"""Registered queries of the graph engine and the SQL that states the same rows."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from seedspread.operators import diffusion as d
from seedspread.operators import kernels, measures, profile, sweep
from seedspread.operators.graph import Graph, graph_stats
from seedspread.runtime import materialize, table
from seedspread.sources import builders, generators

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}

# ---- SQL of the graphs ---------------------------------------------------------------------------------

PAIRS = {
    "geo": "SELECT c_custkey::BIGINT * 4 AS a, c_nationkey::BIGINT * 4 + 2 AS b FROM customer UNION ALL SELECT s_suppkey::BIGINT * 4 + 1, s_nationkey::BIGINT * 4 + 2 FROM supplier UNION ALL SELECT n_nationkey::BIGINT * 4 + 2, n_regionkey::BIGINT * 4 + 3 FROM nation",
    "cust_part": "SELECT o_custkey::BIGINT * 2 AS a, l_partkey::BIGINT * 2 + 1 AS b FROM lineitem JOIN orders ON l_orderkey = o_orderkey",
    "cust_supp": "SELECT o_custkey::BIGINT * 2 AS a, l_suppkey::BIGINT * 2 + 1 AS b FROM lineitem JOIN orders ON l_orderkey = o_orderkey",
    "part_supp": "SELECT l_partkey::BIGINT * 2 AS a, l_suppkey::BIGINT * 2 + 1 AS b FROM lineitem",
    "order_part": "SELECT l_orderkey::BIGINT * 2 AS a, l_partkey::BIGINT * 2 + 1 AS b FROM lineitem",
    "copart": "SELECT x.l_partkey::BIGINT AS a, y.l_partkey::BIGINT AS b FROM lineitem x JOIN lineitem y ON x.l_orderkey = y.l_orderkey AND x.l_partkey < y.l_partkey",
    "user_hour": "SELECT user_id::BIGINT * 2 AS a, (epoch_us(ts) // 3600000000) * 2 + 1 AS b FROM events",
    "user_key": "SELECT user_id::BIGINT * 2 AS a, json_extract_string(props, '$.k')::BIGINT * 2 + 1 AS b FROM events WHERE json_extract_string(props, '$.k') IS NOT NULL",
    "page_path": "SELECT page_id * 2 AS a, ('0x' || substr(md5(path), 1, 12))::BIGINT * 2 + 1 AS b FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS path FROM pages)",
    "doc_line": "SELECT x.doc_id AS a, y.doc_id AS b FROM ln x JOIN ln y ON x.line = y.line AND x.doc_id < y.doc_id",
}
LINES = "ln AS (SELECT DISTINCT doc_id, trim(line, ' ') AS line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(trim(line, ' ')) >= 20),"


def graph_sql(name: str) -> str:
    """CTEs e(src, dst), g(v, d) and tot(x) of a built graph."""
    lines = LINES if name == "doc_line" else ""
    return f"""{lines} pairs AS ({PAIRS[name]}), e AS (SELECT a AS src, b AS dst FROM pairs WHERE a <> b UNION SELECT b, a FROM pairs WHERE a <> b),
g AS (SELECT src AS v, count(*) AS d FROM e GROUP BY src), tot AS (SELECT count(*) AS x FROM e)"""


def walk_sql(seeds: list[int], steps: int, eps: float) -> str:
    """CTE wv(run_id, v, p): the vector that the truncated walk returns."""
    start = ", ".join(f"({k}, 0, {v}, 1.0::DOUBLE)" for k, v in enumerate(seeds))
    on = f"(w.k = 0 OR w.p >= {eps!r} * g.d)"
    return f"""w(run_id, k, v, p) AS (SELECT * FROM (VALUES {start}) AS s(run_id, k, v, p) UNION ALL
 SELECT run_id, k + 1, v, sum(m) FROM (
  SELECT w.run_id, w.k, w.v, w.p / 2 AS m FROM w JOIN g ON g.v = w.v WHERE w.k < {steps} AND {on}
  UNION ALL SELECT w.run_id, w.k, e.dst, w.p / 2 / g.d FROM w JOIN g ON g.v = w.v JOIN e ON e.src = w.v WHERE w.k < {steps} AND {on}) GROUP BY run_id, k, v),
wk AS (SELECT run_id, max(k) AS k FROM w JOIN g ON g.v = w.v WHERE w.k = 0 OR w.p >= {eps!r} * g.d GROUP BY run_id),
wv AS (SELECT w.run_id, w.v, w.p FROM w JOIN wk ON wk.run_id = w.run_id AND wk.k = w.k WHERE w.p > 0)"""


def push_sql(seeds: dict[int, list[int]], alpha: float, eps: float, rule: str, rounds: int, beta: float = 1.0) -> str:
    """CTEs s(run_id, k, v, p, r) for all rounds and pv(run_id, v, p) after the last; idle rounds change nothing."""
    gain, send, stay = kernels.coefficients(rule, alpha)
    start = ", ".join(f"({run}, 0, {v}, 0.0::DOUBLE, {1.0 / len(vs)!r}::DOUBLE)" for run, vs in seeds.items() for v in vs)
    over = f"((s.r >= {eps!r} * g.d AND s.r > 0) OR s.k = 0)"
    if beta < 1:
        rank = f"row_number() OVER (PARTITION BY s.run_id, {over} ORDER BY round(s.r / g.d, 12) DESC, s.v) <= ceil({beta!r} * count(*) OVER (PARTITION BY s.run_id, {over}))"
        over = f"({over} AND {rank})"
    flagged = f"SELECT s.run_id, s.k, s.v, s.p, s.r, g.d, {over} AS on_ FROM s JOIN g ON g.v = s.v WHERE s.k < {rounds}"
    return f"""s(run_id, k, v, p, r) AS (SELECT * FROM (VALUES {start}) AS t(run_id, k, v, p, r) UNION ALL
 SELECT run_id, k + 1, v, sum(p), sum(r) FROM (
  SELECT run_id, k, v, CASE WHEN on_ THEN p + {gain!r} * r ELSE p END AS p, CASE WHEN on_ THEN {stay!r} * r ELSE r END AS r FROM ({flagged})
  UNION ALL SELECT f.run_id, f.k, e.dst, 0.0, {send!r} * f.r / f.d FROM ({flagged}) f JOIN e ON e.src = f.v WHERE f.on_) GROUP BY run_id, k, v),
pv AS (SELECT run_id, v, p FROM s WHERE k = {rounds} AND p > 0)"""


def heat_sql(seeds: list[int], t: float, degree: int, eps: float, threshold: str = "scaled", last_level: str = "bare") -> str:
    """CTE hv(run_id, v, p): e^t times the kernel."""
    weights = kernels.psi(degree, t)
    floors = ", ".join(f"({j}, {(kernels.level_floor(j, t, degree, eps, threshold, weights) if j else 0.0)!r}::DOUBLE)" for j in range(degree))
    start = ", ".join(f"({k}, 0, {v}, 1.0::DOUBLE)" for k, v in enumerate(seeds))
    return f"""fl(j, f) AS (VALUES {floors}),
h(run_id, j, v, r) AS (SELECT * FROM (VALUES {start}) AS s(run_id, j, v, r) UNION ALL
 SELECT h.run_id, h.j + 1, e.dst, sum({t!r}::DOUBLE * h.r / ((h.j + 1) * g.d)) FROM h JOIN g ON g.v = h.v JOIN fl ON fl.j = h.j JOIN e ON e.src = h.v
 WHERE h.j + 1 < {degree} AND (h.j = 0 OR h.r >= fl.f * g.d) GROUP BY h.run_id, h.j, e.dst),
on_ AS (SELECT h.*, g.d FROM h JOIN g ON g.v = h.v JOIN fl ON fl.j = h.j WHERE h.j = 0 OR h.r >= fl.f * g.d),
hv AS (SELECT run_id, v, sum(p) AS p FROM (SELECT run_id, v, r AS p FROM on_ UNION ALL SELECT run_id, e.dst, {kernels.last_share(t, degree, last_level)!r}::DOUBLE * r / d FROM on_ JOIN e ON e.src = on_.v WHERE j = {degree - 1}) GROUP BY run_id, v)"""


def sweep_sql(vector: str) -> str:
    """CTE sp(run_id, rank, v, vol, cut, phi) of a vector CTE."""
    return f"""rk AS (SELECT x.run_id, x.v, g.d, row_number() OVER (PARTITION BY x.run_id ORDER BY round(x.p / g.d, 12) DESC, x.v) AS rank FROM {vector} x JOIN g ON g.v = x.v WHERE x.p > 0),
ea AS (SELECT a.run_id, a.v, count(*) AS n FROM rk a JOIN e ON e.src = a.v JOIN rk b ON b.run_id = a.run_id AND b.v = e.dst AND b.rank < a.rank GROUP BY a.run_id, a.v),
sc AS (SELECT rk.run_id, rk.rank, rk.v, sum(rk.d) OVER o AS vol, sum(rk.d - 2 * coalesce(ea.n, 0)) OVER o AS cut FROM rk LEFT JOIN ea ON ea.run_id = rk.run_id AND ea.v = rk.v WINDOW o AS (PARTITION BY rk.run_id ORDER BY rk.rank)),
sp AS (SELECT run_id, rank, v, vol, cut, CASE WHEN least(vol, x - vol) > 0 THEN cut / least(vol, x - vol) END AS phi FROM sc, tot)"""


BEST_SQL = "bp AS (SELECT run_id, rank AS size, vol, cut, phi FROM (SELECT *, row_number() OVER (PARTITION BY run_id ORDER BY phi, rank) AS o FROM sp WHERE phi IS NOT NULL) WHERE o = 1)"
PROFILE_OUT = "run_id::BIGINT AS run_id, rank::BIGINT AS rank, v::BIGINT AS v, vol::BIGINT AS vol, cut::BIGINT AS cut, round(phi, 9) AS phi"
BEST_OUT = "run_id::BIGINT AS run_id, size::BIGINT AS size, vol::BIGINT AS vol, cut::BIGINT AS cut, round(phi, 9) AS phi"


def full_sql(graph: str, *ctes: str, select: str) -> str:
    return f"WITH RECURSIVE {', '.join([graph_sql(graph), *ctes])} {select}"


def vector_out(df: DataFrame) -> DataFrame:
    return df.select("run_id", "v", F.round("p", 9).alias("p"))


def profile_out(df: DataFrame) -> DataFrame:
    return df.select("run_id", "rank", "v", "vol", "cut", F.round("phi", 9).alias("phi"))


def best_out(df: DataFrame) -> DataFrame:
    return df.select("run_id", "size", "vol", "cut", F.round("phi", 9).alias("phi"))


VECTOR_OUT = "run_id::BIGINT AS run_id, v::BIGINT AS v, round(p, 9) AS p"


def register(name: str, sql: str | None = None):
    def add(query):
        QUERIES[name] = query
        if sql is not None:
            ORACLES[name] = sql
        return query
    return add


def seeds(spark: SparkSession, *vertices: int) -> DataFrame:
    return d.seeds_frame(spark, list(vertices))


# ---- construction --------------------------------------------------------------------------------------

STAT_GRAPHS = ["geo", "cust_part", "part_supp", "cust_supp", "order_part", "copart", "user_hour", "user_key", "page_path"]


@register("graph_stats_all", "\nUNION ALL\n".join(
    f"SELECT * FROM (WITH {graph_sql(n)} SELECT '{n}' AS graph, count(*)::BIGINT AS n, (sum(d) / 2)::BIGINT AS m, min(d)::BIGINT AS min_deg, max(d)::BIGINT AS max_deg, round(avg(d), 6) AS mean_deg FROM g)" for n in STAT_GRAPHS))
def graph_stats_all(spark, sf):
    out = None
    for n in STAT_GRAPHS:
        one = graph_stats(builders.BUILDERS[n](spark, sf)).select(F.lit(n).alias("graph"), "*")
        out = one if out is None else out.union(one)
    return out


def _edges(name):
    def query(spark, sf):
        return builders.BUILDERS[name](spark, sf).edges
    register(f"{name}_edges", f"WITH {graph_sql(name)} SELECT src::BIGINT AS src, dst::BIGINT AS dst FROM e")(query)


for _name in PAIRS:
    if _name != "doc_line":
        _edges(_name)


@register("doc_line_edges", f"""WITH RECURSIVE {LINES}
hub AS (SELECT line, min(doc_id) AS h FROM ln GROUP BY line), arm AS (SELECT DISTINCT doc_id, h FROM ln JOIN hub USING (line) WHERE doc_id <> h),
star AS (SELECT doc_id AS a, h AS b FROM arm UNION SELECT h, doc_id FROM arm),
low(v, c) USING KEY (v) AS (SELECT DISTINCT doc_id, doc_id FROM documents WHERE doc_id IS NOT NULL UNION
 SELECT star.a, min(low.c) FROM low JOIN star ON star.b = low.v JOIN recurring.low AS now ON now.v = star.a WHERE low.c < now.c GROUP BY star.a),
n AS (SELECT x.doc_id, count(DISTINCT y.doc_id) - 1 AS n FROM ln x JOIN ln y ON x.line = y.line GROUP BY x.doc_id)
SELECT v::BIGINT AS doc_id, coalesce(n, 0)::BIGINT AS n_links, c::BIGINT AS component_id FROM low LEFT JOIN n ON n.doc_id = low.v""")
def doc_line_edges(spark, sf):
    """One row per document with its number of links and its class; the links of hot lines are counted, not listed."""
    return builders.doc_line_links(spark, sf)


def _degrees(name):
    def query(spark, sf):
        return builders.BUILDERS[name](spark, sf).degrees.groupBy("deg").agg(F.count("*").alias("vertices"))
    register(f"degree_hist_{name}", f"WITH {graph_sql(name)} SELECT d::BIGINT AS deg, count(*)::BIGINT AS vertices FROM g GROUP BY d")(query)


for _name in ("geo", "order_part"):
    _degrees(_name)


@register("adjacency_geo", f"WITH {graph_sql('geo')} SELECT e.src::BIGINT AS v, g.d::BIGINT AS deg, string_agg(e.dst::VARCHAR, ',' ORDER BY e.dst) AS nbrs FROM e JOIN g ON g.v = e.src GROUP BY ALL")
def adjacency_geo(spark, sf):
    """One row per vertex: the chunks of a hub's list are put together again."""
    pieces = builders.geo(spark, sf).adjacency.groupBy("v", "deg").agg(F.flatten(F.collect_list(F.col("nbrs.v"))).alias("l"))
    return pieces.select("v", "deg", F.array_join(F.array_sort("l").cast("array<string>"), ",").alias("nbrs"))


@register("relabel_geo", f"WITH {graph_sql('geo')} SELECT v::BIGINT AS v, row_number() OVER (ORDER BY v) - 1 AS id FROM g")
def relabel_geo(spark, sf):
    from seedspread.operators.graph import relabel

    return relabel(builders.geo(spark, sf).degrees.select("v"), "v")


def cells_sql(k: int) -> str:
    """CTE c(i): cells of the wrap-around grid in which line items stand."""
    return f"c AS (SELECT DISTINCT l_orderkey % {k} + l_partkey % {k} * {k} + l_suppkey % {k} * {k * k} AS i FROM lineitem WHERE l_orderkey + l_partkey + l_suppkey IS NOT NULL)"


def cells(spark: SparkSession, sf: str, k: int) -> DataFrame:
    return generators.grid_cells(table(spark, sf, "lineitem"), k, "l_orderkey", "l_partkey", "l_suppkey")


def torus_sql(k: int) -> str:
    """CTEs c(i) and e(src, dst): both directions between neighbouring cells that are both in c."""
    return f"""{cells_sql(k)}, v AS (SELECT i, i % {k} AS x, (i // {k}) % {k} AS y, i // {k * k} AS z FROM c),
a AS (SELECT i, unnest([(x + 1) % {k} + y * {k} + z * {k * k}, x + ((y + 1) % {k}) * {k} + z * {k * k}, x + y * {k} + ((z + 1) % {k}) * {k * k}]) AS j FROM v),
b AS (SELECT i, j FROM a WHERE j IN (SELECT i FROM c)), e AS (SELECT i AS src, j AS dst FROM b UNION SELECT j, i FROM b)"""


@register("torus_edges_6", f"WITH {torus_sql(6)} SELECT src, dst FROM e")
def torus_edges_6(spark, sf):
    return generators.torus3d(spark, 6, cells(spark, sf, 6)).edges


@register("id_local_graph")
def id_local_graph(spark, sf):
    """Customers in key order, each joined to others at drawn distances in that order."""
    from seedspread.operators.graph import relabel

    customers = materialize(relabel(table(spark, sf, "customer"), "c_custkey").select("id"), "customers")
    return graph_stats(generators.id_local(spark, customers.count(), vertices=customers))


@register("knn_edges_embeddings", """WITH c AS (SELECT a.vec_id AS s, b.vec_id AS t, round(list_dot_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[]) / sqrt(list_dot_product(a.embedding::DOUBLE[], a.embedding::DOUBLE[])) / sqrt(list_dot_product(b.embedding::DOUBLE[], b.embedding::DOUBLE[])), 9) AS c FROM embeddings a, embeddings b WHERE a.vec_id <> b.vec_id),
k AS (SELECT s, t FROM (SELECT *, row_number() OVER (PARTITION BY s ORDER BY c DESC, t) AS o FROM c) WHERE o <= 10) SELECT s AS src, t AS dst FROM k UNION SELECT t, s FROM k""")
def knn_edges_embeddings(spark, sf):
    return builders.emb_knn(spark, sf).edges


# ---- sweep ---------------------------------------------------------------------------------------------

VECTOR_SQL = "vec AS (SELECT 0 AS run_id, v, d * (1 + v % 13) / 100.0::DOUBLE AS p FROM g WHERE v % 5 < 3)"


def given_vector(graph: Graph) -> DataFrame:
    return graph.degrees.filter("v % 5 < 3").select(F.lit(0).cast("long").alias("run_id"), "v", (F.col("deg") * (1 + F.col("v") % 13) / F.lit(100.0)).alias("p"))


def _sweep(name, run):
    def query(spark, sf):
        g = builders.geo(spark, sf)
        return profile_out(run(g, given_vector(g)))
    register(name, full_sql("geo", VECTOR_SQL, sweep_sql("vec"), select=f"SELECT {PROFILE_OUT} FROM sp"))(query)


@register("toy_sweep_profile", full_sql("user_hour", VECTOR_SQL, sweep_sql("vec"), select=f"SELECT {PROFILE_OUT} FROM sp"))
def toy_sweep_profile(spark, sf):
    """The profile of a given vector on users and hours; the worked example itself is in the tests."""
    g = builders.user_hour(spark, sf)
    return profile_out(sweep.sweep_profile(g, given_vector(g)))


_sweep("sweep_profile_geo", lambda g, p: sweep.sweep_profile(g, p))
_sweep("sweep_pairs_geo", lambda g, p: sweep.sweep_profile(g, p, "pairs"))
_sweep("sweep_large_geo", lambda g, p: sweep.sweep_profile(g, p, large=True).withColumn("run_id", F.lit(0).cast("long")))
_sweep("sweep_naive_geo", lambda g, p: sweep.sweep_cut_naive(g, p))
_sweep("seq_sweep_geo", lambda g, p: sweep.sweep_cut_sequential(g, p))


@register("sweep_best_geo", full_sql("geo", VECTOR_SQL, sweep_sql("vec"), BEST_SQL, select=f"SELECT {BEST_OUT} FROM bp"))
def sweep_best_geo(spark, sf):
    g = builders.geo(spark, sf)
    return best_out(sweep.sweep_cut(g, given_vector(g)).summary())


STARS_SQL = "st AS (SELECT v AS set_id, v FROM g WHERE v % 4 = 2 UNION SELECT e.dst, e.src FROM e WHERE e.dst % 4 = 2 AND e.src % 4 < 2)"


def nation_stars(graph: Graph) -> DataFrame:
    """Every nation with its customers and suppliers."""
    own = graph.degrees.filter("v % 4 = 2").select(F.col("v").alias("set_id"), "v")
    return own.union(graph.edges.filter("dst % 4 = 2 and src % 4 < 2").select(F.col("dst").alias("set_id"), F.col("src").alias("v")))


SETS_SQL = """z AS (SELECT st.set_id, count(*) AS size, sum(g.d) AS vol FROM st JOIN g ON g.v = st.v GROUP BY 1),
c AS (SELECT st.set_id, count(*) AS cut FROM st JOIN e ON e.src = st.v WHERE NOT EXISTS (SELECT 1 FROM st o WHERE o.set_id = st.set_id AND o.v = e.dst) GROUP BY 1)"""


@register("conductance_nation_stars", full_sql("geo", STARS_SQL, SETS_SQL, select="SELECT z.set_id::BIGINT AS set_id, size::BIGINT AS size, vol::BIGINT AS vol, coalesce(cut, 0)::BIGINT AS cut, round(coalesce(cut, 0) / least(vol, x - vol), 9) AS phi FROM z LEFT JOIN c USING (set_id), tot"))
def conductance_nation_stars(spark, sf):
    g = builders.geo(spark, sf)
    return measures.conductance(g, nation_stars(g)).withColumn("phi", F.round("phi", 9))


@register("volume_boundary_sets", full_sql("geo", STARS_SQL, SETS_SQL, select="SELECT z.set_id::BIGINT AS set_id, size::BIGINT AS size, vol::BIGINT AS vol, cut::BIGINT AS cut FROM z JOIN c USING (set_id)"))
def volume_boundary_sets(spark, sf):
    g = builders.geo(spark, sf)
    sets = nation_stars(g)
    return measures.volume(g, sets).join(measures.boundary(g, sets), "set_id")


# ---- truncated walk ------------------------------------------------------------------------------------

HOUR_SEED_SQL = "(SELECT min(v) FROM g WHERE v % 2 = 1)"


def _walk(name, run, steps, eps, vertices=(0,)):
    def query(spark, sf):
        return vector_out(run(builders.geo(spark, sf), seeds(spark, *vertices)).p)
    register(name, full_sql("geo", walk_sql(list(vertices), steps, eps), select=f"SELECT {VECTOR_OUT} FROM wv"))(query)


_walk("walk_T5_geo", lambda g, s: d.truncated_walk(g, s, 5, 1e-5), 5, 1e-5)
_walk("walk_frames_geo", lambda g, s: d.truncated_walk(g, s, 5, 1e-5, mode="frames"), 5, 1e-5)
_walk("walk_T20_geo", lambda g, s: d.truncated_walk(g, s, 20, 1e-4), 20, 1e-4, (0, 4, 8))
_walk("walk_early_end_geo", lambda g, s: d.truncated_walk(g, s, 20, 0.004), 20, 0.004, (0, 4))
_walk("walk_exact_T5", lambda g, s: d.lazy_walk_exact(g, s, 5), 5, 0.0)
_walk("seq_walk_T5_geo", lambda g, s: d.truncated_walk_sequential(g, s, 5, 1e-5), 5, 1e-5)


@register("walk_truncated_output_geo", full_sql("geo", walk_sql([0], 10, 1e-4), select=f"SELECT {VECTOR_OUT} FROM wv JOIN g USING (v) WHERE p >= 1e-4 * d"))
def walk_truncated_output_geo(spark, sf):
    return vector_out(d.truncated_walk(builders.geo(spark, sf), seeds(spark, 0), 10, 1e-4, truncate_output=True).p)


@register("walk_T10_user_hour", full_sql("user_hour", walk_sql([0], 10, 1e-5).replace("(0, 0, 0, 1.0::DOUBLE)", f"(0, 0, {HOUR_SEED_SQL}, 1.0::DOUBLE)"), select=f"SELECT {VECTOR_OUT} FROM wv"))
def walk_T10_user_hour(spark, sf):  # noqa: N802
    g = builders.user_hour(spark, sf)
    first = g.degrees.filter("v % 2 = 1").agg(F.min("v")).first()[0]
    return vector_out(d.truncated_walk(g, seeds(spark, first), 10, 1e-5).p)


@register("walk_target_phi_geo")
def walk_target_phi_geo(spark, sf):
    out = d.truncated_walk(builders.geo(spark, sf), seeds(spark, 0, 4), 8, 1e-5, target_phi=0.01)
    return out.p.select("run_id", "v", F.round("p", 9).alias("p"), F.round("reached", 9).alias("reached"))


# ---- residual push -------------------------------------------------------------------------------------


def _push(name, run, alpha, eps, rule, rounds, start=None, beta=1.0):
    start = start or {0: [0]}
    def query(spark, sf):
        return vector_out(run(builders.geo(spark, sf), d.seeds_frame(spark, start)).p)
    register(name, full_sql("geo", push_sql(start, alpha, eps, rule, rounds, beta), select=f"SELECT {VECTOR_OUT} FROM pv"))(query)


_push("push_lazy_geo", lambda g, s: d.residual_push(g, s, 0.05, 1e-4, "lazy"), 0.05, 1e-4, "lazy", 100)
_push("push_aggr_geo", lambda g, s: d.residual_push(g, s, 0.05, 1e-4), 0.05, 1e-4, "aggressive", 60)
_push("push_frames_geo", lambda g, s: d.residual_push(g, s, 0.05, 1e-4, mode="frames", chain=4), 0.05, 1e-4, "aggressive", 60)
_push("push_beta_geo", lambda g, s: d.residual_push(g, s, 0.05, 1e-4, beta=0.25, max_rounds=40), 0.05, 1e-4, "aggressive", 40, beta=0.25)
_push("push_multi_seed", lambda g, s: d.residual_push(g, s, 0.1, 1e-4), 0.1, 1e-4, "aggressive", 60, {0: [0, 4, 8], 1: [12], 2: [2, 6]})
_push("push_dense_geo", lambda g, s: d.residual_push_dense(g, s, 0.05, 1e-3), 0.05, 1e-3, "aggressive", 40)


@register("push_round_stats_geo", full_sql("geo", push_sql({0: [0]}, 0.05, 1e-4, "aggressive", 60), select="""SELECT s.k::INTEGER AS round, count(*)::BIGINT AS frontier, sum(g.d)::BIGINT AS edges,
 round((SELECT sum(p) FROM s n WHERE n.k = s.k + 1), 9) AS mass_p, round((SELECT sum(r) FROM s n WHERE n.k = s.k + 1), 9) AS mass_r
 FROM s JOIN g ON g.v = s.v WHERE s.k < 60 AND ((s.r >= 1e-4 * g.d AND s.r > 0) OR s.k = 0) GROUP BY s.k"""))
def push_round_stats_geo(spark, sf):
    out = d.residual_push(builders.geo(spark, sf), seeds(spark, 0), 0.05, 1e-4)
    return out.stats.select("round", "frontier", "edges", F.round("mass_p", 9).alias("mass_p"), F.round("mass_r", 9).alias("mass_r"))


@register("push_aggr_page_path", full_sql("page_path", push_sql({0: [0]}, 0.05, 1e-4, "aggressive", 100).replace("(0, 0, 0, 0.0::DOUBLE", "(0, 0, (SELECT min(v) FROM g WHERE v % 2 = 0), 0.0::DOUBLE"), select=f"SELECT {VECTOR_OUT} FROM pv"))
def push_aggr_page_path(spark, sf):
    g = builders.page_path(spark, sf)
    first = g.degrees.filter("v % 2 = 0").agg(F.min("v")).first()[0]
    return vector_out(d.residual_push(g, seeds(spark, first), 0.05, 1e-4).p)


for _name, _run in {
    "seq_push_aggr_geo": lambda g, s: d.residual_push_fifo(g, s, 0.05, 1e-4), "seq_push_lazy_geo": lambda g, s: d.residual_push_fifo(g, s, 0.05, 1e-4, "lazy"),
    "seq_push_priority_geo": lambda g, s: d.residual_push_priority(g, s, 0.05, 1e-4), "push_blocks_geo": lambda g, s: d.residual_push(g, s, 0.05, 1e-4, blocks=4),
}.items():
    register(_name)(lambda spark, sf, run=_run: vector_out(run(builders.geo(spark, sf), seeds(spark, 0)).p))


@register("push_inflation_geo")
def push_inflation_geo(spark, sf):
    g, s = builders.geo(spark, sf), seeds(spark, 0)
    return measures.push_inflation(d.residual_push(g, s, 0.05, 1e-4).stats, d.residual_push_fifo(g, s, 0.05, 1e-4).stats)


@register("pagerank_exact_geo", full_sql("geo", push_sql({0: [0]}, 0.2, 0.0, "aggressive", 100), select="SELECT run_id::BIGINT AS run_id, v::BIGINT AS v, round(p, 6) AS p FROM pv WHERE round(p, 6) > 0"))
def pagerank_exact_geo(spark, sf):
    out = d.pagerank_exact(builders.geo(spark, sf), seeds(spark, 0), 0.2, 1e-13)
    return out.p.select("run_id", "v", F.round("p", 6).alias("p")).filter("p > 0")


@register("push_mass_geo", full_sql("geo", push_sql({0: [0]}, 0.05, 1e-4, "aggressive", 60), select="SELECT 0::BIGINT AS run_id, round(sum(p) + sum(r), 9) AS mass, max(r / d) < 1e-4 AS settled FROM s JOIN g ON g.v = s.v WHERE k = 60"))
def push_mass_geo(spark, sf):
    out = d.residual_push(builders.geo(spark, sf), seeds(spark, 0), 0.05, 1e-4)
    both = out.p.select("run_id", "p").union(out.r.select("run_id", "r")).groupBy("run_id").agg(F.round(F.sum("p"), 9).alias("mass"))
    return both.join(measures.residual_peak(out.r), "run_id").select("run_id", "mass", (F.col("peak") < 1e-4).alias("settled"))


# ---- heat kernel ---------------------------------------------------------------------------------------


def _heat(name, run, t, degree, eps, threshold="scaled", last_level="bare", vertices=(0,)):
    def query(spark, sf):
        return vector_out(run(builders.geo(spark, sf), seeds(spark, *vertices)).p)
    register(name, full_sql("geo", heat_sql(list(vertices), t, degree, eps, threshold, last_level), select=f"SELECT {VECTOR_OUT} FROM hv"))(query)


_heat("heat_taylor_geo", lambda g, s: d.heat_taylor(g, s, 5, 15, 1e-4), 5, 15, 1e-4, vertices=(0, 4))
_heat("heat_frames_geo", lambda g, s: d.heat_taylor(g, s, 5, 5, 1e-3, mode="frames"), 5, 5, 1e-3)
_heat("heat_taylor_strict", lambda g, s: d.heat_taylor(g, s, 5, 15, 1e-3, threshold="strict"), 5, 15, 1e-3, "strict")
_heat("heat_taylor_last_level", lambda g, s: d.heat_taylor(g, s, 5, 15, 1e-4, last_level="taylor"), 5, 15, 1e-4, last_level="taylor")
_heat("seq_heat_taylor_geo", lambda g, s: d.heat_taylor_queue(g, s, 5, 15, 1e-4), 5, 15, 1e-4)
_heat("heat_exact_geo", lambda g, s: d.heat_exact(g, s, 3, 12), 3, 12, 0.0, last_level="taylor")


@register("heat_taylor_user_hour", full_sql("user_hour", heat_sql([0], 5, 15, 1e-3).replace("(0, 0, 0, 1.0::DOUBLE)", f"(0, 0, {HOUR_SEED_SQL}, 1.0::DOUBLE)"), select=f"SELECT {VECTOR_OUT} FROM hv"))
def heat_taylor_user_hour(spark, sf):
    g = builders.user_hour(spark, sf)
    first = g.degrees.filter("v % 2 = 1").agg(F.min("v")).first()[0]
    return vector_out(d.heat_taylor(g, seeds(spark, first), 5, 15, 1e-3).p)


@register("heat_psi_table", "SELECT k::INTEGER AS k, round((SELECT sum(factorial(k::INTEGER) / factorial((m + k)::INTEGER) * pow(5.0, m)) FROM range(0, 16 - k) AS x(m)), 9) AS psi FROM (SELECT DISTINCT user_id % 16 AS k FROM events WHERE user_id IS NOT NULL) AS t(k)")
def heat_psi_table(spark, sf):
    """Tail weights of the levels that users are dealt to by their ids."""
    from seedspread.functions.sql import psi

    levels = table(spark, sf, "events").select((F.col("user_id") % 16).cast("int").alias("k")).filter("k is not null").distinct()
    return levels.select("k", F.round(psi(F.col("k"), 15, 5.0), 9).alias("psi"))


def _draw_sql(what: str) -> str:
    return f"('0x' || substr(md5('7:0:' || walk_id || ':' || {what}), 1, 8))::BIGINT / 4294967296.0::DOUBLE"


def lengths_sql(t: float, longest: int, walks: str) -> str:
    cdf = kernels.length_cdf(t, longest)
    index = " + ".join(f"CASE WHEN u >= {c!r}::DOUBLE THEN 1 ELSE 0 END" for c in cdf[:-1])
    return f"wl AS (SELECT walk_id, {index} AS remaining FROM (SELECT walk_id, {_draw_sql(chr(39) + 'length' + chr(39))} AS u FROM {walks} AS r(walk_id)))"


@register("walk_lengths_clamped", f"WITH {lengths_sql(5.0, 10, '(SELECT o_orderkey FROM orders)')} SELECT remaining::INTEGER AS remaining, count(*)::BIGINT AS walks FROM wl GROUP BY remaining")
def walk_lengths_clamped(spark, sf):
    """One walk for every order."""
    walks = table(spark, sf, "orders").select(F.col("o_orderkey").alias("walk_id"))
    return d.walk_lengths(spark, seeds(spark, 0), walks, 5.0, 10, 7, rng="md5").groupBy("remaining").agg(F.count("*").alias("walks"))


def ends_sql(n: int, longest: int) -> str:
    return f"""{lengths_sql(5.0, longest, f"range({n})")}, nb AS (SELECT src, list(dst ORDER BY dst) AS l FROM e GROUP BY src),
wk(walk_id, k, remaining, spot) AS (SELECT walk_id, 0, remaining, 0::BIGINT FROM wl UNION ALL
 SELECT walk_id, k + 1, remaining - 1, l[1 + floor({_draw_sql("'step' || k")} * len(l))::INTEGER] FROM wk JOIN nb ON nb.src = wk.spot WHERE remaining > 0),
ends AS (SELECT walk_id, spot FROM wk WHERE remaining = 0)"""


@register("heat_walks_md5_geo", full_sql("geo", ends_sql(1000, 6), select="SELECT 0::BIGINT AS run_id, spot::BIGINT AS v, round(count(*) / 1000.0::DOUBLE, 9) AS p FROM ends GROUP BY spot"))
def heat_walks_md5_geo(spark, sf):
    return vector_out(d.heat_walks(builders.geo(spark, sf), seeds(spark, 0), 5.0, 6, 1000, seed=7, rng="md5").p)


COUNT_SQL = "SELECT 0::BIGINT AS run_id, l_suppkey::BIGINT AS at, count(*)::BIGINT AS walks FROM lineitem GROUP BY l_suppkey"


def _ends(spark, sf):
    rows = table(spark, sf, "lineitem")
    return rows.select(F.lit(0).cast("long").alias("run_id"), F.concat_ws("-", "l_orderkey", "l_linenumber").alias("walk_id") if "l_linenumber" in rows.columns else F.col("l_orderkey").alias("walk_id"), F.col("l_suppkey").cast("long").alias("at"))


register("walk_counts_hash", COUNT_SQL)(lambda spark, sf: d.count_ends_hash(_ends(spark, sf)))
register("walk_counts_sort", COUNT_SQL)(lambda spark, sf: d.count_ends_sort(_ends(spark, sf)))
register("heat_walks_sorted_geo")(lambda spark, sf: vector_out(d.heat_walks(builders.geo(spark, sf), seeds(spark, 0), 5.0, 6, 1000, aggregate="sort", overflow="renormalize").p))
register("heat_walks_grouped_geo")(lambda spark, sf: vector_out(d.heat_walks_grouped(builders.geo(spark, sf), seeds(spark, 0), 5.0, 6, 5000).p))
register("seq_heat_walks_geo")(lambda spark, sf: vector_out(d.heat_walks_sequential(builders.geo(spark, sf), seeds(spark, 0), 5.0, 6, 1000).p))

# ---- whole tasks ---------------------------------------------------------------------------------------


@register("local_cluster_geo", full_sql("geo", push_sql({0: [4]}, 0.05, 1e-4, "aggressive", 60), sweep_sql("pv"), BEST_SQL, select="SELECT sp.run_id::BIGINT AS run_id, sp.v::BIGINT AS v, sp.rank::BIGINT AS rank FROM sp JOIN bp ON bp.run_id = sp.run_id WHERE sp.rank <= bp.size"))
def local_cluster_geo(spark, sf):
    return profile.local_cluster(builders.geo(spark, sf), seeds(spark, 4), "push", alpha=0.05, eps=1e-4).members()


COMPARE = {"walk": ("wv", walk_sql([4], 10, 1e-5)), "push": ("pv", push_sql({0: [4]}, 0.05, 1e-4, "aggressive", 60)), "heat": ("hv", heat_sql([4], 5, 15, 1e-4))}


@register("compare_methods_geo", "\nUNION ALL\n".join(f"SELECT '{n}' AS name, * FROM ({full_sql('geo', cte, sweep_sql(v), BEST_SQL, select=f'SELECT {BEST_OUT} FROM bp')})" for n, (v, cte) in COMPARE.items()))
def compare_methods_geo(spark, sf):
    specs = {"walk": ("walk", {"T": 10, "eps": 1e-5}), "push": ("push", {"alpha": 0.05, "eps": 1e-4}), "heat": ("heat", {"t": 5, "N": 15, "eps": 1e-4})}
    return profile.compare_methods(builders.geo(spark, sf), seeds(spark, 4), specs).withColumn("phi", F.round("phi", 9))


@register("peel_once_geo")
def peel_once_geo(spark, sf):
    return profile.peel(builders.geo(spark, sf), lambda g: g.degrees.agg(F.min("v")).first()[0], 2, alpha=0.05, eps=1e-4)


NCP_SEEDS = [0, 4, 8, 12, 16]
NCP_SQL = full_sql("geo", push_sql({v: [v] for v in NCP_SEEDS}, 0.05, 1e-4, "aggressive", 60), sweep_sql("pv"), select="SELECT rank::BIGINT AS size, round(min(phi), 9) AS phi FROM sp WHERE phi IS NOT NULL GROUP BY rank")


@register("ncp_geo", NCP_SQL)
def ncp_geo(spark, sf):
    start = d.seeds_frame(spark, {v: [v] for v in NCP_SEEDS})
    return profile.community_profile(builders.geo(spark, sf), start, [0.05], [1e-4]).withColumn("phi", F.round("phi", 9))


@register("run_grid_geo", "\nUNION ALL\n".join(f"SELECT {k}::INTEGER AS point, * FROM ({full_sql('geo', push_sql({0: [0], 1: [4]}, a, 1e-4, 'aggressive', n), sweep_sql('pv'), BEST_SQL, select=f'SELECT {BEST_OUT} FROM bp')})" for k, (a, n) in enumerate([(0.05, 60), (0.2, 60)])))
def run_grid_geo(spark, sf):
    out = profile.run_grid(builders.geo(spark, sf), seeds(spark, 0, 4), [{"alpha": 0.05, "eps": 1e-4}, {"alpha": 0.2, "eps": 1e-4}])
    return out.withColumn("phi", F.round("phi", 9))


@register("best_seed_geo")
def best_seed_geo(spark, sf):
    return profile.best_seed(builders.geo(spark, sf), 8, alpha=0.05, eps=1e-4)


REACH_SQL = "r(v, c) AS (SELECT v, v FROM g UNION SELECT e.dst, r.c FROM r JOIN e ON e.src = r.v), cc AS (SELECT v, min(c) AS c FROM r GROUP BY v)"


@register("components_page_path", full_sql("page_path", REACH_SQL, select="SELECT v::BIGINT AS v, c::BIGINT AS component FROM cc"))
def components_page_path(spark, sf):
    return profile.components(builders.page_path(spark, sf))


@register("largest_component_seed", full_sql("page_path", REACH_SQL, select="SELECT c::BIGINT AS v, count(*)::BIGINT AS size FROM cc GROUP BY c ORDER BY 2 DESC, 1 LIMIT 1"))
def largest_component_seed(spark, sf):
    return profile.largest_component_seed(builders.page_path(spark, sf))


@register("vector_error_geo")
def vector_error_geo(spark, sf):
    g, s = builders.geo(spark, sf), seeds(spark, 0)
    return measures.vector_error(g, d.residual_push(g, s, 0.2, 1e-5).p, d.pagerank_exact(g, s, 0.2, 1e-13).p)


@register("jaccard_methods_geo")
def jaccard_methods_geo(spark, sf):
    g, s = builders.geo(spark, sf), seeds(spark, 4)
    a, b = (profile.local_cluster(g, s, m, **kw).members().select(F.col("run_id").alias("set_id"), "v") for m, kw in (("push", {"alpha": 0.05, "eps": 1e-4}), ("walk", {"T": 10, "eps": 1e-5})))
    return measures.set_scores(a, b)



@register("gen_torus_degree", f"WITH {torus_sql(5)} SELECT src AS v, count(*)::BIGINT AS deg FROM e GROUP BY src")
def gen_torus_degree(spark, sf):
    """Edges of the data source between cells in which line items stand."""
    from seedspread.sources import datasource

    datasource.register(spark)
    held = cells(spark, sf, 5)
    edges = spark.read.format("seed_graph").option("k", 5).load()
    both = edges.join(held.withColumnRenamed("id", "src"), "src", "left_semi").join(held.withColumnRenamed("id", "dst"), "dst", "left_semi")
    return both.groupBy(F.col("src").alias("v")).agg(F.count("*").alias("deg"))


@register("store_neighbours_geo", f"WITH {graph_sql('geo')} SELECT dst::BIGINT AS v FROM e WHERE src = 2")
def store_neighbours_geo(spark, sf):
    from seedspread.runtime import scratch_path
    from seedspread.sources.store import AdjacencyStore

    store = AdjacencyStore.write(builders.geo(spark, sf), scratch_path(spark, "store"), 16)
    return store.lists_of(spark.createDataFrame([(2,)], "v long")).select(F.inline("nbrs")).select("v")


def _workload(name, **settings):
    def query(spark, sf):
        from seedspread.plans import workloads

        return workloads.WORKLOADS[name](spark, sf, **settings)
    register(f"work_{name}")(query)


_workload("rule_ablation", eps=1e-4, graphs=("geo", "page_path"))
_workload("push_counts", eps=1e-4, graphs=("geo", "page_path"))
_workload("beta_study", eps=1e-4)
_workload("no_good_cluster")
_workload("local_against_dense", rounds=3)
