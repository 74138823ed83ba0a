"""Registered queries of the hop-distance engine, and the SQL that must give the same rows.

Distances in SQL come from a depth-bounded recursive walk over the same tables; ``BOUND`` is beyond every distance
of the graph. Selections, records and answers are then spelled out in SQL on top of the distances.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import sql
from .functions import masks
from .operators import cohorts as C
from .operators import landmarks as L
from .operators import measures as M
from .operators import search as S
from .operators.compact import distances, fits
from .operators.twohop import TwoHopIndex, batch_sizes
from .plans.store import shared_folder, written
from .sources import graphs as G
from .streaming import feeds

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def register(name: str, run: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    QUERIES[name] = run
    if sql:
        ORACLES[name] = sql


# ---- graphs

_ORDERED = "orders JOIN lineitem ON o_orderkey = l_orderkey"
PAIRS = {
    "part_supplier": "SELECT 2 * l_partkey AS src, 2 * l_suppkey + 1 AS dst FROM lineitem",
    "order_part": "SELECT 2 * l_orderkey AS src, 2 * l_partkey + 1 AS dst FROM lineitem",
    "customer_part": f"SELECT 2 * o_custkey AS src, 2 * l_partkey + 1 AS dst FROM {_ORDERED}",
    "customer_supplier": f"SELECT 2 * o_custkey AS src, 2 * l_suppkey + 1 AS dst FROM {_ORDERED}",
    "customer_order": "SELECT 2 * o_custkey AS src, 2 * o_orderkey + 1 AS dst FROM orders",
    "copurchase": "SELECT a.l_partkey AS src, b.l_partkey AS dst FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey",
    "nation_region": "SELECT 1000 + n_nationkey AS src, 1 + n_regionkey AS dst FROM nation UNION ALL SELECT 10000 + s_suppkey, 1000 + s_nationkey FROM supplier",
    "page_link": "SELECT page_id AS src, 1000000000 + dense_rank() OVER (ORDER BY t) AS dst FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS t FROM pages)",
    "event_flow": "SELECT user_id AS src, lead(user_id) OVER (PARTITION BY date_trunc('hour', ts) ORDER BY ts, event_id) AS dst FROM events",
    "turn_path": "SELECT a.conv_id * 1000 + a.turn AS src, b.conv_id * 1000 + b.turn AS dst FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND a.turn + 1 = b.turn",
    "embedding_knn": """SELECT vec_id AS src, o AS dst FROM (SELECT a.vec_id, b.vec_id AS o, row_number() OVER (PARTITION BY a.vec_id ORDER BY
        round(list_dot_product(a.x, b.x) / (sqrt(list_dot_product(a.x, a.x)) * sqrt(list_dot_product(b.x, b.x))), 9) DESC, b.vec_id) AS r
        FROM (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS x FROM embeddings) a, (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS x FROM embeddings) b WHERE a.vec_id <> b.vec_id) WHERE r <= 4""",
    "near_duplicate": """SELECT x.rep AS src, y.rep AS dst FROM (SELECT a.rep AS ra, b.rep AS rb, count(*) AS n FROM grams a JOIN grams b ON a.g = b.g AND a.rep < b.rep GROUP BY ALL)
        JOIN sizes x ON x.rep = ra JOIN sizes y ON y.rep = rb WHERE 10 * n >= 8 * (x.size + y.size - n) UNION ALL SELECT doc_id, rep FROM classes""",
}
_GRAMS = """classes AS (SELECT doc_id, w, min(doc_id) OVER (PARTITION BY array_to_string(w, ' ')) AS rep
        FROM (SELECT doc_id, regexp_extract_all(lower(text), '[a-z]+') AS w FROM documents) WHERE len(w) >= 5),
    grams AS (SELECT DISTINCT rep, unnest(list_transform(range(1, CAST(len(w) AS BIGINT) - 3), lambda i: array_to_string(w[i : i + 4], ' '))) AS g FROM classes WHERE doc_id = rep),
    sizes AS (SELECT rep, count(*) AS size FROM grams GROUP BY rep)"""
BOUND = {"part_supplier": 7, "customer_part": 7, "copurchase": 5, "page_link": 18, "nation_region": 7, "customer_order": 4, "embedding_knn": 10, "turn_path": 9, "event_flow": 12}


def edges_sql(name: str, directed: bool = False) -> str:
    """CTEs that end in e(src, dst)."""
    back = "" if directed else " UNION ALL SELECT dst, src FROM p"
    extra = _GRAMS + ", " if name == "near_duplicate" else ""
    return f"{extra}p AS ({PAIRS[name]}), e AS (SELECT DISTINCT CAST(src AS BIGINT) AS src, CAST(dst AS BIGINT) AS dst FROM (SELECT src, dst FROM p{back}) WHERE src <> dst)"


def walk_sql(name: str, sources: str, directed: bool = False, bound: int | None = None) -> str:
    """The edges, deg(v, deg), src(s), and dist(s, v, dist)."""
    return f"""WITH RECURSIVE {edges_sql(name, directed)}, deg AS (SELECT src AS v, count(*) AS deg FROM e GROUP BY src), {sources},
    walk(s, v, dist) AS (SELECT s, s, 0 FROM src UNION SELECT walk.s, e.dst, walk.dist + 1 FROM walk JOIN e ON e.src = walk.v WHERE walk.dist < {bound or BOUND[name]}),
    dist AS (SELECT s, v, min(dist) AS dist FROM walk GROUP BY s, v)"""


_TOP = "src AS (SELECT v AS s FROM deg ORDER BY deg DESC, v LIMIT {n})"


def star_sql(w: int) -> str:
    """mem(s, bit) and src(s): the vertex of the highest degree and its w-1 best neighbours."""
    return f"""anchor AS (SELECT v FROM deg ORDER BY deg DESC, v LIMIT 1),
    best AS (SELECT deg.v, deg.deg FROM e JOIN anchor ON e.src = anchor.v JOIN deg ON deg.v = e.dst ORDER BY deg DESC, deg.v LIMIT {w - 1}),
    mem AS (SELECT v AS s, CAST(0 AS BIGINT) AS bit FROM anchor UNION ALL SELECT v, row_number() OVER (ORDER BY deg DESC, v) FROM best), src AS (SELECT s FROM mem)"""


def two_stars_sql(w: int) -> str:
    """mem(cid, s, bit) of the first two cohorts at d = 2."""
    return f"""c0 AS (SELECT v FROM deg ORDER BY deg DESC, v LIMIT 1),
    m0 AS (SELECT v, CAST(0 AS BIGINT) AS bit FROM c0 UNION ALL SELECT v, row_number() OVER (ORDER BY deg DESC, v) FROM
      (SELECT deg.v, deg.deg FROM e JOIN c0 ON e.src = c0.v JOIN deg ON deg.v = e.dst ORDER BY deg DESC, deg.v LIMIT {w - 1})),
    c1 AS (SELECT v FROM deg WHERE v NOT IN (SELECT v FROM m0) ORDER BY deg DESC, v LIMIT 1),
    m1 AS (SELECT v, CAST(0 AS BIGINT) AS bit FROM c1 UNION ALL SELECT v, row_number() OVER (ORDER BY deg DESC, v) FROM
      (SELECT deg.v, deg.deg FROM e JOIN c1 ON e.src = c1.v JOIN deg ON deg.v = e.dst WHERE deg.v NOT IN (SELECT v FROM m0) ORDER BY deg DESC, deg.v LIMIT {w - 1})),
    mem AS (SELECT 0 AS cid, v AS s, bit FROM m0 UNION ALL SELECT 1, v, bit FROM m1), src AS (SELECT s FROM mem)"""


_RECORDS = """ SELECT v, base, off, bit_or(CAST(1 AS BIGINT) << bit) AS mask FROM
    (SELECT v, bit, min(dist) OVER (PARTITION BY v) AS base, dist - min(dist) OVER (PARTITION BY v) AS off FROM dist JOIN mem USING (s)) GROUP BY v, base, off"""


def long_records(arrivals: DataFrame) -> DataFrame:
    base = F.min("round").over(Window.partitionBy("v", "cid", "word"))
    return arrivals.withColumn("base", base).select("v", "base", (F.col("round") - F.col("base")).alias("off"), F.col("fresh").alias("mask"))


for _name, _build in G.BUILDERS.items():
    register(f"edges_{_name}", lambda s, d, b=_build: b(s, d).edges, f"WITH {edges_sql(_name)} SELECT src, dst FROM e")
register("edges_page_link_directed", lambda s, d: G.page_link(s, d, directed=True).edges, f"WITH {edges_sql('page_link', True)} SELECT src, dst FROM e")


def graph_inventory(spark: SparkSession, d: str) -> DataFrame:
    out = None
    for name in G.BUILDERS:
        one = G.BUILDERS[name](spark, d).vertices.agg(F.count("*").alias("n"), F.sum("deg").alias("m"), F.max("deg").alias("max_deg")).select(F.lit(name).alias("graph"), "n", "m", "max_deg")
        out = one if out is None else out.unionByName(one)
    return out


register(
    "graph_inventory",
    graph_inventory,
    " UNION ALL ".join(
        f"SELECT '{n}' AS graph, count(*) AS n, CAST(sum(deg) AS BIGINT) AS m, max(deg) AS max_deg FROM (WITH {edges_sql(n)} SELECT src, count(*) AS deg FROM e GROUP BY src)"
        for n in G.BUILDERS
    ),
)
register("degree_histogram", lambda s, d: G.customer_part(s, d).vertices.groupBy("deg").agg(F.count("*").alias("n")), f"WITH {edges_sql('customer_part')} SELECT deg, count(*) AS n FROM (SELECT src, count(*) AS deg FROM e GROUP BY src) GROUP BY deg")

# ---- searches

PS = "part_supplier"


def _ps(spark: SparkSession, d: str) -> G.HopGraph:
    return G.part_supplier(spark, d).cached()


def _bfs_top(mode: str) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, d: str) -> DataFrame:
        g = _ps(spark, d)
        return S.bfs_each(g, C.pick_landmarks(g, 1), mode).select("v", "dist")

    return run


_ONE = walk_sql(PS, _TOP.format(n=1)) + " SELECT v, dist FROM dist"
for _m in ("push", "pull", "auto"):
    register(f"bfs_single_{_m}", _bfs_top(_m), _ONE)


def bfs_many(n: int, sequential: bool = False) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, d: str) -> DataFrame:
        g = _ps(spark, d)
        top = C.pick_landmarks(g, n)
        return S.bfs_sequential(g, [r["s"] for r in top.collect()]) if sequential else S.bfs_each(g, top)

    return run


register("bfs_each_64", bfs_many(64), walk_sql(PS, _TOP.format(n=64)) + " SELECT s, v, dist FROM dist")
register("bfs_one_by_one", bfs_many(2, True), walk_sql(PS, _TOP.format(n=2)) + " SELECT s, v, dist FROM dist")


def bfs_directed(spark: SparkSession, d: str) -> DataFrame:
    g = G.page_link(spark, d, directed=True).cached()
    return S.bfs_each(g, C.pick_landmarks(g, 5))


register("bfs_directed_page", bfs_directed, walk_sql("page_link", _TOP.format(n=5), True) + " SELECT s, v, dist FROM dist")


def bfs_forest(spark: SparkSession, d: str) -> DataFrame:
    g = G.customer_order(spark, d).cached()
    found = S.bfs(g, C.pick_landmarks(g, 1).first()["s"])
    return g.vertices.join(found, "v", "left").groupBy("dist").agg(F.count("*").alias("n"))


register(
    "bfs_forest_unreached", bfs_forest, walk_sql("customer_order", _TOP.format(n=1)) + " SELECT dist, count(*) AS n FROM deg LEFT JOIN dist USING (v) GROUP BY dist"
)
register("bfs_stopped_at_2", lambda s, d: (lambda g: S.bfs_each(g, C.pick_landmarks(g, 3), stop_after=2))(_ps(s, d)), walk_sql(PS, _TOP.format(n=3), bound=2) + " SELECT s, v, dist FROM dist")


def eccentricity(spark: SparkSession, d: str) -> DataFrame:
    g = _ps(spark, d)
    return S.bfs_each(g, C.pick_landmarks(g, 8)).groupBy("s").agg(F.max("dist").alias("ecc"))


register("eccentricity", eccentricity, walk_sql(PS, _TOP.format(n=8)) + " SELECT s, max(dist) AS ecc FROM dist GROUP BY s")

register("bfs_broadcast_64", lambda s, d: (lambda g: S.bfs_any_size(g, C.pick_landmarks(g, 64)))(_ps(s, d)), walk_sql(PS, _TOP.format(n=64)) + " SELECT s, v, dist FROM dist")
_FORESTS = {"customer_order": 4, "nation_region": 7, "turn_path": 40}


def component_sizes(spark: SparkSession, d: str) -> DataFrame:
    """graph, n (vertices of a component), components: how many components there are of each size."""
    out = None
    for name in _FORESTS:
        sizes = S.components(G.BUILDERS[name](spark, d)).groupBy("component").agg(F.count("*").alias("n"))
        one = sizes.groupBy("n").agg(F.count("*").alias("components")).select(F.lit(name).alias("graph"), "n", "components")
        out = one if out is None else out.unionByName(one)
    return out


register(
    "component_sizes",
    component_sizes,
    " UNION ALL ".join(
        f"SELECT '{name}' AS graph, n, count(*) AS components FROM (SELECT least, count(*) AS n FROM (SELECT v, min(s) AS least FROM ({walk_sql(name, 'src AS (SELECT v AS s FROM deg)', bound=bound)} SELECT s, v FROM dist) GROUP BY v) GROUP BY least) GROUP BY n"
        for name, bound in _FORESTS.items()
    ),
)

# ---- cluster sweeps


def sweep(w: int, mode: str = "push", delta: bool = True, gate: bool = True, graph: str = PS) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, d: str) -> DataFrame:
        g = G.BUILDERS[graph](spark, d).cached()
        return long_records(S.cluster_sweep(g, C.pick_cohorts(g, 1, w), 2 if gate else None, mode, delta))

    return run


for _w in (8, 16, 32, 63):
    register(f"sweep_star_w{_w}", sweep(_w), walk_sql(PS, star_sql(_w)) + _RECORDS)
for _label, _run in (("pull", sweep(16, "pull")), ("auto", sweep(16, "auto")), ("seen_messages", sweep(16, delta=False)), ("no_gate", sweep(16, gate=False))):
    register(f"sweep_{_label}", _run, walk_sql(PS, star_sql(16)) + _RECORDS)
register("sweep_copurchase", sweep(32, graph="copurchase"), walk_sql("copurchase", star_sql(32)) + _RECORDS)


def _star_run(make: Callable[[G.HopGraph, DataFrame], DataFrame]) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, d: str) -> DataFrame:
        g = _ps(spark, d)
        return make(g, C.pick_cohorts(g, 1, 16))

    return run


register("sweep_postprocess", _star_run(lambda g, c: long_records(S.sweep_postprocess(g, c))), walk_sql(PS, star_sql(16)) + _RECORDS)
register("star_sweep", _star_run(lambda g, c: long_records(S.star_sweep(g, c))), walk_sql(PS, star_sql(16)) + _RECORDS)
register(
    "sweep_explode",
    _star_run(lambda g, c: S.explode_records(S.records(S.cluster_sweep(g, c, 2), 2), c).select("s", "v", "dist")),
    walk_sql(PS, star_sql(16)) + " SELECT s, v, dist FROM dist",
)
register(
    "record_lookup",
    _star_run(lambda g, c: S.records(S.cluster_sweep(g, c, 2), 2).select("v", masks.record_distance(F.col("base"), F.col("m"), F.lit(3)).alias("dist"))),
    walk_sql(PS, star_sql(16)) + " SELECT v, dist FROM dist JOIN mem USING (s) WHERE bit = 3",
)
register("cohort_diameter", _star_run(lambda g, c: C.cohort_diameter(g, c).select("diameter")), walk_sql(PS, star_sql(16)) + " SELECT max(dist) AS diameter FROM dist JOIN mem m ON dist.v = m.s")
register("cohorts_star", _star_run(lambda g, c: c.select("s", F.col("bit").cast("long").alias("bit"))), f"WITH {edges_sql(PS)}, deg AS (SELECT src AS v, count(*) AS deg FROM e GROUP BY src), {star_sql(16)} SELECT s, bit FROM mem")


def sweep_many(spark: SparkSession, d: str) -> DataFrame:
    g = _ps(spark, d)
    c = C.pick_cohorts(g, 2, 16)
    return S.explode_records(S.records(S.cluster_sweep(g, c, 2), 2), c)


register("sweep_many_cohorts", sweep_many, walk_sql(PS, two_stars_sql(16)) + " SELECT cid, s, v, dist FROM dist JOIN mem USING (s)")


def sweep_wide(spark: SparkSession, d: str) -> DataFrame:
    g = _ps(spark, d)
    c = C.pick_cohorts(g, 1, 100)
    return S.explode_records(S.records(S.cluster_sweep(g, c, 2), 2), c).select("s", "v", "dist")


register("sweep_k_over_w", sweep_wide, walk_sql(PS, star_sql(100)) + " SELECT s, v, dist FROM dist")


def sweep_directed(spark: SparkSession, d: str) -> DataFrame:
    g = G.page_link(spark, d, directed=True).cached()
    marks = C.pick_landmarks(g, 16)
    c = marks.select(F.lit(0).alias("cid"), (F.col("rank") - 1).alias("bit"), "s")
    arrivals = S.cluster_sweep(g, c, None)
    return arrivals.select("v", "round", F.bit_count("fresh").cast("long").alias("members"))


register("sweep_directed", sweep_directed, walk_sql("page_link", _TOP.format(n=16), True) + " SELECT v, dist AS round, count(*) AS members FROM dist GROUP BY v, dist")


def sweep_general(d_: int) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, d: str) -> DataFrame:
        g = G.page_link(spark, d).cached()
        c = C.pick_cohorts(g, 1, 32, d_)
        return long_records(S.cluster_sweep(g, c, d_))

    return run


def _ball_sql(radius: int, w: int) -> str:
    return f"""anchor AS (SELECT v FROM deg ORDER BY deg DESC, v LIMIT 1),
    near(v, n) AS (SELECT v, 0 FROM anchor UNION SELECT e.dst, near.n + 1 FROM near JOIN e ON e.src = near.v WHERE near.n < {radius}),
    best AS (SELECT DISTINCT deg.v, deg.deg FROM near JOIN deg USING (v) WHERE deg.v NOT IN (SELECT v FROM anchor) ORDER BY deg.deg DESC, deg.v LIMIT {w - 1}),
    mem AS (SELECT v AS s, CAST(0 AS BIGINT) AS bit FROM anchor UNION ALL SELECT v, row_number() OVER (ORDER BY deg DESC, v) FROM best), src AS (SELECT s FROM mem)"""


for _d in (3, 4, 6):
    register(f"sweep_d{_d}", sweep_general(_d), walk_sql("page_link", _ball_sql(_d // 2, 32)) + _RECORDS)


def all_pairs_small(spark: SparkSession, d: str) -> DataFrame:
    """Every vertex in some cohort: all distances by sweeps."""
    return C.all_pairs(G.nation_region(spark, d).cached(), 64, 6)


register("all_pairs_small", all_pairs_small, walk_sql("nation_region", "src AS (SELECT v AS s FROM deg)") + " SELECT s, v, dist FROM dist")

# ---- landmark index

CP = "customer_part"
_DRAW = "CAST(concat('0x', substring(md5(concat('0-', j, '-{k}')), 1, 12)) AS BIGINT) % n"
_PAIRS_SQL = (
    "numbered AS (SELECT v, row_number() OVER (ORDER BY v) - 1 AS i, count(*) OVER () AS n FROM deg), drawn AS (SELECT j AS pid, "
    + _DRAW.replace("{k}", "a") + " AS a, " + _DRAW.replace("{k}", "b")
    + " AS b FROM range({count}) t(j), (SELECT DISTINCT n FROM numbered)), pairs AS (SELECT pid, x.v AS u, y.v AS v FROM drawn JOIN numbered x ON x.i = a JOIN numbered y ON y.i = b WHERE a <> b)"
)
_TRUTH = "truth AS (SELECT pid, dist AS truth FROM pairs LEFT JOIN dist ON dist.s = u AND dist.v = pairs.v)"


def _index_sql(graph: str, members: str, count: int, tail: str) -> str:
    """Distances from members and from the pairs' first ends; est is the least sum over members."""
    pairs = _PAIRS_SQL.format(count=count)
    return (
        walk_sql(graph, f"{members.replace('src AS', 'own AS')}, {pairs}, src AS (SELECT s FROM own UNION SELECT u FROM pairs)")
        + f""", {_TRUTH}, answers AS (SELECT pid, min(x.dist + y.dist) AS est FROM pairs JOIN dist x ON x.v = pairs.u JOIN own ON own.s = x.s
        JOIN dist y ON y.s = x.s AND y.v = pairs.v GROUP BY pid) {tail}"""
    )


#: evaluation pairs; the bench takes 10,000
N_PAIRS = 1000
#: where the SQL walks from every first end, for several variants
N_GRADED = 250


def _landmark_case(graph: str, count: int = N_PAIRS):
    def setup(spark: SparkSession, d: str):
        g = G.BUILDERS[graph](spark, d).cached()
        return g, L.sample_pairs(g, count).persist()

    return setup


def landmark_plain(spark: SparkSession, d: str) -> DataFrame:
    g, pairs = _landmark_case(CP)(spark, d)
    return L.plain_query(L.plain_index(g, C.pick_landmarks(g, 8)), pairs)


register("landmark_plain_index", lambda s, d: (lambda g: L.plain_index(g, C.pick_landmarks(g, 8)))(G.customer_part(s, d).cached()), walk_sql(CP, _TOP.format(n=8)) + " SELECT v, s AS h, dist FROM dist")
register("landmark_plain_query", landmark_plain, _index_sql(CP, _TOP.format(n=8), N_PAIRS, "SELECT pid, est FROM pairs LEFT JOIN answers USING (pid)"))


def landmark_cluster(encoding: str) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, d: str) -> DataFrame:
        g, pairs = _landmark_case(CP)(spark, d)
        return L.LandmarkIndex.build(g, C.pick_cohorts(g, 2, 16), 2, encoding).query(pairs)

    return run


for _e in L.ENCODINGS:
    register(f"landmark_cluster_query_{_e}", landmark_cluster(_e), _index_sql(CP, two_stars_sql(16), N_PAIRS, "SELECT pid, est FROM pairs LEFT JOIN answers USING (pid)"))


def _graded(measure) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, d: str) -> DataFrame:
        g, pairs = _landmark_case(CP)(spark, d)
        truth = L.exact_pairs(g, pairs)  # first: cohorts are chosen on the graph that it broadcasts
        return measure(L.LandmarkIndex.build(g, C.pick_cohorts(g, 2, 16), 2).query(pairs), truth)

    return run


_SCORED = "scored AS (SELECT truth, est FROM answers JOIN truth USING (pid) WHERE truth > 0)"
register(
    "landmark_distortion",
    _graded(M.mean_excess),
    _index_sql(CP, two_stars_sql(16), N_PAIRS, f", {_SCORED} SELECT count(*) AS pairs, round(avg(est / truth) - 1, 6) AS eps, count(*) FILTER (est = truth) AS hits, round(max(est / truth), 6) AS worst FROM scored"),
)
register(
    "landmark_distortion_profile",
    _graded(M.distortion_profile),
    _index_sql(CP, two_stars_sql(16), N_PAIRS, f", {_SCORED} SELECT truth, count(*) AS pairs, round(avg(est / truth) - 1, 6) AS eps, count(*) FILTER (est = truth) AS hits FROM scored GROUP BY truth"),
)


def landmark_budget(spark: SparkSession, d: str) -> DataFrame:
    """t, w, d, clusters: how many cohorts fit t bytes a vertex, where t is what the customer-part graph's edges take (16
    bytes each) a vertex, a quarter, a half and twice of that; w = 1 is single landmarks."""
    size = G.customer_part(spark, d).vertices.agg(F.count("*").alias("n"), F.sum("deg").alias("m")).first()
    budgets = [16 * size["m"] * q // (4 * size["n"]) for q in (1, 2, 4, 8)]
    rows = [(q, t, w, k, C.clusters_for_budget(t, w, k)) for q, t in zip((1, 2, 4, 8), budgets, strict=True) for w in (1, 8, 16, 32, 64) for k in (2, 3, 4)]
    return spark.createDataFrame(rows, "quarters int, t int, w int, d int, clusters int")


register(
    "landmark_budget",
    landmark_budget,
    f"WITH {edges_sql('customer_part')}, size AS (SELECT count(*) AS m, count(DISTINCT src) AS n FROM e), budget AS (SELECT q, 16 * m * q // (4 * n) AS t FROM size, (VALUES (1), (2), (4), (8)) a(q)) "
    "SELECT CAST(q AS INT) AS quarters, CAST(t AS INT) AS t, CAST(w AS INT) AS w, CAST(d AS INT) AS d, CAST(CASE WHEN w = 1 THEN t ELSE t // (1 + d * w // 8) END AS INT) AS clusters FROM budget, (VALUES (1), (8), (16), (32), (64)) b(w), (VALUES (2), (3), (4)) c(d)",
)

_ENDS = "src AS (SELECT u AS s FROM pairs UNION SELECT v FROM pairs)"
_MEET = """, balls AS (SELECT s, v AS x, dist FROM (SELECT *, row_number() OVER (PARTITION BY s ORDER BY dist, v) AS r FROM dist) WHERE r <= {tau}),
    met AS (SELECT pid, min(a.dist + b.dist) AS est FROM pairs JOIN balls a ON a.s = pairs.u JOIN balls b ON b.s = pairs.v AND a.x = b.x GROUP BY pid)"""


def local_meet(spark: SparkSession, d: str) -> DataFrame:
    g, pairs = _landmark_case(CP, 200)(spark, d)
    return L.local_meet(g, pairs, 128)


register("local_meet_tau", local_meet, walk_sql(CP, f"{_PAIRS_SQL.format(count=200)}, {_ENDS}") + _MEET.format(tau=128) + " SELECT pid, est FROM pairs LEFT JOIN met USING (pid)")


def local_plus(spark: SparkSession, d: str) -> DataFrame:
    g, pairs = _landmark_case(CP, 200)(spark, d)
    return L.least_answer(L.LandmarkIndex.build(g, C.pick_cohorts(g, 1, 16), 2).query(pairs), L.local_meet(g, pairs, 128))


register(
    "local_plus_index",
    local_plus,
    walk_sql(CP, f"{star_sql(16).replace('src AS', 'own AS')}, {_PAIRS_SQL.format(count=200)}, src AS (SELECT s FROM own UNION SELECT u FROM pairs UNION SELECT v FROM pairs)")
    + _MEET.format(tau=128)
    + """, answers AS (SELECT pid, min(x.dist + y.dist) AS est FROM pairs JOIN dist x ON x.v = pairs.u JOIN own ON own.s = x.s JOIN dist y ON y.s = x.s AND y.v = pairs.v GROUP BY pid)
    SELECT pid, least(answers.est, met.est) AS est FROM pairs LEFT JOIN answers USING (pid) LEFT JOIN met USING (pid)""",
)

# ---- exact index


def exact(graph: str, r: int, **how) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, d: str) -> DataFrame:
        g, pairs = _landmark_case(graph)(spark, d)
        return TwoHopIndex.build(g, r, 16, **how).query(pairs).select("pid", "est")

    return run


def _exact_sql(graph: str) -> str:
    return walk_sql(graph, f"{_PAIRS_SQL.format(count=N_PAIRS)}, src AS (SELECT DISTINCT u AS s FROM pairs)") + " SELECT pid, dist AS est FROM pairs LEFT JOIN dist ON dist.s = u AND dist.v = pairs.v"


register("exact_query_forest", exact("nation_region", 0, first=30), _exact_sql("nation_region"))
# graphs with cycles, where several shortest paths meet
register("exact_query", exact("event_flow", 0), _exact_sql("event_flow"))
register("exact_cluster_phase_query", exact("event_flow", 2), _exact_sql("event_flow"))
register("exact_trimmed_query", exact("event_flow", 2, trim=True), _exact_sql("event_flow"))


def exact_label_superset(spark: SparkSession, d: str) -> DataFrame:
    """Labels of a build of one search at a time that a build in batches lacks (none), and how many more it has."""
    g = G.from_pairs(G.table(spark, d, "nation").select((1000 + F.col("n_nationkey")).alias("src"), (1 + F.col("n_regionkey")).alias("dst"))).cached()
    one, batched = (TwoHopIndex.build(g, 0, **how).labels for how in ({"first": 1, "growth": 1.0, "cap": 1}, {"first": 10}))
    missing = one.join(batched, ["v", "hub", "dist"], "left_anti")
    return missing.agg(F.count("*").alias("missing")).withColumn("fewer_than_batched", F.lit(one.count() <= batched.count()))


def exact_batch_plan(spark: SparkSession, d: str) -> DataFrame:
    """batch, size: the batches in which the exact index of the event graph is built."""
    n = G.event_flow(spark, d).vertices.count()
    return spark.createDataFrame(list(enumerate(batch_sizes(n))), "batch int, size int")


register(
    "exact_batch_plan",
    exact_batch_plan,
    f"WITH {edges_sql('event_flow')}, size AS (SELECT count(DISTINCT src) AS n FROM e), plan AS (SELECT i, least(1000, CAST(floor(200 * pow(1.5, least(i, 20))) AS BIGINT)) AS size FROM size, range(n // 1000 + 10) t(i)), "
    "sums AS (SELECT *, coalesce(sum(size) OVER (ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM plan) SELECT CAST(i AS INT) AS batch, CAST(least(sums.size, n - before) AS INT) AS size FROM sums, size WHERE before < n",
)

# ---- selections, budgets, diameters

_DEG = "WITH {edges}, deg AS (SELECT src AS v, count(*) AS deg FROM e GROUP BY src)"


def _deg_sql(graph: str) -> str:
    return _DEG.format(edges=edges_sql(graph))


register("landmarks_top_degree", lambda s, d: C.pick_landmarks(_ps(s, d), 50), _deg_sql(PS) + " SELECT v AS s, CAST(row_number() OVER (ORDER BY deg DESC, v) AS INT) AS rank FROM deg QUALIFY rank <= 50")
register("landmarks_random", lambda s, d: C.pick_landmarks(_ps(s, d), 50, "hash"), _deg_sql(PS) + " SELECT v AS s, CAST(row_number() OVER (ORDER BY md5(concat('0-', v)), v) AS INT) AS rank FROM deg QUALIFY rank <= 50")


def _members(graph: str, r: int, w: int, d_: int, rule: str = "floor") -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, d: str) -> DataFrame:
        g = G.BUILDERS[graph](spark, d).cached()
        return C.pick_cohorts(g, r, w, d_, rule).select("s", F.col("bit").cast("long").alias("bit"))

    return run


_EDGE_BALL = """anchor AS (SELECT v FROM deg ORDER BY deg DESC, v LIMIT 1),
    second AS (SELECT deg.v FROM e JOIN anchor ON e.src = anchor.v JOIN deg ON deg.v = e.dst ORDER BY deg DESC, deg.v LIMIT 1),
    near AS (SELECT DISTINCT e.dst AS v FROM e WHERE e.src IN (SELECT v FROM anchor UNION SELECT v FROM second)),
    best AS (SELECT deg.v, deg.deg FROM near JOIN deg USING (v) WHERE deg.v NOT IN (SELECT v FROM anchor) ORDER BY deg.deg DESC, deg.v LIMIT {n}),
    mem AS (SELECT v AS s, CAST(0 AS BIGINT) AS bit FROM anchor UNION ALL SELECT v, row_number() OVER (ORDER BY deg DESC, v) FROM best)"""
_BITS = " SELECT s, bit FROM mem"
register("cohorts_d4", _members("page_link", 1, 32, 4), _deg_sql("page_link").replace("WITH", "WITH RECURSIVE", 1) + ", " + _ball_sql(2, 32) + _BITS)
register("cohorts_edge_d3", _members("copurchase", 1, 64, 3, "edge"), _deg_sql("copurchase") + ", " + _EDGE_BALL.format(n=63) + _BITS)
# degrees below w: cohorts stay short
register("cohorts_short", _members("customer_order", 2, 64, 2), _deg_sql("customer_order") + ", " + two_stars_sql(64) + _BITS)


def sweep_edge_d3(spark: SparkSession, d: str) -> DataFrame:
    g = G.copurchase(spark, d).cached()
    return long_records(S.cluster_sweep(g, C.pick_cohorts(g, 1, 32, 3, "edge"), 3))


register("sweep_edge_d3", sweep_edge_d3, walk_sql("copurchase", _EDGE_BALL.format(n=31) + ", src AS (SELECT s FROM mem)") + _RECORDS)


def exact_hits(spark: SparkSession, d: str) -> DataFrame:
    """The pairs that the index answers exactly: those with a member of a cohort on a shortest path."""
    g, pairs = _landmark_case(CP)(spark, d)
    truth = L.exact_pairs(g, pairs)
    found = L.LandmarkIndex.build(g, C.pick_cohorts(g, 2, 16), 2).query(pairs)
    return M.scored(found, truth).where("est = truth").select("pid")


register("landmark_exact_hits", exact_hits, _index_sql(CP, two_stars_sql(16), N_PAIRS, f", {_SCORED.replace('SELECT truth', 'SELECT pid, truth')} SELECT pid FROM scored WHERE est = truth"))


def _eps(graph: str, variants: tuple[tuple[int, int, int], ...]) -> Callable[[SparkSession, str], DataFrame]:
    """t, w, d, clusters, eps for variants (t bytes a vertex, w, d); w = 1 is single landmarks."""

    def run(spark: SparkSession, folder: str) -> DataFrame:
        g, pairs = _landmark_case(graph, N_GRADED)(spark, folder)
        truth = L.exact_pairs(g, pairs).persist()
        # the landmarks and cohorts of a small budget are the first of a large one: one index has them all
        single = [C.clusters_for_budget(t, w, d) for t, w, d in variants if w == 1]
        if single:
            marks = C.pick_landmarks(g, max(single))
            found = written(distances(g, marks), "plain") if fits(g) else S.bfs_bits(g, marks)
            plain = found.withColumnRenamed("s", "h").join(F.broadcast(marks.withColumnRenamed("s", "h")), "h")
        most: dict[tuple[int, int], int] = {}
        for t, w, d in variants:
            if w > 1:
                most[w, d] = max(most.get((w, d), 0), C.clusters_for_budget(t, w, d))
        index = {(w, d): L.LandmarkIndex.build(g, C.pick_cohorts(g, n, w, d), d, "complement") for (w, d), n in most.items()}
        out = None
        for t, w, d in variants:
            n = C.clusters_for_budget(t, w, d)
            answers = L.plain_query(L.wide(plain.where(F.col("rank") <= n).select("v", "h", "dist")), pairs) if w == 1 else index[w, d].first(n).query(pairs)
            one = M.mean_excess(answers, truth).select(F.lit(t).alias("t"), F.lit(w).alias("w"), F.lit(d).alias("d"), F.lit(n).alias("clusters"), "eps")
            out = one if out is None else out.unionByName(one)
        return out

    return run


def _eps_sql(graph: str, variants: tuple[tuple[int, int, int], ...]) -> str:
    def members(t: int, w: int, d: int) -> str:
        n = C.clusters_for_budget(t, w, d)
        if w == 1:
            return _TOP.format(n=n)
        if d == 2:
            return two_stars_sql(w) if n == 2 else star_sql(w)
        return _ball_sql(d // 2, w)

    graded = f", {_SCORED} SELECT {{}} AS t, {{}} AS w, {{}} AS d, {{}} AS clusters, round(avg(est / truth) - 1, 6) AS eps FROM scored"
    parts = [_index_sql(graph, members(*v), N_GRADED, graded.format(*v, C.clusters_for_budget(*v))) for v in variants]
    return " UNION ALL ".join(f"SELECT CAST(t AS INT) AS t, CAST(w AS INT) AS w, CAST(d AS INT) AS d, CAST(clusters AS INT) AS clusters, eps FROM ({p})" for p in parts)


_BUDGETS = ((17, 1, 2), (17, 64, 2), (34, 1, 2), (34, 64, 2))
_DIAMETERS = ((34, 64, 2), (34, 64, 3), (34, 64, 4))
register("landmark_budget_eps", _eps("copurchase", _BUDGETS), _eps_sql("copurchase", _BUDGETS))
register("landmark_tradeoff_eps", _eps(CP, _BUDGETS), _eps_sql(CP, _BUDGETS))
register("landmark_diameter_eps", _eps("copurchase", _DIAMETERS), _eps_sql("copurchase", _DIAMETERS))


def local_tau_sweep(spark: SparkSession, d: str) -> DataFrame:
    g, pairs = _landmark_case(CP, 200)(spark, d)
    out = None
    for tau, scope in ((32, "side"), (128, "side"), (128, "total"), (512, "side")):
        one = L.local_meet(g, pairs, tau, scope=scope).select(F.lit(tau).alias("tau"), F.lit(scope).alias("scope"), "pid", "est")
        out = one if out is None else out.unionByName(one)
    return out


register(
    "local_tau_sweep",
    local_tau_sweep,
    " UNION ALL ".join(
        f"SELECT CAST({tau} AS INT) AS tau, '{scope}' AS scope, * FROM ({walk_sql(CP, f'{_PAIRS_SQL.format(count=200)}, {_ENDS}') + _MEET.format(tau=tau if scope == 'side' else tau // 2)} SELECT pid, est FROM pairs LEFT JOIN met USING (pid))"
        for tau, scope in ((32, "side"), (128, "side"), (128, "total"), (512, "side"))
    ),
)


register("exact_label_superset", exact_label_superset, "SELECT CAST(0 AS BIGINT) AS missing, true AS fewer_than_batched")

# ---- surroundings


def rollup_report(spark: SparkSession, d: str) -> DataFrame:
    o = G.table(spark, d, "orders")
    return o.rollup("o_orderpriority", "o_orderstatus").agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


register("report_rollup", rollup_report, "SELECT o_orderpriority, o_orderstatus, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM orders GROUP BY ROLLUP (o_orderpriority, o_orderstatus)")


def top_customers(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("c_nationkey").orderBy(F.desc("n"), "c_custkey")
    n = G.table(spark, d, "orders").groupBy(F.col("o_custkey").alias("c_custkey")).agg(F.count("*").alias("n"))
    return G.table(spark, d, "customer").join(n, "c_custkey").withColumn("r", F.row_number().over(w)).where("r <= 3").select("c_nationkey", "c_custkey", "n", "r")


register(
    "top_k_per_group", top_customers, "SELECT * FROM (SELECT c_nationkey, c_custkey, n, CAST(row_number() OVER (PARTITION BY c_nationkey ORDER BY n DESC, c_custkey) AS INT) AS r FROM customer JOIN (SELECT o_custkey AS c_custkey, count(*) AS n FROM orders GROUP BY 1) USING (c_custkey)) WHERE r <= 3"
)


def last_order_before_event(spark: SparkSession, d: str) -> DataFrame:
    """As-of join: each purchase event with its user's latest order before it, by one window over the union."""
    e = G.table(spark, d, "events").where("event_type = 'purchase'").select(F.col("user_id").alias("k"), F.col("ts").alias("t"), F.col("event_id").alias("e"), F.lit(None).cast("long").alias("o"))
    o = G.table(spark, d, "orders").select(F.col("o_custkey").alias("k"), F.col("o_orderdate").alias("t"), F.lit(None).cast("long").alias("e"), F.col("o_orderkey").alias("o"))
    w = Window.partitionBy("k").orderBy("t", F.col("e").asc_nulls_first(), "o").rowsBetween(Window.unboundedPreceding, 0)
    return e.unionByName(o).withColumn("o", F.last("o", ignorenulls=True).over(w)).where("e is not null").select(F.col("e").alias("event_id"), F.col("o").alias("o_orderkey"))


register(
    "asof_order",
    last_order_before_event,
    "SELECT event_id, max_by(o_orderkey, (o_orderdate, o_orderkey)) AS o_orderkey FROM (SELECT * FROM events WHERE event_type = 'purchase') e LEFT JOIN orders ON o_custkey = user_id AND o_orderdate <= ts GROUP BY event_id",
)


def edges_by_year(spark: SparkSession, d: str) -> DataFrame:
    """Date slices of the customer-part graph."""
    j = G.table(spark, d, "orders").join(G.table(spark, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"))
    return j.select(F.year("o_orderdate").alias("y"), "o_custkey", "l_partkey").distinct().groupBy("y").agg(F.count("*").alias("n"))


register("edges_by_year", edges_by_year, "SELECT CAST(year(o_orderdate) AS INT) AS y, count(*) AS n FROM (SELECT DISTINCT o_custkey, l_partkey, date_trunc('year', o_orderdate) AS o_orderdate FROM orders JOIN lineitem ON o_orderkey = l_orderkey) GROUP BY 1")
register(
    "set_difference",
    lambda s, d: G.part_supplier(s, d).vertices.select("v").subtract(G.customer_part(s, d).vertices.select("v")),
    f"(SELECT DISTINCT src AS v FROM (WITH {edges_sql(PS)} SELECT src FROM e)) EXCEPT (SELECT DISTINCT src FROM (WITH {edges_sql(CP)} SELECT src FROM e))",
)
register(
    "stream_hourly_counts",
    lambda s, d: feeds.drained(feeds.windowed_counts(feeds.events(s, d), "1 hour"), "complete").select(F.date_format("start", "yyyy-MM-dd HH:mm").alias("start"), "event_type", "n"),
    "SELECT strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M') AS start, event_type, count(*) AS n FROM events GROUP BY ALL",
)


def _table(name: str, use: Callable[[DataFrame], DataFrame]) -> Callable[[SparkSession, str], DataFrame]:
    return lambda spark, d: use(G.table(spark, d, name))


register(
    "report_cube",
    _table("orders", lambda o: o.cube("o_orderpriority", "o_orderstatus").agg(F.count("*").alias("n"), F.grouping_id().cast("int").alias("level"))),
    "SELECT o_orderpriority, o_orderstatus, count(*) AS n, CAST(grouping_id(o_orderpriority, o_orderstatus) AS INT) AS level FROM orders GROUP BY CUBE (o_orderpriority, o_orderstatus)",
)
register(
    "report_pivot",
    _table("orders", lambda o: o.groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count("o_orderkey")).fillna(0)),
    "SELECT o_orderpriority, " + ", ".join(f"count(*) FILTER (o_orderstatus = '{x}') AS \"{x}\"" for x in "FOP") + " FROM orders GROUP BY 1",
)
register(
    "report_unpivot",
    lambda s, d: _ps(s, d).vertices.agg(F.count("*").alias("n"), F.sum("deg").alias("m"), F.max("deg").alias("max_deg")).unpivot([], ["n", "m", "max_deg"], "measure", "value"),
    _deg_sql(PS) + ", t AS (SELECT count(*) AS n, CAST(sum(deg) AS BIGINT) AS m, max(deg) AS max_deg FROM deg) SELECT 'n' AS measure, n AS value FROM t UNION ALL SELECT 'm', m FROM t UNION ALL SELECT 'max_deg', max_deg FROM t",
)
register(
    "degree_quantiles",
    lambda s, d: _ps(s, d).vertices.agg(*(F.round(F.percentile("deg", F.lit(q)), 6).alias(f"p{int(100 * q)}") for q in (0.25, 0.5, 0.9)), F.round(F.stddev_samp("deg"), 6).alias("sd")),
    _deg_sql(PS) + " SELECT " + ", ".join(f"round(quantile_cont(deg, {q}), 6) AS p{int(100 * q)}" for q in (0.25, 0.5, 0.9)) + ", round(stddev_samp(deg), 6) AS sd FROM deg",
)
register(
    "set_intersect",
    lambda s, d: G.part_supplier(s, d).vertices.select("v").intersect(G.customer_part(s, d).vertices.select("v")),
    f"(SELECT DISTINCT src AS v FROM (WITH {edges_sql(PS)} SELECT src FROM e)) INTERSECT (SELECT DISTINCT src FROM (WITH {edges_sql(CP)} SELECT src FROM e))",
)
register(
    "set_except_all",
    lambda s, d: G.table(s, d, "events").select(F.col("user_id").alias("k")).exceptAll(G.table(s, d, "orders").select(F.col("o_custkey").alias("k"))),
    "SELECT user_id AS k FROM events EXCEPT ALL SELECT o_custkey FROM orders",
)
register(
    "json_filter",
    _table("events", lambda e: e.select("event_type", F.get_json_object("props", "$.k").cast("long").alias("k")).where("k < 10").groupBy("event_type", "k").agg(F.count("*").alias("n"))),
    "SELECT event_type, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events WHERE CAST(json_extract_string(props, '$.k') AS BIGINT) < 10 GROUP BY ALL",
)


def status_maps(orders: DataFrame) -> DataFrame:
    """A map of counts by status for each priority, read by its keys."""
    n = orders.groupBy("o_orderpriority", "o_orderstatus").agg(F.count("*").alias("n"))
    maps = n.groupBy("o_orderpriority").agg(F.map_from_entries(F.collect_list(F.struct("o_orderstatus", "n"))).alias("m"))  # a few statuses
    return maps.select("o_orderpriority", F.size(F.map_keys("m")).cast("long").alias("statuses"), F.try_element_at("m", F.lit("F")).alias("f"))


register("status_maps", _table("orders", status_maps), "SELECT o_orderpriority, count(DISTINCT o_orderstatus) AS statuses, count(*) FILTER (o_orderstatus = 'F') AS f FROM orders GROUP BY 1")


def json_edges(spark: SparkSession, d: str) -> DataFrame:
    """Edges written as JSON lines and read back."""
    g = G.nation_region(spark, d)
    path = f"{shared_folder(spark)}/edges-json-{uuid.uuid4().hex}"
    g.edges.write.json(path)
    return G.read_edge_json(spark, path).edges


def text_edges(spark: SparkSession, d: str) -> DataFrame:
    """Edges written as tab-separated lines and read back."""
    path = f"{shared_folder(spark)}/edges-text-{uuid.uuid4().hex}"
    G.nation_region(spark, d).edges.write.csv(path, sep="\t")
    return G.read_edge_list(spark, path).edges


register("edges_json_round_trip", json_edges, f"WITH {edges_sql('nation_region')} SELECT src, dst FROM e")
register("edges_text_round_trip", text_edges, f"WITH {edges_sql('nation_region')} SELECT src, dst FROM e")
register(
    "sql_table_function",
    lambda s, d: sql.exploded(s, _ps(s, d), 16),
    walk_sql(PS, star_sql(16)) + " SELECT v, bit, dist FROM dist JOIN mem USING (s)",
)
register(
    "stream_sliding_counts",
    lambda s, d: feeds.drained(feeds.windowed_counts(feeds.events(s, d), "2 hours", "1 hour"), "complete").select(F.date_format("start", "yyyy-MM-dd HH:mm").alias("start"), "event_type", "n"),
    "SELECT strftime(date_trunc('hour', ts) - h * INTERVAL 1 HOUR, '%Y-%m-%d %H:%M') AS start, event_type, count(*) AS n FROM events, (VALUES (0), (1)) t(h) GROUP BY ALL",
)
register(
    "stream_interval_join",
    lambda s, d: feeds.drained(feeds.clicks_before_purchases(s, d)),
    "SELECT p.event_id AS purchase, c.event_id AS click FROM events p JOIN events c ON p.user_id = c.user_id AND c.ts BETWEEN p.ts - INTERVAL 1 HOUR AND p.ts WHERE p.event_type = 'purchase' AND c.event_type = 'click'",
)
