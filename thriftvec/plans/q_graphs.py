"""Queries on proximity graphs as tables."""

from pyspark.sql import functions as F

from ..catalog import query
from ..operators import graphs as g
from ..sources.storage import stored
from .inputs import VECTORS, sql_l2, table, vec_base

_G = f"""WITH RECURSIVE {VECTORS}, kn AS (SELECT x.node_id AS u, y.node_id AS v, {sql_l2('x.v', 'y.v')} AS dist FROM b x JOIN b y ON x.node_id <> y.node_id QUALIFY row_number() OVER (PARTITION BY x.node_id ORDER BY dist, y.node_id) <= 10),
bg AS (SELECT u, v, min(dist) AS dist FROM (SELECT u, v, dist FROM kn UNION ALL SELECT v, u, dist FROM kn) GROUP BY 1, 2),
dg AS (SELECT node_id, sum(o)::BIGINT AS out_deg, sum(i)::BIGINT AS in_deg FROM (SELECT u AS node_id, 1 AS o, 0 AS i FROM bg UNION ALL SELECT v, 0, 1 FROM bg) GROUP BY 1),
hb AS (SELECT node_id FROM dg QUALIFY row_number() OVER (ORDER BY out_deg + in_deg DESC, node_id) <= ceil(0.02 * (SELECT count(*) FROM dg))),
hc AS (SELECT u, v, dist FROM bg LEFT JOIN hb ON u = node_id QUALIFY row_number() OVER (PARTITION BY u ORDER BY dist, v) <= CASE WHEN node_id IS NULL THEN 4 ELSE 20 END),
hs AS (SELECT u, v, min(dist) AS dist FROM (SELECT u, v, dist FROM hc UNION ALL SELECT v, u, dist FROM hc) GROUP BY 1, 2),
hp AS (SELECT u, v, dist FROM hs QUALIFY row_number() OVER (PARTITION BY u ORDER BY dist, v) <= 20),
rp AS (SELECT u, v, dist FROM bg WHERE ('0x' || substr(md5('7,' || u || ',' || v), 1, 8))::BIGINT < 2147483648),
dc AS (SELECT u, v, dist FROM bg QUALIFY row_number() OVER (PARTITION BY u ORDER BY dist, v) <= 6)"""


def _v(spark, d):
    return vec_base(spark, d).select("node_id", "v")


def _base(spark, d):
    return stored(g.base_graph(_v(spark, d), 10))


def _edges(e):
    return e.select("u", "v", F.round("dist", 6).alias("dist"))


@query("base_graph_degrees", f"{_G} SELECT node_id, out_deg, in_deg FROM dg")
def base_graph_degrees(spark, d):
    return g.degrees(_base(spark, d))


@query("degree_hist", f"{_G} SELECT out_deg AS deg, count(*) AS nodes, round(sum(count(*)) OVER (ORDER BY out_deg) / (SELECT count(*) FROM dg), 6)::DOUBLE AS cdf FROM dg GROUP BY out_deg")
def degree_hist(spark, d):
    return g.degree_hist(_base(spark, d))


@query("hubs_top2pct", f"{_G} SELECT node_id FROM hb")
def hubs_top2pct(spark, d):
    return g.hubs(_base(spark, d), 0.02)


@query("hub_prune_exact", f"{_G} SELECT u, v, round(dist, 6) AS dist FROM hp")
def hub_prune_exact(spark, d):
    e = _base(spark, d)
    return _edges(g.hub_prune(e, e, 20, 4, 0.02))


@query("random_prune_half", f"{_G} SELECT u, v, round(dist, 6) AS dist FROM rp")
def random_prune_half(spark, d):
    return _edges(g.random_prune(_base(spark, d), 0.5))


@query("degree_cap", f"{_G} SELECT u, v, round(dist, 6) AS dist FROM dc")
def degree_cap(spark, d):
    return _edges(g.degree_cap(_base(spark, d), 6))


@query("degree_cap_rebuild", f"""{_G}, k6 AS (SELECT u, v, dist FROM kn QUALIFY row_number() OVER (PARTITION BY u ORDER BY dist, v) <= 6),
s6 AS (SELECT u, v, min(dist) AS dist FROM (SELECT u, v, dist FROM k6 UNION ALL SELECT v, u, dist FROM k6) GROUP BY 1, 2)
SELECT u, v, round(dist, 6) AS dist FROM s6 QUALIFY row_number() OVER (PARTITION BY u ORDER BY s6.dist, v) <= 6""")
def degree_cap_rebuild(spark, d):
    return _edges(g.degree_cap(_base(spark, d), 6, "rebuild", _v(spark, d)))


@query("prune_compare_degrees", f"""{_G}, al AS (SELECT 'original' AS method, u FROM bg UNION ALL SELECT 'hub', u FROM hp UNION ALL SELECT 'random', u FROM rp UNION ALL SELECT 'cap', u FROM dc),
c AS (SELECT method, u, count(*) AS deg FROM al GROUP BY 1, 2) SELECT method, count(*) AS nodes, sum(deg)::BIGINT AS edges, max(deg) AS max_deg, min(deg) AS min_deg FROM c GROUP BY method""")
def prune_compare_degrees(spark, d):
    e = _base(spark, d)
    all_ = [("original", e), ("hub", g.hub_prune(e, e, 20, 4, 0.02)), ("random", g.random_prune(e, 0.5)), ("cap", g.degree_cap(e, 6))]
    u = None
    for name, x in all_:
        r = x.groupBy("u").agg(F.count("*").alias("deg")).select(F.lit(name).alias("method"), "deg")
        u = r if u is None else u.unionByName(r)
    return u.groupBy("method").agg(F.count("*").alias("nodes"), F.sum("deg").alias("edges"), F.max("deg").alias("max_deg"), F.min("deg").alias("min_deg"))


@query("csr_pack", f"""{_G}, a AS (SELECT u AS node_id, count(*) AS deg, array_to_string(list(v ORDER BY dist, v), ',') AS nbrs FROM bg GROUP BY u)
SELECT node_id, coalesce(sum(deg) OVER (ORDER BY node_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS start, deg, nbrs FROM a""")
def csr_pack(spark, d):
    a = g.adjacency(_base(spark, d))
    return a.select("node_id", "start", "deg", F.array_join(F.transform("nbrs", lambda x: x.cast("string")), ",").alias("nbrs"))


@query("csr_round_trip", f"{_G} SELECT u, v FROM bg")
def csr_round_trip(spark, d):
    return g.from_csr(g.to_csr(_base(spark, d), F.pmod(F.col("u"), F.lit(4)))).select("u", "v")


@query("graph_reachable", f"{_G}, r(n) AS (SELECT min(node_id) FROM b UNION SELECT bg.v FROM r JOIN bg ON bg.u = r.n) SELECT n AS node_id FROM r")
def graph_reachable(spark, d):
    start = _v(spark, d).agg(F.min("node_id").alias("node_id"))
    return g.reachable(_base(spark, d), start).select("node_id")


@query("coorder_graph_degrees", """WITH p AS (SELECT DISTINCT l_orderkey AS o, l_partkey AS k FROM lineitem),
e AS (SELECT a.k AS u, b.k AS v, count(*) AS w FROM p a JOIN p b ON a.o = b.o AND a.k <> b.k GROUP BY 1, 2) SELECT u AS node_id, count(*) AS out_deg, sum(w)::BIGINT AS weight FROM e GROUP BY u""")
def coorder_graph_degrees(spark, d):
    e = g.coorder_graph(table(spark, d, "lineitem"))
    return e.groupBy(F.col("u").alias("node_id")).agg(F.count("*").alias("out_deg"), F.sum("w").alias("weight"))


@query("coorder_random_prune", """WITH p AS (SELECT DISTINCT l_orderkey AS o, l_partkey AS k FROM lineitem),
e AS (SELECT DISTINCT a.k AS u, b.k AS v FROM p a JOIN p b ON a.o = b.o AND a.k <> b.k), k AS (SELECT u, v FROM e WHERE ('0x' || substr(md5('7,' || u || ',' || v), 1, 8))::BIGINT < 2147483648)
SELECT u AS node_id, count(*) AS deg FROM k GROUP BY u""")
def coorder_random_prune(spark, d):
    e = g.coorder_graph(table(spark, d, "lineitem")).withColumn("dist", F.lit(0.0))
    return g.random_prune(e, 0.5).groupBy(F.col("u").alias("node_id")).agg(F.count("*").alias("deg"))


@query("compact_deleted", f"{_G} SELECT u, v FROM bg WHERE u % 7 <> 0 AND v % 7 <> 0")
def compact_deleted(spark, d):
    from ..operators.updates import compact

    return compact(_base(spark, d), _v(spark, d).where("node_id % 7 = 0")).select("u", "v")
