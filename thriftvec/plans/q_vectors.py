"""Queries on exact search, product quantization and coarse clusters over the embeddings."""

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..catalog import query
from ..operators import clusters as cl
from ..operators import pq
from ..operators.exact import knn_exact, knn_graph, range_search
from ..operators.measures import recall_at_k
from ..sources.storage import stored
from .inputs import VECTORS, rounded, sql_dot, sql_l2, sql_top, vec_base, vec_query

_W = f"WITH {VECTORS}, "
KNN = f"{_W} d AS (SELECT query_id, node_id, {sql_l2()} AS dist FROM b, q) {sql_top('d', 10)}"


@query("knn_l2", KNN)
def knn_l2(spark, d):
    return rounded(knn_exact(vec_base(spark, d), vec_query(spark, d), 10), "dist")


@query("knn_l2_blocked", KNN)
def knn_l2_blocked(spark, d):
    return rounded(knn_exact(vec_base(spark, d), vec_query(spark, d), 10), "dist")


@query("knn_ip", f"{_W} d AS (SELECT query_id, node_id, -{sql_dot()} AS dist FROM b, q) {sql_top('d', 10)}")
def knn_ip(spark, d):
    return rounded(knn_exact(vec_base(spark, d), vec_query(spark, d), 10, "ip"), "dist")


@query("knn_cosine", f"{_W} d AS (SELECT query_id, node_id, 1 - {sql_dot()} / (sqrt({sql_dot('v', 'v')}) * sqrt({sql_dot('qv', 'qv')})) AS dist FROM b, q) {sql_top('d', 10)}")
def knn_cosine(spark, d):
    return rounded(knn_exact(vec_base(spark, d), vec_query(spark, d), 10, "cosine"), "dist")


@query("knn_filtered", f"{_W} d AS (SELECT query_id, node_id, {sql_l2()} AS dist FROM b, q WHERE label < 5) {sql_top('d', 10)}")
def knn_filtered(spark, d):
    return rounded(knn_exact(vec_base(spark, d), vec_query(spark, d), 10, predicate=F.col("label") < 5), "dist")


@query("range_search", f"{_W} d AS (SELECT query_id, node_id, {sql_l2()} AS dist FROM b, q) SELECT query_id, node_id, round(dist, 6) AS dist FROM d WHERE dist <= 1.4")
def range_query(spark, d):
    return rounded(range_search(vec_base(spark, d), vec_query(spark, d), 1.4), "dist")


@query("knn_graph_10", f"""{_W} d AS (SELECT x.node_id AS u, y.node_id AS v, {sql_l2('x.v', 'y.v')} AS dist FROM b x JOIN b y ON x.node_id <> y.node_id)
SELECT u, v, rank::INT AS rank, round(dist, 6) AS dist FROM (SELECT *, row_number() OVER (PARTITION BY u ORDER BY dist, v) AS rank FROM d) WHERE rank <= 10""")
def knn_graph_10(spark, d):
    return rounded(knn_graph(vec_base(spark, d), 10), "dist")


# product quantization: 8 subspaces of 8 coordinates, 16 codewords
_SUB = """s AS (SELECT node_id, unnest(range(0, 8)) AS sub, v FROM b), x AS (SELECT node_id, sub::INT AS sub, v[sub * 8 + 1:sub * 8 + 8] AS x FROM s),
seed AS (SELECT node_id, (row_number() OVER (ORDER BY node_id) - 1)::INT AS code FROM b QUALIFY code < 16),
book AS (SELECT sub, code, x AS c FROM x JOIN seed USING (node_id)),
asg AS (SELECT node_id, sub, code, dist FROM (SELECT node_id, x.sub, code, """ + sql_l2("x", "c") + """ AS dist FROM x JOIN book USING (sub)) QUALIFY row_number() OVER (PARTITION BY node_id, sub ORDER BY dist, code) = 1)"""


def _points(spark, d):
    return pq.subvectors(vec_base(spark, d), 8, 64)


def _seeds(spark, d, n=16):
    b = vec_base(spark, d).select("node_id").orderBy("node_id").limit(n)
    return b.withColumn("code", (F.row_number().over(Window.orderBy("node_id")) - 1).cast("int"))


def _book(spark, d):
    return pq.seeded(_points(spark, d), _seeds(spark, d))


def _codes(spark, d):
    return pq.assign(_points(spark, d), _book(spark, d))


@query("pq_codes_seeded", f"{_W} {_SUB} SELECT node_id, sub, code FROM asg")
def pq_codes_seeded(spark, d):
    return _codes(spark, d).select("node_id", "sub", "code")


@query("pq_error", f"{_W} {_SUB} SELECT sub, count(*) AS n, sum(floor(dist * 1000000)::BIGINT)::BIGINT AS error FROM asg GROUP BY sub")
def pq_error(spark, d):
    return pq.pq_error(_codes(spark, d))


def _lloyd_sql(parts: str, k: int, rounds: int = 2) -> str:
    """parts: SQL of fx(node_id, sub, x BIGINT[]); seeds are the first k nodes."""
    out = f"{parts}, sd AS (SELECT node_id, (row_number() OVER (ORDER BY node_id) - 1)::INT AS code FROM (SELECT DISTINCT node_id FROM fx) QUALIFY code < {k}), k0 AS (SELECT sub, code, x AS c FROM fx JOIN sd USING (node_id))"
    for r in range(rounds):
        out += f""", a{r} AS (SELECT node_id, sub, x, code FROM (SELECT node_id, fx.sub AS sub, x, code, {sql_l2('x', 'c')} AS dd FROM fx JOIN k{r} ON fx.sub = k{r}.sub) QUALIFY row_number() OVER (PARTITION BY node_id, sub ORDER BY dd, code) = 1),
m{r} AS (SELECT sub, code, i, sum(x[i])::BIGINT AS s, count(*) AS n FROM (SELECT sub, code, x, unnest(range(1, len(x) + 1)) AS i FROM a{r}) GROUP BY 1, 2, 3),
g{r} AS (SELECT sub, code, list((s // n) - CASE WHEN s % n < 0 THEN 1 ELSE 0 END ORDER BY i) AS c FROM m{r} GROUP BY 1, 2),
k{r + 1} AS (SELECT k{r}.sub, k{r}.code, coalesce(g{r}.c, k{r}.c) AS c FROM k{r} LEFT JOIN g{r} ON k{r}.sub = g{r}.sub AND k{r}.code = g{r}.code)"""
    return out


@query("pq_lloyd_fixed", _W + _lloyd_sql("fx AS (SELECT node_id, sub::INT AS sub, list_transform(v[sub * 8 + 1:sub * 8 + 8], lambda c: floor(c * 1000000)::BIGINT) AS x FROM (SELECT node_id, unnest(range(0, 8)) AS sub, v FROM b))", 16) + " SELECT sub, code, array_to_string(c, ',') AS centroid FROM k2")
def pq_lloyd_fixed(spark, d):
    p = _points(spark, d).withColumn("x", pq.to_fixed(F.col("x")))
    b = pq.lloyd_fixed(p, pq.seeded(p, _seeds(spark, d)), 2)
    return b.select("sub", "code", F.array_join(F.transform("centroid", lambda c: c.cast("string")), ",").alias("centroid"))


_ADC = f"""qs AS (SELECT query_id, unnest(range(0, 8)) AS sub, qv FROM q), qx AS (SELECT query_id, sub::INT AS sub, qv[sub * 8 + 1:sub * 8 + 8] AS qx FROM qs),
lut AS (SELECT query_id, sub, code, floor({sql_l2('qx', 'c')} * 1000000)::BIGINT AS dd FROM qx JOIN book USING (sub)),
ad AS (SELECT query_id, node_id, sum(dd)::BIGINT AS dist FROM asg JOIN lut USING (sub, code) GROUP BY 1, 2),
adt AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY dist, node_id) AS rank FROM ad)"""


def _adc(spark, d, k):
    lut = pq.adc_lut(vec_query(spark, d), _book(spark, d), 8, 64)
    return pq.pq_topk_sql(_codes(spark, d).select("node_id", "sub", "code"), lut, k)


@query("pq_adc_topk", f"{_W} {_SUB}, {_ADC} SELECT query_id, rank::INT AS rank, node_id, dist FROM adt WHERE rank <= 10")
def pq_adc_topk(spark, d):
    return _adc(spark, d, 10)


@query("pq_rerank_100", f"{_W} {_SUB}, {_ADC}, rr AS (SELECT query_id, node_id, {sql_l2()} AS dist FROM adt JOIN b USING (node_id) JOIN q USING (query_id) WHERE rank <= 100) {sql_top('rr', 10)}")
def pq_rerank_100(spark, d):
    return rounded(pq.rerank(_adc(spark, d, 100), vec_base(spark, d), vec_query(spark, d), 10), "dist")


_TRUTH = f"tr AS (SELECT query_id, node_id FROM (SELECT query_id, node_id, {sql_l2()} AS dist FROM b, q) QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY dist, node_id) <= 10)"


@query("recall_at_k_pq", f"{_W} {_SUB}, {_ADC}, {_TRUTH} SELECT query_id, round(count(adt.node_id) / 10.0, 6)::DOUBLE AS recall FROM tr LEFT JOIN (SELECT * FROM adt WHERE rank <= 10) adt USING (query_id, node_id) GROUP BY query_id")
def recall_pq(spark, d):
    return recall_at_k(_adc(spark, d, 10), knn_exact(vec_base(spark, d), vec_query(spark, d), 10), 10)


@query("pq_decode", f"{_W} {_SUB} SELECT node_id, round(list_sum(list_transform(list_zip(v, w), lambda z: (z[1] - z[2]) * (z[1] - z[2]))), 5) AS error FROM b JOIN (SELECT node_id, flatten(list(c ORDER BY sub)) AS w FROM asg JOIN book USING (sub, code) GROUP BY 1) USING (node_id)")
def pq_decode(spark, d):
    from ..functions.distance import l2sq

    dec = pq.pq_decode(_codes(spark, d).select("node_id", "sub", "code"), _book(spark, d)).withColumnRenamed("v", "w")
    return vec_base(spark, d).join(dec, "node_id").select("node_id", F.round(l2sq("v", "w"), 5).alias("error"))


# coarse clusters
_FX = "fx AS (SELECT node_id, 0 AS sub, list_transform(v, lambda c: floor(c * 1000000)::BIGINT) AS x FROM b)"


@query("kmeans_fixed", _W + _lloyd_sql(_FX, 8) + " SELECT code AS cell, array_to_string(c, ',') AS centroid FROM k2")
def kmeans_fixed(spark, d):
    c = cl.kmeans_fixed(vec_base(spark, d), 8, 2)
    return c.select("cell", F.array_join(F.transform("centroid", lambda x: x.cast("string")), ",").alias("centroid"))


_CELLS = _lloyd_sql(_FX, 16) + f""", cen AS (SELECT code AS cell, list_transform(c, lambda z: z / 1000000) AS c FROM k2),
nc AS (SELECT node_id, cell, row_number() OVER (PARTITION BY node_id ORDER BY dd, cell) AS rank FROM (SELECT node_id, cell, {sql_l2('v', 'c')} AS dd FROM b, cen)),
qc AS (SELECT query_id, cell, row_number() OVER (PARTITION BY query_id ORDER BY dd, cell) AS rank FROM (SELECT query_id, cell, {sql_l2('qv', 'c')} AS dd FROM q, cen))"""


def _centres(spark, d):
    return stored(cl.to_float(cl.kmeans_fixed(vec_base(spark, d), 16, 2)))


@query("ivf_assign", f"{_W} {_CELLS} SELECT node_id, cell FROM nc WHERE rank = 1")
def ivf_assign(spark, d):
    return cl.nearest_cells(vec_base(spark, d).select("node_id", "v"), _centres(spark, d), 1).select("node_id", "cell")


def _ivf_sql(n: int) -> str:
    return f"{_W} {_CELLS}, iv AS (SELECT query_id, node_id, {sql_l2()} AS dist FROM nc JOIN qc USING (cell) JOIN b USING (node_id) JOIN q USING (query_id) WHERE nc.rank = 1 AND qc.rank <= {n}) {sql_top('iv', 10)}"


def _ivf(spark, d, n):
    c = _centres(spark, d)
    return cl.ivf_search(cl.ivf_build(vec_base(spark, d).select("node_id", "v"), c), c, vec_query(spark, d), 10, n)


@query("ivf_search_np4", _ivf_sql(4))
def ivf_search_np4(spark, d):
    return rounded(_ivf(spark, d, 4), "dist")


@query("ivf_search_all", KNN)
def ivf_search_all(spark, d):
    return rounded(_ivf(spark, d, 16), "dist")


@query("ivf_disk_np4", _ivf_sql(4))
def ivf_disk_np4(spark, d):
    from ..sources.storage import shared_folder

    c = _centres(spark, d)
    path = shared_folder(spark)
    cl.ivf_write(cl.ivf_build(vec_base(spark, d).select("node_id", "v"), c), path)
    lists = spark.read.schema("node_id long, v array<float>, cell int").parquet(path)
    return rounded(cl.ivf_search(lists, c, vec_query(spark, d), 10, 4), "dist")


@query("recall_at_k_ivf", f"{_W} {_CELLS}, {_TRUTH}, iv AS (SELECT query_id, node_id FROM nc JOIN qc USING (cell) JOIN tr USING (query_id, node_id) WHERE nc.rank = 1 AND qc.rank <= 4) SELECT query_id, round(count(iv.node_id) / 10.0, 6)::DOUBLE AS recall FROM tr LEFT JOIN iv USING (query_id, node_id) GROUP BY query_id")
def recall_ivf(spark, d):
    return recall_at_k(_ivf(spark, d, 4), knn_exact(vec_base(spark, d), vec_query(spark, d), 10), 10)


@query("two_home_assign", f"{_W} {_CELLS} SELECT node_id, cell, rank::INT AS rank FROM nc WHERE rank <= 2")
def two_home_assign(spark, d):
    from ..operators.shards import assign_two

    return assign_two(vec_base(spark, d).select("node_id", "v"), _centres(spark, d))


@query("shard_merge", f"""{_W} {_CELLS}, hm AS (SELECT node_id, cell, v FROM nc JOIN b USING (node_id) WHERE rank <= 2),
sk AS (SELECT x.cell, x.node_id AS u, y.node_id AS v, {sql_l2('x.v', 'y.v')} AS dd FROM hm x JOIN hm y ON x.cell = y.cell AND x.node_id <> y.node_id QUALIFY row_number() OVER (PARTITION BY x.cell, x.node_id ORDER BY dd, y.node_id) <= 5),
ed AS (SELECT u, v FROM sk UNION SELECT v, u FROM sk) SELECT u AS node_id, count(*) AS deg, sum(v)::BIGINT AS nbr_sum FROM ed GROUP BY u""")
def shard_merge(spark, d):
    from ..operators.shards import assign_two, shard_knn

    v = vec_base(spark, d).select("node_id", "v")
    g = shard_knn(v, stored(assign_two(v, _centres(spark, d))), 5)
    return g.groupBy(F.col("u").alias("node_id")).agg(F.count("*").alias("deg"), F.sum("v").alias("nbr_sum"))


@query("shard_merge_capped", f"""{_W} {_CELLS}, hm AS (SELECT node_id, cell, v FROM nc JOIN b USING (node_id) WHERE rank <= 2),
sk AS (SELECT x.cell, x.node_id AS u, y.node_id AS v, {sql_l2('x.v', 'y.v')} AS dd FROM hm x JOIN hm y ON x.cell = y.cell AND x.node_id <> y.node_id QUALIFY row_number() OVER (PARTITION BY x.cell, x.node_id ORDER BY dd, y.node_id) <= 5),
ed AS (SELECT u, v FROM sk UNION SELECT v, u FROM sk),
cp AS (SELECT u, v FROM ed QUALIFY row_number() OVER (PARTITION BY u ORDER BY md5('7,' || u || ',' || v), v) <= 8) SELECT u AS node_id, array_to_string(list(v ORDER BY v), ',') AS nbrs FROM cp GROUP BY u""")
def shard_merge_capped(spark, d):
    from ..operators.shards import assign_two, merge_shards, shard_knn

    v = vec_base(spark, d).select("node_id", "v")
    g = shard_knn(v, stored(assign_two(v, _centres(spark, d))), 5)
    lists = g.groupBy(F.col("u").alias("node_id")).agg(F.collect_list("v").alias("nbrs")).withColumn("level", F.lit(0))
    return merge_shards(lists, 8, 7).select("node_id", F.array_join(F.transform("nbrs", lambda x: x.cast("string")), ",").alias("nbrs"))


@query("peak_storage", f"""{_W} {_CELLS}, n AS (SELECT cell, count(*) AS n FROM nc WHERE rank <= 2 GROUP BY 1),
l AS (SELECT n * 256 + sum(n * 72) OVER (ORDER BY cell) AS held FROM n) SELECT max(held)::BIGINT AS sharded_peak, (SELECT count(*) * (256 + 72) FROM b)::BIGINT AS single_peak FROM l""")
def peak_storage(spark, d):
    from ..operators.shards import assign_two
    from ..operators.shards import peak_storage as peak

    return peak(stored(assign_two(vec_base(spark, d).select("node_id", "v"), _centres(spark, d))), 64, 18)
