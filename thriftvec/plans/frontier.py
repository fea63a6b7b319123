"""Interleaved search as relational supersteps: explainable, spillable, batched over all queries of a round.

State is one row per query: the exact queue (dist, node, visited), the cheap queue and the set of nodes encoded so far. One
round picks the closest unvisited node of each query, joins its neighbours and their codes, chooses the best share of the
cheap queue, encodes the distinct objects that all queries want, and merges. The state is written after each round, which
cuts lineage and survives lost executors; the driver learns only whether any query goes on.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.distance import l2sq
from ..functions.encoders import encode
from ..operators import pq as pqm
from ..operators.search import Found, VectorIndex
from ..sources.storage import stored


def _cheap(index: VectorIndex, pairs: DataFrame, queries: DataFrame) -> DataFrame:
    """pairs(query_id, node_id) -> with d, by the query's look-up table and the node's code bytes."""
    book = pqm.codebook_array(index.codebook)
    m, ks, _ = book.shape
    lut = pqm.adc_lut(queries, index.codebook, m, index.meta["dim"]).groupBy("query_id").agg(F.map_from_entries(F.collect_list(F.struct((F.col("sub") * ks + F.col("code")).alias("k"), "d"))).alias("lut"))
    j = pairs.join(index.codes, "node_id").join(F.broadcast(lut), "query_id")
    byte = lambda i: F.conv(F.hex(F.substring("code", i + 1, 1)), 16, 10).cast("int")
    terms = [F.element_at("lut", F.lit(i * ks) + byte(i)) for i in range(m)]
    return j.select("query_id", "node_id", sum(terms[1:], terms[0]).alias("d"))


def search(index: VectorIndex, queries: DataFrame, k: int = 3, ef: int = 60, alpha: float | None = 0.5, max_rounds: int = 500) -> Found:
    """queries(query_id, qv) -> the same result as the kernel with one batch per step. alpha None: recompute all."""
    if ef < k:
        raise ValueError("ef must be at least k")
    queries = stored(queries.select("query_id", "qv"))
    adj = index.adjacency.select("node_id", "nbrs")
    entry = adj.orderBy(F.desc(F.size("nbrs")), "node_id").limit(1).select(F.col("node_id").alias("entry"))

    def exact(want: DataFrame) -> DataFrame:
        """(query_id, node_id) -> dist; each distinct object is encoded once for all queries."""
        obj = index.objects.select("node_id", "text").join(want.select("node_id").distinct(), "node_id", "left_semi")
        v = encode(obj, index.encoder, "node_id")
        return want.join(v, "node_id").join(F.broadcast(queries), "query_id").select("query_id", "node_id", l2sq("v", "qv").alias("dist"))

    first = exact(queries.select("query_id").crossJoin(F.broadcast(entry)).withColumnRenamed("entry", "node_id"))
    none = F.expr("cast(array() as array<struct<d: double, node: bigint>>)")
    state = stored(first.select("query_id", F.array(F.struct("dist", F.col("node_id").alias("node"), F.lit(False).alias("visited"))).alias("eq"), none.alias("aq"), F.array("node_id").alias("computed"), F.array("node_id").alias("seen"), F.lit(1).cast("long").alias("n_exact"), F.lit(0).cast("long").alias("steps")))
    unseen = lambda c: F.filter(c, lambda x: ~x["visited"])
    for _ in range(max_rounds):
        live = state.where(F.size(unseen(F.col("eq"))) > 0)
        if not live.limit(1).count():
            break
        pick = live.select("query_id", "seen", F.array_min(unseen(F.col("eq")))["node"].alias("u"))
        new = pick.join(adj, F.col("u") == F.col("node_id")).select("query_id", F.explode(F.array_except("nbrs", "seen")).alias("node_id"))
        new = stored(new)
        if alpha is None:
            offered = new.groupBy("query_id").agg(F.collect_list("node_id").alias("fresh")).withColumn("add", none)
        else:
            offered = _cheap(index, new, queries).groupBy("query_id").agg(F.collect_list("node_id").alias("fresh"), F.collect_list(F.struct("d", F.col("node_id").alias("node"))).alias("add"))
        s = live.join(pick.select("query_id", "u"), "query_id").join(offered, "query_id", "left")
        s = s.withColumn("fresh", F.coalesce("fresh", F.expr("cast(array() as array<bigint>)"))).withColumn("aq", F.array_sort(F.concat("aq", F.coalesce("add", none))))
        share = F.ceil(F.round(F.lit(alpha or 1.0) * F.size("aq"), 9)).cast("int")
        chosen = F.col("fresh") if alpha is None else F.array_except(F.transform(F.slice("aq", F.lit(1), F.greatest(share, F.lit(0))), lambda x: x["node"]), F.col("computed"))
        s = stored(s.withColumn("chosen", chosen).withColumn("eq", F.transform("eq", lambda x: F.struct(x["dist"].alias("dist"), x["node"].alias("node"), (x["visited"] | (x["node"] == F.col("u"))).alias("visited")))))
        got = exact(s.select("query_id", F.explode("chosen").alias("node_id"))).groupBy("query_id").agg(F.collect_list(F.struct("dist", F.col("node_id").alias("node"), F.lit(False).alias("visited"))).alias("got"))
        s = s.join(got, "query_id", "left")
        merged = F.slice(F.array_sort(F.concat("eq", F.coalesce("got", F.filter("eq", lambda x: F.lit(False))))), 1, ef)
        s = s.select("query_id", merged.alias("eq"), "aq", F.concat("computed", "chosen").alias("computed"), F.concat("seen", "fresh").alias("seen"), (F.col("n_exact") + F.size("chosen")).alias("n_exact"), (F.col("steps") + 1).alias("steps"))
        state = stored(s.unionByName(state.where(F.size(unseen(F.col("eq"))) == 0)))
    res = state.select("query_id", F.posexplode(F.slice("eq", 1, k)).alias("r", "x")).select("query_id", (F.col("r") + 1).alias("rank"), F.col("x.node").alias("node_id"), F.col("x.dist").alias("dist"))
    stats = state.select("query_id", F.col("steps").alias("n_steps"), "n_exact", F.col("steps").alias("n_batches"), F.col("n_exact").alias("n_encoded"))
    return Found(res, stats)
