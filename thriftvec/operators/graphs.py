"""Proximity graphs as edge tables: base graph, hubs, pruning rules, packing, reachability and distributions.

Edges are (u, v, dist), directed. Random choices are hashes of (seed, u, v), so a retried task makes the same graph.
Per-node limits are window top-k, which Spark pushes below the shuffle; hubs are a bounded share of nodes.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .exact import knn_graph


def symmetric(edges: DataFrame) -> DataFrame:
    """Every edge in both directions, once."""
    back = edges.select(F.col("v").alias("u"), F.col("u").alias("v"), "dist")
    return edges.select("u", "v", "dist").unionByName(back).groupBy("u", "v").agg(F.min("dist").alias("dist"))


def base_graph(vectors: DataFrame, k: int) -> DataFrame:
    """Exact neighbours of every node, symmetrised."""
    return symmetric(knn_graph(vectors, k))


def nearest_edges(edges: DataFrame, cap) -> DataFrame:
    """The `cap` (number or column) nearest edges of each node by (dist, v)."""
    w = Window.partitionBy("u").orderBy("dist", "v")
    return edges.withColumn("_r", F.row_number().over(w)).where(F.col("_r") <= cap).drop("_r")


def degrees(edges: DataFrame) -> DataFrame:
    """node_id, out_deg, in_deg."""
    both = edges.select(F.col("u").alias("node_id"), F.lit(1).alias("o"), F.lit(0).alias("i")).unionByName(edges.select(F.col("v").alias("node_id"), F.lit(0).alias("o"), F.lit(1).alias("i")))
    return both.groupBy("node_id").agg(F.sum("o").alias("out_deg"), F.sum("i").alias("in_deg"))


def hubs(edges: DataFrame, beta: float, by: str = "total") -> DataFrame:
    """node_id of the ceil(beta * N) nodes of highest degree, ties by smaller id.

    No global sort: an exact count by degree finds the threshold, and only the threshold's own class is ranked.
    """
    size = {"total": F.col("out_deg") + F.col("in_deg"), "out": F.col("out_deg"), "in": F.col("in_deg")}[by]
    d = degrees(edges).select("node_id", size.alias("deg"))
    counts = sorted(((r["deg"], r["count"]) for r in d.groupBy("deg").count().collect()), reverse=True)
    want = math.ceil(round(beta * sum(c for _, c in counts), 9))
    seen, limit, rest = 0, None, 0
    for deg, c in counts:
        if seen + c >= want:
            limit, rest = deg, want - seen
            break
        seen += c
    if limit is None or want == 0:
        return d.select("node_id").limit(0)
    tie = d.where(F.col("deg") == limit).select("node_id").orderBy("node_id").limit(rest)
    return d.where(F.col("deg") > limit).select("node_id").unionByName(tie)


def hub_prune(edges: DataFrame, candidates: DataFrame, cap: int, low: int | None = None, beta: float = 0.02, by: str = "total") -> DataFrame:
    """Hub-preserving pruning in set form.

    edges: the full graph, whose degrees choose the hubs; candidates (u, v, dist): what each node may link to (all
    original edges, or exact neighbours). Hubs keep up to `cap` of them, others `low` (default cap / 5); links are
    made both ways, and only then is every node cut back to its `cap` nearest.
    """
    low = low or max(1, cap // 5)
    h = hubs(edges, beta, by).withColumn("hub", F.lit(True))
    mine = candidates.join(h, candidates["u"] == h["node_id"], "left").drop("node_id")
    kept = nearest_edges(mine, F.when(F.coalesce("hub", F.lit(False)), cap).otherwise(low)).select("u", "v", "dist")
    return nearest_edges(symmetric(kept), cap)


def edge_rank(seed: int):
    """A number in 0..2^32-1 of an edge, from md5."""
    return F.conv(F.substring(F.md5(F.concat_ws(",", F.lit(str(seed)), F.col("u").cast("string"), F.col("v").cast("string"))), 1, 8), 16, 10).cast("long")


def random_prune(edges: DataFrame, keep: float, seed: int = 7, undirected: bool = False) -> DataFrame:
    """Keep about the share `keep` of the edges, each by its own hash."""
    e = edges
    if undirected:
        lo = edges.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v"), "dist").dropDuplicates(["u", "v"])
        return symmetric(lo.where(edge_rank(seed) < int(keep * (1 << 32))))
    return e.where(edge_rank(seed) < int(keep * (1 << 32)))


def degree_cap(edges: DataFrame, cap: int, how: str = "cut", vectors: DataFrame | None = None) -> DataFrame:
    """Smaller degree limit: `cut` afterwards, or `rebuild` with the small limit during construction."""
    if how == "cut":
        return nearest_edges(edges, cap)
    return nearest_edges(symmetric(knn_graph(vectors, cap)), cap)


def diverse(edges: DataFrame, vectors: DataFrame, cap: int, relax: float = 1.0) -> DataFrame:
    """Occlusion rule: a neighbour stays unless an already kept one is nearer to it than the node is (times relax)."""
    import numpy as np
    import pandas as pd

    x = edges.join(vectors.select(F.col("node_id").alias("v"), F.col("v").alias("x")), "v")

    def pick(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["dist", "v"], ignore_index=True)
        m = np.array(pdf["x"].tolist(), float)
        kept: list[int] = []
        for i in range(len(pdf)):
            if len(kept) == cap:
                break
            if all(((m[i] - m[j]) ** 2).sum() * relax > pdf["dist"][i] for j in kept):
                kept.append(i)
        return pdf.loc[kept, ["u", "v", "dist"]]

    return x.select("u", "v", "dist", "x").groupBy("u").applyInPandas(pick, "u long, v long, dist double")


def average_degree(edges: DataFrame) -> float:
    e, n = edges.agg(F.count("*"), F.countDistinct("u")).first()
    return e / n if n else 0.0


def calibrate(prune, lo: float, hi: float, target: float, steps: int = 8, whole: bool = False):
    """Bisection on a pruning knob for an average degree: (knob, graph)."""
    for _ in range(steps):
        mid = (lo + hi) // 2 if whole else (lo + hi) / 2
        g = prune(mid)
        lo, hi = (mid, hi) if average_degree(g) < target else (lo, mid)
        if whole and hi - lo <= 1:
            break
    return hi, prune(hi)


def degree_hist(edges: DataFrame) -> DataFrame:
    """deg, nodes, share of nodes with at most that out-degree."""
    d = degrees(edges).groupBy(F.col("out_deg").alias("deg")).agg(F.count("*").alias("nodes"))
    w = Window.orderBy("deg").rowsBetween(Window.unboundedPreceding, 0)
    total = d.agg(F.sum("nodes").alias("t"))
    return d.withColumn("run", F.sum("nodes").over(w)).crossJoin(total).select("deg", "nodes", F.round(F.col("run") / F.col("t"), 6).alias("cdf"))


def access_hist(trace: DataFrame, edges: DataFrame, queries: int) -> DataFrame:
    """trace(query_id, node_id) -> degree class (log2), nodes, mean share of queries that visit a node of the class."""
    d = degrees(edges).select("node_id", F.floor(F.log2(F.greatest(F.col("out_deg"), F.lit(1)))).cast("int").alias("class"))
    seen = trace.select("query_id", "node_id").distinct().groupBy("node_id").agg(F.count("*").alias("n"))
    return d.join(seen, "node_id", "left").groupBy("class").agg(F.count("*").alias("nodes"), F.round(F.avg(F.coalesce("n", F.lit(0))) / queries, 6).alias("visit_share"))


def to_csr(edges: DataFrame, shard=None) -> DataFrame:
    """Compressed sparse rows: one row per shard with first node, offsets and neighbours (ids ascending by node, dist)."""
    s = shard if shard is not None else F.lit(0)
    lists = edges.groupBy(s.alias("shard"), "u").agg(F.transform(F.array_sort(F.collect_list(F.struct("dist", "v"))), lambda x: x["v"]).alias("nbrs"))
    rows = F.array_sort(F.collect_list(F.struct("u", "nbrs")))
    g = lists.groupBy("shard").agg(rows.alias("r"))
    nodes = F.transform("r", lambda x: x["u"])
    size = F.transform("r", lambda x: F.size(x["nbrs"]))
    off = F.transform(F.sequence(F.lit(0), F.size(size)), lambda i: F.aggregate(F.slice(size, 1, i), F.lit(0), lambda a, b: a + b))
    return g.select("shard", nodes.alias("nodes"), off.alias("offsets"), F.flatten(F.transform("r", lambda x: x["nbrs"])).alias("nbrs"))


def adjacency(edges: DataFrame) -> DataFrame:
    """node_id, start (offset in the packed neighbour array in id order), deg, nbrs by (dist, v).

    Offsets are a running sum inside blocks of ids, added to block totals, so no task sees all nodes.
    """
    a = edges.groupBy(F.col("u").alias("node_id")).agg(F.transform(F.array_sort(F.collect_list(F.struct("dist", "v"))), lambda x: x["v"]).alias("nbrs"))
    a = a.withColumn("deg", F.size("nbrs").cast("long")).withColumn("_b", F.floor(F.col("node_id") / 4096))
    inside = F.sum("deg").over(Window.partitionBy("_b").orderBy("node_id").rowsBetween(Window.unboundedPreceding, -1))
    blocks = a.groupBy("_b").agg(F.sum("deg").alias("_t"))
    before = blocks.select("_b", F.coalesce(F.sum("_t").over(Window.orderBy("_b").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_s"))
    return a.withColumn("_i", F.coalesce(inside, F.lit(0))).join(before, "_b").select("node_id", (F.col("_i") + F.col("_s")).alias("start"), "deg", "nbrs")


def from_csr(csr: DataFrame) -> DataFrame:
    """Edges (shard, u, v) of to_csr."""
    d = csr.select("shard", "offsets", "nbrs", F.posexplode("nodes").alias("i", "u"))
    part = F.slice("nbrs", F.element_at("offsets", F.col("i") + 1) + 1, F.element_at("offsets", F.col("i") + 2) - F.element_at("offsets", F.col("i") + 1))
    return d.select("shard", "u", F.explode(part).alias("v"))


def reachable(edges: DataFrame, start: DataFrame, max_rounds: int = 1000) -> DataFrame:
    """start(node_id) -> node_id, hops of all nodes reached; each round joins the frontier and drops what is known."""
    from ..sources.storage import stored

    seen = stored(start.select("node_id", F.lit(0).alias("hops")))
    front = seen
    for r in range(1, max_rounds + 1):
        new = front.select("node_id").join(edges, F.col("node_id") == F.col("u")).select(F.col("v").alias("node_id")).distinct()
        front = stored(new.join(seen, "node_id", "left_anti").select("node_id", F.lit(r).alias("hops")))
        if not front.limit(1).count():
            break
        seen = stored(seen.unionByName(front)) if r % 8 == 0 else seen.unionByName(front)
    return seen


def coorder_graph(lineitem: DataFrame) -> DataFrame:
    """Parts that share an order: u, v, w = number of shared orders, both directions."""
    p = lineitem.select("l_orderkey", "l_partkey").distinct()
    a, b = p.select("l_orderkey", F.col("l_partkey").alias("u")), p.select("l_orderkey", F.col("l_partkey").alias("v"))
    return a.join(b, "l_orderkey").where("u <> v").groupBy("u", "v").agg(F.count("*").alias("w"))
