"""Sharded construction under a storage peak: every object joins the shards of its two nearest centres; shard graphs are
built one group at a time from vectors that live only in the task, and merged by node."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.encoders import Encoder
from .clusters import nearest_cells
from .graphs import nearest_edges, symmetric
from .kernels import layered_build


def assign_two(vectors: DataFrame, centres: DataFrame) -> DataFrame:
    """node_id, cell, rank (1, 2): ids only, vectors stay behind."""
    return nearest_cells(vectors, centres, 2)


def build_shards(objects: DataFrame, homes: DataFrame, encoder: Encoder, cap: int = 18, ef: int = 100, seed: int = 7, rule: str = "diverse") -> DataFrame:
    """objects(node_id, text), homes(node_id, cell) -> cell, node_id, level, nbrs; a task encodes, links and forgets one shard."""

    def one(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("node_id", ignore_index=True)
        ids = pdf["node_id"].to_numpy()
        g = layered_build(ids, encoder.encode(pdf["text"].tolist()), cap, ef, seed, rule)
        lists = [ids[[v for _, v in sorted((d, v) for v, d in a.items())]].tolist() if a else [] for a in g.layers[0]]
        return pd.DataFrame({"cell": pdf["cell"], "node_id": ids, "level": g.levels.astype(np.int32), "nbrs": lists})

    return homes.select("node_id", "cell").join(objects.select("node_id", "text"), "node_id").groupBy("cell").applyInPandas(one, "cell int, node_id long, level int, nbrs array<long>")


def shard_knn(vectors: DataFrame, homes: DataFrame, k: int) -> DataFrame:
    """Deterministic shard graphs: exact k nearest within each cell, both directions: u, v, dist."""
    from ..functions.distance import l2sq

    a = homes.select("node_id", "cell").join(vectors, "node_id")
    b = a.select("cell", F.col("node_id").alias("w"), F.col("v").alias("x"))
    d = a.join(b, "cell").where("node_id <> w").select("cell", F.col("node_id").alias("u"), F.col("w").alias("v"), l2sq("v", "x").alias("dist"))
    r = d.withColumn("r", F.row_number().over(Window.partitionBy("cell", "u").orderBy("dist", "v"))).where(F.col("r") <= k)
    return symmetric(r.select("u", "v", "dist"))


def merge_shards(graphs: DataFrame, cap: int, seed: int = 7) -> DataFrame:
    """(node_id, level, nbrs) of all shards -> level = highest, lists united, a hash-chosen part beyond the cap dropped."""
    rank = lambda v: F.md5(F.concat_ws(",", F.lit(str(seed)), F.col("node_id").cast("string"), v.cast("string")))
    g = graphs.groupBy("node_id").agg(F.max("level").alias("level"), F.array_distinct(F.flatten(F.collect_list("nbrs"))).alias("all"))
    pick = F.transform(F.slice(F.array_sort(F.transform("all", lambda v: F.struct(rank(v).alias("h"), v.alias("v")))), 1, cap), lambda s: s["v"])
    return g.select("node_id", "level", F.array_sort(pick).alias("nbrs"))


def merge_diverse(edges: DataFrame, vectors: DataFrame, cap: int) -> DataFrame:
    """Alternative merge: keep neighbours that no kept one hides, instead of a random part."""
    from .graphs import diverse

    return diverse(edges, vectors, cap)


def cut_by_distance(edges: DataFrame, cap: int) -> DataFrame:
    return nearest_edges(edges, cap)


def build_ledger(homes: DataFrame, dim: int, avg_degree: int) -> DataFrame:
    """Bytes alive while shards are built one after another: cell, n, vectors, graph (its own), held (peak up to its turn)."""
    n = homes.groupBy("cell").agg(F.count("*").alias("n"))
    w = Window.orderBy("cell").rowsBetween(Window.unboundedPreceding, 0)
    return n.select("cell", "n", (F.col("n") * 4 * dim).alias("vectors"), (F.col("n") * 4 * avg_degree).alias("graph")).withColumn("held", F.col("vectors") + F.sum("graph").over(w))


def peak_storage(homes: DataFrame, dim: int, avg_degree: int) -> DataFrame:
    """The peak of the ledger beside an unsharded build's: sharded_peak, single_peak."""
    led = build_ledger(homes, dim, avg_degree)
    one = homes.select("node_id").distinct().agg((F.count("*") * (4 * dim + 4 * avg_degree)).alias("single_peak"))
    return led.agg(F.max("held").alias("sharded_peak")).crossJoin(one)
