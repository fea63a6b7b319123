"""Coarse clusters and the cluster-based indexes: in memory, on disk, and with vectors recomputed at query time.

At scale the list table is bucketed or partitioned by cell, so that a search reads probed lists only; centroids are k * dim
numbers and broadcast, in two levels when k is large.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.distance import l2sq
from ..functions.encoders import Encoder, encode
from .exact import Best, matrix, query_blocks, scan, top_k
from .pq import SCALE, assign, lloyd_fixed, to_fixed


def kmeans_fixed(vectors: DataFrame, k: int, rounds: int, sample: int = 1_000_000) -> DataFrame:
    """Centres (cell, centroid LONG of 1e-6) from the first k vectors by id, after `rounds` of exact integer Lloyd steps.

    More than `sample` vectors are thinned by hash of node_id.
    """
    n = vectors.count()
    few = vectors.where(F.pmod(F.xxhash64("node_id"), F.lit(-(-n // sample))) == 0) if n > sample else vectors
    points = few.select("node_id", F.lit(0).alias("sub"), to_fixed(F.col("v")).alias("x")).cache()
    first = points.orderBy("node_id").limit(k).withColumn("code", (F.row_number().over(Window.orderBy("node_id")) - 1).cast("int"))
    book = lloyd_fixed(points, first.select("sub", "code", F.col("x").alias("centroid")), rounds)
    return book.select(F.col("code").alias("cell"), "centroid")


def to_float(centres: DataFrame) -> DataFrame:
    return centres.select("cell", F.transform("centroid", lambda c: c / SCALE).alias("centroid"))


def kmeans_two_level(vectors: DataFrame, outer: int, inner: int, rounds: int = 3) -> tuple[DataFrame, DataFrame]:
    """(outer centres, inner centres with their outer cell): routing needs outer + inner distances instead of their product."""
    top = to_float(kmeans_fixed(vectors, outer, rounds))
    home = nearest_cells(vectors, top, 1).join(vectors, "node_id")
    parts = []
    for r in top.select("cell").collect():
        own = home.where(F.col("cell") == r["cell"]).select("node_id", "v")
        parts.append(to_float(kmeans_fixed(own, inner, rounds)).select(F.lit(r["cell"]).alias("outer"), "cell", "centroid"))
    low = parts[0]
    for p in parts[1:]:
        low = low.unionByName(p)
    return top, low


def nearest_cells(vectors: DataFrame, centres: DataFrame, n: int) -> DataFrame:
    """(node_id, v) -> node_id, cell, rank of the n nearest centres by (distance, cell); centres are broadcast."""
    d = vectors.crossJoin(F.broadcast(centres)).select("node_id", "cell", l2sq("v", "centroid").alias("dist"))
    best = F.slice(F.array_sort(F.collect_list(F.struct("dist", "cell"))), 1, n)
    return d.groupBy("node_id").agg(best.alias("b")).select("node_id", F.posexplode("b").alias("r", "c")).select("node_id", F.col("c.cell").alias("cell"), (F.col("r") + 1).alias("rank"))


def ivf_build(vectors: DataFrame, centres: DataFrame) -> DataFrame:
    """Inverted lists: cell, node_id, v."""
    return nearest_cells(vectors, centres, 1).join(vectors, "node_id").select("cell", "node_id", "v")


def ivf_write(lists: DataFrame, path: str) -> None:
    lists.repartition("cell").sortWithinPartitions("cell", "node_id").write.partitionBy("cell").parquet(path)


def probes(queries: DataFrame, centres: DataFrame, nprobe: int) -> DataFrame:
    q = queries.select(F.col("query_id").alias("node_id"), F.col("qv").alias("v"))
    return nearest_cells(q, centres, nprobe).select(F.col("node_id").alias("query_id"), "cell")


def _scan_lists(qid: np.ndarray, q: np.ndarray, asked: dict[int, np.ndarray], k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best = Best(qid, k)
        for b in batches:
            cell, ids, x = b.column(0).to_numpy(), b.column(1).to_numpy(), matrix(b.column(2))
            for c in np.unique(cell).tolist():
                if c in asked:
                    mine = cell == c
                    scan(best, q, ids[mine], x[mine], "l2", asked=asked[c])
        yield best.rows()

    return run


def ivf_search(lists: DataFrame, centres: DataFrame, queries: DataFrame, k: int, nprobe: int) -> DataFrame:
    """Scan the centres, then the nprobe nearest lists, each by those who probe it. With lists read from partitioned files,
    pruning reads probed ones only. A task holds a block of queries and leaves k rows for each."""
    queries = queries.where("qv is not null").select(F.col("query_id").cast("long").alias("query_id"), "qv")
    first = queries.first()
    if first is None:
        return top_k(lists.select(F.lit(0).cast("long").alias("query_id"), "node_id", F.lit(0.0).alias("dist")).limit(0), k)
    out = None
    for qid, q in query_blocks(queries, len(first["qv"])):
        o = np.argsort(qid, kind="stable")
        qid, q = qid[o], q[o]
        rows = queries.sparkSession.createDataFrame(pa.table({"query_id": qid, "qv": list(q)}))
        p = probes(rows, centres, nprobe).toArrow()
        cell, at = p.column("cell").to_numpy(), np.searchsorted(qid, p.column("query_id").to_numpy())
        asked = {int(c): at[cell == c] for c in np.unique(cell)}
        near = lists.where("v is not null").where(F.col("cell").isin(list(asked))).select(F.col("cell").cast("int").alias("cell"), F.col("node_id").cast("long").alias("node_id"), "v")
        part = near.mapInArrow(_scan_lists(qid, q, asked, k), "query_id long, node_id long, dist double")
        out = part if out is None else out.unionByName(part)
    return top_k(out, k)


def ivf_recompute_search(assignment: DataFrame, centres: DataFrame, objects: DataFrame, encoder: Encoder, queries: DataFrame, k: int, nprobe: int) -> tuple[DataFrame, DataFrame]:
    """Only centres and the cell of each object are stored; members of probed lists are encoded now.

    assignment(node_id, cell), objects(node_id, text) -> (result, counts per query: query_id, n_recomputed).
    """
    p = probes(queries, centres, nprobe)
    hits = assignment.join(F.broadcast(p), "cell").select("query_id", "node_id")
    wanted = objects.join(hits.select("node_id").distinct(), "node_id", "left_semi")
    fresh = encode(wanted, encoder, "node_id")
    j = hits.join(fresh, "node_id").join(F.broadcast(queries), "query_id")
    return top_k(j.select("query_id", "node_id", l2sq("v", "qv").alias("dist")), k), hits.groupBy("query_id").agg(F.count("*").alias("n_recomputed"))


def tune_nprobe(search, truth: DataFrame, k: int, target: float, grid: list[int]) -> int | None:
    """The smallest nprobe of the grid whose mean recall reaches the target."""
    from .measures import mean_recall

    return next((n for n in sorted(grid) if mean_recall(search(n), truth, k) >= target), None)


__all__ = ["assign", "ivf_build", "ivf_recompute_search", "ivf_search", "ivf_write", "kmeans_fixed", "kmeans_two_level", "nearest_cells", "probes", "to_float", "tune_nprobe"]
