"""The index: packed neighbour lists and small codes, no vectors; exact distances are computed again at query time.

Two executors with the same kernel. `local` ships all nodes to tasks of queries, after a size check. `sharded` routes queries to
the nearest shards and co-groups them with the shards' nodes, so a task holds one shard; results of all shards are
merged by one window top-k. Text is read only for the objects of the shards a query visits.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import asdict, dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.encoders import Encoder, Meter, encode
from ..plans.planner import SearchSpec, choose
from ..sources.storage import stored
from . import pq as pqm
from .clusters import kmeans_fixed, nearest_cells, to_float
from .exact import knn_exact, matrix, nearest_rows, top_k
from .graphs import adjacency, base_graph, degrees, hub_prune
from .kernels import Shard, _exact, cheap_then_exact, traverse, waves

OUT = "kind string, query_id long, node_id long, dist double, step long, a long, b long, c long"
_FIELDS = pa.schema([("kind", pa.string()), ("query_id", pa.int64()), ("node_id", pa.int64()), ("dist", pa.float64()), ("step", pa.int64()), ("a", pa.int64()), ("b", pa.int64()), ("c", pa.int64())])
BLOCK = 8192  # nodes whose distances are taken at once


def _shard(t: pa.Table) -> Shard:
    lists = [np.asarray(x or [], np.int64) for x in t.column("nbrs").to_pylist()]
    codes = t.column("code").to_pylist()
    codes = np.frombuffer(b"".join(codes), np.uint8).reshape(len(codes), -1) if codes and codes[0] is not None else None
    vec = t.column("v").to_pylist() if "v" in t.column_names else None
    return Shard.build(t.column("node_id").to_numpy(), lists, codes=codes, vectors=vec, texts=t.column("text").to_pylist())


def fold(x: np.ndarray, parts: int = 4) -> np.ndarray:
    """Vectors of a hashing encoder at a quarter of the width: coordinates that the narrow one joins are added."""
    y = x.reshape(len(x), parts, -1).sum(1, dtype=np.float64)
    n = np.sqrt((y * y).sum(1, keepdims=True))
    return np.divide(y, n, out=np.zeros_like(y), where=n > 0)


def blend(g: Shard, book: np.ndarray, share: float = 0.25) -> np.ndarray:
    """Decoded vectors drawn towards the mean of their neighbours' ones."""
    dec = np.concatenate([book[s][g.codes[:, s]] for s in range(len(book))], 1).astype(np.float64)
    out = dec.copy()
    for u in range(len(g.ids)):
        nb = g.of(u)
        if len(nb):
            out[u] = (1 - share) * dec[u] + share * dec[nb].mean(0)
    return out


def _together(g: Shard, start: int, queries: pa.Table, spec: SearchSpec, encoder: Encoder, fetch) -> pa.Table:
    """Queries whose queue has room for all nodes: they visit the same nodes, so a node's vector is fetched once for all of
    them. Each is counted as if it had asked alone; a round's new nodes make one encoder call, or calls of batch_target."""
    parts = []
    for w in waves(g.offsets, g.nbrs, start) if start >= 0 and spec.k else []:
        n = spec.batch_target or len(w)
        parts += [w[a : a + n] for a in range(0, len(w), n)]
    x = np.concatenate([fetch(p) for p in parts]) if parts else np.empty((0, 0), np.float32)
    ids = g.ids[np.concatenate(parts)] if parts else np.empty(0, np.int64)
    out = []
    for qid, q in zip(queries.column("query_id").to_pylist(), matrix(queries.column("qv")), strict=True):
        d = np.concatenate([np.empty(0), *(_exact(spec.metric, q, x[a : a + BLOCK]) for a in range(0, len(x), BLOCK))])
        r = nearest_rows(d, ids, spec.k)
        zero = np.zeros(len(r), np.int64)
        out.append(pa.table([pa.array(["r"] * len(r), pa.string()), pa.array(np.full(len(r), qid)), pa.array(ids[r]), pa.array(d[r]), *[pa.array(zero)] * 4], schema=_FIELDS))
        out.append(pa.table([[v] for v in ("s", qid, None, None, len(x), len(x), len(parts), encoder.meter.objects)], schema=_FIELDS))
    return pa.concat_tables(out).combine_chunks() if out else _FIELDS.empty_table()


def run_queries(nodes: pa.Table, queries: pa.Table, spec: SearchSpec, encoder: Encoder, book: np.ndarray | None, entry: int | None, trace: bool) -> pa.Table:
    """The kernel over one shard's nodes for all queries given; rows r (result), s (counts), t (trace)."""
    g = _shard(nodes)
    start = g.hub() if entry is None or entry not in set(g.ids.tolist()) else int(np.searchsorted(g.ids, entry))
    encoder = replace(encoder, meter=Meter(), held={})
    rows: list[tuple] = []

    def fetch(at: np.ndarray) -> np.ndarray:
        have = g.vectors
        if spec.mode == "stored" and have is not None:
            return np.array([have[i] for i in at], np.float32)
        miss = [i for i in at.tolist() if have is None or have[i] is None]
        got = dict(zip(miss, encoder.encode([g.texts[i] for i in miss]), strict=True)) if miss else {}
        return np.array([got[i] if i in got else have[i] for i in at.tolist()], np.float32)

    if spec.ef >= len(g.ids) and not trace and (spec.mode in ("stored", "recompute") or spec.mode == "interleaved" and spec.alpha >= 1):
        return _together(g, start, queries, spec, encoder, fetch)
    if spec.approx == "small_encoder":
        # a quarter-width encoder; what an index would store of it, in half precision
        small = fold(encoder.encode(g.texts)).astype(np.float16).astype(np.float64)
        encoder.meter.objects = 0
    elif spec.approx == "neighbour_mean":
        blended = blend(g, book)
    for qid, q in zip(queries.column("query_id").to_pylist(), matrix(queries.column("qv")), strict=True):
        before = encoder.meter.objects
        cheap = None
        if spec.approx == "small_encoder":
            cheap = lambda at, f=fold(q[None])[0]: ((small[at] - f) ** 2).sum(1)
        elif spec.approx == "neighbour_mean":
            cheap = lambda at, q=q: ((blended[at] - q) ** 2).sum(1)
        elif book is not None and g.codes is not None:
            table = pqm.adc_table(q.astype(np.float32), book)
            cheap = lambda at, table=table: pqm.adc(table, g.codes[at])
        if spec.mode in ("pq", "rerank"):
            res, t = cheap_then_exact(g, q, start, spec.k, spec.ef, cheap, fetch, spec.rerank_n if spec.mode == "rerank" else 0, spec.metric)
        else:
            res, t = traverse(g, q, start, spec.k, spec.ef, fetch, metric=spec.metric, alpha=spec.alpha if spec.mode == "interleaved" else None, cheap=cheap, alpha_base=spec.alpha_base, min_fresh=spec.min_fresh, aq_cap=spec.aq_cap, batch_target=spec.batch_target)
        rows += [("r", qid, n, float(d), 0, 0, 0, 0) for d, n in res]
        rows.append(("s", qid, None, None, len(t.steps), t.exact, len(t.batches), encoder.meter.objects - before))
        if trace:
            rows += [("t", qid, n, None, s, c, e, b) for s, n, c, e, b in t.steps]
    cols = list(zip(*rows, strict=True)) if rows else [[]] * 8
    return pa.table([pa.array(c, f.type) for c, f in zip(cols, _FIELDS, strict=True)], schema=_FIELDS)


@dataclass
class Found:
    """Result (query_id, rank, node_id, dist), counts per query, and the trace where asked for."""

    result: DataFrame
    stats: DataFrame
    trace: DataFrame | None = None


@dataclass
class VectorIndex:
    """adjacency(shard, node_id, nbrs), codes(node_id, code), codebook, centres of shards, and the objects they stand for."""

    spark: SparkSession
    objects: DataFrame
    adjacency: DataFrame
    codes: DataFrame | None
    codebook: DataFrame | None
    encoder: Encoder
    meta: dict
    centres: DataFrame | None = None
    vectors: DataFrame | None = None
    edges: DataFrame | None = None

    @classmethod
    def build(cls, objects: DataFrame, encoder: str | Encoder = "hash_unit:256", k: int = 9, M: int = 60, m: int | None = None, beta: float = 0.02, shards: int = 1, pq_ratio: float = 64, ks: int = 64, seed: int = 7, prune: bool = True, keep_vectors: bool = False, ef: int = 100) -> VectorIndex:
        """objects(node_id, text). One shard: exact k-neighbour graph, pruned; more: two-home shards built apart and merged."""
        spark = objects.sparkSession
        enc = Encoder.parse(encoder) if isinstance(encoder, str) else encoder
        vec = stored(encode(objects, enc, "node_id"))
        m_sub, _ = pqm.pq_shape(enc.width, pq_ratio)
        book = pqm.pq_train(vec, m_sub, enc.width, ks=ks, iters=2)
        codes = stored(pqm.pq_encode(vec, book))
        centres = None
        if shards > 1:
            from .shards import assign_two, build_shards, merge_shards

            centres = stored(to_float(kmeans_fixed(vec, shards, 2)))
            home = stored(assign_two(vec, centres))
            graph = stored(merge_shards(build_shards(objects, home, enc, cap=min(M, 2 * k), ef=ef, seed=seed), M, seed))
            own = home.where("rank = 1").select("node_id", F.col("cell").alias("shard"))
            adj = graph.select("node_id", "nbrs").join(own, "node_id")
            edges = graph.select(F.col("node_id").alias("u"), F.explode("nbrs").alias("v"))
        else:
            full = stored(base_graph(vec, k))
            edges = stored(hub_prune(full, full, M, m, beta)) if prune else full
            adj = adjacency(edges).select("node_id", "nbrs").withColumn("shard", F.lit(0))
        meta = {"dim": enc.width, "encoder_id": enc.id, "m_sub": m_sub, "ks": ks, "M": M, "m": m or M // 5, "beta": beta, "shards": shards, "seed": seed, "metric": "l2", "format_version": 1}
        return cls(spark, objects, stored(adj), codes, book, enc, meta, centres, vec if keep_vectors else None, edges)

    def rows(self, vectors: DataFrame | None) -> DataFrame:
        """All a traversal reads, by shard."""
        r = self.objects.select("node_id", "text").join(self.adjacency, "node_id", "left").withColumn("shard", F.coalesce("shard", F.lit(0)))
        r = r.join(self.codes, "node_id", "left") if self.codes is not None else r.withColumn("code", F.lit(None).cast("binary"))
        return r.join(vectors.select("node_id", "v"), "node_id", "left") if vectors is not None else r

    def search(self, queries: DataFrame, executor: str = "auto", deleted: DataFrame | None = None, buffer: DataFrame | None = None, cache: DataFrame | None = None, predicate: Column | None = None, return_trace: bool = False, entry: int | None = None, **spec) -> Found:
        """queries(query_id, text) or (query_id, qv).

        deleted(node_id): traversed, never returned. buffer(node_id, text): scanned exactly and merged. cache(node_id, v):
        vectors that need no encoding. predicate over the objects' columns: post-filter of the ef nearest.
        """
        s = SearchSpec(**spec)
        if "qv" not in queries.columns:
            queries = encode(queries, self.encoder, "query_id").withColumnRenamed("v", "qv")
        queries = queries.select(F.col("query_id").cast("long").alias("query_id"), "qv")
        wide = replace(s, k=s.ef) if deleted is not None or predicate is not None else s
        vec = self.vectors if s.mode == "stored" else cache
        rows = self.rows(vec)
        book = pqm.codebook_array(self.codebook) if self.codebook is not None else None
        n = self.objects.count()
        how = choose(executor, n * 4096, self.meta["shards"])
        enc = self.encoder
        if how == "local":
            shipped = self.spark.sparkContext.broadcast(rows.toArrow().combine_chunks())

            def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
                for b in batches:
                    if b.num_rows:
                        yield from run_queries(shipped.value, pa.Table.from_batches([b]), wide, enc, book, entry, return_trace).to_batches()

            out = queries.repartition(self.spark.sparkContext.defaultParallelism).mapInArrow(run, OUT)
        else:
            q = queries.select(F.col("query_id").alias("node_id"), F.col("qv").alias("v"))
            routed = nearest_cells(q, self.centres, s.nprobe).select(F.col("node_id").alias("query_id"), F.col("cell").alias("shard")).join(queries, "query_id") if self.centres is not None else queries.withColumn("shard", F.lit(0))

            def group(key, left, right):
                return run_queries(right, left, wide, enc, book, entry, return_trace) if left.num_rows and right.num_rows else run_queries(right.slice(0, 0), left.slice(0, 0), wide, enc, book, entry, False)

            out = routed.groupBy("shard").cogroup(rows.groupBy("shard")).applyInArrow(group, OUT)
        out = stored(out)
        res = out.where("kind = 'r'").groupBy("query_id", "node_id").agg(F.min("dist").alias("dist"))
        if deleted is not None:
            res = res.join(deleted.select("node_id"), "node_id", "left_anti")
        if predicate is not None:
            res = res.join(self.objects.where(predicate).select("node_id"), "node_id", "left_semi")
        if buffer is not None:
            extra = knn_exact(encode(buffer, enc, "node_id"), queries, s.k, s.metric).select("query_id", "node_id", "dist")
            res = res.select("query_id", "node_id", "dist").unionByName(extra).groupBy("query_id", "node_id").agg(F.min("dist").alias("dist"))
        stats = out.where("kind = 's'").groupBy("query_id").agg(F.sum("step").alias("n_steps"), F.sum("a").alias("n_exact"), F.sum("b").alias("n_batches"), F.sum("c").alias("n_encoded"))
        trace = out.where("kind = 't'").select("query_id", "step", "node_id", F.col("a").alias("n_approx"), F.col("b").alias("n_exact"), F.col("c").alias("batch_id")) if return_trace else None
        return Found(top_k(res.select("query_id", "node_id", "dist"), s.k), stats, trace)

    def with_cache(self, budget_bytes: int, popularity: DataFrame | None = None) -> DataFrame:
        """Vectors of the most popular nodes (popularity(node_id, n); default: by degree) within the budget: node_id, v."""
        n = budget_bytes // (4 * self.meta["dim"])
        p = popularity if popularity is not None else degrees(self.edges).select("node_id", (F.col("out_deg") + F.col("in_deg")).alias("n"))
        hot = p.orderBy(F.desc("n"), "node_id").limit(int(n)).select("node_id")
        return encode(self.objects.join(hot, "node_id", "left_semi"), self.encoder, "node_id")

    def tune(self, queries: DataFrame, truth: DataFrame, k: int, target: float, grid: list[int], **spec) -> tuple[int | None, list[tuple[int, float, float]]]:
        """Smallest ef of the grid whose mean recall reaches the target, and all (ef, recall, mean encodes)."""
        from .measures import mean_recall

        seen = []
        for ef in sorted(grid):
            f = self.search(queries, k=k, ef=ef, **spec)
            seen.append((ef, mean_recall(f.result, truth, k), f.stats.agg(F.avg("n_encoded")).first()[0] or 0.0))
            if seen[-1][1] >= target:
                return ef, seen
        return None, seen

    def storage(self) -> dict:
        """Measured bytes: packed and padded lists, codes, codebook."""
        e, n = self.adjacency.agg(F.coalesce(F.sum(F.size("nbrs")), F.lit(0)), F.count("*")).first()
        code = self.codes.agg(F.coalesce(F.sum(F.length("code")), F.lit(0))).first()[0] if self.codes is not None else 0
        return {"nodes": n, "edges": e, "csr": 4 * e + 4 * (n + 1), "padded": 4 * n * self.meta["M"], "codes": code, "codebook": 4 * self.meta["ks"] * self.meta["dim"], "vectors": 4 * n * self.meta["dim"]}

    def describe(self) -> dict:
        return self.meta | {"spec": asdict(SearchSpec())}
