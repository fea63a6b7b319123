"""Stored-vector baselines as indexes of their own: a layered graph in memory, and a graph on disk steered by codes.

Objects are dealt to shards by a hash of their id, every shard is built in one task of bounded size, and a query visits all
shards; their results are merged by one top-k. A task of the search holds one shard and the queries.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.encoders import Encoder
from ..sources.storage import stored
from . import pq as pqm
from .exact import matrix, nearest_rows, top_k
from .kernels import Bounded, _exact, _search_layer, all_distances, layered_build, waves

SHARD = 4096  # objects that one task builds
SECTOR = 4096  # bytes that a read from disk brings
BEAM = 4  # sectors that one round trip reads
RESULT = "query_id long, node_id long, dist double, steps long, reads long, cheap long"
_FIELDS = pa.schema([("query_id", pa.int64()), ("node_id", pa.int64()), ("dist", pa.float64()), ("steps", pa.int64()), ("reads", pa.int64()), ("cheap", pa.int64())])


def connect(links: list[dict[int, float]], x: np.ndarray, entry: int) -> None:
    """Nodes that cuts have left out of reach get a link from the nearest reachable node; nodes that the entry is out of
    reach of get one to the nearest that reaches it. So every node leads to every other."""
    xx = np.einsum("ij,ij->i", x, x)
    for back in (False, True):
        ways: list[list[int]] = [[] for _ in links] if back else [list(a) for a in links]
        if back:
            for u, a in enumerate(links):
                for v in a:
                    ways[v].append(u)
        seen, todo, lost = {entry}, [entry], 0
        far = np.full(len(links), np.inf)  # nodes out of reach are no candidates
        far[entry] = 0
        while True:
            while todo:
                for v in ways[todo.pop()]:
                    if v not in seen:
                        seen.add(v)
                        far[v] = 0
                        todo.append(v)
            while lost in seen:
                lost += 1
            if lost == len(links):
                break
            near = int(np.argmin(xx - 2 * (x @ x[lost]) + far))
            u, v = (lost, near) if back else (near, lost)
            links[u][v] = float(((x[near] - x[lost]) ** 2).sum())
            seen.add(lost)
            far[lost] = 0
            todo.append(lost)


class _Reach:
    """What a queue with room for all nodes visits from an entry; nearly always all nodes, which are kept once."""

    def __init__(self, lists: list[list[int]]):
        self.offsets = np.cumsum([0, *map(len, lists)])
        self.nbrs = np.fromiter((v for a in lists for v in a), np.int64, int(self.offsets[-1]))
        self.all, self.known = np.arange(len(lists)), {}

    def __call__(self, entry: int) -> tuple[np.ndarray, list[int]]:
        """(nodes visited, nodes of each round)."""
        if entry not in self.known:
            w = waves(self.offsets, self.nbrs, entry)
            size = [len(a) for a in w]
            self.known[entry] = (self.all if sum(size) == len(self.all) else np.sort(np.concatenate(w)), size)
        return self.known[entry]


def _shards(objects: DataFrame, shards: int | None) -> tuple[DataFrame, int]:
    n = shards or max(1, math.ceil(objects.count() / SHARD))
    return objects.select("node_id", "text", F.pmod(F.xxhash64("node_id"), F.lit(n)).cast("int").alias("shard")), n


def _answer(out: DataFrame, queries: DataFrame, k: int) -> tuple[DataFrame, DataFrame]:
    out = stored(out)
    res = top_k(out.where("node_id is not null").select("query_id", "node_id", "dist"), k)
    return res, out.where("node_id is null").groupBy("query_id").agg(F.sum("steps").alias("n_steps"), F.sum("reads").alias("n_reads"), F.sum("cheap").alias("n_cheap"))


def _rows(found: list[tuple]) -> pa.Table:
    cols = list(zip(*found, strict=True)) if found else [[]] * 6
    return pa.table([pa.array(c, f.type) for c, f in zip(cols, _FIELDS, strict=True)], schema=_FIELDS)


@dataclass
class LayeredIndex:
    """nodes(shard, node_id, level, layers, v): neighbour lists of each layer a node is in, lowest first, and its vector."""

    nodes: DataFrame
    meta: dict

    @classmethod
    def build(cls, objects: DataFrame, encoder: Encoder, cap: int = 30, ef: int = 100, seed: int = 7, rule: str = "diverse", shards: int | None = None) -> LayeredIndex:
        """objects(node_id, text). Lists hold up to `cap` neighbours, twice as many are charged on the lowest layer."""
        dealt, n = _shards(objects, shards)

        def one(key, t):
            t = t.sort_by("node_id")
            ids, x = t.column("node_id").to_numpy(), encoder.encode(t.column("text").to_pylist())
            g = layered_build(ids, x, cap, ef, seed, rule)
            if len(ids):
                connect(g.layers[0], x.astype(np.float64), g.entry)
            lists = [[[int(ids[v]) for v in g.layers[a][u]] for a in range(int(g.levels[u]) + 1)] for u in range(len(ids))]
            entry = np.arange(len(ids)) == g.entry
            return pa.table({"shard": t.column("shard"), "node_id": t.column("node_id"), "level": pa.array(g.levels.astype(np.int32)), "entry": pa.array(entry), "layers": pa.array(lists, pa.list_(pa.list_(pa.int64()))), "v": pa.array(list(x.astype(np.float32)), pa.list_(pa.float32()))})

        nodes = dealt.groupBy("shard").applyInArrow(one, "shard int, node_id long, level int, entry boolean, layers array<array<long>>, v array<float>")
        return cls(stored(nodes), {"cap": cap, "shards": n, "dim": encoder.width, "rule": rule})

    def search(self, queries: DataFrame, k: int = 3, ef: int = 60, entry: str = "top") -> tuple[DataFrame, DataFrame]:
        """queries(query_id, qv) -> (query_id, rank, node_id, dist), counts per query.

        entry: `top` descends from the highest layer, `hub` starts at the node of highest degree, `medoid` at the node
        nearest to the mean, both on the lowest layer.
        """
        if ef < k:
            raise ValueError("ef must be at least k")
        if entry not in ("top", "hub", "medoid"):
            raise ValueError(f"unknown entry {entry}")
        dealt = queries.select(F.col("query_id").cast("long").alias("query_id"), "qv").withColumn("shard", F.explode(F.sequence(F.lit(0), F.lit(self.meta["shards"] - 1))))

        def one(key, left, right):
            if not left.num_rows or not right.num_rows:
                return _rows([])
            right = right.sort_by("node_id")  # equal distances go by the smaller id
            ids = right.column("node_id").to_numpy()
            at = {int(i): u for u, i in enumerate(ids)}
            x = matrix(right.column("v")).astype(np.float64)
            layers: list[list[dict]] = [[{} for _ in ids] for _ in range(int(right.column("level").to_numpy().max()) + 1)]
            for u, lists in enumerate(right.column("layers").to_pylist()):
                for a, nb in enumerate(lists):
                    layers[a][u] = dict.fromkeys((at[v] for v in nb), 0.0)
            top = int(np.flatnonzero(right.column("entry").to_numpy(zero_copy_only=False))[0])
            if entry == "hub":
                top = int(np.argmax([len(a) for a in layers[0]]))
            elif entry == "medoid":
                top = int(np.argmin(((x - x.mean(0)) ** 2).sum(1)))
            out = []
            reach = _Reach([list(a) for a in layers[0]]) if ef >= len(ids) else None
            asked = matrix(left.column("qv")).astype(np.float64)
            for n, (q, v) in enumerate(zip(left.column("query_id").to_pylist(), asked, strict=True)):
                if n % 256 == 0 and not reach:
                    some = all_distances(x, asked[n : n + 256])
                far = None if reach else some[n % 256]
                near = [top]
                for a in range(len(layers) - 1 if entry == "top" else 0, 0, -1):
                    near = [u for _, u in _search_layer(x, v, layers[a], near, 1, far)]
                if reach:
                    found, _ = reach(near[0])
                    d = _exact("l2", v, x[found])
                    out += [(q, int(ids[found[i]]), float(d[i]), 0, 0, 0) for i in nearest_rows(d, ids[found], k)]
                else:
                    found = _search_layer(x, v, layers[0], near, ef, far)
                    at_last = np.array([u for _, u in found])
                    d = _exact("l2", v, x[at_last])  # the order of the answer goes by direct distances
                    out += [(q, int(ids[at_last[i]]), float(d[i]), 0, 0, 0) for i in nearest_rows(d, ids[at_last], k)]
                out.append((q, None, None, len(found), 0, 0))
            return _rows(out)

        return _answer(dealt.groupBy("shard").cogroup(self.nodes.groupBy("shard")).applyInArrow(one, RESULT), queries, k)

    def storage(self) -> dict:
        """Bytes: lists padded to twice the cap on the lowest layer and to the cap above, and the vectors."""
        n, up = self.nodes.agg(F.count("*"), F.coalesce(F.sum("level"), F.lit(0))).first()
        return {"nodes": n, "graph": 4 * self.meta["cap"] * (2 * n + up), "vectors": 4 * n * self.meta["dim"]}


@dataclass
class DiskIndex:
    """codes(shard, node_id, code) kept in memory, sectors(shard, node_id, sector): vector and neighbours in one record."""

    nodes: DataFrame
    codebook: DataFrame
    meta: dict

    @classmethod
    def build(cls, objects: DataFrame, encoder: Encoder, cap: int = 24, ef: int = 60, seed: int = 7, relax: str = "relaxed", pq_ratio: float = 64, ks: int = 64, shards: int | None = None) -> DiskIndex:
        from ..functions.encoders import encode

        dealt, n = _shards(objects, shards)
        vec = stored(encode(objects, encoder, "node_id"))
        m_sub, _ = pqm.pq_shape(encoder.width, pq_ratio)
        book = pqm.pq_train(vec, m_sub, encoder.width, ks=ks, iters=2)
        size = -(-(4 * encoder.width + 4 * (cap + 1)) // SECTOR) * SECTOR

        def one(key, t):
            t = t.sort_by("node_id")
            ids, x = t.column("node_id").to_numpy(), encoder.encode(t.column("text").to_pylist()).astype(np.float32)
            g = layered_build(ids, x, cap, ef, seed, relax)
            if len(ids):
                connect(g.layers[0], x.astype(np.float64), g.entry)
            raw = []
            for u, nb in enumerate(g.layers[0]):
                body = x[u].tobytes() + np.array([len(nb)], "<u4").tobytes() + ids[list(nb)].astype("<i8").tobytes()
                raw.append(body.ljust(size, b"\0"))
            entry = np.arange(len(ids)) == g.entry
            return pa.table({"shard": t.column("shard"), "node_id": t.column("node_id"), "entry": pa.array(entry), "sector": pa.array(raw, pa.binary())})

        sectors = dealt.groupBy("shard").applyInArrow(one, "shard int, node_id long, entry boolean, sector binary")
        nodes = stored(sectors.join(pqm.pq_encode(vec, book), "node_id"))
        return cls(nodes, book, {"cap": cap, "shards": n, "dim": encoder.width, "m_sub": m_sub, "ks": ks, "sector": size})

    def search(self, queries: DataFrame, k: int = 3, ef: int = 60) -> tuple[DataFrame, DataFrame]:
        """queries(query_id, qv): a beam steered by code distances; every expanded node costs a sector, which brings its
        vector for the final order, too."""
        if ef < k:
            raise ValueError("ef must be at least k")
        dealt = queries.select(F.col("query_id").cast("long").alias("query_id"), "qv").withColumn("shard", F.explode(F.sequence(F.lit(0), F.lit(self.meta["shards"] - 1))))
        book, dim = pqm.codebook_array(self.codebook), self.meta["dim"]

        def one(key, left, right):
            if not left.num_rows or not right.num_rows:
                return _rows([])
            right = right.sort_by("node_id")
            ids = right.column("node_id").to_numpy()
            code = right.column("code").to_pylist()
            codes = np.frombuffer(b"".join(code), np.uint8).reshape(len(code), -1)
            sectors = right.column("sector")
            start = int(np.flatnonzero(right.column("entry").to_numpy(zero_copy_only=False))[0])
            out, held = [], {}

            def read(u: int) -> tuple[np.ndarray, np.ndarray]:
                raw = sectors[u].as_py()
                n = int(np.frombuffer(raw, "<u4", 1, 4 * dim)[0])
                return np.frombuffer(raw, "<f4", dim), np.searchsorted(ids, np.frombuffer(raw, "<i8", n, 4 * dim + 4))

            if ef >= len(ids):  # every query reads all sectors within reach: they are read once for all
                x, lists = zip(*map(read, range(len(ids))), strict=True)
                x = np.array(x)
                found, sizes = _Reach([a.tolist() for a in lists])(start)
                steps = sum(-(-n // BEAM) for n in sizes)
            for q, v in zip(left.column("query_id").to_pylist(), matrix(left.column("qv")), strict=True):
                if ef >= len(ids):
                    d = _exact("l2", v, x[found])
                    out += [(q, int(ids[found[i]]), float(d[i]), 0, 0, 0) for i in nearest_rows(d, ids[found], k)]
                    out.append((q, None, None, steps, len(found), len(found) - 1))
                    continue
                table = pqm.adc_table(v.astype(np.float32), book)
                eq, seen, exact = Bounded(ef), {start}, []
                about = pqm.adc(table, codes).astype(np.float64)
                eq.offer(float(about[start]), int(ids[start]), start)
                steps = cheap = 0
                while batch := eq.take(BEAM):
                    steps += 1
                    new: dict[int, None] = {}
                    for _, key_id, u in batch:
                        if u not in held:  # each query counts the read, the bytes are cut into arrays once
                            held[u] = read(u)
                        own, nb = held[u]
                        exact.append((float(((own.astype(np.float64) - v) ** 2).sum()), key_id))
                        new |= dict.fromkeys(nb.tolist())
                    fresh = [w for w in new if w not in seen]
                    seen.update(fresh)
                    cheap += len(fresh)
                    most = eq.rows[-1][0] if len(eq.rows) == ef else math.inf
                    for w, d in zip(fresh, about.take(fresh).tolist() if fresh else [], strict=True):
                        if d <= most:
                            eq.offer(d, int(ids[w]), w)
                out += [(q, i, d, 0, 0, 0) for d, i in sorted(exact)[:k]]
                out.append((q, None, None, steps, len(exact), cheap))
            return _rows(out)

        return _answer(dealt.groupBy("shard").cogroup(self.nodes.groupBy("shard")).applyInArrow(one, RESULT), queries, k)

    def storage(self) -> dict:
        n = self.nodes.count()
        return {"nodes": n, "sectors": n * self.meta["sector"], "codes": n * self.meta["m_sub"]}


def smallest_ef(search, truth: DataFrame, k: int, target: float, n: int, grid: tuple[int, ...] = (10, 20, 40, 80, 160, 320, 640)) -> tuple[int | None, float, DataFrame, DataFrame]:
    """search(ef) -> (result, counts): the first ef that reaches the recall, trying all n nodes at last.

    (ef or None where even n does not reach it, recall, result, counts).
    """
    from .measures import mean_recall

    for ef in [*(e for e in grid if k <= e < n), max(k, n)]:
        res, counts = search(ef)
        res = stored(res)
        r = mean_recall(res, truth, k)
        if r >= target:
            return ef, r, res, counts
    return None, r, res, counts
