"""Product quantization in relational form, with fixed-point training whose result does not depend on row order.

A vector is cut into `m_sub` subvectors; each is replaced by the number of its nearest codeword. Training keeps coordinates as
integers of 1e-6, so that sums are exact: a round is a broadcast of the codebook, an assignment and one aggregate.
The codebook is ks * dim numbers whatever the corpus; training reads a sample of fixed size at scale.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .exact import QUERY_BYTES, Best, matrix, nearest_rows, query_blocks, top_k

SCALE = 1_000_000


def pq_shape(dim: int, ratio: float, ks: int = 256) -> tuple[int, int]:
    """(subspaces, codewords) whose code is nearest to 4 * dim / ratio bytes; subspaces divide dim."""
    want = 4 * dim / ratio
    legal = [m for m in range(1, dim + 1) if dim % m == 0]
    return min(legal, key=lambda m: (abs(np.log(m / want)), m)), ks


def subvectors(vectors: DataFrame, m_sub: int, dim: int) -> DataFrame:
    """(node_id, v) -> node_id, sub, x."""
    w = dim // m_sub
    s = F.explode(F.sequence(F.lit(0), F.lit(m_sub - 1)))
    return vectors.select("node_id", "v", s.alias("sub")).select("node_id", "sub", F.slice("v", F.col("sub") * w + 1, w).alias("x"))


def to_fixed(x: Column) -> Column:
    return F.transform(x, lambda c: F.floor(c.cast("double") * SCALE).cast("long"))


def _sq(a: Column, b: Column, kind: str) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0).cast(kind), lambda s, v: s + v)


def assign(points: DataFrame, codebook: DataFrame, kind: str = "double") -> DataFrame:
    """points(node_id, sub, x), codebook(sub, code, centroid) -> node_id, sub, code, dist: nearest by (dist, code).

    The codebook has a fixed number of rows and is broadcast.
    """
    j = points.join(F.broadcast(codebook), "sub")
    x, c = (F.transform(F.col(n), lambda v: v.cast(kind)) for n in ("x", "centroid"))
    best = j.groupBy("node_id", "sub").agg(F.min(F.struct(_sq(x, c, kind).alias("dist"), "code")).alias("b"))
    return best.select("node_id", "sub", F.col("b.code").alias("code"), F.col("b.dist").alias("dist"))


def seeded(points: DataFrame, seeds: DataFrame) -> DataFrame:
    """Codewords are the subvectors of the seed nodes (node_id, code)."""
    return points.join(F.broadcast(seeds), "node_id").select("sub", "code", F.col("x").alias("centroid"))


def nearest_fixed(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    """Row number of the nearest codeword of each row, both in whole numbers; ties: the first. Exact."""
    top = x.shape[1] * (int(np.abs(x).max(initial=0)) + int(np.abs(c).max(initial=0))) ** 2
    if top < 1 << 52:  # all terms are whole numbers that doubles hold
        x, c = x.astype(np.float64), c.astype(np.float64)
        return ((c * c).sum(1)[None] - 2 * (x @ c.T)).argmin(1)
    if top >= 1 << 63:
        raise OverflowError("squared distances of fixed-point vectors exceed 64 bits")
    return np.array([((c - v) ** 2).sum(1).argmin() for v in x], np.int64)


def _sums(book: dict[int, tuple[list[int], np.ndarray]], some: int = 4096):
    """points(sub, x) of a task -> sums and numbers of the coordinates that each codeword is nearest to."""
    schema = pa.schema([("sub", pa.int32()), ("code", pa.int32()), ("i", pa.int32()), ("s", pa.int64()), ("n", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = {s: (np.zeros(c.shape, np.int64), np.zeros(c.shape, np.int64)) for s, (_, c) in book.items()}
        for b in batches:
            sub, x = b.column(0).to_numpy(), b.column(1)
            size = np.where(x.is_valid().to_numpy(zero_copy_only=False), np.diff(x.offsets.to_numpy()), -1)
            for s in np.unique(sub).tolist():
                if s not in book:
                    continue
                (sums, n), c = total[s], book[s][1]
                rows = np.flatnonzero((sub == s) & (size >= 0))
                for a in range(0, len(rows), some):
                    part = rows[a : a + some]
                    lists = x.take(pa.array(part))
                    if lists.flatten().null_count or (size[part] != c.shape[1]).any():
                        # without a distance a vector goes to the first codeword
                        whole = [len(v) == c.shape[1] and None not in v for v in lists.to_pylist()]
                        for v in lists.filter(pa.array(np.invert(whole))).to_pylist():
                            for i, y in enumerate(v[: c.shape[1]]):
                                sums[0, i] += y or 0
                                n[0, i] += 1
                        lists = lists.filter(pa.array(whole))
                    m = lists.flatten().to_numpy().reshape(-1, c.shape[1])
                    at = nearest_fixed(m, c)
                    np.add.at(sums, at, m)
                    n += np.bincount(at, minlength=len(c))[:, None]
        for s, (sums, n) in total.items():
            k, i = np.nonzero(n)
            cols = (np.full(len(k), s), np.array(book[s][0])[k], i, sums[k, i], n[k, i])
            yield pa.RecordBatch.from_arrays([pa.array(v, f.type) for v, f in zip(cols, schema, strict=True)], schema=schema)

    return run


def lloyd_fixed(points: DataFrame, codebook: DataFrame, rounds: int) -> DataFrame:
    """points(node_id, sub, x LONG), codebook with LONG centroids -> codebook after `rounds`; empty codewords stay.

    Each round ships the small codebook, adds up whole numbers within tasks and collects it, so plans don't grow.
    """
    spark = points.sparkSession
    rows = sorted((r["sub"], r["code"], list(r["centroid"])) for r in codebook.collect())
    schema = "sub int, code int, centroid array<long>"
    points = points.select(F.col("sub").cast("int").alias("sub"), "x")
    for _ in range(rounds):
        book: dict = {}
        for s, c, x in rows:
            book.setdefault(s, ([], []))[0].append(c)
            book[s][1].append(x)
        book = {s: (c, np.array(x, np.int64)) for s, (c, x) in book.items()}
        sums = points.mapInArrow(_sums(book), "sub int, code int, i int, s long, n long").groupBy("sub", "code", "i").agg(F.sum("s").alias("s"), F.sum("n").alias("n"))
        new: dict = {}
        for r in sums.select("sub", "code", "i", F.floor(F.expr("s div n - if(s % n < 0, 1, 0)")).alias("c")).collect():
            new.setdefault((r["sub"], r["code"]), {})[r["i"]] = r["c"]
        rows = [(s, c, [new[s, c][i] for i in range(len(x))] if (s, c) in new else x) for s, c, x in rows]
    return spark.createDataFrame(rows, schema)


def pq_train(vectors: DataFrame, m_sub: int, dim: int, ks: int = 256, iters: int = 4, sample: int = 100_000) -> DataFrame:
    """Codebook (sub, code, centroid array<float>) from at most `sample` vectors chosen by hash of node_id."""
    n = vectors.count()
    few = vectors.where(F.pmod(F.xxhash64("node_id"), F.lit(max(1, -(-n // sample)))) == 0).cache()
    seeds = few.select("node_id").orderBy(F.xxhash64("node_id"), "node_id").limit(ks).toArrow().column("node_id").to_pylist()
    code = vectors.sparkSession.createDataFrame([(s, i) for i, s in enumerate(seeds)], "node_id long, code int")
    points = subvectors(few, m_sub, dim).withColumn("x", to_fixed(F.col("x")))
    fixed = lloyd_fixed(points, seeded(points, code), iters)
    return fixed.select("sub", "code", F.transform("centroid", lambda c: (c / SCALE).cast("float")).alias("centroid"))


def codebook_array(codebook: DataFrame) -> np.ndarray:
    """float32 [m_sub, ks, width]."""
    rows = {(r["sub"], r["code"]): r["centroid"] for r in codebook.collect()}
    m, k = max(s for s, _ in rows) + 1, max(c for _, c in rows) + 1
    return np.array([[rows[s, c] for c in range(k)] for s in range(m)], np.float32)


def encode_rows(x: np.ndarray, book: np.ndarray) -> np.ndarray:
    """uint8 codes of float rows."""
    m, _, w = book.shape
    out = np.empty((len(x), m), np.uint8)
    for s in range(m):
        d = ((x[:, s * w : (s + 1) * w, None].transpose(0, 2, 1) - book[s][None]) ** 2).sum(2) if len(x) * book.shape[1] * w < 1 << 24 else None
        if d is None:
            part, b = x[:, s * w : (s + 1) * w], book[s]
            d = (part * part).sum(1)[:, None] - 2 * part @ b.T + (b * b).sum(1)[None]
        out[:, s] = d.argmin(1)
    return out


def pq_encode(vectors: DataFrame, codebook: DataFrame) -> DataFrame:
    """(node_id, v) -> node_id, code BINARY: one byte a subspace; a narrow map with the codebook shipped along."""
    book = vectors.sparkSession.sparkContext.broadcast(codebook_array(codebook))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            c = encode_rows(matrix(b.column(1)).astype(np.float32), book.value) if b.num_rows else []
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([r.tobytes() for r in c], pa.binary())], names=["node_id", "code"])

    return vectors.select(F.col("node_id").cast("long").alias("node_id"), "v").mapInArrow(run, "node_id long, code binary")


def adc_table(q: np.ndarray, book: np.ndarray) -> np.ndarray:
    """Squared distances of one query's subvectors to all codewords: [m_sub, ks]."""
    m, _, w = book.shape
    return ((q.reshape(m, 1, w) - book) ** 2).sum(2)


def adc(table: np.ndarray, codes: np.ndarray) -> np.ndarray:
    return table[np.arange(len(table))[None, :], codes].sum(1)


def adc_lut(queries: DataFrame, codebook: DataFrame, m_sub: int, dim: int) -> DataFrame:
    """Relational look-up table: query_id, sub, code, d."""
    q = subvectors(queries.select(F.col("query_id").alias("node_id"), F.col("qv").alias("v")), m_sub, dim)
    x, c = (F.transform(F.col(n), lambda v: v.cast("double")) for n in ("x", "centroid"))
    return q.join(F.broadcast(codebook), "sub").select(F.col("node_id").alias("query_id"), "sub", "code", _sq(x, c, "double").alias("d"))


def pq_topk_sql(codes: DataFrame, lut: DataFrame, k: int) -> DataFrame:
    """codes(node_id, sub, code) and a look-up table -> top k; contributions are floored to 1e-6 and summed as integers.

    A node's codes meet in one row, a block of queries' tables is shipped with the tasks, and k rows a query leave each."""
    rows = codes.groupBy(F.col("node_id").cast("long").alias("node_id")).agg(F.transform(F.array_sort(F.collect_list(F.struct("sub", "code"))), lambda s: s["code"].cast("int")).alias("codes"))
    table = lut.select(F.col("query_id").cast("long").alias("query_id"), "sub", "code", F.floor(F.col("d") * SCALE).cast("long").alias("d")).where("d is not null")
    size, out = table.count(), None
    parts = max(1, -(-size * 24 // QUERY_BYTES))
    for i in range(parts):
        t = table.where(F.pmod(F.xxhash64("query_id"), F.lit(parts)) == i).toArrow()
        qid, r = np.unique(t.column("query_id").to_numpy(), return_inverse=True)
        sub, code = t.column("sub").to_numpy(), t.column("code").to_numpy()
        tables = np.zeros((int(sub.max(initial=-1)) + 1, len(qid), int(code.max(initial=-1)) + 1), np.int64)
        tables[sub, r, code] = t.column("d").to_numpy()

        def run(batches: Iterator[pa.RecordBatch], qid=qid, tables=tables) -> Iterator[pa.RecordBatch]:
            best = Best(qid, k, np.int64)
            for b in batches:
                ids, c = b.column(0).to_numpy(), b.column(1).flatten().to_numpy().reshape(b.num_rows, -1)
                for a in range(0, len(ids), 512):
                    for s in range(0, len(qid), 512):
                        d = tables[0, s : s + 512].take(c[a : a + 512, 0], 1)
                        for j in range(1, len(tables)):
                            d += tables[j, s : s + 512].take(c[a : a + 512, j], 1)
                        best.offer(d, ids[a : a + 512], np.arange(s, s + len(d)))
            yield best.rows()

        part = rows.mapInArrow(run, "query_id long, node_id long, dist long")
        out = part if out is None else out.unionByName(part)
    return top_k(out, k)


def pq_topk(codes: DataFrame, queries: DataFrame, codebook: DataFrame, k: int) -> DataFrame:
    """codes(node_id, code BINARY) -> top k by asymmetric distance: per task k rows a query leave."""
    book = codebook_array(codebook)
    out = None
    for qid, q in query_blocks(queries.select("query_id", "qv"), book.shape[0] * book.shape[2]):
        tables = np.stack([adc_table(x.astype(np.float32), book) for x in q])

        def run(batches: Iterator[pa.RecordBatch], qid=qid, tables=tables) -> Iterator[pa.RecordBatch]:
            for b in batches:
                ids = b.column(0).to_numpy()
                c = np.frombuffer(b"".join(b.column(1).to_pylist()), np.uint8).reshape(len(ids), -1)
                for j, t in enumerate(tables):
                    d = adc(t, c).astype(np.float64)
                    r = nearest_rows(d, ids, k)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(r), qid[j])), pa.array(ids[r]), pa.array(d[r])], names=["query_id", "node_id", "dist"])

        part = codes.select("node_id", "code").mapInArrow(run, "query_id long, node_id long, dist double")
        out = part if out is None else out.unionByName(part)
    return top_k(out, k)


def rerank(candidates: DataFrame, base: DataFrame, queries: DataFrame, k: int) -> DataFrame:
    """Exact squared L2 of (query_id, node_id) candidates, then the k nearest."""
    from ..functions.distance import l2sq

    j = candidates.select("query_id", "node_id").join(base, "node_id").join(F.broadcast(queries), "query_id")
    return top_k(j.select("query_id", "node_id", l2sq("v", "qv").alias("dist")), k)


def pq_decode(codes: DataFrame, codebook: DataFrame) -> DataFrame:
    """codes(node_id, sub, code) -> node_id, v."""
    j = codes.join(F.broadcast(codebook), ["sub", "code"])
    parts = F.array_sort(F.collect_list(F.struct("sub", "centroid")))
    return j.groupBy("node_id").agg(F.flatten(F.transform(parts, lambda p: p["centroid"])).alias("v"))


def pq_error(assigned: DataFrame) -> DataFrame:
    """Quantization error by subspace, in integer units of 1e-6: sub, n, error."""
    return assigned.groupBy("sub").agg(F.count("*").alias("n"), F.sum(F.floor(F.col("dist") * SCALE).cast("long")).alias("error"))
