"""Embedding near-duplicates by a subspace pigeonhole join.

Unit vectors with cosine >= t lie within squared distance 2 - 2t. After a rotation the coordinates are cut into blocks; some
block of a pair within that distance holds at most its proportional share of it, and no block holds more than all of it.

Equal vectors are one node with a multiplicity. Nodes are ordered along grid cells of the blocks' widest coordinates and
packed into chunks. Every pair of chunks meets once, without a shuffle: a pair whose boxes lie too far apart is left out, for
the others one product over the `LEAD` first blocks and the lengths of what they leave rules out nearly all pairs (by
Cauchy-Schwarz, so none in reach is lost), the shares of the blocks rule on the rest, and the exact cosine in double precision
decides. Links are counted without gathering pairs: a task gives each node its number of links and, for the
components, only links that join parts not yet joined within the task.

At 100 TB: the vectors are shuffled twice and stored twice, whatever the number of chunks; products grow with the square of
what the boxes leave (all of it, if the vectors are isotropic noise). The rotation is a small matrix from one aggregate.
"""

from __future__ import annotations

from collections.abc import Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import discard, stored
from .components import components

BLOCKS = 4
LEAD = 2  # blocks in the product that is asked of all pairs of a pair of chunks
AXES = 2  # coordinates of a block that its cells are cut along
CHUNK = 8192
TILE = 256  # rows of a chunk that are multiplied at once
SLICE = 1 << 15  # pairs that are compared exactly at once
HELD = 1 << 20  # nodes whose links a task holds
ROOM = 1e-6  # widening of each share, far above rounding
SINGLE = 2e-5  # widening of the product, far above rounding in single precision


def _matrix(col: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(usable rows, their vectors in double precision, lengths of all rows) of a list column."""
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
    size = np.diff(col.offsets.to_numpy()) * np.asarray(col.is_valid())
    return np.asarray(col.is_valid()), col, size


def _scaled(x: np.ndarray) -> np.ndarray:
    """Rows by a power of two near their largest component, so that squares neither overflow nor vanish. Exact."""
    top = np.abs(x).max(1, initial=0)
    top = np.where(np.isfinite(top) & (top > 0), top, 1.0)
    return np.ldexp(x, -np.frexp(top)[1][:, None])


def _clean(batches: Iterator[pa.RecordBatch], dim: int):
    for b in batches:
        ok, col, size = _matrix(b.column("embedding"))
        rows = np.flatnonzero(ok & (size == dim))
        flat = col.take(pa.array(rows)).flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, dim)
        flat = _scaled(flat)
        norm = np.sqrt((flat * flat).sum(1))
        fine = np.isfinite(flat).all(1) & np.isfinite(norm) & (norm > 0)
        yield b, rows[fine], flat[fine], norm[fine]


def _gram(dim: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((dim, dim))
        for _, _, x, norm in _clean(batches, dim):
            u = x / norm[:, None]
            total += u.T @ u
        i, j = np.indices((dim, dim))
        yield pa.RecordBatch.from_arrays([pa.array(i.ravel()), pa.array(j.ravel()), pa.array(total.ravel())], names=["i", "j", "v"])

    return run


def rotation(vectors: DataFrame, dim: int) -> np.ndarray:
    """Orthogonal matrix: principal axes of all unit vectors, dealt to the blocks in turn."""
    rows = vectors.mapInArrow(_gram(dim), "i long, j long, v double").groupBy("i", "j").agg(F.sum("v").alias("v")).collect()
    g = np.zeros((dim, dim))
    for r in rows:
        g[r["i"], r["j"]] = r["v"]
    axes = np.linalg.eigh((g + g.T) / 2)[1][:, ::-1]
    return np.concatenate([axes[:, k::BLOCKS] for k in range(BLOCKS)], axis=1)


def _edges(dim: int) -> np.ndarray:
    return np.cumsum([0, *(len(range(k, dim, BLOCKS)) for k in range(BLOCKS))])


def _cells(dim: int, turn: np.ndarray, share: float, kind: str):
    """Nodes with their vectors as bytes and the number of their cell, which the chunks are ordered by."""
    edges = _edges(dim)
    wide = [c for k in range(BLOCKS) for c in range(edges[k], min(edges[k] + AXES, edges[k + 1]))][:8]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b, rows, x, norm in _clean(batches, dim):
            g = np.floor((x / norm[:, None]) @ turn[:, wide] / np.sqrt(share)).astype(np.int64)
            cell = (np.clip(g + 64, 0, 127) << (7 * np.arange(len(wide))[::-1])).sum(1)
            raw = [v.tobytes() for v in x.astype(kind)]  # scaled by powers of two: exact in single precision, too
            cols = [pa.array(cell, pa.int64()), *(b.column(c).take(pa.array(rows)) for c in ("node", "m")), pa.array(raw, pa.binary())]
            yield pa.RecordBatch.from_arrays(cols, names=["cell", "node", "m", "v"])

    return run


def _turned(x: np.ndarray, turn: np.ndarray) -> np.ndarray:
    return (x / np.sqrt((x * x).sum(1))[:, None]) @ turn


def _pack(dim: int, turn: np.ndarray, kind: str):
    """Rows of up to CHUNK nodes: nodes, multiplicities, vectors, and the box around the turned vectors."""
    size = CHUNK

    def one(b: pa.Table) -> pa.RecordBatch:
        raw = b"".join(b.column("v").to_pylist())
        t = _turned(np.frombuffer(raw, kind).astype(np.float64).reshape(-1, dim), turn)
        box = np.r_[t.min(0), t.max(0)]
        cols = [[float(box[0])], [float(box[dim])], [box.tobytes()], *([b.column(c).to_numpy().astype("<i8").tobytes()] for c in ("node", "m")), [raw]]
        return pa.RecordBatch.from_arrays([pa.array(c, pa.float64() if i < 2 else pa.binary()) for i, c in enumerate(cols)], names=["lo", "hi", "box", "node", "m", "v"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0
        for b in batches:
            held, n = [*held, b], n + b.num_rows
            while n >= size:
                t = pa.Table.from_batches(held)
                yield one(t.slice(0, size))
                held, n = t.slice(size).to_batches(), n - size
        if n:
            yield one(pa.Table.from_batches(held))

    return run


class _Links:
    """Links of a task: how many each node has, and such as join its parts."""

    def __init__(self) -> None:
        self.counts: dict[int, int] = {}
        self.root: dict[int, int] = {}
        self.pairs: list[tuple[int, int]] = []

    def find(self, v: int) -> int:
        while (p := self.root.get(v, v)) != v:
            self.root[v] = self.root.get(p, p)
            v = self.root[v]
        return v

    def count(self, nodes: np.ndarray, n: np.ndarray) -> None:
        for v, k in zip(nodes[n > 0].tolist(), n[n > 0].tolist(), strict=True):
            self.counts[v] = self.counts.get(v, 0) + k

    def join(self, a: np.ndarray, b: np.ndarray) -> None:
        for p, q in zip(a.tolist(), b.tolist(), strict=True):
            u, v = self.find(p), self.find(q)
            if u != v:
                self.root[max(u, v)] = min(u, v)
                self.pairs.append((p, q))

    def rows(self) -> pa.RecordBatch:
        a = [*(p for p, _ in self.pairs), *self.counts]
        b = [*(q for _, q in self.pairs), *[None] * len(self.counts)]
        n = [*[0] * len(self.pairs), *self.counts.values()]
        self.__init__()
        return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in (a, b, n)], names=["a", "b", "n"])


def _united(label: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Smallest numbers of the parts of nodes, after the links (i, j)."""
    while True:
        p, q = label[i], label[j]
        new = p != q
        if not new.any():
            return label
        np.minimum.at(label, np.maximum(p, q)[new], np.minimum(p, q)[new])
        while (label[label] != label).any():
            label = label[label]


def _join(dim: int, turn: np.ndarray, share: float, cosine: float, kind: str):
    edges = _edges(dim)
    lead = int(edges[min(LEAD, BLOCKS)])

    class Side:
        def __init__(self, node: bytes, m: bytes, v: bytes):
            self.node, self.m = np.frombuffer(node, "<i8"), np.frombuffer(m, "<i8")
            self.x = np.frombuffer(v, kind).astype(np.float64).reshape(-1, dim)
            self.norm = np.sqrt((self.x * self.x).sum(1))
            self.t = _turned(self.x, turn)
            rest = np.sqrt((self.t[:, lead:] ** 2).sum(1))
            self.asked = np.c_[self.t[:, :lead], rest].astype(np.float32)

    def compare(left: Side, right: Side, same: bool, links: _Links) -> None:
        nl, nr = len(left.node), len(right.node)
        label = np.arange(nl if same else nl + nr)
        cl, cr = np.zeros(nl), np.zeros(nr)
        across = np.ascontiguousarray(right.asked.T)
        for s in range(0, nl, TILE):
            from_ = s if same else 0
            near = left.asked[s : s + TILE] @ across[:, from_:]
            at = np.flatnonzero(near.ravel() >= np.float32(cosine - SINGLE))
            for a in range(0, len(at), SLICE):
                i, j = np.divmod(at[a : a + SLICE], nr - from_)
                i, j = i + s, j + from_
                if same:
                    i, j = i[j > i], j[j > i]
                # some block holds at most its share
                diff = np.add.reduceat((left.t[i] - right.t[j]) ** 2, edges[:-1][np.diff(edges) > 0], axis=1)
                ok = (diff <= share + ROOM).any(1)
                i, j = i[ok], j[ok]
                good = (left.x[i] * right.x[j]).sum(1) / (left.norm[i] * right.norm[j]) >= cosine
                i, j = i[good], j[good]
                if len(i):
                    cl += np.bincount(i, right.m[j], nl)
                    cr += np.bincount(j, left.m[i], nr)
                    label = _united(label, i, j if same else j + nl)
        links.count(left.node, cl.astype(np.int64))
        links.count(right.node, cr.astype(np.int64))
        nodes = left.node if same else np.r_[left.node, right.node]
        moved = np.flatnonzero(label != np.arange(len(label)))
        links.join(nodes[moved], nodes[label[moved]])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        links, last, left = _Links(), None, None
        for b in batches:
            for r in range(b.num_rows):
                get = lambda c: b.column(c)[r].as_py()  # noqa: B023, E731
                p, q = (np.frombuffer(get(c), np.float64) for c in ("box", "r_box"))
                gap = np.maximum(0, np.maximum(p[:dim] - q[dim:], q[:dim] - p[dim:]))
                if (gap * gap).sum() > 2 - 2 * cosine + ROOM:
                    continue
                if last != (no := get("no")):
                    last, left = no, Side(get("node"), get("m"), get("v"))
                same = no == get("r_no")
                compare(left, left if same else Side(get("r_node"), get("r_m"), get("r_v")), same, links)
                if len(links.counts) > HELD:
                    yield links.rows()
        yield links.rows()

    return run


@contextmanager
def _few_rows_a_batch(spark: SparkSession, rows: int = 4):
    """Rows of chunks are megabytes: Python gets few of them at once."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(name)
    spark.conf.set(name, rows)
    try:
        yield
    finally:
        spark.conf.set(name, before)


def near_duplicates(vectors: DataFrame, cosine: float = 0.9) -> DataFrame:
    """vectors(vec_id, embedding) -> vec_id, n_links, component_id, kept, one row per input row.

    n_links: other vectors with cosine >= `cosine` in double precision; component_id: the smallest vec_id reachable by
    links, itself included; kept: vec_id = component_id. Vectors that are null, zero, or hold null or non-finite
    components link with nothing; vectors of unlike lengths never link. Equal vectors link with each other. Rows without vec_id link with nothing and have no component. An empty table gives an empty result.
    """
    # single-precision input travels as such: doubles made of it are the same numbers
    single = vectors.schema["embedding"].dataType.simpleString() == "array<float>"
    kind = "<f4" if single else "<f8"
    vectors = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding") if single else F.col("embedding").cast("array<double>").alias("embedding"))
    spark = vectors.sparkSession
    sized = vectors.where("vec_id is not null and embedding is not null")
    flaw = F.exists("embedding", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))) | ~F.exists("embedding", lambda x: x != 0)
    # equal vectors are one node, named by a hash
    sized = sized.where(~flaw).select("vec_id", F.xxhash64("embedding").alias("node"), "embedding")
    named = sized.select("vec_id", "node")
    nodes = stored(sized.groupBy("node").agg(F.count("*").alias("m"), F.min("vec_id").alias("low"), F.first("embedding").alias("embedding")).withColumn("dim", F.size("embedding")))
    found = None
    # vectors of unlike lengths have no cosine: each length is joined on its own
    for dim in sorted(r["dim"] for r in nodes.groupBy("dim").count().where("count > 1").select("dim").collect()):
        mine = nodes.where(F.col("dim") == dim).select("node", "m", "embedding")
        turn = rotation(mine.select("embedding"), dim)
        share = (2 - 2 * cosine) / min(BLOCKS, dim)  # of the blocks that hold a coordinate
        cells = mine.mapInArrow(_cells(dim, turn, share, kind), "cell long, node long, m long, v binary")
        # by node, too: a cell of near copies is no single task's
        ranged = cells.repartitionByRange("cell", "node").sortWithinPartitions("cell")
        packed = ranged.mapInArrow(_pack(dim, turn, kind), "lo double, hi double, box binary, node binary, m binary, v binary")
        packed = stored(packed.select(F.monotonically_increasing_id().alias("no"), "*"))
        other = packed.select(*(F.col(c).alias(f"r_{c}") for c in packed.columns))
        reach = float(np.sqrt(2 - 2 * cosine) + ROOM)
        meets = packed.join(other, F.expr(f"no <= r_no and lo - r_hi <= {reach!r} and r_lo - hi <= {reach!r}"))
        with _few_rows_a_batch(spark):
            out = stored(meets.mapInArrow(_join(dim, turn, share, cosine, kind), "a long, b long, n long"))
        discard(packed)
        found = out if found is None else found.unionByName(out)
    if found is not None:
        links = found.groupBy("a").agg(F.sum("n").alias("n"))
        comp = components(found.where("b is not null").select("a", "b"))
    else:
        links = nodes.select(F.col("node").alias("a"), F.lit(0).cast("long").alias("n"))
        comp = nodes.select("node", F.col("node").alias("component"))
    per = nodes.drop("embedding", "dim").join(links.withColumnRenamed("a", "node"), "node", "left").join(comp, "node", "left").withColumn("component", F.coalesce("component", "node"))
    lows = per.groupBy("component").agg(F.min("low").alias("component_id"))
    per = per.join(lows, "component").select("node", (F.coalesce("n", F.lit(0)) + F.col("m") - 1).alias("n_links"), "component_id")
    tied = named.select("vec_id", "node").join(per, "node").select("vec_id", "n_links", "component_id")
    rest = vectors.where("vec_id is null").select("vec_id", F.lit(0).cast("long").alias("n_links"), F.lit(None).cast("long").alias("component_id"))
    lone = vectors.where(F.col("vec_id").isNotNull() & (F.col("embedding").isNull() | F.coalesce(flaw, F.lit(True))))
    lone = lone.select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    return tied.unionByName(lone).unionByName(rest).withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(False)))
