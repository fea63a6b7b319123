"""Mixing sources to target weights by balanced sampling with the cube method.

Every document of a source is to be taken target / size-of-source times on average. The whole part is certain; the
fraction is an inclusion probability. The flight phase walks the vector of probabilities through the null space of
the balancing constraints (words and number of documents of the source) until all but two are 0 or 1. It runs per
source and bucket of documents; the undecided documents of all buckets meet in a next, far smaller flight, and only
the last two of a source need a landing, which gives up the document count first and the words last.

At 100 TB: one pass over text to count words, one shuffle of (id, source, size) rows; only one row per source
reaches the driver.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import stored
from .words import Words, blocks

BUCKET = 2048
WEIGHTS = (5, 2, 1)
MOST = 3


def _sizes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in blocks(batches, "text"):
        n = Words(b.column("text"), hashes=False).counts.astype(np.int64)
        yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("source"), pa.array(n)], names=["doc_id", "source", "size"])


def targets(sizes: dict, weights: tuple = WEIGHTS, most: float = MOST) -> dict:
    """Words for each source: shares of all words by weight, none above `most` times its own; the excess is reshared.

    Sources by code point, null last, weigh as `weights` repeated.
    """
    order = sorted(sizes, key=lambda s: (s is None, (s or "").encode()))
    weight = {s: weights[i % len(weights)] for i, s in enumerate(order)}
    out, free, left = {}, list(order), float(sum(sizes.values()))
    while free:
        total = sum(weight[s] for s in free)
        over = [s for s in free if left * weight[s] / total > most * sizes[s]]
        if not over:
            out |= {s: left * weight[s] / total for s in free}
            break
        for s in over:
            out[s] = float(most * sizes[s])
        left -= sum(out[s] for s in over)
        free = [s for s in free if s not in out]
    return out


def flight(p: np.ndarray, size: np.ndarray, rng: np.random.Generator, land: bool) -> np.ndarray:
    """Probabilities moved to 0 or 1 while sums of p and of p * size stay; up to two remain unless `land`."""
    p = p.astype(float).copy()
    wait = [i for i in range(len(p)) if 0 < p[i] < 1]
    wait.reverse()
    draws = rng.random(len(wait) + 3).tolist()
    hold: list[int] = []
    eps = 1e-9
    val, siz = p.tolist(), size.astype(float).tolist()

    def move(v: list[float]) -> None:
        up = down = float("inf")
        for i, d in zip(hold, v, strict=True):
            if d > 0:
                up, down = min(up, (1 - val[i]) / d), min(down, val[i] / d)
            elif d < 0:
                up, down = min(up, -val[i] / d), min(down, (val[i] - 1) / d)
        step = up if draws.pop() * (up + down) < down else -down
        for i, d in zip(hold, v, strict=True):
            val[i] += step * d
            val[i] = 0.0 if val[i] < eps else 1.0 if val[i] > 1 - eps else val[i]
        hold[:] = [i for i in hold if 0 < val[i] < 1]

    while wait or len(hold) == 3:
        while wait and len(hold) < 3:
            hold.append(wait.pop())
        if len(hold) < 3:
            break
        a, b, c = (siz[i] for i in hold)
        v = [b - c, c - a, a - b]
        scale = max(map(abs, v))
        move([x / scale for x in v] if scale else [1.0, -1.0, 0.0])
    if land and len(hold) == 2:
        a, b = (siz[i] for i in hold)
        move([b / max(a, b, 1), -a / max(a, b, 1)] if a or b else [1.0, -1.0])
    if land and hold:
        i = hold[0]
        val[i] = float(draws.pop() < val[i])
    return settle(p, np.array(val), size) if land else np.array(val)


def settle(p: np.ndarray, val: np.ndarray, size: np.ndarray, most: int = 4) -> np.ndarray:
    """End of the landing: turn over up to `most` documents, each time the one that brings the words nearest."""
    free = (p > 0) & (p < 1)
    step = np.where(val > 0.5, -size, size).astype(float)
    miss = float((p * size).sum() - (val * size).sum())
    for _ in range(most):
        gain = np.where(free, np.abs(miss - step), np.inf)
        i = int(np.argmin(gain)) if len(gain) else 0
        if not len(gain) or gain[i] >= abs(miss):
            break
        miss -= step[i]
        val[i], step[i] = 1 - val[i], -step[i]
    return val


def _fly(land: bool, level: int, seed: int):
    def run(key, table):
        # the order is that of a hash of the id, then of the row's values: the same in every run
        table = table.sort_by([("h", "ascending"), ("doc_id", "ascending"), ("size", "ascending"), ("p", "ascending")])
        rng = np.random.default_rng(zlib.crc32(f"{seed}|{level}|{key[0].as_py()}|{key[1].as_py()}".encode()))
        p = flight(table.column("p").to_numpy(), table.column("size").to_numpy(), rng, land)
        return table.set_column(table.schema.get_field_index("p"), "p", pa.array(p)).select(["doc_id", "slot", "size", "p", "whole", "h"])

    return run


def mix_sources(docs: DataFrame, weights: tuple = WEIGHTS, most: float = MOST, seed: int = 11) -> DataFrame:
    """docs(doc_id, text, source) -> one row per input row: doc_id, source, size, source_size, target, copies, taken.

    size is the number of words (runs of bytes other than ASCII white space; null: 0); copies says how often the mix
    takes the document, at most `most` rounded up; taken = copies * size. Null sources form one source. A source
    without words has target 0. Repeated rows and rows without doc_id are documents of their own; reruns agree. An
    empty table gives none. Other columns are ignored.
    """
    spark = docs.sparkSession
    known = stored(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), "text").mapInArrow(_sizes, "doc_id long, source string, size long"))
    sums = known.groupBy("source").agg(F.sum("size").alias("source_size"), F.count("*").alias("n")).collect()
    sums.sort(key=lambda r: (r["source"] is None, (r["source"] or "").encode()))  # slots seed the draws
    want = targets({r["source"]: r["source_size"] for r in sums}, weights, most)
    facts = [(i, r["source"], r["source_size"], want[r["source"]], r["n"]) for i, r in enumerate(sums)]
    dims = spark.createDataFrame(facts, "slot int, source string, source_size long, target double, n long")
    rows = known.join(dims.withColumnRenamed("source", "s"), F.col("source").eqNullSafe(F.col("s"))).drop("s")
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0)
    rows = rows.withColumn("whole", F.floor(rate)).withColumn("p", rate - F.floor(rate))
    few = F.greatest(F.lit(1), F.ceil(F.col("n") / BUCKET))
    done, part = [], rows.select("doc_id", "slot", "size", "p", "whole", F.xxhash64("doc_id", F.lit(seed)).alias("h"), F.pmod(F.when(F.col("doc_id").isNull(), F.xxhash64("size")).otherwise(F.xxhash64("doc_id")), few).alias("bucket"))
    schema = "doc_id long, slot int, size long, p double, whole long, h long"
    largest = max([r["n"] for r in sums], default=0)
    level = 0
    while True:
        last = largest <= BUCKET
        out = stored(part.groupBy("slot", "bucket").applyInArrow(_fly(last, level, seed), schema))
        if last:
            done.append(out)
            break
        done.append(out.where("p = 0 or p = 1"))
        rest = out.where("p > 0 and p < 1")
        buckets = -(-largest // BUCKET)
        largest, level = 2 * buckets, level + 1
        k = -(-largest // BUCKET)
        part = rest.withColumn("bucket", F.pmod(F.xxhash64("doc_id", "size", F.lit(level)), F.lit(k)))
    out = done[0]
    for d in done[1:]:
        out = out.unionByName(d)
    out = out.drop("h").join(dims, "slot")
    copies = (F.col("whole") + F.col("p")).cast("long")
    return out.select("doc_id", "source", "size", "source_size", "target", copies.alias("copies"), (copies * F.col("size")).alias("taken"))
