"""Exact substring de-duplication with fixed-block anchors.

Every document is cut into non-overlapping reference blocks of `block` words, which form the index; every rolling
window of `block` words of every document probes it. A window of `window >= 2 * block` words always contains a whole
reference block of any document that shares it, so no shared window is missed. Blocks and probes are looked up by a
key (the smallest hash of their short runs), which rolling windows share with their neighbours: about a tenth of the
words cause a row. Hits are then extended in both directions: every `window`-word run that holds a hit is compared,
by a 96-bit hash of its words, with those of all documents, and the smallest document that has it is its owner.
Overlapping runs join to maximal repeats, of which the owner keeps the only copy.

At 100 TB: no broadcast, no collect, nothing pairwise; index, probes and runs are grouped by hash with map-side
minima, and joins back may be split by adaptive execution. Text is shuffled only to meet its own document's lists.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, stored
from .words import Words, blocks, mix, run_hash

WINDOW = 50
GRAM = 8


def _rolling_min(x: np.ndarray, k: int) -> np.ndarray:
    width = 1
    while width * 2 <= k:
        x = np.minimum(x[:-width], x[width:])
        width *= 2
    rest = k - width
    return np.minimum(x[: len(x) - rest], x[rest:]) if rest else x


def _keys(w: Words, block: int, gram: int) -> tuple[np.ndarray, np.ndarray]:
    """The key of each rolling window of `block` words of the block of rows, and whether it lies in one row."""
    if len(w.hash) < block:
        return np.empty(0, np.uint64), np.empty(0, bool)
    return _rolling_min(run_hash(w.hash, gram), block - gram + 1), w.inside(block)


def _probe(block: int, gram: int):
    schema = pa.schema([("key", pa.int64()), ("doc_id", pa.int64()), ("anchor", pa.bool_())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in blocks(batches, "text"):
            w = Words(b.column("text"))
            key, ok = _keys(w, block, gram)
            at = np.flatnonzero(ok)
            if not len(at):
                continue
            key, row = key[at], w.row[at]
            aligned = (at - w.bounds[row]) % block == 0
            first = np.flatnonzero(np.r_[True, (key[1:] != key[:-1]) | (row[1:] != row[:-1])])
            ids = np.asarray(b.column("doc_id").to_numpy(zero_copy_only=False), np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(key[first].view(np.int64)), pa.array(ids[row[first]]), pa.array(np.logical_or.reduceat(aligned, first))], schema=schema)

    return run


def _windows(window: int, block: int, gram: int):
    schema = pa.schema([("w", pa.int64()), ("w2", pa.int32()), ("doc_id", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in blocks(batches, "text"):
            w = Words(b.column("text"))
            key, ok = _keys(w, block, gram)
            if len(w.hash) < window:
                continue
            live = b.column("keys")
            flat = live.values.to_numpy(zero_copy_only=False)
            lo = live.offsets.to_numpy()
            hit = np.zeros(len(key) + 1, np.int64)
            for r in range(w.rows):
                s, e = w.bounds[r], max(w.bounds[r], w.bounds[r + 1] - block + 1)
                if e > s:
                    hit[s:e] = np.isin(key[s:e].view(np.int64), flat[lo[r] : lo[r + 1]])
            hit[:-1] &= ok
            c = np.r_[0, np.cumsum(hit[:-1])]
            inside = w.inside(window)
            n = len(inside)
            held = c[window - block + 1 : window - block + 1 + n] - c[:n] > 0
            at = np.flatnonzero(inside & held)
            if not len(at):
                continue
            one = run_hash(w.hash, window)[at]
            two = run_hash(mix(w.hash ^ np.uint64(0x5851F42D4C957F2D)), window)[at]
            ids = np.asarray(b.column("doc_id").to_numpy(zero_copy_only=False), np.int64)[w.row[at]]
            yield pa.RecordBatch.from_arrays([pa.array(one.view(np.int64)), pa.array((two >> np.uint64(32)).astype(np.uint32).view(np.int32)), pa.array(ids)], schema=schema)

    return run


def repeats(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """docs(doc_id, text) -> (doc_id, th, copy, gone): th is the text's md5; copy: a smaller id has the same text;
    gone: hashes of the window-word runs of this document of which a smaller document has the same words."""
    block, gram = window // 2, min(GRAM, window // 2)
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").where("doc_id is not null")
    ids = stored(docs.select("doc_id", F.md5(F.coalesce("text", F.lit(""))).alias("th")).distinct())
    least = ids.groupBy("th").agg(F.min("doc_id").alias("least"), F.max("doc_id").alias("most")).where("least < most")
    copies = ids.join(least, "th").where("doc_id > least").select("doc_id", "th", F.lit(True).alias("copy"))

    probes = docs.mapInArrow(_probe(block, gram), "key long, doc_id long, anchor boolean")
    live = probes.groupBy("key").agg(F.min(F.when(F.col("anchor"), F.col("doc_id"))).alias("ref"), F.max("doc_id").alias("far")).where("ref < far").select("key")
    live = stored(live)  # apart from the join, so that hot keys can be split there
    lists = probes.select("key", "doc_id").join(live, "key").groupBy("doc_id").agg(F.collect_set("key").alias("keys"))
    # whole copies are decided by their md5; the smallest of them stands for all
    alone = copies.join(ids.groupBy("doc_id").agg(F.count("*").alias("texts")).where("texts = 1"), "doc_id").select("doc_id")
    near = stored(docs.join(lists.join(alone, "doc_id", "left_anti"), "doc_id"))
    discard(live)
    runs = near.mapInArrow(_windows(window, block, gram), "w long, w2 int, doc_id long")
    owner = runs.groupBy("w", "w2").agg(F.min("doc_id").alias("least"), F.max("doc_id").alias("most")).where("least < most").select("w", "w2", "least")
    owner = stored(owner)
    gone = runs.join(owner, ["w", "w2"]).where("doc_id > least").groupBy("doc_id").agg(F.collect_set("w").alias("gone"))
    return ids.join(copies, ["doc_id", "th"], "left").join(gone, "doc_id", "left").where("copy or gone is not null").select("doc_id", "th", F.coalesce("copy", F.lit(False)).alias("copy"), "gone")


def _cut(window: int, digest: bool, others: list[str], fields: pa.Schema):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in blocks(batches, "text"):
            w = Words(b.column("text"), hashes=False)
            texts = b.column("text")
            copy, gone = b.column("copy").to_pylist(), b.column("gone")
            has = np.asarray(gone.is_valid())
            removed = np.zeros(w.rows, np.int64)
            kept: list = [None] * w.rows
            for r in range(w.rows):
                n = w.counts[r]
                if n >= window and copy[r]:
                    removed[r] = n
                    kept[r] = b""
                elif n >= window and has[r]:
                    h = Words(texts.slice(r, 1)).hash
                    hit = np.isin(run_hash(h, window).view(np.int64), gone[r].values.to_numpy(zero_copy_only=False))
                    edge = np.zeros(n + 1, np.int64)
                    edge[: len(hit)] += hit
                    edge[window : window + len(hit)] -= hit
                    stay = np.cumsum(edge[:n]) == 0
                    removed[r] = n - stay.sum()
                    if removed[r]:
                        parts = texts[r].as_py().encode().split()
                        kept[r] = b" ".join([parts[i] for i in np.flatnonzero(stay)])
            rest = [b.column(c) for c in others]
            counts = [pa.array(w.counts.astype(np.int64)), pa.array(removed)]
            if digest:
                data = memoryview(w.data)
                sha = [hashlib.sha256(k if k is not None else b" ".join(bytes(data[w.offsets[r] : w.offsets[r + 1]]).split())).hexdigest() for r, k in enumerate(kept)]
                yield pa.RecordBatch.from_arrays([*rest, *counts, pa.array(sha, pa.string())], schema=fields)
            else:
                out = [None if not t.is_valid else (t.as_py() if k is None else k.decode()) for t, k in zip(texts, kept, strict=True)]
                yield pa.RecordBatch.from_arrays([*rest, *counts, pa.array(out, pa.string())], schema=fields)

    return run


def remove_repeats(docs: DataFrame, window: int = WINDOW, digest: bool = False) -> DataFrame:
    """Remove every word covered by a `window`-word run whose words also start in a document of smaller doc_id.

    docs: at least doc_id and text; the other columns are carried along. Adds _n_words and _n_removed and the kept
    text (_kept: the text itself where nothing goes, else the kept words joined by one space), or with digest the
    sha256 of the kept words (_kept_sha256). A word is a run of bytes other than white space of ASCII.

    Null or empty texts have no words and stay as they are; rows without doc_id neither lose words nor serve as
    reference; columns named like the added ones are replaced; repeated rows of one doc_id don't count as repeats of each other; documents shorter than the window
    keep all. An empty table gives an empty result.
    """
    from pyspark.sql import types as T
    from pyspark.sql.pandas.types import to_arrow_schema

    gone = repeats(docs.select("doc_id", "text"), window).withColumnsRenamed({"doc_id": "g_id", "th": "g_th"})
    others = [c for c in docs.columns if c != "text" and c.lower() not in ("_n_words", "_n_removed", "_kept", "_kept_sha256")]
    names = [f"c{i}" for i in range(len(others))]
    j = docs.select(*(F.col(c).alias(n) for c, n in zip(others, names, strict=True)), F.col("text").alias("text"), F.col("doc_id").cast("long").alias("d_id"), F.md5(F.coalesce("text", F.lit(""))).alias("d_th"))
    j = j.join(gone, (F.col("d_id") == F.col("g_id")) & (F.col("d_th") == F.col("g_th")), "left").select(*names, "text", "copy", "gone")
    last = "_kept_sha256" if digest else "_kept"
    schema = T.StructType([j.schema[n] for n in names] + [T.StructField("_n_words", T.LongType()), T.StructField("_n_removed", T.LongType()), T.StructField(last, T.StringType())])
    out = j.mapInArrow(_cut(window, digest, names, to_arrow_schema(schema)), schema)
    return out.withColumnsRenamed(dict(zip(names, others, strict=True)))
