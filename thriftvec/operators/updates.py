"""Inserts in four grades of cost, deletes by mark, compaction."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.encoders import Encoder, Meter
from .kernels import insert

_SCHEMA = pa.schema([("shard", pa.int32()), ("node_id", pa.int64()), ("kind", pa.string()), *((c, pa.int64()) for c in ("search", "choose", "repair", "cheap", "called")), ("nbrs", pa.list_(pa.int64()))])
MODES = ("naive", "cached", "light", "simple")


def insert_batch(nodes: DataFrame, rows: DataFrame, encoder: Encoder, cap: int = 18, ef: int = 60, mode: str = "simple", codebook: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """nodes(shard, node_id, text, nbrs[, code]), rows(shard, node_id, text) -> (lists: shard, node_id, nbrs; ledger per
    insert).

    A task holds one shard; an existing id is replaced. Vectors are encoded when an insert asks for them, and then only.
    The ledger counts encoder calls by purpose; `called` is what the encoder's own meter saw during the insert. The light
    and the simple form read the stored codes and need `codebook`.
    """
    from ..sources.storage import stored
    from .pq import codebook_array, encode_rows

    if mode not in MODES:
        raise ValueError(f"unknown mode {mode}")
    by_code = mode in ("light", "simple")
    if by_code and codebook is None:
        raise ValueError(f"{mode} inserts need the codebook")
    book = codebook_array(codebook) if by_code else None
    nodes = nodes.select("shard", "node_id", "text", "nbrs", *(["code"] if by_code else []))

    def decoded(codes: np.ndarray) -> np.ndarray:
        return np.concatenate([book[s][codes[:, s]] for s in range(len(book))], 1).astype(np.float64)

    def run(key, old, new):
        shard = (key[0]).as_py()
        fresh = dict(zip(new.column("node_id").to_pylist(), new.column("text").to_pylist(), strict=True))
        old = old.filter(pc.invert(pc.is_in(old.column("node_id"), pa.array(list(fresh), pa.int64())))).sort_by("node_id")
        added = sorted(fresh)
        ids = [*old.column("node_id").to_pylist(), *added]
        texts = [*old.column("text").to_pylist(), *(fresh[i] for i in added)]
        at = {i: n for n, i in enumerate(ids)}
        meter = Meter()
        ask = replace(encoder, meter=meter, held={})
        links: list[list[int]] = [[at[v] for v in (a or []) if v in at] for a in old.column("nbrs").to_pylist()] + [[] for _ in added]
        approx = None
        if by_code:
            code = old.column("code").to_pylist()
            approx = np.zeros((len(ids), sum(b.shape[1] for b in book)))
            if code:
                approx[: len(code)] = decoded(np.frombuffer(b"".join(code), np.uint8).reshape(len(code), -1))
        out = []
        n_old = old.num_rows
        entry = int(np.argmax([len(a) for a in links[:n_old]])) if n_old else -1
        for u in range(n_old, len(ids)):
            own = ask.encode([texts[u]])[0]
            if by_code:
                approx[u] = decoded(encode_rows(own[None].astype(np.float32), book))[0]
            if entry < 0:
                entry = u
                continue
            before = meter.objects
            led = insert(links, u, own, lambda miss: ask.encode([texts[v] for v in miss]), entry, cap, ef, mode, approx)
            out.append((shard, ids[u], "ledger", led.search, led.select, led.repair, led.cheap, meter.objects - before, None))
        out += [(shard, ids[u], "list", 0, 0, 0, 0, 0, [ids[v] for v in a]) for u, a in enumerate(links)]
        return pa.table([pa.array(c, f.type) for c, f in zip(zip(*out, strict=True), _SCHEMA, strict=True)], schema=_SCHEMA) if out else _SCHEMA.empty_table()

    both = nodes.groupBy("shard").cogroup(rows.select("shard", "node_id", "text").groupBy("shard"))
    both = stored(both.applyInArrow(run, "shard int, node_id long, kind string, search long, choose long, repair long, cheap long, called long, nbrs array<long>"))
    ledger = both.where("kind = 'ledger'").select("node_id", F.lit(mode).alias("mode"), "search", "choose", "repair", "cheap", "called", (F.col("search") + F.col("choose") + F.col("repair")).alias("encodes"))
    return both.where("kind = 'list'").select("shard", "node_id", "nbrs"), ledger


def delete(tombstones: DataFrame, ids: DataFrame) -> DataFrame:
    """Marks are only added: node_id."""
    return tombstones.select("node_id").unionByName(ids.select("node_id")).distinct()


def compact(edges: DataFrame, tombstones: DataFrame, vectors: DataFrame | None = None, cap: int | None = None) -> DataFrame:
    """Drop marked nodes; their neighbours are linked to each other (two-hop repair), then cut to the cap by distance."""
    from ..functions.distance import l2sq
    from .graphs import nearest_edges

    d = tombstones.select("node_id")
    live = edges.join(d, edges["u"] == d["node_id"], "left_anti").join(d, edges["v"] == d["node_id"], "left_anti").select("u", "v", "dist")
    if vectors is None:
        return live
    into = edges.join(d, edges["v"] == d["node_id"], "left_semi").join(d, edges["u"] == d["node_id"], "left_anti").select("u", F.col("v").alias("dead"))
    outof = edges.join(d, edges["u"] == d["node_id"], "left_semi").join(d, edges["v"] == d["node_id"], "left_anti").select(F.col("u").alias("dead"), F.col("v").alias("w"))
    hop = into.join(outof, "dead").where("u <> w").select("u", F.col("w").alias("v")).distinct()
    a, b = vectors.select(F.col("node_id").alias("u"), F.col("v").alias("x")), vectors.select(F.col("node_id").alias("v"), F.col("v").alias("y"))
    bridged = hop.join(a, "u").join(b, "v").select("u", "v", l2sq("x", "y").alias("dist"))
    e = live.unionByName(bridged).groupBy("u", "v").agg(F.min("dist").alias("dist"))
    return nearest_edges(e, cap) if cap else e
