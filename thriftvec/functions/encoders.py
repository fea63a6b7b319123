"""Deterministic stand-ins for an embedding model, metered: calls, objects, batches and bytes.

No model runs here. E1 counts hashed tokens with a sign (integers, so SQL gives the same bit for bit); E2 is its unit
vector; E3 hashes character n-grams; E4 is E2 at a quarter of the width; E5 looks vectors up as if they were costly.
"""

from __future__ import annotations

import hashlib
import re
import time
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .text import tokens

_TOKEN = re.compile(r"[^\W_]+")
_known: dict[str, int] = {}
HELD = 1 << 16  # texts whose token counts are held, at most


def _hash(token: str) -> int:
    h = _known.get(token)
    if h is None:
        h = int(hashlib.md5(token.encode()).hexdigest()[:8], 16)
        if len(_known) < 1 << 19:
            _known[token] = h
    return h


@dataclass
class Meter:
    """What an encoder was asked for."""

    calls: int = 0
    objects: int = 0
    bytes: int = 0
    fills: list[int] = field(default_factory=list)


@dataclass
class Encoder:
    """kind: hash_int, hash_unit, hash_ngram, hash_small or lookup (the object's text is its vector); simulated costs are off unless set."""

    kind: str = "hash_unit"
    dim: int = 256
    ngram: int = 3
    us_per_object: float = 0.0
    us_per_batch: float = 0.0
    meter: Meter = field(default_factory=Meter)
    held: dict[str, np.ndarray] | None = None  # token counts of texts encoded before; their calls are metered all the same

    @property
    def id(self) -> str:
        return f"{self.kind}:{self.width}"

    @property
    def width(self) -> int:
        return self.dim // 4 if self.kind == "hash_small" else self.dim

    @classmethod
    def parse(cls, spec: str) -> Encoder:
        kind, _, dim = spec.partition(":")
        return cls(kind, int(dim or 256))

    def units(self, text: str) -> list[str]:
        low = text.lower()
        if self.kind == "hash_ngram":
            return [low[i : i + self.ngram] for i in range(max(0, len(low) - self.ngram + 1))]
        return _TOKEN.findall(low)

    def encode(self, texts: list[str | None]) -> np.ndarray:
        """One row per text; a text without tokens is the zero vector."""
        out = np.zeros((len(texts), self.width), np.float64)
        for i, t in enumerate(texts):
            if self.kind == "lookup":
                if t:
                    out[i] = np.array(t.split(","), np.float32)
                self.meter.bytes += len(t or "")
                continue
            self.meter.bytes += len(t or "")
            if self.held is not None and (c := self.held.get(t or "")) is not None:
                out[i] = c
                continue
            h = np.fromiter((_hash(u) for u in self.units(t or "")), np.int64)
            np.add.at(out[i], h % self.width, np.where(h >> 16 & 1, -1, 1))
            if self.held is not None and len(self.held) < HELD:
                self.held[t or ""] = out[i].astype(np.int32)
        self.meter.calls += 1
        self.meter.objects += len(texts)
        self.meter.fills.append(len(texts))
        cost = self.us_per_batch + self.us_per_object * len(texts)
        if cost:
            time.sleep(cost / 1e6)
        if self.kind == "hash_int":
            return out
        if self.kind == "lookup":
            return out.astype(np.float32)
        n = np.sqrt((out * out).sum(1, keepdims=True))
        return np.divide(out, n, out=np.zeros_like(out), where=n > 0).astype(np.float32)


def encode(objects: DataFrame, encoder: Encoder, key: str = "chunk_id", batch: int = 1024) -> DataFrame:
    """objects(key, text) -> key, v: a narrow map; only vectors leave the worker, texts don't."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for a in range(0, b.num_rows, batch):
                part = b.slice(a, batch)
                v = encoder.encode(part.column(1).to_pylist()).astype(np.float32)
                flat = pa.FixedSizeListArray.from_arrays(pa.array(v.ravel()), v.shape[1]).cast(pa.list_(pa.float32()))
                yield pa.RecordBatch.from_arrays([part.column(0), flat], names=[key, "v"])

    return objects.select(F.col(key).cast("long").alias(key), "text").mapInArrow(run, f"{key} long, v array<float>")


def encode_int(objects: DataFrame, dim: int = 256, key: str = "chunk_id") -> DataFrame:
    """E1 in relational form: key, dim, v (non-zero coordinates only), with a partial sum before the one shuffle."""
    h = F.conv(F.substring(F.md5("t"), 1, 8), 16, 10).cast("long")
    sign = F.when(F.shiftright("h", 16).bitwiseAND(F.lit(1)) == 1, -1).otherwise(1)
    t = objects.select(key, F.explode(tokens(F.col("text"))).alias("t")).select(key, h.alias("h"))
    return t.groupBy(key, (F.col("h") % dim).cast("int").alias("dim")).agg(F.sum(sign).alias("v")).where("v <> 0")


def encode_int_rows(objects: DataFrame, dim: int = 256, key: str = "chunk_id") -> DataFrame:
    """E1 without a shuffle: key, at, with one signed number, coordinate + 1, for each token."""
    h = lambda t: F.conv(F.substring(F.md5(t), 1, 8), 16, 10).cast("long")
    one = lambda h: (F.when(F.shiftright(h, 16).bitwiseAND(F.lit(1)) == 1, -1).otherwise(1) * (h % dim + 1)).cast("int")
    return objects.select(key, F.transform(F.transform(tokens(F.col("text")), h), one).alias("at"))


def profile_batch(encoder: Encoder, texts: list[str], sizes: tuple = (1, 4, 16, 64, 256)) -> list[tuple[int, float]]:
    """Objects a second for each batch size, to choose the batching target from."""
    out = []
    for n in sizes:
        t = time.perf_counter()
        for a in range(0, len(texts), n):
            encoder.encode(texts[a : a + n])
        out.append((n, len(texts) / max(time.perf_counter() - t, 1e-9)))
    return out
