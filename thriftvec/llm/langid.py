"""Language identification with string kernels.

The kernel of two texts is the number of character n-grams (1 to 4) that both have, over the root of the product of
their numbers: a blended-spectrum presence kernel. Landmarks drawn from the labelled texts turn it into features by
Nyström's method, and kernel ridge regression, one language against the rest, is solved on a bounded labelled sample.
Scoring a batch of texts is a product of their presence rows with landmarks times regression weights; the latter product is
the same for all texts and made once.

n-grams are told apart by `BUCKETS` hash buckets. White space counts as one space; case is ignored. The score is the
winner's share of all languages' positive outputs, so that it does not depend on a text's length.

At 100 TB: the model is fitted on a bounded sample, `PER_LANGUAGE` texts of each language and `LABELLED` in all, chosen by
hash of doc_id in two steps, so that no task meets all rows of a language; what reaches the driver are their presence rows
(`BUCKETS` bits each), not their texts. Scoring is a map without shuffle that ships a model of fixed size.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .words import blocks

BUCKETS = 1 << 16
ORDERS = (1, 2, 3, 4)
PER_LANGUAGE = 400  # labelled texts of a language that the model is fitted on, at most
LABELLED = 1 << 14  # of all languages; with very many languages each gets fewer
LANDMARKS = 24  # of them for each language
RIDGE = 1e-2
UNKNOWN = "und"
_BLANK = re.compile(r"\s+")


def presence(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Sorted (row, bucket) pairs of the n-grams that the texts have, as rows and buckets."""
    clean = [f" {_BLANK.sub(' ', t.lower()).strip()} " for t in texts]
    n = np.array([len(t) for t in clean], np.int64)
    cp = np.frombuffer("".join(clean).encode("utf-32-le", "surrogatepass"), "<u4").astype(np.uint64)
    row = np.repeat(np.arange(len(texts), dtype=np.int64), n)
    left = np.repeat(np.cumsum(n), n) - np.arange(len(cp))
    seen = np.zeros(len(texts) * BUCKETS, bool)
    h = np.zeros(len(cp), np.uint64)
    shift = np.uint64(64 - (BUCKETS.bit_length() - 1))
    for k in range(1, max(ORDERS) + 1):
        h[: len(cp) - k + 1] = (h[: len(cp) - k + 1] ^ (cp[k - 1 :] + np.uint64(k))) * np.uint64(0x9E3779B97F4A7C15)
        if k in ORDERS:
            ok = left >= k
            seen[row[ok] * BUCKETS + ((h[ok] ^ (h[ok] >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9) >> shift).astype(np.int64)] = True
    at = np.flatnonzero(seen)
    return at // BUCKETS, at % BUCKETS


class KernelModel:
    """Languages, landmark presence (scaled; one row for each bucket) and regression weights."""

    def __init__(self, langs: list[str], marks: np.ndarray, weights: np.ndarray):
        self.langs, self.marks, self.weights = langs, marks, weights

    def kernel(self, rows: np.ndarray, buckets: np.ndarray, texts: int) -> np.ndarray:
        """Product of the sparse presence rows with the landmarks; every text has an n-gram (the space around it)."""
        start = np.searchsorted(rows, np.arange(texts))
        size = np.diff(np.r_[start, len(rows)])
        out = np.add.reduceat(self.marks[buckets], start, axis=0) if len(rows) else np.zeros((texts, self.marks.shape[1]), np.float32)
        return out / np.sqrt(np.maximum(size, 1))[:, None]

    def scorer(self) -> Scorer:
        return Scorer(self.langs, np.ascontiguousarray((self.marks @ self.weights).T))


class Scorer:
    """Languages and, for each, what an n-gram of each bucket adds."""

    def __init__(self, langs: list[str], adds: np.ndarray):
        self.langs, self.adds = langs, adds

    def scores(self, texts: list[str]) -> np.ndarray:
        rows, buckets = presence(texts)
        start = np.searchsorted(rows, np.arange(len(texts)))
        size = np.diff(np.r_[start, len(rows)])
        total = np.stack([np.add.reduceat(a[buckets], start, dtype=np.float64) for a in self.adds], 1)
        return total / np.sqrt(size)[:, None]


def fit(buckets: list[np.ndarray], labels: list[str]) -> KernelModel:
    """Buckets of each labelled text, in the order of their draw; the first of each language are its landmarks."""
    langs = sorted(set(labels))
    y = np.array([langs.index(x) for x in labels], int)
    at = np.concatenate([np.flatnonzero(y == i)[:LANDMARKS] for i in range(len(langs))]) if langs else np.empty(0, int)
    marks = np.zeros((BUCKETS, len(at)), np.float32)
    for j, i in enumerate(at):
        marks[buckets[i], j] = 1 / np.sqrt(max(1, len(buckets[i])))
    model = KernelModel(langs, marks, np.zeros((len(at), len(langs)), np.float32))
    if not len(at):
        return model
    k = np.concatenate([model.kernel(np.zeros(len(b), np.int64), b, 1) for b in buckets]).astype(float)
    value, vector = np.linalg.eigh((k[at] + k[at].T) / 2)
    keep = value > 1e-6 * value.max()
    half = vector[:, keep] / np.sqrt(value[keep])
    phi = k @ half
    w = 1 / np.bincount(y)[y]
    target = (y[:, None] == np.arange(len(langs))).astype(float)
    gram = (phi * w[:, None]).T @ phi + RIDGE * np.eye(phi.shape[1])
    model.weights = (half @ np.linalg.solve(gram, (phi * w[:, None]).T @ target)).astype(np.float32)
    return model


def _bits(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in blocks(batches, "text"):
        for a in range(0, b.num_rows, 64):
            part = b.slice(a, 64)
            row, bucket = presence(part.column("text").to_pylist())
            cut = np.searchsorted(row, np.arange(part.num_rows + 1))
            raw = []
            for s, e in zip(cut[:-1], cut[1:], strict=True):
                full = np.zeros(BUCKETS, bool)
                full[bucket[s:e]] = True
                raw.append(np.packbits(full).tobytes())
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("lang"), part.column("h"), pa.array(raw, pa.binary())], names=["doc_id", "lang", "h", "bits"])


def train(docs: DataFrame) -> KernelModel:
    """Fit on docs(doc_id, text, lang): of each language the rows with the smallest hash of doc_id."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.col("lang").cast("string").alias("lang"))
    docs = docs.where("lang is not null and text is not null and doc_id is not null").withColumn("h", F.xxhash64("doc_id"))
    rows = docs.select("doc_id", "lang", "h", F.pmod(F.xxhash64("doc_id", F.lit(3)), F.lit(256)).alias("salt"))
    langs = docs.select("lang").distinct().limit(LABELLED + 1).count()  # a count, one row for each language
    most = max(1, min(PER_LANGUAGE, LABELLED // max(1, langs)))
    first = lambda *by: F.row_number().over(Window.partitionBy(*by).orderBy("h", "doc_id"))
    pick = rows.withColumn("r", first("lang", "salt")).where(F.col("r") <= most).withColumn("r", first("lang")).where(F.col("r") <= most)
    pick = pick.orderBy("r", "h", "lang").limit(LABELLED).select("doc_id", "lang").distinct()
    few = docs.join(F.broadcast(pick), ["doc_id", "lang"])  # LABELLED rows at most
    got = few.mapInArrow(_bits, "doc_id long, lang string, h long, bits binary").collect()
    got.sort(key=lambda r: (r["lang"], r["h"], r["doc_id"], bytes(r["bits"])))
    return fit([np.flatnonzero(np.unpackbits(np.frombuffer(r["bits"], np.uint8))) for r in got], [r["lang"] for r in got])


def _predict(model, keys: list[str], fields: pa.Schema):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = model.value
        for big in blocks(batches, "text"):
            for a in range(0, big.num_rows, 128):
                b = big.slice(a, 128)
                texts = b.column("text").to_pylist()
                ask = [i for i, t in enumerate(texts) if t and any(map(str.isalpha, t))]
                lang, score = [UNKNOWN] * len(texts), np.zeros(len(texts))
                if ask and m.langs:
                    s = m.scores([texts[i] for i in ask])
                    share = s.max(1) / np.maximum(np.maximum(s, 0).sum(1), 1e-9)
                    for i, j, v in zip(ask, s.argmax(1), share, strict=True):
                        lang[i], score[i] = m.langs[j], v
                yield pa.RecordBatch.from_arrays([*(b.column(k) for k in keys), pa.array(lang), pa.array(np.clip(score.astype(float), 0, 1))], schema=fields)

    return run


def identify(docs: DataFrame, model: KernelModel, keep: list[str] | None = None) -> DataFrame:
    """docs with a column text -> columns `keep` (default doc_id), _lang and _score (0 to 1).

    A text that is null or has no letter is `und` with score 0, as is every text where no labelled row was learned.
    Rows are judged one by one, whole; repeated rows get equal results; an empty table gives an empty result. Of kept
    columns that are named _lang or _score only the new ones are returned.
    """
    from pyspark.sql import types as T
    from pyspark.sql.pandas.types import to_arrow_schema

    keep = [c for c in keep or ["doc_id"] if c.lower() not in ("_lang", "_score")]
    names = [f"c{i}" for i in range(len(keep))]
    d = docs.select(*(F.col(c).alias(n) for c, n in zip(keep, names, strict=True)), F.col("text").alias("text"))
    schema = T.StructType([d.schema[n] for n in names] + [T.StructField("_lang", T.StringType()), T.StructField("_score", T.DoubleType())])
    shared = docs.sparkSession.sparkContext.broadcast(model.scorer())
    return d.mapInArrow(_predict(shared, names, to_arrow_schema(schema)), schema).withColumnsRenamed(dict(zip(names, keep, strict=True)))
