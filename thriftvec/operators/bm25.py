"""BM25: postings, statistics and top-k; contributions are floored to 1e-6 and summed as integers, so order is fixed."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.text import tokens
from .exact import top_k


@dataclass
class Bm25Index:
    postings: DataFrame  # term, node_id, tf
    lengths: DataFrame  # node_id, dl
    df: DataFrame  # term, df
    n: int
    total: int


def bm25_build(objects: DataFrame) -> Bm25Index:
    """objects(node_id, text) -> index; one shuffle of (term, node) pairs after partial counts."""
    t = objects.select("node_id", F.explode(tokens(F.col("text"))).alias("term"))
    postings = t.groupBy("term", "node_id").agg(F.count("*").alias("tf"))
    lengths = objects.select("node_id", F.size(tokens(F.coalesce("text", F.lit("")))).cast("long").alias("dl"))
    df = postings.groupBy("term").agg(F.count("*").alias("df"))
    n, total = lengths.agg(F.count("*"), F.coalesce(F.sum("dl"), F.lit(0))).first()
    return Bm25Index(postings, lengths, df, n, total)


def bm25_search(index: Bm25Index, queries: DataFrame, k: int, k1: float = 1.2, b: float = 0.75) -> DataFrame:
    """queries(query_id, text) -> query_id, rank, node_id, dist (dist = -score in units of 1e-6).

    Distinct query terms meet their postings in an equi join; query terms are few and broadcast while small.
    """
    q = queries.select("query_id", F.explode(F.array_distinct(tokens(F.col("text")))).alias("term"))
    j = index.postings.join(q, "term").join(index.df, "term").join(index.lengths, "node_id")
    idf = F.log1p((F.lit(index.n) - F.col("df") + 0.5) / (F.col("df") + 0.5))
    mean = index.total / max(index.n, 1)
    part = idf * (F.col("tf") * (k1 + 1)) / (F.col("tf") + k1 * (1 - b + b * F.col("dl") / mean))
    s = j.groupBy("query_id", "node_id").agg(F.sum(-F.floor(part * 1_000_000).cast("long")).alias("dist"))
    return top_k(s, k)


def bm25_bytes(index: Bm25Index) -> int:
    """Plain size of the postings: 8-byte id and 4-byte count a posting, term text and 8 bytes a term."""
    p = index.postings.count()
    t = index.df.agg(F.coalesce(F.sum(F.length("term") + 8), F.lit(0))).first()[0]
    return 12 * p + t
