"""Accuracy and cost measures; every search returns the same columns, so they apply to all methods alike."""

from __future__ import annotations

import re
from collections import Counter

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.text import tokens


def recall_at_k(result: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """Per query of the truth: share of its k true neighbours found (missing queries count 0)."""
    t = truth.where(F.col("rank") <= k).select("query_id", "node_id")
    hit = t.join(result.where(F.col("rank") <= k).select("query_id", "node_id", F.lit(1).alias("h")), ["query_id", "node_id"], "left")
    return hit.groupBy("query_id").agg(F.round(F.sum(F.coalesce("h", F.lit(0))) / F.count("*"), 6).alias("recall"))


def mean_recall(result: DataFrame, truth: DataFrame, k: int) -> float:
    return recall_at_k(result, truth, k).agg(F.avg("recall")).first()[0] or 0.0


def normal(text: Column) -> Column:
    """Answer normalisation: lower case, letters and digits only, articles dropped, single spaces."""
    return F.array_join(F.filter(tokens(text), lambda t: ~t.isin("a", "an", "the")), " ")


def exact_match(pairs: DataFrame) -> DataFrame:
    """pairs(query_id, pred, gold), several gold answers allowed -> query_id, em (best over answers)."""
    return pairs.groupBy("query_id").agg(F.max((normal(F.col("pred")) == normal(F.col("gold"))).cast("int")).alias("em"))


def token_f1(pairs: DataFrame) -> DataFrame:
    """Harmonic mean of token precision and recall, best over answers: query_id, f1."""
    d = pairs.select("query_id", "gold", F.split(normal(F.col("pred")), " ").alias("p"), F.split(normal(F.col("gold")), " ").alias("g"))
    d = d.select("query_id", *(F.filter(c, lambda t: t != "").alias(c) for c in ("p", "g")))
    same = F.aggregate(F.array_distinct("p"), F.lit(0), lambda s, t: s + F.least(F.size(F.filter("p", lambda x: x == t)), F.size(F.filter("g", lambda x: x == t))))
    f1 = F.when(F.size("p") + F.size("g") > 0, F.lit(2.0) * same / (F.size("p") + F.size("g"))).otherwise(1.0)
    return d.groupBy("query_id").agg(F.round(F.max(f1), 6).alias("f1"))


def answer_f1(pred: str, gold: str) -> float:
    """token_f1 of one pair."""
    p, g = ([t for t in re.findall(r"[^\W_]+", x.lower()) if t not in ("a", "an", "the")] for x in (pred, gold))
    return 2 * sum((Counter(p) & Counter(g)).values()) / (len(p) + len(g)) if p or g else 1.0


def recompute_count(trace: DataFrame) -> DataFrame:
    """trace(query_id, step, n_exact, ...) -> objects encoded per query."""
    return trace.groupBy("query_id").agg(F.sum("n_exact").alias("recomputes"))


def batch_stats(stats: DataFrame) -> DataFrame:
    """stats(query_id, n_exact, n_batches) -> queries, objects, batches, mean fill."""
    return stats.agg(F.count("*").alias("queries"), F.sum("n_exact").alias("objects"), F.sum("n_batches").alias("batches"), F.round(F.sum("n_exact") / F.sum("n_batches"), 3).alias("mean_fill"))


def overhead_pct(retrieval: Column, generation: Column) -> Column:
    return F.round(F.lit(100) * retrieval / (retrieval + generation), 6)


def at_recall(runs: list[tuple[float, float]], target: float) -> float | None:
    """runs of (recall, cost): the least cost that reaches the target, None where none does."""
    return min((c for r, c in runs if r >= target), default=None)


def speedup(base: float | None, other: float | None) -> float | None:
    return base / other if base and other else None


def storage_bytes(method: str, n: float, dim: int, cap: int = 60, avg_degree: float = 18, code_bytes: float | None = None, cells: float = 0, sector: int = 4096, postings: float = 0) -> tuple[float, float]:
    """(metadata, vectors) of an index over n objects. Lists are padded to the cap for the stored-vector graph and the
    quantized one; the recompute index has packed rows at its average degree."""
    full, codes = 4.0 * dim * n, (code_bytes if code_bytes is not None else 4.0 * dim / 100) * n
    return {
        "hnsw": (4.0 * cap * n, full),
        "hnsw_csr": (4.0 * avg_degree * n, full),
        "disk_graph": (0.0, float(sector) * n + codes),
        "ivf": (4.0 * dim * cells, full),
        "ivf_disk": (4.0 * dim * cells, full),
        "ivf_recompute": (4.0 * dim * cells + 4.0 * n, 0.0),
        "pq": (4.0 * cap * n, codes),
        "bm25": (postings, 0.0),
        "recompute": (4.0 * avg_degree * n, codes),
    }[method]
