"""Tables and fixtures that the registered queries share, and the same in SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.text import chunk


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def chunks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chunk(table(spark, sf_dir, "documents").select("doc_id", "text", "lang", "source"))


def objects(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distinct chunks as search objects: node_id, text, lang, source."""
    c = chunks(spark, sf_dir)
    # the rows of the smallest chunk_id come along, so that texts are cut once
    row = F.struct("chunk_id", "text", "lang", "source")
    return c.groupBy(F.md5("text").alias("h")).agg(F.min(row).alias("r")).select(F.col("r.chunk_id").alias("node_id"), "r.text", "r.lang", "r.source")


def bench_queries(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "benchmark").select(F.col("item_id").alias("query_id"), "text")


def vec_base(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All vectors: what operators run over and searches look through."""
    e = table(spark, sf_dir, "embeddings")
    return e.select(F.col("vec_id").alias("node_id"), F.col("embedding").alias("v"), "label")


def vec_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stated query set: a tenth of the vectors, asked against all of them."""
    e = table(spark, sf_dir, "embeddings")
    return e.where("vec_id % 10 = 0").select(F.col("vec_id").alias("query_id"), F.col("embedding").alias("qv"))


def rounded(df: DataFrame, *cols: str) -> DataFrame:
    for c in cols:
        df = df.withColumn(c, F.round(F.col(c), 6))
    return df


# SQL of the same, as common table expressions
CHUNKS = r"""t AS (SELECT doc_id, lang, source, regexp_extract_all(lower(text), '[\p{L}\p{N}]+') AS t FROM documents WHERE text IS NOT NULL),
p AS (SELECT doc_id, lang, source, t, unnest(range(0, (len(t) + 255) // 256)) AS pos FROM t WHERE len(t) > 0),
ch AS (SELECT doc_id * 1000000 + pos AS chunk_id, doc_id, pos, lang, source, t[pos * 256 + 1:pos * 256 + 256] AS w FROM p)"""
VECTORS = """e AS (SELECT vec_id, label, list_transform(embedding, lambda x: x::DOUBLE) AS v FROM embeddings),
b AS (SELECT vec_id AS node_id, v, label FROM e), q AS (SELECT vec_id AS query_id, v AS qv FROM e WHERE vec_id % 10 = 0)"""


def sql_l2(a: str = "v", b: str = "qv") -> str:
    return f"list_sum(list_transform(list_zip({a}, {b}), lambda z: (z[1] - z[2]) * (z[1] - z[2])))"


def sql_dot(a: str = "v", b: str = "qv") -> str:
    return f"list_sum(list_transform(list_zip({a}, {b}), lambda z: z[1] * z[2]))"


def sql_top(pairs: str, k: int) -> str:
    """Final select over a relation with query_id, node_id, dist."""
    return f"SELECT query_id, node_id, rank::INT AS rank, round(dist, 6) AS dist FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY dist, node_id) AS rank FROM {pairs}) WHERE rank <= {k}"
