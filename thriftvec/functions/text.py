"""Corpus preparation: chunks of tokens, plain text of pages, conversation windows, exact copies, splits."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

TOKEN = r"[\p{L}\p{N}]+"
ID_STEP = 1_000_000  # chunk_id = doc_id * ID_STEP + pos


def tokens(text: Column) -> Column:
    """Lower-cased runs of letters and digits."""
    return F.regexp_extract_all(F.lower(text), F.lit(TOKEN), F.lit(0))


def chunk(docs: DataFrame, size: int = 256, overlap: int = 0) -> DataFrame:
    """docs(doc_id, text, ...) -> chunk_id, doc_id, pos, n_tokens, text and the other columns; narrow, no shuffle.

    Null and empty texts give no chunk. With overlap, a chunk starts every size - overlap tokens and the last one is the
    first that reaches the end.
    """
    if not 0 <= overlap < size:
        raise ValueError("overlap must be smaller than the chunk")
    step = size - overlap
    n = F.size("_t")
    # no filter on the tokens: it would be pushed down and cut every text twice
    starts = F.when(n > 0, F.sequence(F.lit(0), F.greatest(F.lit(0), F.ceil((n - overlap) / step).cast("int") - 1))).otherwise(F.expr("cast(array() as array<int>)"))
    rest = [c for c in docs.columns if c not in ("doc_id", "text")]
    d = docs.where(F.col("text").isNotNull()).withColumn("_t", tokens(F.col("text")))
    d = d.select("doc_id", *rest, "_t", F.explode(starts).alias("pos"))
    part = F.slice("_t", F.col("pos") * step + 1, size)
    return d.select((F.col("doc_id") * ID_STEP + F.col("pos")).alias("chunk_id"), "doc_id", "pos", F.size(part).alias("n_tokens"), F.array_join(part, " ").alias("text"), *rest)


def strip_html(html: Column) -> Column:
    """Text of a page by removal of scripts, styles, comments and tags; white space becomes one space."""
    out = F.regexp_replace(html, r"(?s)<(script|style)[^>]*>.*?</(script|style)>", " ")
    out = F.regexp_replace(out, r"(?s)<!--.*?-->", " ")
    out = F.regexp_replace(out, r"<[^>]*>", " ")
    out = F.regexp_replace(out, r"&[a-zA-Z#0-9]+;", " ")
    return F.trim(F.regexp_replace(out, r"[ \t\n\r]+", " "))


def turns_to_objects(conv: DataFrame, window: int = 1) -> DataFrame:
    """conversations -> one object per turn: its text after those of up to `window` turns before."""
    w = Window.partitionBy("conv_id").orderBy("turn").rowsBetween(-window, 0)
    return conv.select("conv_id", "turn", F.array_join(F.collect_list(F.concat_ws(": ", "role", "text")).over(w), "\n").alias("text"))


def dedup_exact(chunks: DataFrame) -> DataFrame:
    """One row per distinct text: its smallest chunk_id and the number of copies (partial aggregation before the shuffle)."""
    return chunks.groupBy(F.md5("text").alias("_h")).agg(F.min("chunk_id").alias("chunk_id"), F.count("*").alias("copies")).drop("_h")


def split(df: DataFrame, key: str, modulus: int, rest: int) -> tuple[DataFrame, DataFrame]:
    """(others, rows whose key leaves `rest`)."""
    hit = F.pmod(F.col(key), F.lit(modulus)) == rest
    return df.where(~hit), df.where(hit)
