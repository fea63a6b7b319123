"""op8: language of every document, learned from two thirds of them."""

from pyspark.sql import functions as F

from .common import crc_residue, table
from .langid import identify, train

NAME = "op8_language_id"


def query(spark, sf_dir):
    docs = table(spark, sf_dir, "documents")
    model = train(docs.where(crc_residue("doc_id", 3) != 1).select("doc_id", "text", "lang"))
    out = identify(docs.select("doc_id", "text"), model)
    return out.select("doc_id", (crc_residue("doc_id", 3) == 1).alias("held_out"), F.col("_lang").alias("lang_pred"), F.col("_score").alias("score"))
