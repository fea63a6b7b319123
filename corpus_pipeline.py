"""Pipeline over `documents`: language ID, near-duplicate groups, repeated passages, source mix, packed sequences.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; run() writes each result as Parquet to the shared folder
and reads it again as the next stage's docs. All stages but the last return the columns of `documents`. Null texts
leave in the first stage; a table with no rows passes through all stages. Further columns may have any name, also
those that the operators use: inside a stage they go by their position.

A stage first deletes the tables that the stage before it kept in the shared folder, save those that docs is read from.
"""

from functools import wraps

from pyspark.sql import functions as F

from thriftvec.llm.common import crc_residue, discard_since, held, prepare, shared_folder
from thriftvec.llm.jaccard import similar_groups
from thriftvec.llm.langid import UNKNOWN, identify, train
from thriftvec.llm.mixing import mix_sources
from thriftvec.llm.packing import pack_documents
from thriftvec.llm.substring import remove_repeats

SURE = 0.5  # a predicted language that differs from the row's own counts from this score on
USED = ("doc_id", "text", "lang", "source", "n_chars")
_kept = {"mark": None}


def stage(f):
    """Columns other than USED go by position inside; the tables of the stage before are deleted."""

    @wraps(f)
    def run_stage(spark, docs, sf_dir):
        prepare(spark)
        if _kept["mark"] is not None:
            discard_since(_kept["mark"], docs)
        _kept["mark"] = held()
        names = docs.columns
        inner = [c if c in USED and names.index(c) == i else f"other{i}" for i, c in enumerate(names)]
        out = f(spark, docs.toDF(*inner), sf_dir)
        return out if f is packed_rows else out.select(*inner).toDF(*names)

    return run_stage


@stage
def by_language(spark, docs, sf_dir):
    """Keep documents whose language is known and not surely another than the one they claim."""
    model = train(docs.where(crc_residue("doc_id", 3) != 1).select("doc_id", "text", "lang"))
    seen = identify(docs, model, docs.columns)
    wrong = F.coalesce((F.col("_lang") != F.col("lang")) & (F.col("_score") >= SURE), F.lit(False))
    return seen.where((F.col("_lang") != UNKNOWN) & ~wrong)


@stage
def without_near_copies(spark, docs, sf_dir):
    """Keep the document of smallest id of each group linked by five-word shingles of similarity 0.8 or more."""
    groups = similar_groups(docs.select("doc_id", "text"), k=5, percent=80)
    drop = groups.where("component_id <> doc_id").select("doc_id").distinct()
    return docs.join(drop, "doc_id", "left_anti")


@stage
def without_repeats(spark, docs, sf_dir):
    """Cut passages of 50 words and more that an earlier document has; documents with nothing left go."""
    cut = remove_repeats(docs).where("_kept is not null and not (_n_removed > 0 and _kept = '')")
    cut = cut.withColumn("text", F.col("_kept"))
    if "n_chars" in docs.columns:
        cut = cut.withColumn("n_chars", F.when(F.col("_n_removed") > 0, F.length("text").cast("long")).otherwise(F.col("n_chars")))
    return cut


@stage
def mixed(spark, docs, sf_dir):
    """Each document as often as the mix of source weights takes it."""
    taken = mix_sources(docs).where("copies > 0").groupBy("doc_id").agg(F.max("copies").alias("_copies")).withColumnRenamed("doc_id", "_taken")
    rows = docs.join(taken, F.col("doc_id").eqNullSafe(F.col("_taken")))
    return rows.withColumn("_i", F.explode(F.sequence(F.lit(1), F.col("_copies"))))


def packed_rows(spark, docs, sf_dir):
    """Pieces of all documents in sequences of at most 2048 tokens."""
    return pack_documents(docs)


packed = stage(packed_rows)
STAGES = [("language_id", by_language), ("ngram_jaccard", without_near_copies), ("substring_dedup", without_repeats), ("mix_sources", mixed), ("bestfit_packing", packed)]
ORACLE_SQL = None


def run(spark, sf_dir):
    prepare(spark)
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    folder = shared_folder(spark)
    for name, one in STAGES:
        out = one(spark, docs, sf_dir)
        out.write.parquet(f"{folder}/{name}")
        docs = spark.read.schema(out.schema).parquet(f"{folder}/{name}")
    return docs
