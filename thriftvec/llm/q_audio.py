"""op9: chroma fingerprints of recordings made from all embeddings, and their alignment.

No given table holds sound, so each vector is played as a melody; the media column is made and read as any other.
"""

from pyspark.sql import functions as F

from .audio import fingerprint, match, render
from .common import stored, table

NAME = "op9_audio_fingerprints"


def query(spark, sf_dir):
    vectors = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("v"))
    return match(stored(fingerprint(render(vectors)))).withColumnRenamed("id", "vec_id")
