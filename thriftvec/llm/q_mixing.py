"""op5: documents mixed to source weights 5, 2, 1."""

from .common import table
from .mixing import mix_sources

NAME = "op5_mix_sources"


def query(spark, sf_dir):
    return mix_sources(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken", "copies", "source")
