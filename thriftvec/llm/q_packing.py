"""op1: all documents packed into sequences of at most 2048 tokens."""

from .common import table
from .packing import pack_documents

NAME = "op1_bestfit_packing"


def query(spark, sf_dir):
    return pack_documents(table(spark, sf_dir, "documents"))
