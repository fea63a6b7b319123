"""op2: ids of all documents written as Huffman-coded files and read back."""

from .common import table
from .token_codec import round_trip

NAME = "op2_token_binary"


def query(spark, sf_dir):
    return round_trip(table(spark, sf_dir, "documents"))
