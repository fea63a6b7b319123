"""op7: log10 probabilities of all documents under a mixing model and a unigram base."""

from .common import table
from .lm_score import score_texts

NAME = "op7_lm_scoring"


def query(spark, sf_dir):
    return score_texts(table(spark, sf_dir, "documents"))
