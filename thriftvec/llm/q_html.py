"""op4: main text of every page."""

from .common import table
from .html_text import extract

NAME = "op4_html_extraction"


def query(spark, sf_dir):
    return extract(table(spark, sf_dir, "pages")).withColumnsRenamed({"_text": "text", "_n_chars": "n_chars"})
