"""op10: words of repeated 50-word windows are removed; digest of what stays."""

from pyspark.sql import functions as F

from .common import table
from .substring import remove_repeats

NAME = "op10_substring_dedup"


def query(spark, sf_dir):
    d = remove_repeats(table(spark, sf_dir, "documents").select("doc_id", "text"), digest=True)
    return d.select("doc_id", F.col("_n_words").alias("n_words"), F.col("_n_removed").alias("n_removed"), F.col("_kept_sha256").alias("kept_sha256"))


ORACLE = r"""
WITH w AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS ws FROM documents),
s AS (SELECT doc_id, unnest(range(1, len(ws) - 48)) AS p, ws FROM w WHERE len(ws) >= 50),
k AS (SELECT doc_id, p, md5(array_to_string(ws[p:p + 49], ' ')) AS h FROM s),
o AS (SELECT h, min(doc_id) AS least FROM k GROUP BY h),
hit AS (SELECT k.doc_id, k.p FROM k JOIN o USING (h) WHERE o.least < k.doc_id),
gone AS (SELECT DISTINCT doc_id, unnest(range(p, p + 50)) AS i FROM hit),
pos AS (SELECT doc_id, unnest(range(1, len(ws) + 1)) AS i, unnest(ws) AS word FROM w WHERE len(ws) > 0),
kept AS (SELECT pos.doc_id, string_agg(word, ' ' ORDER BY i) AS t, count(*) AS n FROM pos ANTI JOIN gone USING (doc_id, i) GROUP BY 1)
SELECT w.doc_id, len(ws)::BIGINT AS n_words, (len(ws) - coalesce(n, 0))::BIGINT AS n_removed, sha256(coalesce(t, '')) AS kept_sha256
FROM w LEFT JOIN kept USING (doc_id)
"""
