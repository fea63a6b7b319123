"""op6: near-duplicate groups of all embeddings at cosine 0.9."""

from .common import table
from .embeddings import near_duplicates

NAME = "op6_embedding_neardup"


def query(spark, sf_dir):
    return near_duplicates(table(spark, sf_dir, "embeddings"))


ORACLE = r"""
WITH RECURSIVE v AS (SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS e FROM embeddings),
f AS (SELECT vec_id, e, sqrt(list_sum(list_transform(e, lambda x: x * x))) AS n FROM v
  WHERE e IS NOT NULL AND len(list_filter(e, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
g AS (SELECT * FROM f WHERE n > 0),
l AS (SELECT x.vec_id AS a, y.vec_id AS b FROM g x JOIN g y ON x.vec_id <> y.vec_id
  AND list_sum(list_transform(list_zip(x.e, y.e), lambda z: z[1] * z[2])) / (x.n * y.n) >= 0.9),
r(x, y) AS (SELECT a, a FROM l UNION SELECT r.x, l.b FROM r JOIN l ON l.a = r.y),
c AS (SELECT x, min(y) AS low FROM r GROUP BY x),
k AS (SELECT a, count(*) AS n FROM l GROUP BY a)
SELECT vec_id, coalesce(k.n, 0)::BIGINT AS n_links, coalesce(c.low, vec_id)::BIGINT AS component_id, coalesce(c.low, vec_id) = vec_id AS kept
FROM embeddings LEFT JOIN k ON k.a = vec_id LEFT JOIN c ON c.x = vec_id
"""
