"""Queries on corpus preparation, integer encodings, sparse search and BM25."""

from pyspark.sql import functions as F

from ..catalog import query
from ..functions import text as tx
from ..functions.encoders import encode_int, encode_int_rows
from ..operators.bm25 import bm25_build, bm25_search
from ..operators.exact import knn_exact_sparse
from .inputs import CHUNKS, bench_queries, chunks, table


@query("chunk_256", rf"WITH {CHUNKS} SELECT chunk_id, doc_id, pos::INT AS pos, len(w)::INT AS n_tokens, md5(array_to_string(w, ' ')) AS h FROM ch")
def chunk_256(spark, d):
    return chunks(spark, d).select("chunk_id", "doc_id", "pos", "n_tokens", F.md5("text").alias("h"))


@query("chunk_overlap", r"""WITH t AS (SELECT doc_id, regexp_extract_all(lower(text), '[\p{L}\p{N}]+') AS t FROM documents WHERE text IS NOT NULL),
p AS (SELECT doc_id, t, unnest(range(0, greatest(1, ceil((len(t) - 64) / 192)::BIGINT))) AS pos FROM t WHERE len(t) > 0)
SELECT doc_id * 1000000 + pos AS chunk_id, pos::INT AS pos, len(t[pos * 192 + 1:pos * 192 + 256])::INT AS n_tokens, md5(array_to_string(t[pos * 192 + 1:pos * 192 + 256], ' ')) AS h FROM p""")
def chunk_overlap(spark, d):
    c = tx.chunk(table(spark, d, "documents").select("doc_id", "text"), 256, 64)
    return c.select("chunk_id", "pos", "n_tokens", F.md5("text").alias("h"))


_E1 = """h AS (SELECT chunk_id, ('0x' || substr(md5(x), 1, 8))::BIGINT AS h FROM (SELECT chunk_id, unnest(w) AS x FROM ch)),
e1 AS (SELECT chunk_id, (h % 256)::INT AS dim, sum(CASE WHEN (h >> 16) & 1 = 1 THEN -1 ELSE 1 END)::BIGINT AS v FROM h GROUP BY 1, 2 HAVING v <> 0)"""


@query("encode_hash_int", f"WITH {CHUNKS}, {_E1} SELECT chunk_id, dim, v FROM e1")
def encode_hash_int(spark, d):
    return encode_int(chunks(spark, d))


@query("strip_html", r"""SELECT page_id, md5(trim(regexp_replace(regexp_replace(regexp_replace(regexp_replace(regexp_replace(html, '<(script|style)[^>]*>.*?</(script|style)>', ' ', 'gs'), '<!--.*?-->', ' ', 'gs'), '<[^>]*>', ' ', 'g'), '&[a-zA-Z#0-9]+;', ' ', 'g'), '[ \t\n\r]+', ' ', 'g'))) AS h FROM pages""")
def strip_html(spark, d):
    return table(spark, d, "pages").select("page_id", F.md5(tx.strip_html(F.col("html"))).alias("h"))


@query("conv_windows", """SELECT conv_id, turn, string_agg(concat_ws(': ', role, text), chr(10)) OVER (PARTITION BY conv_id ORDER BY turn ROWS BETWEEN 1 PRECEDING AND CURRENT ROW) AS text FROM conversations""")
def conv_windows(spark, d):
    return tx.turns_to_objects(table(spark, d, "conversations"))


@query("dedup_exact", f"WITH {CHUNKS} SELECT min(chunk_id) AS chunk_id, count(*) AS copies FROM ch GROUP BY array_to_string(w, ' ')")
def dedup_exact(spark, d):
    return tx.dedup_exact(chunks(spark, d)).select("chunk_id", "copies")


@query("split_train", "SELECT count(*) FILTER (WHERE vec_id % 10 <> 0) AS train, count(*) FILTER (WHERE vec_id % 10 = 0) AS held FROM embeddings")
def split_train(spark, d):
    train, held = tx.split(table(spark, d, "embeddings").select("vec_id"), "vec_id", 10, 0)
    return train.agg(F.count("*").alias("train")).crossJoin(held.agg(F.count("*").alias("held")))


@query("knn_sparse_docs", rf"""WITH {CHUNKS}, {_E1},
qt AS (SELECT item_id AS query_id, unnest(regexp_extract_all(lower(text), '[\p{{L}}\p{{N}}]+')) AS x FROM benchmark),
qh AS (SELECT query_id, ('0x' || substr(md5(x), 1, 8))::BIGINT AS h FROM qt),
qe AS (SELECT query_id, (h % 256)::INT AS dim, sum(CASE WHEN (h >> 16) & 1 = 1 THEN -1 ELSE 1 END)::BIGINT AS w FROM qh GROUP BY 1, 2 HAVING w <> 0),
s AS (SELECT query_id, chunk_id AS node_id, sum(-v * w)::BIGINT AS dist FROM e1 JOIN qe USING (dim) GROUP BY 1, 2)
SELECT query_id, rank::INT AS rank, node_id, dist FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY dist, node_id) AS rank FROM s) WHERE rank <= 5""")
def knn_sparse_docs(spark, d):
    terms = encode_int_rows(chunks(spark, d)).withColumnRenamed("chunk_id", "node_id")
    q = encode_int(bench_queries(spark, d), key="query_id")
    return knn_exact_sparse(terms, q, 5)


_BM = r"""tk AS (SELECT doc_id AS node_id, regexp_extract_all(lower(coalesce(text, '')), '[\p{L}\p{N}]+') AS t FROM documents),
po AS (SELECT term, node_id, count(*) AS tf FROM (SELECT node_id, unnest(t) AS term FROM tk) GROUP BY 1, 2),
dl AS (SELECT node_id, len(t) AS dl FROM tk), df AS (SELECT term, count(*) AS df FROM po GROUP BY 1),
st AS (SELECT count(*) AS n, sum(dl) AS total FROM dl)"""


def _docs(spark, d):
    return table(spark, d, "documents").select(F.col("doc_id").alias("node_id"), "text")


@query("bm25_stats", f"WITH {_BM} SELECT (SELECT count(*) FROM po) AS postings, (SELECT count(*) FROM df) AS terms, n, total::BIGINT AS total FROM st")
def bm25_stats(spark, d):
    i = bm25_build(_docs(spark, d))
    return i.postings.agg(F.count("*").alias("postings")).crossJoin(i.df.agg(F.count("*").alias("terms"))).withColumn("n", F.lit(i.n).cast("long")).withColumn("total", F.lit(i.total).cast("long"))


@query("bm25_topk", rf"""WITH {_BM},
qt AS (SELECT DISTINCT item_id AS query_id, unnest(regexp_extract_all(lower(text), '[\p{{L}}\p{{N}}]+')) AS term FROM benchmark),
s AS (SELECT query_id, node_id, sum(-floor(ln(1 + (n - df + 0.5) / (df + 0.5)) * (tf * 2.2) / (tf + 1.2 * (0.25 + 0.75 * dl / (total / n))) * 1000000)::BIGINT)::BIGINT AS dist
  FROM po JOIN qt USING (term) JOIN df USING (term) JOIN dl USING (node_id), st GROUP BY 1, 2)
SELECT query_id, rank::INT AS rank, node_id FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY dist, node_id) AS rank FROM s) WHERE rank <= 10""")
def bm25_topk(spark, d):
    return bm25_search(bm25_build(_docs(spark, d)), bench_queries(spark, d), 10).select("query_id", "rank", "node_id")
