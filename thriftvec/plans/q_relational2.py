"""Further relational operators around the methods: maps, bits, subqueries, ranks, pivots back, JSON, approximate aggregates."""

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..catalog import query
from .inputs import table


@query("map_functions", "SELECT user_id, count(DISTINCT event_type) AS kinds, count(*) FILTER (WHERE event_type = 'view') AS views, coalesce(round(max(value) FILTER (WHERE event_type = 'purchase'), 6), -1)::DOUBLE AS best FROM events GROUP BY user_id")
def map_functions(spark, d):
    """Counts and largest values by event type as maps, read by key."""
    per = table(spark, d, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"), F.max("value").alias("m"))
    m = per.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("n"), F.map_from_entries(F.collect_list(F.struct("event_type", "m"))).alias("m"))
    return m.select("user_id", F.size(F.map_keys("n")).cast("long").alias("kinds"), F.coalesce(F.element_at("n", F.lit("view")), F.lit(0)).alias("views"), F.coalesce(F.round(F.element_at("m", F.lit("purchase")), 6), F.lit(-1.0)).alias("best"))


@query("bitwise_ops", "SELECT p_partkey, (p_partkey & 255)::BIGINT AS low, (p_partkey >> 4)::BIGINT AS high, xor(p_partkey, 1023)::BIGINT AS flipped, bit_count(p_partkey)::INT AS ones FROM part")
def bitwise_ops(spark, d):
    k = F.col("p_partkey")
    return table(spark, d, "part").select("p_partkey", k.bitwiseAND(F.lit(255)).alias("low"), F.shiftright(k, 4).alias("high"), k.bitwiseXOR(F.lit(1023)).alias("flipped"), F.bit_count(k).alias("ones"))


@query("bitmap_distinct", "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY l_returnflag")
def bitmap_distinct(spark, d):
    """Exact distinct counts by bitmaps of buckets: partial bitmaps are merged, no set of keys is shuffled."""
    t = table(spark, d, "lineitem").groupBy("l_returnflag", F.bitmap_bucket_number("l_partkey").alias("b")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("l_partkey")).alias("m"))
    return t.groupBy("l_returnflag").agg(F.sum(F.bitmap_count("m")).alias("parts"))


@query("subquery_cte", """WITH s AS (SELECT source, avg(n_chars) AS m FROM documents GROUP BY source)
SELECT d.doc_id FROM documents d JOIN s ON d.source IS NOT DISTINCT FROM s.source WHERE d.n_chars > s.m AND EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id AND l.toxic = 0) AND d.doc_id NOT IN (SELECT item_id FROM benchmark)""")
def subquery_cte(spark, d):
    """A common table, a correlated EXISTS and a NOT IN."""
    for n in ("documents", "labels", "benchmark"):
        table(spark, d, n).createOrReplaceTempView(f"thriftvec_{n}")
    return spark.sql("""WITH s AS (SELECT source, avg(n_chars) AS m FROM thriftvec_documents GROUP BY source)
        SELECT d.doc_id FROM thriftvec_documents d JOIN s ON d.source <=> s.source
        WHERE d.n_chars > s.m AND EXISTS (SELECT 1 FROM thriftvec_labels l WHERE l.doc_id = d.doc_id AND l.toxic = 0)
          AND d.doc_id NOT IN (SELECT item_id FROM thriftvec_benchmark)""")


@query("rank_shares", "SELECT o_orderkey, round(percent_rank() OVER w, 9) AS pr, round(cume_dist() OVER w, 9) AS cd, ntile(4) OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice, o_orderkey)::INT AS quarter FROM orders WINDOW w AS (PARTITION BY o_orderpriority ORDER BY o_totalprice)")
def rank_shares(spark, d):
    w = Window.partitionBy("o_orderpriority").orderBy("o_totalprice")
    return table(spark, d, "orders").select("o_orderkey", F.round(F.percent_rank().over(w), 9).alias("pr"), F.round(F.cume_dist().over(w), 9).alias("cd"), F.ntile(4).over(Window.partitionBy("o_orderpriority").orderBy("o_totalprice", "o_orderkey")).alias("quarter"))


@query("label_unpivot", "SELECT doc_id, name, v FROM (SELECT doc_id, 'quality' AS name, quality AS v FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels)")
def label_unpivot(spark, d):
    return table(spark, d, "labels").unpivot(["doc_id"], ["quality", "toxic"], "name", "v")


@query("json_props", "SELECT event_id, (props->>'$.k')::BIGINT AS k FROM events WHERE event_type IN ('view', 'click') AND (props->>'$.k')::BIGINT BETWEEN 10 AND 500")
def json_props(spark, d):
    """Typed JSON, IN and BETWEEN."""
    e = table(spark, d, "events").where(F.col("event_type").isin("view", "click"))
    return e.select("event_id", F.from_json("props", "k bigint")["k"].alias("k")).where("k BETWEEN 10 AND 500")


@query("variant_props", "SELECT event_id, (props->>'$.k')::BIGINT AS k FROM events")
def variant_props(spark, d):
    return table(spark, d, "events").select("event_id", F.try_variant_get(F.parse_json("props"), "$.k", "bigint").alias("k"))


@query("text_patterns", "SELECT doc_id, regexp_matches(text, '[0-9]{3}') AS digits, contains(lower(text), ' the ') AS english, starts_with(text, 'The') AS the FROM documents WHERE text IS NOT NULL")
def text_patterns(spark, d):
    t = F.col("text")
    return table(spark, d, "documents").where(t.isNotNull()).select("doc_id", t.rlike("[0-9]{3}").alias("digits"), F.lower(t).contains(" the ").alias("english"), t.startswith("The").alias("the"))


@query("approx_aggregates", "SELECT l_returnflag, true AS distinct_close, true AS median_close, true AS sketch_close FROM lineitem GROUP BY l_returnflag")
def approx_aggregates(spark, d):
    """Approximate distinct counts, percentiles and mergeable sketches lie near the exact values."""
    g = table(spark, d, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey", 0.02).alias("a"), F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey", 14)).alias("h"), F.count_distinct("l_partkey").alias("n"), F.percentile_approx("l_extendedprice", 0.5, 10000).alias("p"), F.percentile("l_extendedprice", F.lit(0.5)).alias("q"))
    near = lambda x, y, r: F.abs(F.col(x) - F.col(y)) <= r * F.col(y)
    return g.select("l_returnflag", near("a", "n", 0.1).alias("distinct_close"), near("p", "q", 0.02).alias("median_close"), near("h", "n", 0.05).alias("sketch_close"))


@query("histogram_prices", "SELECT least(floor(o_totalprice / 50000), 9)::BIGINT AS bin, count(*) AS n FROM orders GROUP BY 1")
def histogram_prices(spark, d):
    return table(spark, d, "orders").groupBy(F.least(F.floor(F.col("o_totalprice") / 50000), F.lit(9)).alias("bin")).agg(F.count("*").alias("n"))
