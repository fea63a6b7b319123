"""Connected components of a link table by alternating star contractions, wholly in DataFrames.

Every round replaces links by links to smaller ids; nodes of a component end as leaves of its smallest id. Minima are
pre-aggregated before the shuffle and joins may be split by adaptive execution, so one hub with very many leaves is
harmless. Links never reach the driver: it reads one count and one checksum per round.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, stored


def _mark(df: DataFrame) -> tuple:
    r = df.agg(F.count("*"), F.sum(F.xxhash64("a", "b") % F.lit(1_000_003))).first()
    return r[0], r[1]


def components(links: DataFrame) -> DataFrame:
    """links(a, b) of long ids -> (node, component) for every id that occurs; component is the smallest id reachable.

    No links give no rows; self links, repeated links and either direction are allowed, nulls are ignored.
    """
    e = links.where("a is not null and b is not null and a <> b")
    e = stored(e.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct())
    nodes = links.where("a is not null and b is not null").select(F.explode(F.array("a", "b")).alias("node"))
    last = _mark(e)
    while last[0]:
        both = e.unionByName(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        # larger neighbours of each node now point to the smallest id around it
        big = both.where("b > a").join(low, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).distinct()
        low = big.groupBy("a").agg(F.min("b").alias("m"))
        small = big.join(low, "a").where("b > m").select(F.col("b").alias("a"), F.col("m").alias("b"))
        new = stored(small.unionByName(low.select("a", F.col("m").alias("b"))).where("a <> b").distinct())
        discard(e)
        e, now = new, _mark(new)
        if now == last:  # alternating stars settle after a logarithmic number of rounds
            break
        last = now
    out = e.groupBy("a").agg(F.min("b").alias("b"))
    return nodes.distinct().join(out, nodes["node"] == out["a"], "left").select("node", F.coalesce("b", "node").alias("component"))
