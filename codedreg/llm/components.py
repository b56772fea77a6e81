"""Connected components of links, distributed.

Alternating star contractions: each node hands its larger neighbours to the smallest node it knows, then its smaller
ones, until every component is a star around its smallest node.  Hubs cost one partial minimum and a join that Spark
may split; nothing is collected but a row count and a checksum a round.  Tasks between the shuffles are as many as the links
need, so a small graph does not leave a file for each pair of the cluster's partitions.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codedreg.llm.common import cut, shuffle_width

ROUNDS_MAX = 60
#: Links that one task takes.
LINKS_PER_TASK = 200_000


def connected_components(links: DataFrame) -> DataFrame:
    """node, component (the smallest node reached) of every node in the links (a, b); null ends are ignored."""
    edges = cut(links.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct())
    width = min(shuffle_width(links.sparkSession), edges.count() // LINKS_PER_TASK + 1)
    fewer = lambda df: df.coalesce(width)
    edges = fewer(edges)
    before = None
    for _ in range(ROUNDS_MAX):
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = fewer(both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m")))
        edges = fewer(fewer(both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v")).distinct())
        least = fewer(edges.groupBy("u").agg(F.min("v").alias("m")))
        moved = edges.join(least, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        edges = cut(fewer(fewer(moved.unionByName(least.select("u", F.col("m").alias("v")))).distinct()))
        now = edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if tuple(now) == before:
            break
        before = tuple(now)
    else:
        raise RuntimeError("components did not settle")
    return edges.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(edges.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())
