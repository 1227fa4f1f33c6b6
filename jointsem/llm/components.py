"""Connected components of a link table by alternating stars.

No adjacency list is ever gathered: each half round is an aggregate with a
map-side minimum and an equi-join, and each round is written to the shared
folder.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from jointsem.llm.store import drop, stage


def _star(links: DataFrame, both_ways: bool) -> DataFrame:
    """Point neighbours at the least node of a neighbourhood: the larger ones (both_ways) or the smaller ones and the node."""
    if both_ways:
        sides = links.unionByName(links.select(F.col("v").alias("u"), F.col("u").alias("v")))
    else:
        sides = links.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    least = sides.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    joined = sides.join(least, "u")
    out = joined.where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    if not both_ways:
        out = joined.where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(least.select("u", F.col("m").alias("v")))
    return out.where("u <> v").distinct()


def components(links: DataFrame, max_rounds: int = 60) -> DataFrame:
    """links (u, v) -> (node, root) for every node that has a link; root is the least node reachable.

    Self-links and repeated links are ignored.  An empty table gives an empty table.
    """
    spark = links.sparkSession
    now, path, last = stage(links.select("u", "v").where("u <> v").distinct(), "links"), None, None
    for _ in range(max_rounds):
        new = stage(_star(_star(now, True), False), "links")
        seen = tuple(new.agg(F.count("*"), F.expr("bit_xor(xxhash64(u, v))")).first())
        if path:
            drop(spark, path)
        now, path = new, new.inputFiles()[0].rpartition("/")[0] if seen[0] else None
        if seen == last or not seen[0]:
            break
        last = seen
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return now.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(now.select(F.col("v").alias("node"), F.col("v").alias("root"))).distinct()
