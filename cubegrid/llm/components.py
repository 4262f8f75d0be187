"""Connected components of an edge table by alternating large and small stars.

Each round points the neighbours of every vertex at the smallest vertex near it. Minima of hubs are
taken in parts, and they meet their edges again in a join that deals the edges of the hubs over all
tasks, so no vertex is one task's or one group. Rounds are written
to the shared folder, and nothing but a count and a checksum reaches the driver.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cubegrid.llm.common import join_hot, stored


def _star(edges: DataFrame, large: bool) -> DataFrame:
    """edges: u, v with u > v. Large: larger neighbours to the minimum; small: smaller ones and itself."""
    if large:
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("n")).select("u", F.least("u", "m").alias("m"), "n")
        out = join_hot(both.where("v > u"), least, ["u"], "n").select(F.col("v").alias("u"), F.col("m").alias("v"))
    else:
        least = edges.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("n"))
        out = join_hot(edges, least, ["u"], "n").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(least.select("u", F.col("m").alias("v")))
    return out.where("u != v").distinct()


def components(edges: DataFrame, most_rounds: int = 60) -> DataFrame:
    """(u, v): every vertex that is not the least of its component, with that least vertex."""
    now = stored(edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).where("u != v").distinct(), "edges")
    mark = None
    for _ in range(most_rounds):
        now = stored(_star(_star(now, large=True), large=False), "stars")
        new = now.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if new == mark:
            return now
        mark = new
    raise RuntimeError("components did not settle")
