"""Connected components of an undirected edge table.

Alternates the two star operations of the published MapReduce method: every vertex hands
its larger neighbours to its smallest neighbour, then its smaller ones. Each round is a
partial-aggregated ``min`` and a join; the edge count never grows by more than the
vertex count and the rounds are about logarithmic, whatever the diameter.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelrank.plans.staging import materialise


def _large_star(edges: DataFrame) -> DataFrame:
    both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    low = both.groupBy("a").agg(F.min("b").alias("m")).withColumn("m", F.least("m", "a"))
    return both.where("b > a").join(low, "a").select(F.col("b").alias("a"), F.col("m").alias("b"))


def _small_star(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    low = down.groupBy("a").agg(F.min("b").alias("m"))
    moved = down.join(low, "a").select(F.col("b").alias("a"), F.col("m").alias("b"))
    return moved.unionByName(low.select("a", F.col("m").alias("b")))


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(a, b) long pairs -> (id, component), component = smallest id reachable.

    Loops are ignored, repeated pairs are harmless, an empty table gives an empty one. Vertices without edges are
    not listed: their component is themselves.
    """
    cur = materialise(edges.select(F.col("a").cast("long").alias("a"), F.col("b").cast("long").alias("b")).where("a <> b").distinct(), "links")
    state = None
    for _ in range(max_rounds):
        large = _large_star(cur).where("a <> b").distinct()
        cur = materialise(_small_star(large).where("a <> b").distinct(), "stars")
        new = tuple(cur.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())
        if new == state:
            break
        state = new
    else:
        raise RuntimeError("components did not settle")
    roots = cur.groupBy("a").agg(F.min("b").alias("component")).withColumnRenamed("a", "id")
    return roots.unionByName(roots.select(F.col("component").alias("id"), "component").distinct())
