"""Connected components of a link table by repeated contraction.

Every node points at the neighbour (itself included) with the smallest hash of the
round; links are carried over to what they point at and the rest is done again. A
path loses a fixed share of its nodes a round, so rounds grow with the logarithm of
the longest chain. Neither links nor labels ever leave the cluster.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from pairmatch.llm.common import stored


def components(links: DataFrame) -> DataFrame:
    """links: (a, b) longs. Returns (node, root) for every node in a link; any one node stands for its component."""
    links = stored(links.where("a <> b").select("a", "b").distinct(), "cc-links")
    labels = None
    step = 0
    while links.limit(1).count():
        both = links.unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b")))
        weigh = lambda c, s=step: F.struct(F.xxhash64(F.col(c), F.lit(s)).alias("h"), F.col(c).alias("id"))
        point = both.groupBy("a").agg(F.min(weigh("b")).alias("best"))
        point = stored(point.select(F.col("a").alias("node"), F.least(weigh("a"), F.col("best"))["id"].alias("root")), "cc-point")
        if labels is None:
            labels = point
        else:
            labels = labels.join(point.select(F.col("node").alias("root"), F.col("root").alias("to")), "root", "left").select("node", F.coalesce("to", "root").alias("root"))
            labels = stored(labels, "cc-labels")
        end = lambda c: point.select(F.col("node").alias(c), F.col("root").alias(c + "_to"))  # noqa: E731, B023
        links = stored(
            links.join(end("a"), "a").join(end("b"), "b").select(F.col("a_to").alias("a"), F.col("b_to").alias("b")).where("a <> b")
            .select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(),
            "cc-links",
        )
        step += 1
    return labels if labels is not None else links.select(F.col("a").alias("node"), F.col("b").alias("root"))
