"""Connected components of links, as joins and aggregates over tables in the shared folder."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from corpusforge.engine import Rounds, written


def components(edges: DataFrame) -> DataFrame:
    """(id, component) of every id in ``edges`` (columns a, b); the component is the smallest id reachable.

    Each round takes the smallest label among a node's neighbours, then that label's own label, so labels travel in leaps
    and the number of rounds grows with the logarithm of the longest path. Rows are sums over keys, so a node with very
    many links only makes a longer partial aggregate; nothing is gathered at one place.
    """
    spark = edges.sparkSession
    pairs = written(edges.filter("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "links")
    both = pairs.union(pairs.select("b", "a"))
    rounds = Rounds(spark, "labels")
    labels = rounds.write(both.groupBy(F.col("a").alias("id")).agg(F.min("b").alias("m")).select("id", F.least("id", "m").alias("component"), F.lit(True).alias("moved")))
    while True:
        known = labels.select("id", "component")
        near = both.join(known, both.b == known.id).groupBy(F.col("a").alias("node")).agg(F.min("component").alias("near"))
        step = known.join(near, known.id == near.node).select("id", "component", F.least("component", "near").alias("reached"))
        leap = known.select(F.col("id").alias("via"), F.col("component").alias("beyond"))
        moved = step.join(leap, step.reached == leap.via).select("id", F.col("beyond").alias("new"), (F.col("beyond") < F.col("component")).alias("moved"))
        labels = rounds.write(moved.select("id", F.col("new").alias("component"), "moved"))
        if labels.filter("moved").isEmpty():
            return labels.select("id", "component")
