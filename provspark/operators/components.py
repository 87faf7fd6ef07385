"""Connected components of a table of links: least labels spread over links, and jump over the labels found."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.tables import stored


def components(links: DataFrame) -> DataFrame:
    """links (a, b) -> (node, component): the least node that each node reaches; nodes with a link to themselves count.

    A link table of n rows stays one of n rows: nothing is paired within a component.
    """
    both = stored(links.select("a", "b").unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), "links")
    label = stored(both.groupBy("a").agg(F.least(F.col("a"), F.min("b")).alias("c")), "labels")
    while True:
        near = both.join(label.select(F.col("a").alias("b"), F.col("c").alias("d")), "b").groupBy("a").agg(F.min("d").alias("d"))
        moved = label.join(near, "a").select("a", F.least("c", "d").alias("c"), F.col("c").alias("old"))
        jump = label.select(F.col("a").alias("c"), F.col("c").alias("e"))
        moved = stored(moved.join(jump, "c").select("a", F.least("c", "e").alias("c"), "old"), "labels")
        if moved.where("c <> old").isEmpty():
            return moved.select(F.col("a").alias("node"), F.col("c").alias("component"))
        label = moved.select("a", "c")
