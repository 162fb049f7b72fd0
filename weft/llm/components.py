"""Connected components of a link table, without collecting links.

Rounds of two steps, each a grouped minimum and a join: every node hangs its larger
neighbours on the smallest node it knows, then hangs itself and its smaller neighbours on
that node.  The rounds end when the links are stars around the smallest members, after a
number of rounds that grows with the logarithm of the component sizes.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import Workspace


def components(links: DataFrame, work: Workspace) -> DataFrame:
    """``links``: (a, b) longs, any order, repeats and self links allowed, no nulls.

    Returns a written table (node, root): each node that has a link to another one and the
    smallest node it is connected with.  No links: an empty table.
    """
    tidy = links.where("a <> b").select(F.greatest("a", "b").alias("hi"), F.least("a", "b").alias("lo")).distinct()
    now = work.keep(tidy, "links")
    while True:
        both = now.select(F.col("hi").alias("u"), F.col("lo").alias("v")).union(now.select(F.col("lo").alias("u"), F.col("hi").alias("v")))
        # a table of its own, so that both sides of the join are plain exchanges and a hub is split at run time
        least = work.keep(both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m")), "least")
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("hi"), F.col("m").alias("lo")).where("hi <> lo").distinct()
        middle = work.keep(large, "large")
        down = middle.groupBy("hi").agg(F.min("lo").alias("m"))
        small = (
            middle.join(down, "hi")
            .select(F.explode(F.array(F.struct(F.col("lo").alias("x"), F.col("m").alias("m")), F.struct(F.col("hi").alias("x"), F.col("m").alias("m")))).alias("e"))
            .select(F.col("e.x").alias("hi"), F.col("e.m").alias("lo"))
            .where("hi <> lo")
            .distinct()
        )
        after = work.keep(small, "small")
        # stars around roots: every node has one parent and no parent has a parent
        parents = after.groupBy("hi").agg(F.count("*").alias("n"))
        several = parents.where("n > 1").limit(1).count()
        nested = 0 if several else after.select("lo").distinct().join(after.select(F.col("hi").alias("lo")).distinct(), "lo", "left_semi").limit(1).count()
        work.drop(now, least, middle)
        now = after
        if not several and not nested:
            return now.select(F.col("hi").alias("node"), F.col("lo").alias("root")).union(now.select(F.col("lo").alias("node"), F.col("lo").alias("root")).distinct())
