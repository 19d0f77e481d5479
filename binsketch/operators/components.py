"""Connected components of an edge table, without collecting any of it."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..tables import scratch, written


def components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """node, component (the smallest node that it reaches); nodes without an edge have no row.

    Each round hangs every node's larger neighbours on its smallest one, then
    every node's smaller neighbours on the smallest, until nothing moves. A round's
    edges are written to the shared folder. Loops and repeated edges do no harm.
    """
    with scratch(edges.sparkSession) as temp:
        now = written(edges.select(F.greatest(a, b).alias("v"), F.least(a, b).alias("u")).filter("v is not null and u is not null").distinct(), "edges")
        nodes = now
        while True:
            both = now.filter("v > u").select("v", "u").union(now.filter("v > u").select(F.col("u").alias("v"), F.col("v").alias("u")))
            least = written(both.groupBy("v").agg(F.least(F.min("u"), F.first("v")).alias("m")), "least")
            large = both.filter("u > v").join(least, "v").select(F.col("u").alias("v"), F.col("m").alias("u")).filter("v > u").distinct()
            large = written(large, "large")
            low = written(large.groupBy("v").agg(F.min("u").alias("m")), "low")
            after = written(large.join(low, "v").select(F.when(F.col("u") == F.col("m"), F.col("v")).otherwise(F.col("u")).alias("v"), F.col("m").alias("u")).filter("v > u").distinct(), "edges")
            # stars: each node hangs on one root, and no root hangs on another
            loose = after.groupBy("v").agg(F.count(F.lit(1)).alias("n"), F.max("u").alias("u"))
            moved = loose.filter("n > 1").limit(1).count() or loose.select("v").join(after.select(F.col("u").alias("v")).distinct(), "v", "left_semi").limit(1).count()
            now = after
            if not moved:
                break
        roots = now.select(F.col("v").alias("node"), F.col("u").alias("component"))
        every = nodes.select(F.col("v").alias("node")).union(nodes.select(F.col("u").alias("node"))).distinct()
        return temp.keep(written(every.join(roots, "node", "left").select("node", F.coalesce("component", "node").alias("component")), "components"))
