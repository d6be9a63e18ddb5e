"""Connected components of a link table by alternating stars; no node's neighbours are ever gathered."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Stored


def components(links: DataFrame, store: Stored) -> DataFrame:
    """(u, v) links to (node, comp): comp is the least node of the component; only linked nodes appear.

    Large and small stars alternate until the link set is a set of stars.  Each step is one grouped minimum and one join
    on the same key, stored in the shared folder, so neither hubs nor lost executors matter.
    """
    edges = store.put(links.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct())
    mark = None
    while True:
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).withColumn("m", F.least("u", "m"))
        large = store.put(both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct())
        small = large.groupBy("u").agg(F.min("v").alias("m"))
        joined = large.join(small, "u")
        nxt = store.put(joined.select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").unionByName(small.select("u", F.col("m").alias("v"))).distinct())
        store.drop(edges, large)
        edges = nxt
        now = edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if now == mark:
            break
        mark = now
    comp = edges.select(F.col("u").alias("node"), F.col("v").alias("comp"))
    return comp.unionByName(comp.select(F.col("comp").alias("node"), "comp").distinct())
