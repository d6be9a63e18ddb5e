"""The exhaustive search that the family plans are measured against, and its variants."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.patterns import pattern_of
from ..model import Hypergraph
from ..stages import stage
from .families import COLUMNS
from .links import project


def _both_ways(pairs: DataFrame) -> DataFrame:
    return pairs.select(F.col("i").alias("x"), F.col("j").alias("y")).unionByName(pairs.select(F.col("j").alias("x"), F.col("i").alias("y")))


def _near(hg: Hypergraph) -> DataFrame:
    """One-hop lists: every later neighbour of an edge with both sizes and the common members, from the member sets, so that
    sets are compared once for each pair and not for each triple the pair is in."""
    m = lambda x: hg.edges.select(F.col("e").alias(x), F.col("n").alias(f"n{x}"), F.col("members").alias(f"m{x}"))
    met = project(hg).join(m("i"), "i").join(m("j"), "j").withColumn("s", F.array_intersect("mi", "mj"))
    return stage(met.select("i", "j", "ni", "nj", F.size("s").alias("w"), "s"))


def _pairs(near: DataFrame) -> DataFrame:
    """Every pair of later neighbours of an edge, connected or not."""
    first = near.select("i", "j", "ni", "nj", F.col("w").alias("wij"), F.col("s").alias("s1"))
    second = near.select("i", F.col("j").alias("k"), F.col("nj").alias("nk"), F.col("w").alias("wik"), F.col("s").alias("s2"))
    return first.join(second, "i").where("j < k").withColumn("g", F.size(F.array_intersect("s1", "s2"))).drop("s1", "s2")


def _classified(pairs: DataFrame, near: DataFrame) -> DataFrame:
    """The connected pairs with the pattern of their three sets."""
    rows = pairs.join(near.select(F.col("i").alias("j"), F.col("j").alias("k"), F.col("w").alias("wjk")), ["j", "k"])
    return rows.withColumn("pattern", pattern_of(*[F.col(c) for c in ("wij", "wik", "wjk", "g", "ni", "nj", "nk")])).select(*COLUMNS)


def baseline_triads(hg: Hypergraph, keep_two_hop: bool = False, parallelism: int | None = None) -> DataFrame:
    """Every edge as the least id, every pair of its later neighbours, the connected ones classified from member sets.

    keep_two_hop: also store the pairs of neighbours (connected or not), as the original does; else one hop only.
    """
    near = _near(hg)
    # a few megabytes of lists form very many pairs, so they are spread over all cores
    near = near.repartition(parallelism or near.sparkSession.sparkContext.defaultParallelism, "i")
    pairs = stage(_pairs(near)) if keep_two_hop else _pairs(near)
    return _classified(pairs, near)


def baseline_motifs(hg: Hypergraph, include_open: bool = True) -> DataFrame:
    """Closed triads as above and, as rows (i, j, k in id order, pattern 0), the open ones around each centre edge."""
    near = _near(hg)
    closed = _classified(_pairs(near), near).select("i", "j", "k", "pattern")
    if not include_open:
        return closed
    both = _both_ways(near.select("i", "j"))
    ends = both.join(both.select("x", F.col("y").alias("z")), "x").where("y < z")
    open_ = ends.join(near, (F.col("y") == near["i"]) & (F.col("z") == near["j"]), "left_anti")
    ids = F.sort_array(F.array("x", "y", "z"))
    return closed.unionByName(open_.select(ids[0].alias("i"), ids[1].alias("j"), ids[2].alias("k"), F.lit(0).alias("pattern")))
