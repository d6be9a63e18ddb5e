"""Counts, open triads, clustering coefficients, errors, and the cost and space figures of the methods."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.patterns import PATTERN_TABLE, pattern_rows
from ..model import Hypergraph
from ..stages import stage
from .links import adjacency, cross, nest


def pattern_counts(triads: DataFrame, patterns: tuple[int, ...] = tuple(PATTERN_TABLE), counted: bool = False) -> DataFrame:
    """(pattern, cnt) with a row for every pattern, counts of absent ones 0."""
    counts = triads if counted else triads.groupBy("pattern").agg(F.count(F.lit(1)).alias("cnt"))
    every = pattern_rows(triads.sparkSession).where(F.col("pattern").isin(*patterns)).select("pattern")
    return F.broadcast(every).join(counts, "pattern", "left").select("pattern", F.coalesce("cnt", F.lit(0)).cast("long").alias("cnt"))


def safe_ratio(a: Column, b: Column) -> Column:
    """a / b, null where b is 0."""
    return F.when(b != 0, a / b)


def choose2(c: Column) -> Column:
    return (c * (c - 1) / 2).cast("long")


def choose3(c: Column) -> Column:
    return (c * (c - 1) * (c - 2) / 6).cast("long")


def link_degrees(links: DataFrame) -> DataFrame:
    return adjacency(links).groupBy("x").agg(F.count(F.lit(1)).alias("d"))


def open_triad_count(links: DataFrame | None, counts: DataFrame, pairs: DataFrame | None = None) -> DataFrame:
    """(closed, open) without forming an open triad: pairs of neighbours, less three for every closed triad.  pairs: a single
    row that holds the former, as of a census by blocks; links are not read then."""
    if pairs is None:
        pairs = link_degrees(links).agg(F.coalesce(F.sum(choose2(F.col("d"))), F.lit(0)).alias("pairs"))
    closed = counts.agg(F.coalesce(F.sum("cnt"), F.lit(0)).alias("closed"))
    return pairs.join(closed).select("closed", (F.col("pairs") - 3 * F.col("closed")).alias("open"))


def open_triads(links: DataFrame) -> DataFrame:
    """Open triads one by one: centre x and its unlinked neighbours y < z."""
    both = adjacency(links).select("x", "y")
    ends = both.join(both.select("x", F.col("y").alias("z")), "x").where("y < z")
    return ends.join(links.select(F.col("i").alias("y"), F.col("j").alias("z")), ["y", "z"], "left_anti").select("x", "y", "z")


def clustering_coefficient(links: DataFrame | None, counts: DataFrame, pairs: DataFrame | None = None) -> DataFrame:
    """closed, open, and three times their ratio (null without open triads; it may pass 1)."""
    return open_triad_count(links, counts, pairs).withColumn("coefficient", safe_ratio(3 * F.col("closed"), F.col("open")))


def weights_map(weights: dict[int, float]) -> Column:
    """Weights of patterns as a map column; patterns that are not given weigh 1.  Each must lie in [0, 1]."""
    for p, w in weights.items():
        if p not in PATTERN_TABLE or not 0 <= w <= 1:
            raise ValueError(f"weight {w} of pattern {p}")
    return F.create_map(*[F.lit(x) for p in PATTERN_TABLE for x in (p, float(weights.get(p, 1.0)))])


def weighted_coefficient(links: DataFrame, counts: DataFrame, weights: dict[int, float]) -> DataFrame:
    """Three times the weighted closed triads over the open ones; all weights 1 give the plain coefficient."""
    total = counts.agg(F.sum(F.element_at(weights_map(weights), F.col("pattern")) * F.col("cnt")).alias("weighted"))
    return total.join(open_triad_count(links, counts)).select("weighted", "open", safe_ratio(3 * F.col("weighted"), F.col("open")).alias("coefficient"))


def coefficient_profile(links: DataFrame | None, counts: DataFrame, pairs: DataFrame | None = None) -> DataFrame:
    """The coefficient of each pattern alone, and its share of all triads."""
    total = open_triad_count(links, counts, pairs)
    return counts.join(total).select("pattern", "cnt", safe_ratio(3 * F.col("cnt"), F.col("open")).alias("coefficient"), safe_ratio(F.col("cnt").cast("double"), F.col("closed")).alias("share"))


def profile_distance(a: DataFrame, b: DataFrame) -> DataFrame:
    """L1 distance and cosine of two normalised count vectors."""
    sa, sb = a.agg(F.sum("cnt").alias("ta")), b.agg(F.sum("cnt").alias("tb"))
    x = a.select("pattern", F.col("cnt").alias("ca")).join(b.select("pattern", F.col("cnt").alias("cb")), "pattern").join(sa).join(sb)
    x = x.select((F.col("ca") / F.col("ta")).alias("p"), (F.col("cb") / F.col("tb")).alias("q"))
    return x.agg(F.sum(F.abs(F.col("p") - F.col("q"))).alias("l1"), (F.sum(F.col("p") * F.col("q")) / F.sqrt(F.sum(F.col("p") * F.col("p")) * F.sum(F.col("q") * F.col("q")))).alias("cosine"))


def mean_relative_error(counts: DataFrame, estimates: DataFrame, empty: str = "skip") -> DataFrame:
    """Mean over patterns of |cnt - est| / cnt, and accuracy, which is 1 less that.

    empty: ``skip`` leaves out patterns without triads; ``strict`` gives null if there is one.
    """
    x = counts.join(estimates.select("pattern", "est"), "pattern", "left")
    error = F.abs(F.col("cnt") - F.coalesce("est", F.lit(0.0))) / F.col("cnt")
    mean = F.avg(F.when(F.col("cnt") > 0, error))
    mean = F.when(F.min("cnt") > 0, mean) if empty == "strict" else mean
    return x.agg(mean.alias("error")).withColumn("accuracy", 1 - F.col("error"))


def triads_per_edge(triads: DataFrame) -> DataFrame:
    """(e, pattern, cnt): triads an edge takes part in."""
    return triads.select(F.explode(F.array("i", "j", "k")).alias("e"), "pattern").groupBy("e", "pattern").agg(F.count(F.lit(1)).alias("cnt"))


def triads_per_vertex(triads: DataFrame, hg: Hypergraph) -> DataFrame:
    """(v, pattern, cnt): triads with an edge that holds the vertex."""
    at = triads.select("i", "j", "k", "pattern", F.explode(F.array("i", "j", "k")).alias("e")).join(hg.incidence, "e")
    return at.select("v", "i", "j", "k", "pattern").distinct().groupBy("v", "pattern").agg(F.count(F.lit(1)).alias("cnt"))


def space_model(hg: Hypergraph, links: DataFrame | None, figures: DataFrame | None = None) -> DataFrame:
    """Entries each method keeps: member lists and links; the original baseline also its two-hop lists; ours the shared
    vertices of links.  figures: a single row (links, overlaps, two_hop), as ``blocks.link_figures`` gives; links are not read
    then."""
    members = hg.edges.agg(F.sum("n").alias("members"))
    if figures is None:
        kept = links.agg(F.count(F.lit(1)).alias("links"), F.sum("w").alias("overlaps"))
        figures = kept.join(link_degrees(links).agg(F.sum(choose2(F.col("d"))).alias("two_hop")))
    x = members.join(figures)
    return x.select((F.col("members") + F.col("links")).alias("baseline_one_hop"), (F.col("members") + F.col("links") + F.col("two_hop")).alias("baseline_two_hop"), (F.col("members") + F.col("overlaps")).alias("proposed")).withColumn("ratio", F.col("proposed") / F.col("baseline_one_hop"))


def work_counters(links: DataFrame, counts: DataFrame) -> DataFrame:
    """What searches look at: links by kind, lead pairs, open triads filtered away by the exhaustive search."""
    lead = links.groupBy("i").agg(F.count(F.lit(1)).alias("d")).agg(F.sum(choose2(F.col("d"))).alias("lead_pairs"))
    kinds = links.agg(F.count(F.lit(1)).alias("links"), F.sum((F.col("kind") == "C").cast("long")).alias("nest_links"), F.sum((F.col("kind") == "T").cast("long")).alias("cross_links"))
    return kinds.join(lead).join(open_triad_count(links, counts)).select("links", "nest_links", "cross_links", F.coalesce("lead_pairs", F.lit(0)).alias("lead_pairs"), "closed", "open")


def complexity_terms(hg: Hypergraph, links: DataFrame) -> DataFrame:
    """(method, step_one, step_two): the work terms of each method as numbers.  Step one of the typed methods adds the
    sizes of linked edges; step two adds, over the links a search starts from, the neighbours it scans."""
    t, c = cross(links), nest(links)
    one = F.coalesce(F.sum(F.col("ni") + F.col("nj")), F.lit(0))
    deg = link_degrees(links).withColumnRenamed("x", "e")
    base = hg.sizes.join(deg, "e").agg(F.sum(F.col("n") * F.col("d")).alias("step_one"), F.sum(F.col("n") * F.col("d") * F.col("d")).alias("step_two"))
    out_t = t.groupBy(F.col("i").alias("e")).agg(F.count(F.lit(1)).alias("ot"))
    all_t = adjacency(t).groupBy(F.col("x").alias("e")).agg(F.count(F.lit(1)).alias("at"))
    nests = c.select(F.col("big").alias("e"), F.lit(1).alias("b"), F.lit(0).alias("s")).unionByName(c.select(F.col("small").alias("e"), F.lit(0).alias("b"), F.lit(1).alias("s"))).groupBy("e").agg(F.sum("b").alias("b"), F.sum("s").alias("s"))
    total = lambda df: df.select(F.coalesce(F.sum("x"), F.lit(0)).alias("step_two"))
    ttc = total(c.select(F.col("big").alias("e")).join(all_t, "e").select(F.col("at").alias("x")))
    tcc = total(t.select(F.col("i").alias("e")).join(nests, "e").select((F.col("b") + F.col("s")).alias("x")))
    ccc = total(c.groupBy("big").agg((F.count(F.lit(1)) * F.count(F.lit(1))).alias("x")))
    ttt = total(t.select(F.col("i").alias("e"), "w").join(out_t, "e").select((F.col("ot") * F.col("w")).alias("x")))
    at = t.select("i", "j", "w", F.explode("shared").alias("v"))
    meet = at.join(at.select("i", "v", F.col("j").alias("k")), ["i", "v"]).where("j < k").select("i", "j", "k", "w").distinct()
    dense = total(meet.select(F.col("w").alias("x")))
    first = links.agg(one.alias("step_one"))
    rows = base.select(F.lit("exhaustive").alias("method"), "step_one", "step_two")
    for name, second in (("one_nest", ttc), ("two_nests", tcc), ("nest_chain", ccc), ("cross", ttt), ("core", dense), ("coreless", ttt)):
        rows = rows.unionByName(first.join(second).select(F.lit(name).alias("method"), "step_one", "step_two"))
    return rows.select("method", F.col("step_one").cast("long").alias("step_one"), F.col("step_two").cast("long").alias("step_two"))


def hub_edges(triads: DataFrame, k: int, pattern: int = 5) -> DataFrame:
    """The k edges that contain the other two of most triads of a pattern (a top-k report)."""
    sizes = F.greatest("ni", "nj", "nk")
    hub = F.when(F.col("ni") == sizes, F.col("i")).when(F.col("nj") == sizes, F.col("j")).otherwise(F.col("k"))
    return triads.where(F.col("pattern") == pattern).groupBy(hub.alias("e")).agg(F.count(F.lit(1)).alias("cnt")).orderBy(F.desc("cnt"), "e").limit(k)


def triad_core(hg: Hypergraph, k: int, find) -> DataFrame:
    """Edges left when edges in fewer than k triads go, again and again, until none goes.  ``find(hg)`` gives the triads that
    count; every round is staged, and there are as many as it takes (each takes one edge away at least, the last none)."""
    from ..model import Hypergraph as H

    left, n = hg.edges, hg.edges.count()
    while True:
        now = H(left.select("e", F.explode("members").alias("v")), left)
        has = find(now).select(F.explode(F.array("i", "j", "k")).alias("e")).groupBy("e").agg(F.count(F.lit(1)).alias("t")).where(F.col("t") >= k)
        left = stage(left.join(has.select("e"), "e", "left_semi"))
        kept = left.count()
        if kept == n:
            return left.select("e", "n")
        n = kept


def clique_edges(links: DataFrame, k: int) -> DataFrame:
    """Links (i, j, w) whose two edges have k common neighbours at least: the pairs that cliques of k + 2 edges are made of."""
    common = links.select("i", "j").join(links.select("i", F.col("j").alias("k")), "i").where("j < k").join(links.select(F.col("i").alias("j"), F.col("j").alias("k")), ["j", "k"])
    sides = common.select(F.explode(F.array(F.struct("i", "j"), F.struct("i", F.col("k").alias("j")), F.struct(F.col("j").alias("i"), F.col("k").alias("j")))).alias("l")).groupBy("l.i", "l.j").agg(F.count(F.lit(1)).alias("t"))
    return links.select("i", "j", "w").join(sides.where(F.col("t") >= k), ["i", "j"]).select("i", "j", "w")


def edge_ranks(per_edge: DataFrame) -> DataFrame:
    """Ranks of edges by triads inside each pattern: rank, dense_rank, row_number and ntile of 4 (ties: least id) and percent_rank."""
    by = Window.partitionBy("pattern").orderBy(F.desc("cnt"))
    return per_edge.select("e", "pattern", "cnt", F.ntile(4).over(by.orderBy(F.desc("cnt"), "e")).alias("quarter"), F.rank().over(by).alias("rnk"), F.dense_rank().over(by).alias("dense"), F.row_number().over(by.orderBy(F.desc("cnt"), "e")).alias("pos"), F.percent_rank().over(by).alias("share"))
