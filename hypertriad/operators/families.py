"""Exact triad searches, one for each family of patterns.

Every search gives rows of the triads schema
    i < j < k BIGINT, wij, wik, wjk, g INT, ni, nj, nk INT, pattern INT
and takes only the links its family has.  ``lead`` (a table of links with a multiplicity ``mult``) restricts a search to
the triads of which one of these links is the lead, and adds the multiplicity to the rows; samplers use it.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.patterns import CORE, CORELESS, PATTERN_TABLE, members_of, pattern_of
from .links import adjacency, cross, nest

COLUMNS = ("i", "j", "k", "wij", "wik", "wjk", "g", "ni", "nj", "nk", "pattern")


def ordered(df: DataFrame, ids: tuple[str, str, str], sizes: tuple[str, str, str], overlaps: dict[str, Column], g: Column, pattern: Column) -> DataFrame:
    """Rows in roles to rows in id order.  overlaps: by the role that is left out, as 'bc' is what a is left out of."""
    a, b, c = ids
    each = [F.struct(F.col(x).alias("e"), F.col(n).cast("int").alias("n"), overlaps[x].cast("int").alias("opposite")) for x, n in zip((a, b, c), sizes)]
    s = F.sort_array(F.array(*each))
    out = df.select("*", s.alias("_s"), g.cast("int").alias("_g"), pattern.alias("_p"))
    more = ["mult"] if "mult" in df.columns else []
    return out.select(
        F.col("_s")[0]["e"].alias("i"), F.col("_s")[1]["e"].alias("j"), F.col("_s")[2]["e"].alias("k"),
        F.col("_s")[2]["opposite"].alias("wij"), F.col("_s")[1]["opposite"].alias("wik"), F.col("_s")[0]["opposite"].alias("wjk"),
        F.col("_g").alias("g"), F.col("_s")[0]["n"].alias("ni"), F.col("_s")[1]["n"].alias("nj"), F.col("_s")[2]["n"].alias("nk"), F.col("_p").alias("pattern"), *more,
    )


def _led(table: DataFrame, lead: DataFrame | None, on: list[str]) -> DataFrame:
    """``table`` with multiplicities of the sampled links.  A sample may be a share of all links, so nothing is broadcast by
    hint; Spark does so where its size allows."""
    return table if lead is None else table.join(lead.select(*on, "mult"), on)


def nest_chain_triads(links: DataFrame, lead: DataFrame | None = None) -> DataFrame:
    """Pattern 1: big over mid over small, each chain once.  Lead: the link of the two larger edges."""
    upper = _led(nest(links).select("big", F.col("small").alias("mid"), "nb", F.col("ns").alias("nm")), None if lead is None else lead.select("big", F.col("small").alias("mid"), "mult"), ["big", "mid"])
    lower = nest(links).select(F.col("big").alias("mid"), "small", "ns")
    rows = upper.join(lower, "mid")
    return ordered(rows, ("big", "mid", "small"), ("nb", "nm", "ns"), {"big": F.col("ns"), "mid": F.col("ns"), "small": F.col("nm")}, F.col("ns"), F.lit(1))


def nest_chain_count(links: DataFrame) -> DataFrame:
    """The number of nested chains without forming one: supersets times subsets of each middle edge (inclusion is
    transitive, so the third link is implied)."""
    up = nest(links).groupBy(F.col("small").alias("mid")).agg(F.count(F.lit(1)).alias("up"))
    down = nest(links).groupBy(F.col("big").alias("mid")).agg(F.count(F.lit(1)).alias("down"))
    return up.join(down, "mid").agg(F.coalesce(F.sum(F.col("up") * F.col("down")), F.lit(0)).alias("cnt")).select(F.lit(1).alias("pattern"), "cnt")


def shared_subset_triads(links: DataFrame, patterns: tuple[int, ...] = (2, 3), lead: DataFrame | None = None) -> DataFrame:
    """Patterns 2 and 3: an edge inside both edges of a cross link.  Lead: the cross link."""
    a = nest(links).select(F.col("big").alias("a"), "small", F.col("nb").alias("na"), "ns")
    b = nest(links).select(F.col("big").alias("b"), "small", F.col("nb").alias("nb"))
    t = _led(cross(links).select(F.col("i").alias("a"), F.col("j").alias("b"), "w"), None if lead is None else lead.select(F.col("i").alias("a"), F.col("j").alias("b"), "mult"), ["a", "b"])
    # from sampled cross links outwards, so that only their edges' subsets are read; else from the subsets
    rows = a.join(b, "small").where("a < b").join(t, ["a", "b"]) if lead is None else t.join(a, "a").join(b, ["b", "small"])
    if set(patterns) == {2}:
        rows = rows.where("w = ns")
    elif set(patterns) == {3}:
        rows = rows.where("w > ns")
    pattern = F.when(F.col("w") == F.col("ns"), 2).otherwise(3)
    return ordered(rows, ("a", "b", "small"), ("na", "nb", "ns"), {"a": F.col("ns"), "b": F.col("ns"), "small": F.col("w")}, F.col("ns"), pattern)


def shared_superset_triads(links: DataFrame, patterns: tuple[int, ...] = (4, 5), lead: DataFrame | None = None) -> DataFrame:
    """Patterns 4 and 5: a cross link inside one edge.  Lead: the cross link."""
    least = 3 if 4 in patterns else 4
    inside = nest(links).where(F.col("nb") >= least)
    a = inside.select("big", F.col("small").alias("a"), F.col("ns").alias("na"), "nb")
    b = inside.select("big", F.col("small").alias("b"), F.col("ns").alias("n2"))
    t = _led(cross(links).select(F.col("i").alias("a"), F.col("j").alias("b"), "w"), None if lead is None else lead.select(F.col("i").alias("a"), F.col("j").alias("b"), "mult"), ["a", "b"])
    rows = a.join(b, "big").where("a < b").join(t, ["a", "b"]) if lead is None else t.join(a, "a").join(b, ["b", "big"])
    covers = F.col("na") + F.col("n2") - F.col("w") == F.col("nb")
    if set(patterns) == {4}:
        rows = rows.where(covers)
    elif set(patterns) == {5}:
        rows = rows.where(~covers)
    return ordered(rows, ("big", "a", "b"), ("nb", "na", "n2"), {"big": F.col("w"), "a": F.col("n2"), "b": F.col("na")}, F.col("w"), F.when(covers, 4).otherwise(5))


def one_nest_triads(links: DataFrame, patterns: tuple[int, ...] = (6, 7, 8), lead: DataFrame | None = None) -> DataFrame:
    """Patterns 6 to 8: a nest link whose two edges both cross a third.  Lead: the nest link."""
    c = _led(nest(links), None if lead is None else lead.select("big", "small", "mult"), ["big", "small"])
    near = adjacency(cross(links)).select(F.col("x").alias("small"), F.col("y").alias("third"), F.col("w").alias("w_small"), F.col("ny").alias("nt"))
    far = adjacency(cross(links)).select(F.col("x").alias("big"), F.col("y").alias("third"), F.col("w").alias("w_big"))
    rows = c.join(near, "small").join(far, ["big", "third"])
    same, covers = F.col("w_big") == F.col("w_small"), F.col("ns") + F.col("w_big") - F.col("w_small") == F.col("nb")
    pattern = F.when(same, 6).when(covers, 7).otherwise(8)
    if set(patterns) != {6, 7, 8}:
        rows = rows.where(pattern.isin(*patterns))
    return ordered(rows, ("big", "small", "third"), ("nb", "ns", "nt"), {"big": F.col("w_small"), "small": F.col("w_big"), "third": F.col("ns")}, F.col("w_small"), pattern)


def close(pairs: DataFrame, crossing: DataFrame, patterns: tuple[int, ...]) -> DataFrame:
    """Lead pairs (i, j, k with wij, wik, sizes and g) closed by the cross link (j, k), typed and filtered.  That the third
    link crosses must be checked: a nested one would make another family."""
    third = crossing.select(F.col("i").alias("j"), F.col("j").alias("k"), F.col("w").alias("wjk"))
    found = pairs.join(third, ["j", "k"])
    p = pattern_of(*[F.col(c) for c in ("wij", "wik", "wjk", "g", "ni", "nj", "nk")])
    more = ["mult"] if "mult" in pairs.columns else []
    out = found.withColumn("pattern", p).select(*COLUMNS, *more)
    return out if set(patterns) == set(members_of("TTT")) else out.where(F.col("pattern").isin(*patterns))


def _lead_pairs(crossing: DataFrame, lead: DataFrame | None = None) -> DataFrame:
    first = _led(crossing.select("i", "j", F.col("w").alias("wij"), "ni", "nj", F.col("shared").alias("s1")), lead, ["i", "j"])
    second = crossing.select("i", F.col("j").alias("k"), F.col("w").alias("wik"), F.col("nj").alias("nk"), F.col("shared").alias("s2"))
    return first.join(second, "i").where("j < k")


def cross_triads(links: DataFrame, patterns: tuple[int, ...] = members_of("TTT"), lead: DataFrame | None = None) -> DataFrame:
    """Patterns 9 to 20: three cross links, from pairs with the same least edge.  Needs ``shared``.  Lead: the link of the
    two least ids."""
    t = cross(links)
    pairs = _lead_pairs(t, lead).withColumn("g", F.size(F.array_intersect("s1", "s2")))
    return close(pairs.drop("s1", "s2"), t, patterns)


def coreless_triads(links: DataFrame, patterns: tuple[int, ...] = CORELESS) -> DataFrame:
    """Patterns 17 to 20: no common vertex; a lead pair goes at the first vertex its shared sets have in common.  Each edge
    must hold two disjoint overlaps, which prunes before the closing join."""
    t = cross(links).where("ni >= 2 AND nj >= 2")
    pairs = _lead_pairs(t).where("ni >= wij + wik").where(~F.arrays_overlap("s1", "s2")).withColumn("g", F.lit(0))
    return close(pairs.drop("s1", "s2"), t, patterns)


def degree_led_triads(links: DataFrame, patterns: tuple[int, ...] = members_of("TTT"), kinds: str = "T") -> DataFrame:
    """As ``cross_triads`` (kinds ``T``) or ``unified_triads`` (``TC``), but led by the edge with fewest of these links (ties:
    least id), so no edge leads more pairs than there are links, however many links a hub has.  The result is the same."""
    t = cross(links) if kinds == "T" else links
    deg = adjacency(t).groupBy("x").agg(F.count(F.lit(1)).alias("d"))
    da, db = deg.select(F.col("x").alias("i"), F.col("d").alias("di")), deg.select(F.col("x").alias("j"), F.col("d").alias("dj"))
    t2 = t.join(da, "i").join(db, "j")
    first = F.struct("di", "i") < F.struct("dj", "j")
    o = t2.select(F.when(first, F.col("i")).otherwise(F.col("j")).alias("a"), F.when(first, F.col("j")).otherwise(F.col("i")).alias("b"), F.when(first, F.col("ni")).otherwise(F.col("nj")).alias("na"), F.when(first, F.col("nj")).otherwise(F.col("ni")).alias("nb"), "w", "shared")
    two = o.select("a", F.col("b").alias("c"), F.col("nb").alias("nc"), F.col("w").alias("wac"), F.col("shared").alias("s2"))
    pairs = o.select("a", "b", "na", "nb", F.col("w").alias("wab"), F.col("shared").alias("s1")).join(two, "a").where("b < c")
    pairs = pairs.withColumn("g", F.size(F.array_intersect("s1", "s2"))).drop("s1", "s2")
    rows = pairs.join(t.select(F.col("i").alias("b"), F.col("j").alias("c"), F.col("w").alias("wbc")), ["b", "c"])
    p = pattern_of(F.col("wab"), F.col("wac"), F.col("wbc"), F.col("g"), F.col("na"), F.col("nb"), F.col("nc"))
    out = ordered(rows, ("a", "b", "c"), ("na", "nb", "nc"), {"a": F.col("wbc"), "b": F.col("wac"), "c": F.col("wab")}, F.col("g"), p)
    return out if len(patterns) == len(PATTERN_TABLE) else out.where(F.col("pattern").isin(*patterns))


def core_triads(links: DataFrame, patterns: tuple[int, ...] = CORE, strategy: str = "vertex") -> DataFrame:
    """Patterns 9 to 16: cross triads with a common vertex, found without visiting pairs of links that share none.

    ``vertex``: links meet on (lead, shared vertex); the number of meetings is the size of the common part.
    ``grouped``: links with the same lead and equal shared sets are one group, and a pair of groups is intersected once.
    """
    t = cross(links)
    if strategy == "grouped":
        return close(_grouped_pairs(t), t, patterns)
    if strategy != "vertex":
        raise ValueError(f"unknown strategy {strategy}")
    at = t.select("i", "j", F.col("w").alias("wij"), "ni", "nj", F.explode("shared").alias("v"))
    two = at.select("i", "v", F.col("j").alias("k"), F.col("wij").alias("wik"), F.col("nj").alias("nk"))
    pairs = at.join(two, ["i", "v"]).where("j < k").groupBy("i", "j", "k", "wij", "wik", "ni", "nj", "nk").agg(F.count(F.lit(1)).cast("int").alias("g"))
    return close(pairs, t, patterns)


def _grouped_pairs(t: DataFrame) -> DataFrame:
    groups = t.groupBy("i", "ni", "shared", "w").agg(F.collect_list(F.struct("j", "nj")).alias("js")).withColumn("gid", F.xxhash64("shared"))
    at = groups.select("i", "gid", F.explode("shared").alias("v"))
    two = at.select("i", "v", F.col("gid").alias("gid2"))
    pairs = at.join(two, ["i", "v"]).where("gid <= gid2").select("i", "gid", "gid2").distinct()
    b = groups.select("i", F.col("gid").alias("gid2"), F.col("shared").alias("s2"), F.col("w").alias("w2"), F.col("js").alias("ks"))
    met = pairs.join(groups.select("i", "ni", "gid", F.col("shared").alias("s1"), "w", "js"), ["i", "gid"]).join(b, ["i", "gid2"])
    g = F.when(F.col("gid") == F.col("gid2"), F.col("w")).otherwise(F.size(F.array_intersect("s1", "s2")))
    flat = met.select("i", "ni", "gid", "gid2", "w", "w2", g.alias("g"), F.explode("js").alias("a"), "ks").select("*", F.explode("ks").alias("b"))
    flat = flat.where((F.col("gid") != F.col("gid2")) | (F.col("a.j") < F.col("b.j")))
    first = F.col("a.j") < F.col("b.j")
    pick = lambda x, y: F.when(first, x).otherwise(y)
    return flat.select("i", pick(F.col("a.j"), F.col("b.j")).alias("j"), pick(F.col("b.j"), F.col("a.j")).alias("k"), pick(F.col("w"), F.col("w2")).alias("wij"), pick(F.col("w2"), F.col("w")).alias("wik"), "ni", pick(F.col("a.nj"), F.col("b.nj")).alias("nj"), pick(F.col("b.nj"), F.col("a.nj")).alias("nk"), "g")


def unified_triads(links: DataFrame) -> DataFrame:
    """All patterns in one pass over all links, told apart by their regions alone: the cross-check of the family plans."""
    first = links.select("i", "j", F.col("w").alias("wij"), "ni", "nj", F.col("shared").alias("s1"))
    second = links.select("i", F.col("j").alias("k"), F.col("w").alias("wik"), F.col("nj").alias("nk"), F.col("shared").alias("s2"))
    third = links.select(F.col("i").alias("j"), F.col("j").alias("k"), F.col("w").alias("wjk"))
    rows = first.join(second, "i").where("j < k").withColumn("g", F.size(F.array_intersect("s1", "s2"))).drop("s1", "s2").join(third, ["j", "k"])
    return rows.withColumn("pattern", pattern_of(*[F.col(c) for c in ("wij", "wik", "wjk", "g", "ni", "nj", "nk")])).select(*COLUMNS)


def triads_by_group(edges: DataFrame, group: str) -> DataFrame:
    """(group, pattern, cnt) of one hypergraph for each group, by one search with the group in every join key.  edges:
    (group, e, members), members sorted and without repeats, no two edges of a group with equal members."""
    key = "_group"  # so that the group may have any name
    at = edges.select(F.col(group).alias(key), F.col("e"), F.size("members").alias("n"), F.explode("members").alias("v"))
    a, b = at.select(key, "v", F.col("e").alias("i"), F.col("n").alias("ni")), at.select(key, "v", F.col("e").alias("j"), F.col("n").alias("nj"))
    links = a.join(b, [key, "v"]).where("i < j").groupBy(key, "i", "j", "ni", "nj").agg(F.count(F.lit(1)).cast("int").alias("w"), F.collect_list("v").alias("s1"))
    second = links.select(key, "i", F.col("j").alias("k"), F.col("w").alias("wik"), F.col("nj").alias("nk"), F.col("s1").alias("s2"))
    third = links.select(key, F.col("i").alias("j"), F.col("j").alias("k"), F.col("w").alias("wjk"))
    rows = links.join(second, [key, "i"]).where("j < k").withColumn("g", F.size(F.array_intersect("s1", "s2"))).join(third, [key, "j", "k"])
    p = pattern_of(*[F.col(c) for c in ("w", "wik", "wjk", "g", "ni", "nj", "nk")])
    return rows.groupBy(F.col(key).alias(group), p.alias("pattern")).agg(F.count(F.lit(1)).alias("cnt"))
