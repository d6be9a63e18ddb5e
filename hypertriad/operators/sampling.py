"""Approximate counts: an induced subgraph, sampled leads, and estimators with their bias, variance and cost.

Draws without replacement order elements by md5 of their ids and a seed, so any engine and any partitioning draws alike;
draws with replacement give multiplicities.  An estimate is a table (pattern, est) with a row for every pattern.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.patterns import FAMILIES, family_of, pattern_of, pattern_rows
from ..model import Hypergraph
from ..stages import numbered, stage
from .block_samples import LinksInBlocks
from .families import cross_triads, nest_chain_triads, one_nest_triads, shared_subset_triads, shared_superset_triads, unified_triads
from .links import adjacency, cross


def draw_key(seed: int, *ids: str) -> Column:
    """md5 of the ids joined by commas, a colon and the seed."""
    return F.md5(F.concat(F.concat_ws(",", *[F.col(c).cast("string") for c in ids]), F.lit(f":{seed}")))


def least_keys(pool: DataFrame, ids: list[str], size: int, seed: int = 0) -> DataFrame:
    """The ``size`` rows of least key.  Two rounds of counts by the key's leading bits (4,096 at a time) name the cell of the
    last one, so only that cell, a share of one in 16 million, is ever sorted."""
    keyed = pool.withColumn("_key", draw_key(seed, *ids)).withColumn("_cell", F.conv(F.substring("_key", 1, 6), 16, 10).cast("int"))
    left, low = size, 0
    for shift, inside in ((12, F.lit(True)), (0, None)):
        counts = keyed.where(inside if inside is not None else F.shiftright("_cell", 12) == low).groupBy(F.shiftright("_cell", shift).alias("c")).agg(F.count(F.lit(1)).alias("n")).collect()  # 4,096 rows at most
        for r in sorted(counts):
            low = r["c"]
            if r["n"] >= left:
                break
            left -= r["n"]
        else:
            return pool  # no more rows than asked for
    whole = keyed.where(F.col("_cell") < low)
    return whole.unionByName(keyed.where(F.col("_cell") == low).orderBy("_key", *ids).limit(left)).drop("_key", "_cell")


def induce(hg: Hypergraph, sigma: float, seed: int = 0, how: str = "topk") -> Hypergraph:
    """Keep a share of the edges, whole.  ``topk``: exactly ceil(sigma E) of least key; ``threshold``: those whose key
    falls below sigma, without counting; ``rand``: each by a seeded draw of its own, so its number is as sigma in the mean
    and depends on how the edges lie in partitions."""
    key = draw_key(seed, "e")
    if how == "topk":
        n = hg.edges.count()
        edges = least_keys(hg.edges, ["e"], -(-n * round(sigma * 10**6) // 10**6), seed)
    elif how == "threshold":
        edges = hg.edges.where(F.conv(F.substring(key, 1, 8), 16, 10).cast("long") < F.lit(int(sigma * 2**32)))
    elif how == "rand":
        edges = hg.edges.where(F.rand(seed) < sigma)
    else:
        raise ValueError(f"unknown way {how}")
    edges = stage(edges)
    return Hypergraph(edges.select("e", F.explode("members").alias("v")), edges)


def scale_up(sigma: float, edges: int | None = None, kept: int | None = None) -> float:
    """Triads of the whole for each triad of the subgraph: 1/sigma cubed, or, with the numbers of edges, the exact ratio of
    triples for draws without replacement."""
    if edges is None or kept is None:
        return sigma**-3
    return edges * (edges - 1) * (edges - 2) / max(1, kept * (kept - 1) * (kept - 2))


def draw(pool: DataFrame, ids: list[str], size: int, seed: int = 0, replacement: bool = False) -> DataFrame:
    """``size`` elements of a pool with their multiplicity.  Without replacement: those of least key, each once.  With:
    pseudo-random positions in a distributed numbering; the number of distinct positions is at most ``size``."""
    if not replacement:
        return least_keys(pool, ids, size, seed).withColumn("mult", F.lit(1).cast("long"))
    lined = stage(numbered(pool, ids, "_pos"))
    n = lined.count()
    if not n:
        return lined.drop("_pos").withColumn("mult", F.lit(1).cast("long"))
    turn = F.conv(F.substring(draw_key(seed, "id"), 1, 15), 16, 10).cast("long")
    at = pool.sparkSession.range(size).select((turn % n).alias("_pos")).groupBy("_pos").agg(F.count(F.lit(1)).alias("mult"))
    return lined.join(at, "_pos").drop("_pos")


def _estimates(rows: DataFrame, factor: Column | float) -> DataFrame:
    """Zero-filled (pattern, raw, est) from counted triads with multiplicities."""
    factor = F.lit(float(factor)) if isinstance(factor, (int, float)) else factor
    raw = rows.groupBy("pattern").agg(F.sum("mult").alias("raw"))
    every = F.broadcast(pattern_rows(rows.sparkSession).select("pattern")).join(raw, "pattern", "left").withColumn("raw", F.coalesce("raw", F.lit(0)).cast("double"))
    return every.select("pattern", "raw", (F.col("raw") * factor).alias("est"))


def sample_by_vertex(hg: Hypergraph, links: DataFrame, alpha: int, seed: int = 0, correct: bool = False, scale: float = 1.0) -> DataFrame:
    """Sampled vertices count the triads whose least edge holds them.  A triad is counted for every vertex of that edge, so
    the plain estimate overshoots by its size; ``correct`` divides by it."""
    vertices = hg.incidence.select("v").distinct()
    n = vertices.count()
    chosen = draw(vertices, ["v"], alpha, seed)
    leads = hg.incidence.join(chosen, "v").groupBy(F.col("e").alias("i")).agg(F.sum("mult").alias("mult"))
    rows = _led_by(links.join(leads, "i"), links)  # only sampled leads reach the triad joins
    weight = F.col("mult") / F.col("ni") if correct else F.col("mult")
    return _estimates(rows.select("pattern", weight.alias("mult")), n / min(alpha, n) * scale)


def sample_by_edge(hg: Hypergraph, links: DataFrame, alpha: int, seed: int = 0, replacement: bool = False, scale: float = 1.0) -> DataFrame:
    """Sampled edges count the triads of which they are the least id."""
    n = hg.edges.count()
    chosen = draw(hg.edges.select("e"), ["e"], alpha, seed, replacement)
    first = links.join(chosen, F.col("i") == F.col("e"))  # only sampled leads reach the triad joins
    rows = _led_by(first, links)
    return _estimates(rows, n / (alpha if replacement else min(alpha, n)) * scale)


def _led_by(first: DataFrame, links: DataFrame) -> DataFrame:
    """Pattern, size of the least edge and multiplicity of the triads whose two least edges are a link of ``first``."""
    a = first.select("i", "j", F.col("w").alias("wij"), "ni", "nj", F.col("shared").alias("s1"), "mult")
    b = links.select("i", F.col("j").alias("k"), F.col("w").alias("wik"), F.col("nj").alias("nk"), F.col("shared").alias("s2"))
    c = links.select(F.col("i").alias("j"), F.col("j").alias("k"), F.col("w").alias("wjk"))
    rows = a.join(b, "i").where("j < k").withColumn("g", F.size(F.array_intersect("s1", "s2"))).drop("s1", "s2").join(c, ["j", "k"])
    return rows.select(pattern_of(*[F.col(x) for x in ("wij", "wik", "wjk", "g", "ni", "nj", "nk")]).alias("pattern"), "ni", "mult")


def sample_by_link(links: DataFrame | LinksInBlocks, alpha: int, seed: int = 0, replacement: bool = False, scale: float = 1.0) -> DataFrame:
    """Sampled links count the triads of which they are the link of least order (the two least ids)."""
    if isinstance(links, LinksInBlocks) and not replacement:
        rows, each = links.by_link(alpha, seed)
        return _estimates(rows, each * scale)
    n = links.count()
    chosen = draw(links, ["i", "j"], alpha, seed, replacement)
    return _estimates(_led_by(chosen, links), n / (alpha if replacement else max(1, min(alpha, n))) * scale)


def sample_links_any_order(links: DataFrame, alpha: int, seed: int = 0) -> DataFrame:
    """The earlier link sampler, without an order: every triad, closed or open, that holds a sampled link is counted.  A
    closed triad holds three links and an open one (pattern 0) two, so the scales differ."""
    n = links.count()
    alpha = max(1, min(alpha, n))
    chosen = stage(draw(links, ["i", "j"], alpha, seed))
    there = links.select(F.col("i").alias("x"), F.col("j").alias("z"), "w", F.col("nj").alias("nz"), "shared")
    near = there.unionByName(links.select(F.col("j").alias("x"), F.col("i").alias("z"), "w", F.col("ni").alias("nz"), "shared"))
    one = near.select(F.col("x").alias("i"), "z", F.col("w").alias("wi"), "nz", F.col("shared").alias("si"))
    two = near.select(F.col("x").alias("j"), "z", F.col("w").alias("wj"))
    ends = chosen.join(one.select("i", "z"), "i").select("i", "j", "z").unionByName(chosen.join(two.select("j", "z"), "j").select("i", "j", "z")).where("z <> i AND z <> j")
    kinds = ends.groupBy("i", "j", "z").agg(F.count(F.lit(1)).alias("c"))
    met = chosen.join(one, "i").where("z <> j").withColumn("g", F.size(F.array_intersect("shared", "si"))).drop("shared", "si").join(two, ["j", "z"])
    pattern = pattern_of(*[F.col(c) for c in ("w", "wi", "wj", "g", "ni", "nj", "nz")])  # the order of the three does not matter
    closed = met.groupBy(pattern.alias("pattern")).agg(F.count(F.lit(1)).alias("raw"))
    opened = kinds.where("c = 1").agg(F.count(F.lit(1)).alias("raw")).select(F.lit(0).alias("pattern"), "raw")
    every = pattern_rows(links.sparkSession).select("pattern").unionByName(links.sparkSession.range(1).select(F.lit(0).alias("pattern")))
    got = F.broadcast(every).join(closed.unionByName(opened), "pattern", "left").withColumn("raw", F.coalesce("raw", F.lit(0)).cast("double"))
    return got.select("pattern", "raw", (F.col("raw") * F.when(F.col("pattern") == 0, n / (2.0 * alpha)).otherwise(n / (3.0 * alpha))).alias("est"))


def allocate(t: int, c: int, alpha: int, allocation: str = "product", families: tuple[str, ...] = FAMILIES) -> dict[str, int]:
    """Samples for each family from its pool (TTT and TCC from t cross links, CCC and TTC from c nest links).

    ``product``: as pairs of kinds occur among two random links; ``equal``; ``pool``: as the pools.  Only the asked families
    share alpha.  A family with a pool gets one sample at least, and none without.
    """
    pool = {"TTT": t, "TCC": t, "CCC": c, "TTC": c}
    part = {"product": {"TTT": t * t, "CCC": c * c, "TCC": t * c, "TTC": t * c}, "equal": dict.fromkeys(FAMILIES, 1), "pool": pool}[allocation]
    total = sum(part[f] for f in families) or 1
    return {f: min(pool[f], max(1, round(alpha * part[f] / total))) if pool[f] else 0 for f in families}


def sample_by_family(links: DataFrame | LinksInBlocks, alpha: int, seed: int = 0, replacement: bool = False, scale: float = 1.0, families: tuple[str, ...] = FAMILIES, allocation: str = "product") -> DataFrame:
    """Stratified sampling: each family's own search from sampled leads of its own pool.  Each triad has one lead: the link
    of the two largest edges in a chain, the only cross link with two nests, the only nest link with one, and the link of
    the two least ids with none."""
    if isinstance(links, LinksInBlocks) and not replacement:
        rows, pool, share = links.by_family(alpha, seed, lambda t, c: allocate(t, c, alpha, allocation, families))
        factor = F.create_map(*[F.lit(x) for f in FAMILIES for x in (f, pool[f] / share[f] if share.get(f) else 0.0)])
        return _estimates(rows, F.element_at(factor, family_of(F.col("pattern"))) * F.lit(float(scale)))
    sizes = {r["kind"]: r["n"] for r in links.groupBy("kind").agg(F.count(F.lit(1)).alias("n")).collect()}  # two rows
    pool = {"TTT": sizes.get("T", 0), "TCC": sizes.get("T", 0), "CCC": sizes.get("C", 0), "TTC": sizes.get("C", 0)}
    share = allocate(pool["TTT"], pool["CCC"], alpha, allocation, families)
    found = []
    for family in families:
        if not share[family]:
            continue
        of = cross(links) if family in ("TTT", "TCC") else links.where("kind = 'C'")
        lead = stage(draw(of.select("i", "j", "big", "small"), ["i", "j"], share[family], seed, replacement))
        got = {"TTT": lambda x: [cross_triads(links, lead=x)], "CCC": lambda x: [nest_chain_triads(links, lead=x)], "TCC": lambda x: [shared_subset_triads(links, lead=x), shared_superset_triads(links, lead=x)], "TTC": lambda x: [one_nest_triads(links, lead=x)]}[family](lead)
        found += [g.select("pattern", "mult") for g in got]
    factor = F.create_map(*[F.lit(x) for f in FAMILIES for x in (f, pool[f] / share[f] if share.get(f) else 0.0)])
    if not found:
        found = [links.sparkSession.createDataFrame([], "pattern int, mult long")]
    return _estimates(reduce(DataFrame.unionByName, found), F.element_at(factor, family_of(F.col("pattern"))) * F.lit(float(scale)))


def sampling_expectation(links: DataFrame, element: str) -> DataFrame:
    """(pattern, expected): what an estimate by vertices, edges or links is in the mean.  By vertices a triad counts once for
    each vertex of its least edge."""
    rows = unified_triads(links)
    value = F.sum("ni") if element == "vertex" else F.count(F.lit(1))
    got = rows.groupBy("pattern").agg(value.alias("expected"))
    return F.broadcast(pattern_rows(links.sparkSession).select("pattern")).join(got, "pattern", "left").select("pattern", F.coalesce("expected", F.lit(0)).cast("long").alias("expected"))


def _lead_loads(links: DataFrame, element: str) -> DataFrame:
    keys = ["i"] if element == "edge" else ["i", "j"]
    return unified_triads(links).groupBy("pattern", *keys).agg(F.count(F.lit(1)).alias("c"))


def variance_uniform(links: DataFrame, element: str, alpha: int, population: int, joint: str = "assumed") -> DataFrame:
    """(pattern, triads, pairs, sharing, variance) of the raw count of alpha draws from ``population`` leads.

    With d the population, H triads, P ordered pairs of triads and S of these with a common lead:
    ``assumed`` takes a pair's joint probability as a third of 1/d where they share an element, giving
    alpha (H (1/d - 1/d^2) + S / (3 d) - P / d^2); ``lead`` has the exact 1/d, which drops the 3.
    """
    loads = _lead_loads(links, element)
    got = loads.groupBy("pattern").agg(F.sum("c").alias("h"), F.sum(F.col("c") * (F.col("c") - 1)).alias("s"))
    every = F.broadcast(pattern_rows(links.sparkSession).select("pattern")).join(got, "pattern", "left").na.fill(0, ["h", "s"])
    return every.select("pattern", F.col("h").cast("long").alias("triads"), (F.col("h") * (F.col("h") - 1)).cast("long").alias("pairs"), F.col("s").cast("long").alias("sharing"), _variance(F.col("h"), F.col("h") * (F.col("h") - 1), F.col("s"), F.lit(float(alpha)), F.lit(float(population)), joint).alias("variance"))


def _variance(h: Column, p: Column, s: Column, alpha: Column, d: Column, joint: str) -> Column:
    third = 3.0 if joint == "assumed" else 1.0
    return F.when(d > 0, alpha * (h * (1 / d - 1 / (d * d)) + s / (F.lit(third) * d) - p / (d * d)))


def variance_by_family(links: DataFrame, alpha: int, joint: str = "assumed") -> DataFrame:
    """The variance of each pattern's raw count under stratified sampling: the uniform one with the family's pool and share
    in place of all links and alpha."""
    sizes = {r["kind"]: r["n"] for r in links.groupBy("kind").agg(F.count(F.lit(1)).alias("n")).collect()}
    t, c = sizes.get("T", 0), sizes.get("C", 0)
    total = float((t + c) ** 2 or 1)
    shares = {"TTT": t * t * alpha / total, "CCC": c * c * alpha / total, "TCC": t * c * alpha / total, "TTC": t * c * alpha / total}
    pools = {"TTT": t, "TCC": t, "CCC": c, "TTC": c}
    f = family_of(F.col("pattern"))
    as_map = lambda d: F.element_at(F.create_map(*[F.lit(x) for k, v in d.items() for x in (k, float(v))]), f)
    loads = family_lead_loads(links)
    got = loads.groupBy("pattern").agg(F.sum("c").alias("h"), F.sum(F.col("c") * (F.col("c") - 1)).alias("s"))
    every = F.broadcast(pattern_rows(links.sparkSession).select("pattern")).join(got, "pattern", "left").na.fill(0, ["h", "s"])
    h, s = F.col("h"), F.col("s")
    return every.select("pattern", h.cast("long").alias("triads"), s.cast("long").alias("sharing"), as_map(shares).alias("alpha"), as_map(pools).alias("pool"), _variance(h, h * (h - 1), s, as_map(shares), as_map(pools), joint).alias("variance"))


def family_lead_loads(links: DataFrame) -> DataFrame:
    """(pattern, a, b, c): triads of a pattern led by each link under the families' own lead rules."""
    rows = unified_triads(links)
    kind = lambda w, x, y: w == F.least(x, y)
    nij, nik, njk = kind(F.col("wij"), F.col("ni"), F.col("nj")), kind(F.col("wik"), F.col("ni"), F.col("nk")), kind(F.col("wjk"), F.col("nj"), F.col("nk"))
    link = lambda x, y: F.struct(F.col(x).alias("a"), F.col(y).alias("b"))
    by_size = F.sort_array(F.array(F.struct("ni", F.col("i").alias("e")), F.struct(F.col("nj").alias("ni"), F.col("j").alias("e")), F.struct(F.col("nk").alias("ni"), F.col("k").alias("e"))))
    chain = F.struct(F.least(by_size[1]["e"], by_size[2]["e"]).alias("a"), F.greatest(by_size[1]["e"], by_size[2]["e"]).alias("b"))
    only = lambda x, y, z: F.when(x, link("i", "j")).when(y, link("i", "k")).otherwise(link("j", "k"))
    f = family_of(F.col("pattern"))
    lead = F.when(f == "CCC", chain).when(f == "TCC", only(~nij, ~nik, ~njk)).when(f == "TTC", only(nij, nik, njk)).otherwise(link("i", "j"))
    return rows.select("pattern", lead.alias("l")).groupBy("pattern", "l.a", "l.b").agg(F.count(F.lit(1)).alias("c"))


def replicate(sampler, seeds: list[int]) -> DataFrame:
    """(pattern, runs, mean, variance) of ``sampler(seed)`` over seeds, as one query."""
    runs = reduce(DataFrame.unionByName, [sampler(s).select("pattern", "est", F.lit(s).alias("seed")) for s in seeds])
    return runs.groupBy("pattern").agg(F.count(F.lit(1)).alias("runs"), F.avg("est").alias("mean"), F.var_samp("est").alias("variance"))


def sampled_cost(links: DataFrame, alpha: int) -> DataFrame:
    """(method, entries): neighbour-list entries a run visits in the mean, at equal alpha, under uniform and stratified
    sampling (with the overlap factor of the cross search)."""
    t, n = cross(links), adjacency(links).groupBy("x").agg(F.sum((F.col("kind") == "T").cast("long")).alias("nt"), F.sum((F.col("kind") == "C").cast("long")).alias("nc"))
    later = links.groupBy(F.col("i").alias("x")).agg(F.count(F.lit(1)).alias("d"), F.sum((F.col("kind") == "T").cast("long")).alias("dt"))
    size = links.agg(F.count(F.lit(1)).alias("all"), F.sum((F.col("kind") == "T").cast("long")).alias("t"), F.sum((F.col("kind") == "C").cast("long")).alias("c"))
    uniform = links.join(later, F.col("i") == F.col("x")).agg(F.sum(F.col("d") * F.col("w")).alias("u"))
    ttt = t.join(later, F.col("i") == F.col("x")).agg(F.sum(F.col("dt") * F.col("w")).alias("a1"))
    ccc = links.where("kind = 'C'").join(n, F.col("small") == F.col("x")).agg(F.sum("nc").alias("a2"))
    tcc = t.join(n, F.col("i") == F.col("x")).agg(F.sum("nc").alias("a3"))
    ttc = links.where("kind = 'C'").join(n, F.col("small") == F.col("x")).agg(F.sum("nt").alias("a4"))
    x = size.join(uniform).join(ttt).join(ccc).join(tcc).join(ttc).na.fill(0)
    a, s2 = F.lit(float(alpha)), F.col("all") * F.col("all")
    strata = F.col("t") * F.col("a1") * a / s2 + F.col("c") * F.col("a2") * a / s2 + F.col("c") * F.col("a3") * a / s2 + F.col("t") * F.col("a4") * a / s2
    return x.select(F.explode(F.array(F.struct(F.lit("uniform").alias("method"), (F.col("u") * a / F.col("all")).alias("entries")), F.struct(F.lit("stratified").alias("method"), strata.alias("entries")))).alias("r")).select("r.method", "r.entries")


