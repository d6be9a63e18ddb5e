"""Which search answers a request: only the families, link kinds and columns that the asked patterns need."""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.patterns import CORE, CORELESS, FAMILIES, PATTERN_TABLE, members_of
from ..model import Hypergraph
from ..operators.families import (
    core_triads,
    coreless_triads,
    cross_triads,
    degree_led_triads,
    nest_chain_count,
    nest_chain_triads,
    one_nest_triads,
    shared_subset_triads,
    shared_superset_triads,
    unified_triads,
)
from ..operators.block_searches import counted as counted_by_blocks
from ..operators.links import build_links, cross, nest
from ..operators.measures import pattern_counts
from ..stages import stage_links


#: Lead pairs of one edge from which on the search is led by degree.
HUB = 5_000
#: Core patterns alone are found by shared vertices where these meet at most this many times as often as lead pairs do.
CORE_MEETINGS = 0.5
#: The fused search is taken where it forms at most this many times the pairs of the separate ones.
FUSED_PAIRS = 1.5


@dataclass(frozen=True)
class TriadPlan:
    """A request resolved: patterns by search, and what must be built for them."""

    chain: bool
    subset: tuple[int, ...]
    superset: tuple[int, ...]
    one_nest: tuple[int, ...]
    core: tuple[int, ...]
    coreless: tuple[int, ...]
    count_only: bool

    @property
    def need_shared(self) -> bool:
        return bool(self.core or self.coreless)

    @property
    def link_kinds(self) -> tuple[str, ...]:
        cross = self.subset or self.superset or self.one_nest or self.core or self.coreless
        nested = self.chain or self.subset or self.superset or self.one_nest
        return (*(("T",) if cross else ()), *(("C",) if nested else ()))

    def __str__(self) -> str:
        parts = [f"{k}={v}" for k, v in self.__dict__.items() if v]
        return f"TriadPlan(links={'+'.join(self.link_kinds)}, shared={self.need_shared}, {', '.join(parts)})"


def patterns_of(request: int | str | list | tuple | None) -> tuple[int, ...]:
    """A pattern, a family name, ``core`` or ``coreless``, a list of patterns, or None for all."""
    if request is None:
        return tuple(PATTERN_TABLE)
    if isinstance(request, int):
        request = [request]
    if isinstance(request, str):
        named = {"core": CORE, "coreless": CORELESS} | {f: members_of(f) for f in FAMILIES}
        if request not in named:
            raise ValueError(f"unknown family {request}")
        return named[request]
    if unknown := set(request) - set(PATTERN_TABLE):
        raise ValueError(f"unknown patterns {sorted(unknown)}")
    return tuple(sorted(set(request)))


def plan_for(request: int | str | list | tuple | None = None, mode: str = "enumerate") -> TriadPlan:
    want = patterns_of(request)
    some = lambda *among: tuple(p for p in among if p in want)
    return TriadPlan(1 in want, some(2, 3), some(4, 5), some(6, 7, 8), some(*CORE), some(*CORELESS), mode == "count")


def _pruned(links: DataFrame, plan: TriadPlan) -> DataFrame:
    """Drops link kinds that no search reads."""
    return links if len(plan.link_kinds) == 2 else links.where(F.col("kind") == plan.link_kinds[0])


def choose(links: DataFrame) -> tuple[str, bool]:
    """(lead, fused) for a search of all patterns, or of several families, from the degrees of the links: led by degree
    where one edge would lead very many pairs, and as one search over all links where that forms few more pairs than the
    searches of the families, which together exchange the links several times."""
    one = F.lit(1)
    led = links.groupBy("i").agg(F.count(one).alias("d"), F.sum((F.col("kind") == "T").cast("long")).alias("t"))
    led = led.agg(F.max("d").alias("most"), F.sum(F.col("d") * (F.col("d") - 1) / 2).alias("all"), F.sum(F.col("t") * (F.col("t") - 1) / 2).alias("cross"))
    c = nest(links)
    pairs = lambda by: c.groupBy(by).agg(F.count(one).alias("n")).agg(F.coalesce(F.sum(F.col("n") * (F.col("n") - 1) / 2), F.lit(0.0)).alias(by))
    seen = led.join(pairs("small")).join(pairs("big")).first()  # single rows
    if seen["most"] is None:
        return "id", False
    separate = seen["cross"] + seen["small"] + seen["big"]
    return ("degree" if seen["most"] > HUB else "id"), seen["all"] <= FUSED_PAIRS * separate


def choose_core(links: DataFrame) -> str:
    """How to find core patterns alone: by meetings on (lead, shared vertex), or by lead pairs where large overlaps would make
    more meetings than there are pairs."""
    t = cross(links)
    half = lambda: F.coalesce(F.sum(F.col("n") * (F.col("n") - 1) / 2), F.lit(0.0))
    pairs = t.groupBy("i").agg(F.count(F.lit(1)).alias("n")).agg(half().alias("pairs"))
    met = t.select("i", F.explode("shared").alias("v")).groupBy("i", "v").agg(F.count(F.lit(1)).alias("n")).agg(half().alias("met"))
    seen = pairs.join(met).first()  # single rows
    return "vertex" if seen["met"] <= CORE_MEETINGS * seen["pairs"] else "cross"


def searches(links: DataFrame, plan: TriadPlan, lead: str = "id", core_strategy: str = "auto", fused: bool = False) -> list[DataFrame]:
    """The searches of a plan.  With core and coreless patterns asked together one lead join serves both; core patterns
    alone avoid open pairs, coreless ones alone stop at the first common vertex."""
    if fused:  # every pattern from one lead join and one closing join over all links
        return [degree_led_triads(links, tuple(PATTERN_TABLE), "TC") if lead == "degree" else unified_triads(links)]
    out = []
    if plan.chain and not plan.count_only:
        out.append(nest_chain_triads(links))
    if plan.subset:
        out.append(shared_subset_triads(links, plan.subset))
    if plan.superset:
        out.append(shared_superset_triads(links, plan.superset))
    if plan.one_nest:
        out.append(one_nest_triads(links, plan.one_nest))
    if plan.core and plan.coreless:
        together = degree_led_triads if lead == "degree" else cross_triads
        out.append(together(links, plan.core + plan.coreless))
    elif plan.core:
        way = choose_core(links) if core_strategy == "auto" else core_strategy
        out.append(cross_triads(links, plan.core) if way == "cross" else core_triads(links, plan.core, way))
    elif plan.coreless:
        out.append(coreless_triads(links, plan.coreless))
    return out


def triads(hg: Hypergraph | None, request: int | str | list | tuple | None = None, mode: str = "enumerate", links: DataFrame | None = None, lead: str = "auto", core_strategy: str = "auto", parallelism: int | None = None, strategy: str = "auto", fused: bool | None = None) -> DataFrame:
    """Triads of the asked patterns, or their counts (pattern, cnt; zeros filled in for every asked pattern).

    Step one builds and stages links (or takes ``links``; they need ``shared`` for patterns 9 to 20); step two runs the
    searches of the plan.  lead: ``id``, ``degree`` or ``auto``; fused: one search for all patterns, or None to let the
    degrees decide both (``choose``).  parallelism sets the partitions of the links that searches start from.
    Counts of all patterns with nothing else asked are taken by blocks (``operators.blocks``), which needs no links.
    """
    plan, want = plan_for(request, mode), patterns_of(request)
    if mode == "count" and hg is not None and len(want) == len(PATTERN_TABLE) and (lead, core_strategy, strategy) == ("auto",) * 3 and parallelism is None and fused is None:
        return pattern_counts(counted_by_blocks(hg), want, counted=True)
    if links is None:
        links = stage_links(_pruned(build_links(hg, with_shared=plan.need_shared, strategy=strategy), plan))
    links = _pruned(links, plan)
    every = len(want) == len(PATTERN_TABLE)
    if plan.core and plan.coreless and (lead == "auto" or every and fused is None):
        found_lead, found_fused = choose(links)
        lead, fused = found_lead if lead == "auto" else lead, found_fused if fused is None else fused
    lead, fused = "id" if lead == "auto" else lead, bool(fused) and every
    links = links.repartition(parallelism, "i") if parallelism else links
    found = searches(links, plan, lead, core_strategy, fused)
    if mode != "count":
        return reduce(DataFrame.unionByName, found)
    parts = [f.groupBy("pattern").agg(F.count(F.lit(1)).alias("cnt")) for f in found]
    if plan.chain and not fused:
        parts.append(nest_chain_count(links))
    counted = reduce(DataFrame.unionByName, parts)
    return pattern_counts(counted, want, counted=True)


def explain_plan(hg: Hypergraph, request: int | str | list | tuple | None = None) -> str:
    """The resolved request and Spark's plan for it."""
    plan = plan_for(request)
    df = triads(hg, request)
    return f"{plan}\n{df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString('formatted'))}"
