"""The experiments, re-expressed on the given tables: each gives a small table of figures.

Times are wall seconds of one run into the ``noop`` sink after the links of step one are staged, unless said otherwise.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.patterns import PATTERN_TABLE
from ..model import Hypergraph
from ..operators import measures, sampling
from ..operators.baseline import baseline_triads
from ..operators.block_searches import SEARCHES, searched
from ..operators.families import core_triads, coreless_triads, cross_triads, nest_chain_count, nest_chain_triads, one_nest_triads, shared_subset_triads, shared_superset_triads
from ..operators.links import build_links
from ..sources.builders import hypergraph
from ..stages import stage, stage_links
from .planner import triads

SEVEN = ("bucket_users", "user_day_keys", "customer_nations", "customer_brands", "order_parts", "day_customers", "doc_lines")


def timed(make: Callable[[], DataFrame], warm: int = 0, reps: int = 1) -> float:
    """Least wall seconds of ``reps`` runs of a plan."""
    for _ in range(warm):
        make().write.format("noop").mode("overwrite").save()
    best = float("inf")
    for _ in range(reps):
        t = time.time()
        make().write.format("noop").mode("overwrite").save()
        best = min(best, time.time() - t)
    return best


def _whole(spark: SparkSession, sf_dir: str, builder: str, sigma: float | None) -> Hypergraph:
    hg = hypergraph(spark, sf_dir, builder)
    return sampling.induce(hg, sigma) if sigma else hg


def _counts(df: DataFrame) -> DataFrame:
    return df.groupBy("pattern").agg(F.count(F.lit(1)).alias("cnt"))


def methods(hg: Hypergraph, links: DataFrame) -> dict[str, Callable[[], DataFrame]]:
    """The exact methods by name, each giving (pattern, cnt) of its own patterns (K1, K2)."""
    return {
        "baseline": lambda: _counts(baseline_triads(hg)),
        "nest_chain": lambda: nest_chain_count(links),
        "nest_chain_enumerated": lambda: _counts(nest_chain_triads(links)),
        "two_nests": lambda: _counts(shared_subset_triads(links).unionByName(shared_superset_triads(links))),
        "one_nest": lambda: _counts(one_nest_triads(links)),
        "cross": lambda: _counts(cross_triads(links)),
        "core_vertex": lambda: _counts(core_triads(links)),
        "core_grouped": lambda: _counts(core_triads(links, strategy="grouped")),
        "coreless": lambda: _counts(coreless_triads(links)),
        "all": lambda: triads(hg, mode="count", links=links),
    }


def counts_by_method(spark: SparkSession, sf_dir: str, builder: str, without: tuple[str, ...] = ()) -> DataFrame:
    """(method, triads) of every exact method: what the runtimes are compared on.  Each searches in its own way, inside blocks."""
    names = tuple(name for name in (*SEARCHES, "all") if name not in without)
    found = searched(hypergraph(spark, sf_dir, builder), names).groupBy("method").agg(F.sum("cnt").alias("triads"))
    every = spark.createDataFrame([(name,) for name in names], "method string")
    return every.join(found, "method", "left").select("method", F.coalesce("triads", F.lit(0)).cast("long").alias("triads"))


def exact_runtimes(spark: SparkSession, sf_dir: str, builder: str, sigma: float | None = None, warm: int = 0, without: tuple[str, ...] = ()) -> DataFrame:
    """Method, seconds, and the baseline's seconds over them (K1, K2).  Counts, as the searches are compared by them."""
    hg = _whole(spark, sf_dir, builder, sigma)
    began = time.time()
    links = stage_links(build_links(hg, with_shared=True))
    step_one = time.time() - began
    runs = {name: run for name, run in methods(hg, links).items() if name not in without}
    seconds = {name: timed(run, warm) for name, run in runs.items()}
    rows = [("links", float(step_one), None), *((k, float(v), seconds["baseline"] / v if "baseline" in seconds else None) for k, v in seconds.items())]
    return spark.createDataFrame(rows, "method string, seconds double, speedup double")


def error_by_time(spark: SparkSession, sf_dir: str, builder: str, sigma: float = 0.2, parts: tuple[float, ...] = (0.02, 0.1, 0.4), seed: int = 0) -> DataFrame:
    """Method, alpha, seconds, error: plain and stratified link sampling on the induced subgraph (K4)."""
    links = stage_links(build_links(_whole(spark, sf_dir, builder, sigma), with_shared=True))
    counts = stage(triads(None, mode="count", links=links))
    n = links.count()
    rows = []
    for part in parts:
        alpha = max(1, int(part * n))
        for name, run in (("uniform", sampling.sample_by_link), ("stratified", sampling.sample_by_family)):
            began = time.time()
            est = stage(run(links, alpha, seed))
            took = time.time() - began
            error = measures.mean_relative_error(counts, est).first()["error"]
            rows.append((name, alpha, took, None if error is None else float(error)))
    return spark.createDataFrame(rows, "method string, alpha long, seconds double, error double")


def bias_of_samplers(spark: SparkSession, sf_dir: str, builder: str, runs: int = 5, part: float = 0.3) -> DataFrame:
    """Sampler, pattern, truth, mean of the estimates over seeds (K13)."""
    hg = hypergraph(spark, sf_dir, builder)
    links = stage_links(build_links(hg, with_shared=True))
    counts = stage(triads(hg, mode="count", links=links))
    edges, n = hg.edges.count(), links.count()
    vertices = hg.incidence.select("v").distinct().count()
    seeds = list(range(1, runs + 1))
    of = {
        "vertex": lambda s: sampling.sample_by_vertex(hg, links, max(1, int(part * vertices)), s),
        "vertex_corrected": lambda s: sampling.sample_by_vertex(hg, links, max(1, int(part * vertices)), s, correct=True),
        "edge": lambda s: sampling.sample_by_edge(hg, links, max(1, int(part * edges)), s),
        "link": lambda s: sampling.sample_by_link(links, max(1, int(part * n)), s),
        "family": lambda s: sampling.sample_by_family(links, max(4, int(part * n)), s),
    }
    out = None
    for name, run in of.items():
        got = sampling.replicate(run, seeds).join(counts, "pattern").select(F.lit(name).alias("sampler"), "pattern", F.col("cnt").alias("truth"), "mean", "variance")
        out = got if out is None else out.unionByName(got)
    return out


def pattern_by_pattern(spark: SparkSession, sf_dir: str, builder: str) -> DataFrame:
    """Pattern, cnt, from twenty targeted searches over the links built once; together they are the combined search (K14).
    Each search's count, a row, is written before the next begins: one plan of all twenty would be compiled as a whole."""
    links = stage_links(build_links(hypergraph(spark, sf_dir, builder), with_shared=True))
    return reduce(DataFrame.unionByName, [stage(triads(None, p, "count", links=links)) for p in PATTERN_TABLE])
