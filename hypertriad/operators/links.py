"""Links: pairs of edges that share a vertex, with their overlap, typed as crossing (T) or nested (C).

links  i BIGINT < j BIGINT, ni, nj INT, w INT, kind STRING, big, small BIGINT [, shared ARRAY]
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import Hypergraph, vertex_degrees

#: Rows of one vertex that meet in one task under the blocked strategy.
BLOCK = 20_000


def link_kind(w: Column, ni: Column, nj: Column) -> Column:
    """C if one edge lies in the other (no two edges are equal), else T."""
    return F.when(w == F.least(ni, nj), F.lit("C")).otherwise(F.lit("T"))


def _sized(hg: Hypergraph) -> DataFrame:
    return hg.edges.select("e", "n", F.explode("members").alias("v"))


def _aggregated(pairs: DataFrame, with_shared: bool) -> DataFrame:
    got = [F.count(F.lit(1)).cast("int").alias("w")] + [F.sort_array(F.collect_list("v")).alias("shared")] * with_shared
    return pairs.groupBy("i", "j", "ni", "nj").agg(*got)


def _meeting(left: DataFrame, right: DataFrame, on: list[str], hint: str | None = None) -> DataFrame:
    r = right.select(*on, F.col("e").alias("j"), F.col("n").alias("nj"), *[F.col(c).alias(f"{c}_r") for c in right.columns if c not in (*on, "e", "n")])
    return left.withColumnRenamed("e", "i").withColumnRenamed("n", "ni").join(r.hint(hint) if hint else r, on).where("i < j")


def _blocked(hg: Hypergraph, block: int, with_shared: bool) -> DataFrame:
    """Vertices of more than ``block`` edges are cut into blocks; a row goes to every pair of blocks its own is in."""
    blocks = F.ceil(F.col("d") / block).cast("int")
    rows = _sized(hg).join(vertex_degrees(hg).where("d > 1"), "v").withColumn("b", F.pmod(F.xxhash64("e"), blocks).cast("int"))
    dealt = rows.withColumn("o", F.explode(F.sequence(F.lit(0), blocks - 1))).select("e", "n", "v", "b", F.least("b", "o").alias("x"), F.greatest("b", "o").alias("y"))
    return _aggregated(_meeting(dealt, dealt, ["v", "x", "y"]).where("x = y OR b <> b_r"), with_shared)


def _by_members(hg: Hypergraph, with_shared: bool) -> DataFrame:
    """Connected pairs first, then the intersection of their member arrays: for few, very large edges."""
    pairs = project(hg)
    a = hg.edges.select(F.col("e").alias("i"), F.col("n").alias("ni"), F.col("members").alias("mi"))
    b = hg.edges.select(F.col("e").alias("j"), F.col("n").alias("nj"), F.col("members").alias("mj"))
    met = pairs.join(a, "i").join(b, "j").withColumn("shared", F.sort_array(F.array_intersect("mi", "mj")))
    return met.select("i", "j", "ni", "nj", F.size("shared").alias("w"), *(["shared"] if with_shared else []))


def build_links(hg: Hypergraph, with_shared: bool = False, strategy: str = "auto", block: int = BLOCK, join_hint: str | None = None) -> DataFrame:
    """All links.  strategy: ``join`` (self-join on the vertex), ``blocked`` (the same, hot vertices cut into blocks),
    ``array`` (member arrays), or ``auto``, which looks at the degrees first: blocked if some vertex has more than ``block`` edges, array if edges are very
    large on average, else join."""
    if strategy == "auto":
        size = hg.edges.agg(F.avg("n").alias("mean"))
        seen = vertex_degrees(hg).agg(F.max("d").alias("top")).join(size).first()
        strategy = "blocked" if (seen["top"] or 0) > block else "array" if (seen["mean"] or 0) > 200 else "join"
    if strategy == "blocked":
        met = _blocked(hg, block, with_shared)
    elif strategy == "array":
        met = _by_members(hg, with_shared)
    elif strategy == "join":
        met = _aggregated(_meeting(_sized(hg), _sized(hg), ["v"], join_hint), with_shared)
    else:
        raise ValueError(f"unknown strategy {strategy}")
    kind = link_kind(F.col("w"), F.col("ni"), F.col("nj"))
    first = F.col("ni") > F.col("nj")
    return met.select("i", "j", "ni", "nj", "w", kind.alias("kind"), F.when(first, F.col("i")).otherwise(F.col("j")).alias("big"), F.when(first, F.col("j")).otherwise(F.col("i")).alias("small"), *(["shared"] if with_shared else []))


def cross(links: DataFrame) -> DataFrame:
    return links.where("kind = 'T'")


def nest(links: DataFrame) -> DataFrame:
    """Nest links as (big, small, nb, ns)."""
    return links.where("kind = 'C'").select("big", "small", F.greatest("ni", "nj").alias("nb"), F.least("ni", "nj").alias("ns"))


def adjacency(links: DataFrame) -> DataFrame:
    """Both directions of every link: (x, y, w, nx, ny, kind)."""
    there = links.select(F.col("i").alias("x"), F.col("j").alias("y"), "w", F.col("ni").alias("nx"), F.col("nj").alias("ny"), "kind")
    return there.unionByName(links.select(F.col("j").alias("x"), F.col("i").alias("y"), "w", F.col("nj").alias("nx"), F.col("ni").alias("ny"), "kind"))


def project(hg: Hypergraph) -> DataFrame:
    """Connected pairs (i, j), i < j, without overlaps: the projection graph."""
    return _meeting(_sized(hg), _sized(hg), ["v"]).select("i", "j").distinct()


def links_at_least(links: DataFrame, s: int) -> DataFrame:
    """The s-overlap graph."""
    return links.where(F.col("w") >= s)


def bruteforce_links(hg: Hypergraph) -> DataFrame:
    """Every pair of edges compared: for tests on small inputs only."""
    a, b = hg.edges.select(F.col("e").alias("i"), F.col("members").alias("mi")), hg.edges.select(F.col("e").alias("j"), F.col("members").alias("mj"))
    return a.crossJoin(b).where((F.col("i") < F.col("j")) & F.arrays_overlap("mi", "mj")).select("i", "j", F.size(F.array_intersect("mi", "mj")).alias("w"))


def save_links(links: DataFrame, path: str) -> None:
    """Links as Parquet by kind: a search that needs one kind reads one folder."""
    links.repartition("kind", "i").write.mode("overwrite").partitionBy("kind").parquet(path)


def load_links(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path)


def save_links_table(links: DataFrame, table: str, buckets: int = 64) -> None:
    """Links as a table bucketed and sorted by i, so that lead joins need no exchange."""
    links.write.mode("overwrite").bucketBy(buckets, "i").sortBy("i").saveAsTable(table)
