"""The hypergraph as tables.

incidence  e BIGINT, v BIGINT or STRING   one row for each membership, distinct
edges      e BIGINT, n INT, members ARRAY  sorted; no two edges have equal members
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .stages import numbered, stage


@dataclass(frozen=True)
class Hypergraph:
    """Two lazy tables; nothing is ever collected."""

    incidence: DataFrame
    edges: DataFrame

    @property
    def sizes(self) -> DataFrame:
        return self.edges.select("e", "n")


def incidence(df: DataFrame, edge: Column | str, vertex: Column | str) -> DataFrame:
    """Distinct (e, v) rows of any table; rows with a null edge or vertex go."""
    col = lambda c: F.col(c) if isinstance(c, str) else c
    return df.select(col(edge).cast("long").alias("e"), col(vertex).alias("v")).dropna().distinct()


def canonicalize(inc: DataFrame, staged: bool = True) -> Hypergraph:
    """The hypergraph of (e, v) rows: of edges with equal members the one with the least id stays."""
    members = inc.groupBy("e").agg(F.sort_array(F.collect_set("v")).alias("members"))
    edges = members.groupBy("members").agg(F.min("e").alias("e")).select("e", F.size("members").alias("n"), "members")
    edges = stage(edges) if staged else edges
    return Hypergraph(edges.select("e", F.explode("members").alias("v")), edges)


def edge_sizes(hg: Hypergraph) -> DataFrame:
    return hg.incidence.groupBy("e").agg(F.count(F.lit(1)).cast("int").alias("n"))


def vertex_degrees(hg: Hypergraph) -> DataFrame:
    return hg.incidence.groupBy("v").agg(F.count(F.lit(1)).alias("d"))


def dictionary_encode(df: DataFrame, column: str, out: str) -> DataFrame:
    """``df`` with a dense BIGINT code for each distinct value of a column, in value order; null stays null."""
    codes = numbered(df.select(column).dropna().distinct(), [column], out)
    return df.join(codes, column, "left")


def summary(hg: Hypergraph, links: DataFrame | None, counted: DataFrame | None = None) -> DataFrame:
    """One row: vertices, edges, largest and mean size, links.  counted: a single row that holds the last; links are not read
    then."""
    v = hg.incidence.agg(F.count_distinct("v").alias("vertices"))
    e = hg.edges.agg(F.count(F.lit(1)).alias("edges"), F.max("n").alias("max_size"), F.round(F.sum("n") / F.count(F.lit(1)), 6).alias("avg_size"))
    return v.join(e).join(links.agg(F.count(F.lit(1)).alias("links")) if counted is None else counted.select("links"))  # three single rows
