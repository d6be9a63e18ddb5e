"""Helpers around hypergraphs: text, time and vector columns to vertices, filters, rankings, reports."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Observation, SparkSession, Window
from pyspark.sql import functions as F

from ..model import Hypergraph
from .patterns import FAMILIES, family_of, members_of, pattern_rows, regions


# --- columns to vertices --------------------------------------------------------------------------------------------


def micros(ts: Column) -> Column:
    """Wall-clock microseconds since the epoch, for timestamps with or without a time zone."""
    return F.timestamp_diff("MICROSECOND", F.expr("TIMESTAMP_NTZ '1970-01-01 00:00:00'"), ts)


def bucket(ts: Column, seconds: int) -> Column:
    """Start of the time bucket, in seconds since the epoch."""
    return (F.floor(micros(ts) / F.lit(seconds * 1_000_000)) * seconds).cast("long")


def calendar_parts(ts: Column) -> list[Column]:
    return [F.to_date(ts).alias("day"), F.hour(ts).alias("hour"), F.dayofweek(ts).alias("weekday")]


def props_key(props: Column) -> Column:
    """The field k of a JSON column, as a number."""
    return F.get_json_object(props, "$.k").cast("long")


def lines_of(df: DataFrame, key: str, text: str) -> DataFrame:
    return df.select(key, F.explode(F.split(text, "\n")).alias("line"))


def words_of(df: DataFrame, key: str, text: str, keep_empty: bool = False) -> DataFrame:
    """Words of lower-cased text: runs of a to z."""
    words = df.select(key, F.explode(F.split(F.lower(text), "[^a-z]+")).alias("word"))
    return words if keep_empty else words.where("word <> ''")


def shingles_of(df: DataFrame, key: str, text: str, w: int = 3) -> DataFrame:
    """Distinct runs of w words; shorter texts give none."""
    words = F.filter(F.split(F.lower(text), "[^a-z]+"), lambda x: x != "")
    rows = df.select(key, words.alias("ws")).where(F.size("ws") >= w)
    each = F.transform(F.sequence(F.lit(1), F.size("ws") - (w - 1)), lambda i: F.concat_ws(" ", F.slice("ws", i, w)))
    return rows.select(key, F.explode(F.array_distinct(each)).alias("shingle"))


def hrefs_of(df: DataFrame, key: str, html: str) -> DataFrame:
    return df.select(key, F.explode(F.regexp_extract_all(html, F.lit('href="([^"]*)"'), 1)).alias("href"))


def top_dims(df: DataFrame, key: str, vector: str, k: int) -> DataFrame:
    """Indices of the k largest coordinates; ties go to the lower index."""
    pairs = F.transform(vector, lambda x, i: F.struct((-x).alias("neg"), i.alias("dim")))
    return df.select(key, F.explode(F.slice(F.sort_array(pairs), 1, k)).alias("p")).select(key, F.col("p.dim").cast("long").alias("dim"))


# --- filters --------------------------------------------------------------------------------------------------------


def _rebuilt(edges: DataFrame) -> Hypergraph:
    return Hypergraph(edges.select("e", F.explode("members").alias("v")), edges)


def filter_edges(hg: Hypergraph, least: int = 1, most: int | None = None) -> Hypergraph:
    """Edges of a size."""
    edges = hg.edges.where(F.col("n") >= least)
    return _rebuilt(edges.where(F.col("n") <= most) if most is not None else edges)


def filter_vertices(hg: Hypergraph, max_degree: int) -> DataFrame:
    """Incidence rows of vertices in at most ``max_degree`` edges (an explicit loss, never applied by itself)."""
    keep = hg.incidence.groupBy("v").agg(F.count(F.lit(1)).alias("d")).where(F.col("d") <= max_degree).select("v")
    return hg.incidence.join(keep, "v", "left_semi").select("e", "v")


def restrict_edges(hg: Hypergraph, keys: DataFrame, how: str = "left_semi") -> Hypergraph:
    """Edges whose id is (``left_semi``) or is not (``left_anti``) in keys(e)."""
    return _rebuilt(hg.edges.join(keys.select("e"), "e", how))


def edges_like(hg: Hypergraph, rows: DataFrame, key: str, **wanted: str | int) -> Hypergraph:
    """Edges whose row in ``rows`` (its id in ``key``) has the wanted values, as in ``edges_like(hg, docs, "doc_id", lang="de")``."""
    for column, value in wanted.items():
        rows = rows.where(F.col(column) == value)
    return restrict_edges(hg, rows.select(F.col(key).cast("long").alias("e")))


def regions_of_sets(a: Column, b: Column, c: Column) -> dict[str, Column]:
    """The seven regions of three sets (arrays without repeats) as arrays."""
    less, meet = F.array_except, F.array_intersect
    return {
        "only_a": less(less(a, b), c), "only_b": less(less(b, a), c), "only_c": less(less(c, a), b),
        "only_ab": less(meet(a, b), c), "only_bc": less(meet(b, c), a), "only_ac": less(meet(a, c), b), "all_abc": meet(meet(a, b), c),
    }


def observed(df: DataFrame, name: str = "work") -> tuple[DataFrame, Observation]:
    """``df`` with an observation that counts its rows and, if it has a pattern, the rows of each family, while some action
    runs it: ``observation.get`` after the action."""
    watch = Observation(name)
    counts = [F.count(F.lit(1)).alias("rows")]
    if "pattern" in df.columns:
        counts += [F.sum(F.col("pattern").isin(*members_of(f)).cast("long")).alias(f) for f in FAMILIES]
    return df.observe(watch, *counts), watch


# --- reports --------------------------------------------------------------------------------------------------------


def select_regions(triads: DataFrame) -> DataFrame:
    """The seven region sizes of each triad."""
    r = regions(*[F.col(c) for c in ("wij", "wik", "wjk", "g", "ni", "nj", "nk")])
    return triads.select("i", "j", "k", *[c.alias(n) for n, c in r.items()])


def size_preview(hg: Hypergraph, exact: bool = False) -> DataFrame:
    count = F.count_distinct if exact else F.approx_count_distinct
    return hg.incidence.agg(count("e").alias("edges"), count("v").alias("vertices"))


def degree_stats(hg: Hypergraph) -> DataFrame:
    """Spread of edge sizes: count, mean, deviation, extremes, the largest edge (ties: least id), median and 90th percentile."""
    top = F.max_by("e", F.struct("n", (-F.col("e"))))
    return hg.edges.agg(F.count(F.lit(1)).alias("edges"), F.round(F.avg("n"), 9).alias("mean"), F.round(F.stddev_samp("n"), 9).alias("deviation"), F.min("n").alias("least"), F.max("n").alias("most"), top.alias("largest"), F.round(F.percentile("n", 0.5), 9).alias("median"), F.round(F.percentile("n", 0.9), 9).alias("p90"))


def counts_rollup(counts: DataFrame) -> DataFrame:
    """Counts by family and pattern, by family, and in all."""
    return counts.withColumn("family", family_of(F.col("pattern"))).rollup("family", "pattern").agg(F.sum("cnt").alias("cnt"), F.grouping_id().cast("int").alias("level"))


def counts_cube(sliced: DataFrame) -> DataFrame:
    """Counts by slice, pattern and both: ``sliced`` is (slice, pattern, cnt)."""
    return sliced.cube("slice", "pattern").agg(F.sum("cnt").alias("cnt"), F.grouping_id().cast("int").alias("level"))


def counts_grouping_sets(spark: SparkSession, sliced: DataFrame) -> DataFrame:
    """Counts by slice, and by pattern, only."""
    sliced.createOrReplaceTempView("ht_sliced")
    return spark.sql("SELECT slice, pattern, sum(cnt) AS cnt FROM ht_sliced GROUP BY GROUPING SETS ((slice), (pattern))")


def profile_matrix(sliced: DataFrame) -> DataFrame:
    """One row a slice, one column a pattern."""
    return sliced.groupBy("slice").pivot("pattern", list(range(1, 21))).agg(F.sum("cnt")).na.fill(0).toDF("slice", *[f"p{k}" for k in range(1, 21)])


def unpivoted(matrix: DataFrame) -> DataFrame:
    """profile_matrix back to (slice, pattern, cnt)."""
    return matrix.unpivot("slice", [f"p{k}" for k in range(1, 21)], "name", "cnt").select("slice", F.substring("name", 2, 2).cast("int").alias("pattern"), "cnt")


def counts_trend(daily: DataFrame) -> DataFrame:
    """(day, pattern, cnt) with the day before's count and the running total of each pattern."""
    w = Window.partitionBy("pattern").orderBy("day")
    return daily.select("day", "pattern", "cnt", F.lag("cnt").over(w).alias("before"), F.sum("cnt").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("running"))


def same_triads(a: DataFrame, b: DataFrame) -> DataFrame:
    """Rows of two searches that the other lacks; none if they agree as multisets."""
    cols = ["i", "j", "k", "pattern"]
    a, b = a.select(*cols), b.select(*cols)
    return a.exceptAll(b).withColumn("side", F.lit("left")).unionByName(b.exceptAll(a).withColumn("side", F.lit("right")))


def common_edges(a: Hypergraph, b: Hypergraph) -> DataFrame:
    """Member sets that occur in both hypergraphs."""
    return a.edges.select("members").intersect(b.edges.select("members"))


def describe_triads(triads: DataFrame, names: DataFrame) -> DataFrame:
    """Triads with the names of their edges; names(e, name) is joined by hash, or broadcast if Spark finds it small."""
    out = triads
    for x in ("i", "j", "k"):
        out = out.join(names.select(F.col("e").alias(x), F.col("name").alias(f"name_{x}")), x, "left")
    return out


def hub_value(hubs: DataFrame, orders: DataFrame) -> DataFrame:
    """Hub customers with the exact decimal value of their orders."""
    value = orders.groupBy(F.col("o_custkey").alias("e")).agg(F.sum(F.col("o_totalprice").cast("decimal(18,2)")).alias("value"))
    return hubs.join(value, "e", "left").select("e", "cnt", F.col("value").cast("decimal(18,2)").alias("value"))


def create_views(hg: Hypergraph, links: DataFrame, triads: DataFrame, counts: DataFrame) -> None:
    """ht_edges, ht_links, ht_triads and ht_counts for plain SQL."""
    for name, df in (("ht_edges", hg.edges), ("ht_links", links), ("ht_triads", triads), ("ht_counts", counts)):
        df.createOrReplaceTempView(name)


def patterns_of_family(spark: SparkSession) -> DataFrame:
    return pattern_rows(spark)
