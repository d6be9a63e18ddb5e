"""Hypergraphs carried by the given tables.  A builder gives (e, v) rows; ``hypergraph`` makes them canonical."""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.relational import bucket, hrefs_of, lines_of, micros, props_key, top_dims, words_of
from ..model import Hypergraph, canonicalize, incidence
from ..stages import stage

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    if name not in TABLES:
        raise ValueError(f"unknown table {name}")
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def bucket_users(spark: SparkSession, sf_dir: str, minutes: int = 10) -> DataFrame:
    """Edge: a time bucket; vertices: the users seen in it."""
    return incidence(read_table(spark, sf_dir, "events"), bucket(F.col("ts"), 60 * minutes), "user_id")


def user_day_types(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edge: a user's day; vertices: the event types."""
    return incidence(read_table(spark, sf_dir, "events"), F.col("user_id") * 100 + F.dayofmonth("ts"), "event_type")


def user_day_keys(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edge: a user's day; vertices: the keys in the events' properties."""
    return incidence(read_table(spark, sf_dir, "events"), F.col("user_id") * 100 + F.dayofmonth("ts"), props_key(F.col("props")))


def purchase_hour_users(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edge: an hour; vertices: the users who purchased in it."""
    return incidence(read_table(spark, sf_dir, "events").where("event_type = 'purchase'"), bucket(F.col("ts"), 3600), "user_id")


def user_keys(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edge: a user; vertices: the keys of its purchases."""
    return incidence(read_table(spark, sf_dir, "events").where("event_type = 'purchase'"), "user_id", props_key(F.col("props")))


def _urgent_returns(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = read_table(spark, sf_dir, "orders").where("o_orderpriority = '1-URGENT'").select("o_orderkey", "o_custkey")
    lines = read_table(spark, sf_dir, "lineitem").where("l_returnflag = 'R'").select("l_orderkey", "l_suppkey", "l_partkey")
    return lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey"))


def customer_nations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edge: a customer; vertices: nations of the suppliers of its urgent, returned lines."""
    s = read_table(spark, sf_dir, "supplier").select("s_suppkey", "s_nationkey")
    return incidence(_urgent_returns(spark, sf_dir).join(s, F.col("l_suppkey") == F.col("s_suppkey")), "o_custkey", F.col("s_nationkey").cast("long"))


def customer_brands(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edge: a customer; vertices: brands of the parts of its urgent, returned lines."""
    p = read_table(spark, sf_dir, "part").select("p_partkey", "p_brand")
    return incidence(_urgent_returns(spark, sf_dir).join(p, F.col("l_partkey") == F.col("p_partkey")), "o_custkey", "p_brand")


def order_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edge: an order; vertices: its parts."""
    return incidence(read_table(spark, sf_dir, "lineitem"), "l_orderkey", "l_partkey")


def order_suppliers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edge: an order; vertices: suppliers of its lines returned that shipped in 1995."""
    return incidence(read_table(spark, sf_dir, "lineitem").where("l_returnflag = 'R' AND year(l_shipdate) = 1995"), "l_orderkey", "l_suppkey")


def day_customers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edge: a day; vertices: the customers who ordered on it."""
    return incidence(read_table(spark, sf_dir, "orders"), F.datediff("o_orderdate", F.lit("1970-01-01").cast("date")), "o_custkey")


def doc_lines(spark: SparkSession, sf_dir: str, lang: str | None = None) -> DataFrame:
    """Edge: a document; vertices: its lines."""
    docs = read_table(spark, sf_dir, "documents")
    return incidence(lines_of(docs.where(F.col("lang") == lang) if lang else docs, "doc_id", "text"), "doc_id", "line")


def lines_of_lang(spark: SparkSession, sf_dir: str, lang: str | None) -> DataFrame:
    """As doc_lines, of the documents of one language, or of none (null)."""
    docs = read_table(spark, sf_dir, "documents").where(F.col("lang").eqNullSafe(F.lit(lang)))
    return incidence(lines_of(docs, "doc_id", "text"), "doc_id", "line")


def labelled_doc_lines(spark: SparkSession, sf_dir: str, quality: int = 1) -> DataFrame:
    """As doc_lines, of documents labelled with a quality."""
    labelled = read_table(spark, sf_dir, "labels").where(F.col("quality") == quality)
    return incidence(lines_of(read_table(spark, sf_dir, "documents").join(labelled, "doc_id", "left_semi"), "doc_id", "text"), "doc_id", "line")


def benchmark_passages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edges: documents, and passages under negative ids; vertices: lines.  A passage inside a document is a nest link."""
    passages = read_table(spark, sf_dir, "benchmark").select((-1 - F.col("item_id")).alias("doc_id"), "text")
    docs = read_table(spark, sf_dir, "documents").select("doc_id", "text")
    return incidence(lines_of(docs.unionByName(passages), "doc_id", "text"), "doc_id", "line")


def conv_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edge: a conversation; vertices: its words."""
    return incidence(words_of(read_table(spark, sf_dir, "conversations"), "conv_id", "text"), "conv_id", "word")


def page_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edge: a page; vertices: targets of its links."""
    return incidence(hrefs_of(read_table(spark, sf_dir, "pages"), "page_id", "html"), "page_id", "href")


def vector_top_dims(spark: SparkSession, sf_dir: str, k: int = 3) -> DataFrame:
    """Edge: a vector; vertices: its k largest coordinates (ties: lower index)."""
    return incidence(top_dims(read_table(spark, sf_dir, "embeddings"), "vec_id", "embedding", k), "vec_id", "dim")


def interval_users(spark: SparkSession, sf_dir: str, seconds: int = 1800) -> DataFrame:
    """Edge: a purchase; vertices: users with any event in the ``seconds`` up to it.  A binned range join: an event can only
    matter for purchases in its own bin or the next."""
    ev = read_table(spark, sf_dir, "events").select("event_id", "event_type", "user_id", micros(F.col("ts")).alias("t"))
    span = seconds * 1_000_000
    at = ev.where("event_type = 'purchase'").select(F.col("event_id").alias("e"), F.col("t").alias("t0"), F.expr(f"t div {span}").alias("bin"))
    near = ev.select("user_id", "t", F.explode(F.array(F.expr(f"t div {span}"), F.expr(f"t div {span}") + 1)).alias("bin"))
    return incidence(at.join(near, "bin").where((F.col("t") <= F.col("t0")) & (F.col("t") >= F.col("t0") - span)), "e", "user_id")


def interval_edges(spark: SparkSession, sf_dir: str, seconds: int = 1800) -> DataFrame:
    """(e, n, members) of the hypergraph of ``interval_users``, with no membership written to disk.  A bin's task holds the
    events of the bin and of the one before, and cuts each purchase's members from them, twice: first only their SHA-256 goes
    on, which names the least id of equal edges, then the members of the edges that stay."""
    ev = read_table(spark, sf_dir, "events").select("event_id", "event_type", "user_id", micros(F.col("ts")).alias("t")).dropna(subset=["t"])
    span = seconds * 1_000_000
    bin_ = F.expr(f"t div {span}")
    seen = ev.where("user_id IS NOT NULL").select(F.explode(F.array(bin_, bin_ + 1)).alias("bin"), "t", F.col("user_id").cast("long").alias("user"), F.lit(None).cast("long").alias("e"))
    bought = ev.where("event_type = 'purchase' AND event_id IS NOT NULL").select(bin_.alias("bin"), "t", F.lit(None).cast("long").alias("user"), F.col("event_id").cast("long").alias("e"))
    if bought.groupBy("e").agg(F.count(F.lit(1)).alias("n")).where("n > 1").limit(1).count():  # one edge of several purchases
        return canonicalize(interval_users(spark, sf_dir, seconds)).edges

    def cut(table: pa.Table):
        e, t, user = (table[c].combine_chunks() for c in ("e", "t", "user"))
        asked = np.asarray(e.is_valid())
        t = t.to_numpy()
        order = np.argsort(t[~asked], kind="stable")
        times, users = t[~asked][order], user.drop_null().to_numpy()[order]
        names, codes = np.unique(users, return_inverse=True)
        at = t[asked]
        low, high = np.searchsorted(times, at - span, "left"), np.searchsorted(times, at, "right")
        for x, a, b in zip(e.drop_null().to_pylist(), low, high):
            if a < b:
                there = np.zeros(len(names), bool)
                there[codes[a:b]] = True
                yield x, names[there]

    def digests(table: pa.Table) -> pa.Table:
        rows = [(x, hashlib.sha256(m.astype(np.int64).tobytes()).digest()) for x, m in cut(table)]
        return pa.table({"e": pa.array([x for x, _ in rows], pa.int64()), "digest": pa.array([h for _, h in rows], pa.binary())})

    def members(table: pa.Table) -> pa.Table:
        rows = list(cut(table))
        return pa.table({"e": pa.array([x for x, _ in rows], pa.int64()), "members": pa.array([m for _, m in rows], pa.list_(pa.int64()))})

    tasks = 16 * spark.sparkContext.defaultParallelism
    by_bin = lambda asked: seen.unionByName(asked).repartition(tasks, "bin").groupBy("bin")
    kept = stage(by_bin(bought).applyInArrow(digests, "e long, digest binary").groupBy("digest").agg(F.min("e").alias("e")).select("e"))
    return by_bin(bought.join(kept, "e", "left_semi").select(*bought.columns)).applyInArrow(members, "e long, members array<long>").select("e", F.size("members").alias("n"), "members")


def asof_clickers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """As-of join: for every purchase the latest click up to it in the same hour; edge: the buyer, vertices: the clickers.
    ``latest_clickers`` looks back over all time."""
    ev = read_table(spark, sf_dir, "events").where("event_type IN ('purchase', 'click')").select("event_id", "event_type", "user_id", micros(F.col("ts")).alias("t"), bucket(F.col("ts"), 3600).alias("hour"))
    w = Window.partitionBy("hour").orderBy("t", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    last = F.last(F.when(F.col("event_type") == "click", F.col("user_id")), ignorenulls=True).over(w)
    return incidence(ev.withColumn("clicker", last).where("event_type = 'purchase'"), "user_id", "clicker")


def trailing_users(spark: SparkSession, sf_dir: str, seconds: int = 3600, event_type: str = "purchase") -> DataFrame:
    """Sliding edges: before every purchase, the users who purchased in the last hour.  The window runs inside a day, so a
    day and its rows are the unit of work; ``rolling_users`` also looks back over midnight."""
    ev = read_table(spark, sf_dir, "events").where(F.col("event_type") == event_type).select("event_id", "user_id", F.floor(micros(F.col("ts")) / 1_000_000).alias("t"), F.to_date("ts").alias("day"))
    w = Window.partitionBy("day").orderBy("t").rangeBetween(-seconds, 0)
    return incidence(ev.select("event_id", F.collect_set("user_id").over(w).alias("users")).select("event_id", F.explode("users").alias("v")), "event_id", "v")


def latest_clickers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """As-of join over all time: for every purchase the latest click up to it; edge: the buyer, vertices: the clickers.  A
    bin's clicks come first, then the last one of earlier bins, carried over by one row for each bin."""
    ev = read_table(spark, sf_dir, "events").where("event_type = 'purchase' OR (event_type = 'click' AND user_id IS NOT NULL)").where("ts IS NOT NULL")
    ev = ev.select("event_id", "event_type", "user_id", micros(F.col("ts")).alias("t"), bucket(F.col("ts"), 3600).alias("bin"))
    click = F.when(F.col("event_type") == "click", F.col("user_id"))
    w = Window.partitionBy("bin").orderBy("t", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    before = Window.orderBy("bin").rowsBetween(Window.unboundedPreceding, -1)  # one row for each bin
    bins = ev.groupBy("bin").agg(F.max_by(click, F.when(click.isNotNull(), F.struct("t", "event_id"))).alias("last"))
    carried = bins.select("bin", F.last("last", ignorenulls=True).over(before).alias("carried"))
    inside = ev.withColumn("clicker", F.last(click, ignorenulls=True).over(w)).where("event_type = 'purchase'")
    return incidence(inside.join(carried, "bin"), "user_id", F.coalesce("clicker", "carried"))


def rolling_users(spark: SparkSession, sf_dir: str, seconds: int = 3600, event_type: str = "purchase") -> DataFrame:
    """Sliding edges over all time: before every purchase, the users who purchased in the last hour.  A binned range join, as
    in interval_users."""
    ev = read_table(spark, sf_dir, "events").where(F.col("event_type") == event_type).select("event_id", "user_id", F.floor(micros(F.col("ts")) / 1_000_000).alias("t"))
    bin_ = F.floor(F.col("t") / seconds)
    at = ev.select(F.col("event_id").alias("e"), F.col("t").alias("t0"), bin_.alias("bin"))
    near = ev.select("user_id", "t").distinct().select("user_id", "t", F.explode(F.array(bin_, bin_ + 1)).alias("bin"))
    return incidence(at.join(near, "bin").where((F.col("t") <= F.col("t0")) & (F.col("t") >= F.col("t0") - seconds)), "e", "user_id")


BUILDERS = {f.__name__: f for f in (bucket_users, user_day_types, user_day_keys, purchase_hour_users, user_keys, customer_nations, customer_brands, order_parts, order_suppliers, day_customers, doc_lines, labelled_doc_lines, benchmark_passages, conv_tokens, page_links, vector_top_dims, interval_users, asof_clickers, trailing_users, latest_clickers, rolling_users)}


def hypergraph(spark: SparkSession, sf_dir: str, name: str, **options: Column | int | str) -> Hypergraph:
    return canonicalize(BUILDERS[name](spark, sf_dir, **options))
