"""Edges from event streams, and triad counts kept up to date as edges arrive.

A window (tumbling, sliding or a user's session) becomes an edge when the watermark seals it; later events of it are
dropped and counted in the query's progress.  ``TriadStore`` adds each micro-batch of edges: it links new edges to stored
ones, counts the triads with at least one new edge, and writes everything under the batch's number, so a batch that runs
again overwrites itself and nothing else.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.patterns import pattern_of
from ..operators.links import link_kind
from ..operators.measures import pattern_counts
from ..operators.sampling import draw_key


def event_stream(spark: SparkSession, path: str, schema, files_per_batch: int = 1) -> DataFrame:
    """Parquet files of events as they arrive in a folder; ts becomes an event time."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def windowed_edges(events: DataFrame, width: str = "10 minutes", slide: str | None = None, late: str = "30 minutes", vertex: str = "user_id") -> DataFrame:
    """(e, members) of each sealed window: e is its start in seconds since the epoch."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    sealed = events.withWatermark("ts", late).groupBy(w.alias("w")).agg(F.sort_array(F.collect_set(vertex)).alias("members"))
    return sealed.select(F.unix_seconds("w.start").alias("e"), "members")


def session_edges(events: DataFrame, gap: str = "30 minutes", late: str = "30 minutes", vertex: str = "event_type") -> DataFrame:
    """(e, user_id, members) of each sealed session of a user."""
    s = F.session_window("ts", gap)
    sealed = events.withWatermark("ts", late).groupBy(s.alias("w"), "user_id").agg(F.sort_array(F.collect_set(vertex)).alias("members"))
    return sealed.select(F.unix_seconds("w.start").alias("e"), "user_id", "members")


def distinct_sets(edges: DataFrame, time: str, late: str = "30 minutes") -> DataFrame:
    """Edges of a stream whose member set was not seen within the watermark."""
    return edges.withColumn("_set", F.xxhash64("members")).withWatermark(time, late).dropDuplicatesWithinWatermark(["_set"]).drop("_set")


@dataclass
class TriadStore:
    """Edges, links and counts under a folder, by batch; the folder must be one that all executors share."""

    spark: SparkSession
    root: str

    def _read(self, name: str, schema: str, before: int | None = None) -> DataFrame:
        try:
            df = self.spark.read.schema(schema + ", batch long").parquet(f"{self.root}/{name}")
        except Exception as e:  # no batch yet
            if "PATH_NOT_FOUND" not in str(e):
                raise
            return self.spark.createDataFrame([], schema)
        return (df.where(F.col("batch") < before) if before is not None else df).drop("batch")

    def _write(self, df: DataFrame, name: str, batch: int) -> None:
        df.write.mode("overwrite").parquet(f"{self.root}/{name}/batch={batch}")

    def edges(self, before: int | None = None) -> DataFrame:
        return self._read("edges", "e long, n int, members array<long>", before)

    def links(self, before: int | None = None) -> DataFrame:
        return self._read("links", "i long, j long, ni int, nj int, w int, kind string, shared array<long>", before)

    def counts(self) -> DataFrame:
        parts = self._read("counts", "pattern int, cnt long")
        return pattern_counts(parts.groupBy("pattern").agg(F.sum("cnt").alias("cnt")), counted=True)

    def add(self, arrived: DataFrame, batch: int) -> None:
        """One micro-batch of (e, members).  An edge whose set is stored or repeated in the batch is ignored."""
        old = self.edges(batch)
        new = arrived.select("e", F.sort_array(F.array_distinct(F.col("members").cast("array<long>"))).alias("members")).groupBy("members").agg(F.min("e").alias("e")).select("e", F.size("members").alias("n"), "members").join(old.select("members"), "members", "left_anti")
        self._write(new.select("e", "n", "members"), "edges", batch)
        own = self.spark.read.parquet(f"{self.root}/edges/batch={batch}")
        flat = lambda df, flag: df.select("e", "n", F.explode("members").alias("v"), F.lit(flag).alias("new"))
        every = flat(own, True).unionByName(flat(old, False))
        a = flat(own, True).select("v", F.col("e").alias("x"), F.col("n").alias("nx"))
        b = every.select("v", F.col("e").alias("y"), F.col("n").alias("ny"), "new")
        met = a.join(b, "v").where("x <> y AND (NOT new OR x < y)")
        links = met.groupBy(F.least("x", "y").alias("i"), F.greatest("x", "y").alias("j"), F.when(F.col("x") < F.col("y"), F.col("nx")).otherwise(F.col("ny")).alias("ni"), F.when(F.col("x") < F.col("y"), F.col("ny")).otherwise(F.col("nx")).alias("nj")).agg(F.count(F.lit(1)).cast("int").alias("w"), F.sort_array(F.collect_list("v")).alias("shared"))
        links = links.withColumn("kind", link_kind(F.col("w"), F.col("ni"), F.col("nj"))).select("i", "j", "ni", "nj", "w", "kind", "shared")
        self._write(links, "links", batch)
        fresh = self.spark.read.parquet(f"{self.root}/links/batch={batch}")
        self._write(self._new_triads(own.select("e"), fresh, fresh.unionByName(self.links(batch).select(*fresh.columns))), "counts", batch)

    @staticmethod
    def _new_triads(new: DataFrame, fresh: DataFrame, links: DataFrame) -> DataFrame:
        """Counts of triads with a new edge, each found from its least new edge x; only new links leave a new edge."""
        both = fresh.select(F.col("i").alias("x"), F.col("j").alias("y"), F.col("ni").alias("nx"), F.col("nj").alias("ny"), "w", "shared").unionByName(fresh.select(F.col("j").alias("x"), F.col("i").alias("y"), F.col("nj").alias("nx"), F.col("ni").alias("ny"), "w", "shared"))
        mine = both.join(new.withColumnRenamed("e", "x"), "x", "left_semi").join(new.select(F.col("e").alias("y"), F.lit(True).alias("y_new")), "y", "left").where("y_new IS NULL OR x < y")
        two = mine.select("x", F.col("y").alias("z"), F.col("ny").alias("nz"), F.col("w").alias("wxz"), F.col("shared").alias("s2"))
        pairs = mine.join(two, "x").where("y < z").withColumn("g", F.size(F.array_intersect("shared", "s2")))
        closed = pairs.join(links.select(F.col("i").alias("y"), F.col("j").alias("z"), F.col("w").alias("wyz")), ["y", "z"])
        p = pattern_of(F.col("w"), F.col("wxz"), F.col("wyz"), F.col("g"), F.col("nx"), F.col("ny"), F.col("nz"))
        return closed.groupBy(p.alias("pattern")).agg(F.count(F.lit(1)).alias("cnt"))

    def sample(self, size: int, seed: int = 0) -> DataFrame:
        """A uniform sample of the stored links: those of least key, the same however the links arrived in batches."""
        return self.links().orderBy(draw_key(seed, "i", "j")).limit(size)

    def start(self, edges: DataFrame, checkpoint: str):
        """A streaming query that adds sealed edges as they come (batch by batch, once over what is there)."""
        return edges.writeStream.foreachBatch(self.add).option("checkpointLocation", checkpoint).outputMode("append").trigger(availableNow=True).start()


def merge_samples(a: DataFrame, b: DataFrame, size: int, seed: int = 0) -> DataFrame:
    """The bottom-k sample of two bottom-k samples."""
    return a.unionByName(b).distinct().orderBy(draw_key(seed, "i", "j")).limit(size)
