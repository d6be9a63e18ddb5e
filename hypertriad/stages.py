"""Stage tables: results that several later steps read, written once to the shared folder."""

from __future__ import annotations

import atexit
import contextlib
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

_ROOTS: set[str] = set()
ROWS_PER_PART = 100_000


def shared_root(spark: SparkSession) -> str:
    """This application's folder under spark.checkpoint.dir.  Where that is unset, a local master (tests, local runs) gets a
    temporary one; on a cluster it is an error, as no machine's own folder is shared."""
    root = spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if not root:
        found = spark.sparkContext._jsc.sc().getCheckpointDir()
        master = spark.sparkContext.master
        if not found.isDefined() and (not master.startswith("local") or master.startswith("local-cluster")):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        root = found.get() if found.isDefined() else tempfile.mkdtemp(prefix="hypertriad-")
        if not found.isDefined():
            spark.sparkContext.setCheckpointDir(root)
    own = f"{root.rstrip('/')}/stages-{spark.sparkContext.applicationId}"
    if own not in _ROOTS:
        _ROOTS.add(own)
        atexit.register(_remove, spark, own)
    return own


def _remove(spark: SparkSession, path: str) -> None:
    with contextlib.suppress(Exception):  # the session may be gone already
        jvm = spark.sparkContext._jvm
        p = jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def stage(df: DataFrame, partition_by: str | None = None) -> DataFrame:
    """Write ``df`` as Parquet and read it back; lineage ends here, and a lost executor loses no stage."""
    path = f"{shared_root(df.sparkSession)}/{uuid.uuid4().hex}"
    writer = df.write.partitionBy(partition_by) if partition_by else df.write
    writer.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def stage_links(links: DataFrame) -> DataFrame:
    """Links staged by kind.  A link leads many triads, so a few megabytes of links are much work: a table that a scan would
    read in fewer tasks than there are cores is written again, spread evenly by link.  Larger tables are left as they are."""
    laid = stage(links, partition_by="kind")
    cores = links.sparkSession.sparkContext.defaultParallelism
    if laid.rdd.getNumPartitions() >= cores:
        return laid
    return stage(laid.repartition(cores, "i", "j"), partition_by="kind")


def numbered(df: DataFrame, order: list[str], out: str = "pos") -> DataFrame:
    """Number all rows 0, 1, ... in a total order without a single-task sort: range partitions with carried-over counts."""
    rows = df.count()
    laid = stage(df.repartitionByRange(max(1, -(-rows // ROWS_PER_PART)), *order).withColumn("_pid", F.spark_partition_id()))
    counts = laid.groupBy("_pid").agg(F.count(F.lit(1)).alias("_n"))  # one row for each partition
    before = Window.orderBy("_pid").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.withColumn("_off", F.coalesce(F.sum("_n").over(before), F.lit(0))).drop("_n")
    inside = Window.partitionBy("_pid").orderBy(*order)
    return laid.withColumn("_r", F.row_number().over(inside)).join(offsets, "_pid").withColumn(out, F.col("_off") + F.col("_r") - 1).drop("_pid", "_r", "_off")
