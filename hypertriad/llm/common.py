"""Shared helpers: tables in the shared checkpoint folder, and gapless numbering without large groups."""

from __future__ import annotations

import atexit
import contextlib
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: Rows that one task numbers at once in ``gapless``.
ROWS_PER_BUCKET = 20_000
LEAST_BUCKETS = 256
#: A key with fewer rows than this is never joined apart; one with a HEAVY_PARTSth of all rows always is, so at most
#: HEAVY_PARTS keys are broadcast.
HEAVY_LEAST, HEAVY_PARTS = 1_000, 1_000


def shared_root(spark: SparkSession) -> str:
    """This application's folder under spark.checkpoint.dir.  Where that is unset, a local master (tests, local runs) gets a
    temporary one; on a cluster it is an error, as no machine's own folder is shared."""
    root = spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if not root:
        found = spark.sparkContext._jsc.sc().getCheckpointDir()
        if found.isDefined():
            root = found.get()
        elif not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        else:
            root = tempfile.mkdtemp(prefix="hypertriad-")
            spark.sparkContext.setCheckpointDir(root)
    own = f"{root.rstrip('/')}/hypertriad-{spark.sparkContext.applicationId}"
    if own not in _ROOTS:
        _ROOTS.add(own)
        atexit.register(_remove, spark, own)
    return own


_ROOTS: set[str] = set()


def _remove(spark: SparkSession, path: str) -> None:
    with contextlib.suppress(Exception):  # the session may be gone already
        jvm = spark.sparkContext._jvm
        p = jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


class Stored:
    """Tables that one query wrote to the shared folder; ``drop`` removes those that no later step reads."""

    def __init__(self, spark: SparkSession):
        self.spark = spark

    def put(self, df: DataFrame) -> DataFrame:
        """Write ``df`` as Parquet and read it back: lineage ends here and lost executors cost no recomputation."""
        path = f"{shared_root(self.spark)}/{uuid.uuid4().hex}"
        df.write.parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        out._stored_path = path
        return out

    def drop(self, *dfs: DataFrame) -> None:
        for df in dfs:
            _remove(self.spark, df._stored_path)


def unsigned_crc32(col: Column) -> Column:
    """CRC-32 of the UTF-8 bytes of a string column (null: of no bytes), 0 to 2**32 - 1."""
    return F.crc32(F.coalesce(col, F.lit("")).cast("binary"))


def utf8_bytes(col: Column) -> Column:
    return F.coalesce(F.octet_length(col), F.lit(0)).cast("long")


def fresh(df: DataFrame, name: str) -> str:
    """``name``, lengthened until no column of ``df`` has it (case aside): a helper column that clashes with none."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def row_uid() -> Column:
    """A number for each row, to be stored before it is used (it depends on the partitioning)."""
    return F.monotonically_increasing_id()


def join_skewed(left: DataFrame, right: DataFrame, on: list[str], size: str, rows: int) -> DataFrame:
    """``left`` with the columns of ``right`` (one row for each key, ``size`` being the number of left rows of the key), as an
    inner join.  Keys with a large share of all ``rows``, of which there are few, are broadcast; the others meet by shuffle."""
    heavy = F.col(size) >= max(HEAVY_LEAST, rows // HEAVY_PARTS)
    some = F.broadcast(right.where(heavy).drop(size))  # at most HEAVY_PARTS rows
    light = left.join(some.select(*on), on, "left_anti").join(right.where(~heavy).drop(size), on)
    return left.join(some, on).unionByName(light)


def gapless(stored: DataFrame, keys: list[str], uid: str, out: str, rows: int) -> DataFrame:
    """Number the rows of every key 0, 1, ... with no gap, however many rows one key has.

    ``stored`` must be a stored table (it is read twice) with a unique ``uid``; ``rows`` is its row count.  Each key is
    dealt into buckets by a hash of ``uid``; bucket counts give bucket offsets, and a window numbers the rows inside a
    bucket.  No task sees more than about ROWS_PER_BUCKET rows of a key.
    """
    n = max(LEAST_BUCKETS, -(-rows // ROWS_PER_BUCKET))
    dealt = stored.withColumn("_b", F.pmod(F.xxhash64(uid), F.lit(n)))
    before = Window.partitionBy(*keys).orderBy("_b").rowsBetween(Window.unboundedPreceding, -1)
    offsets = (
        dealt.groupBy(*keys, "_b").agg(F.count(F.lit(1)).alias("_n"))
        .withColumn("_off", F.coalesce(F.sum("_n").over(before), F.lit(0))).drop("_n")
    )
    inside = Window.partitionBy(*keys, "_b").orderBy(uid)
    return (
        dealt.withColumn("_r", F.row_number().over(inside)).join(offsets, [*keys, "_b"])
        .withColumn(out, (F.col("_off") + F.col("_r") - 1).cast("long")).drop("_b", "_r", "_off")
    )
