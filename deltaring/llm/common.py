"""Helpers shared by the corpus operators: shared storage, ordered offsets, exact selection."""

from __future__ import annotations

import math
import re
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: Java and Python regular expression of one white-space character that parts words.
SPACE = r"[\x20\x09-\x0D]"
WORD = r"[^\x20\x09-\x0D]+"
HASH_BITS = 60


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir, or that of the context. A folder of our own only on a
    local master (tests), where executors see the driver's files."""
    where = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if where:
        return where.rstrip("/")
    if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    where = tempfile.mkdtemp(prefix="deltaring-")
    spark.sparkContext.setCheckpointDir(where)
    return where


def scratch(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/deltaring/{name}-{uuid.uuid4().hex[:12]}"


#: Rows that a Python worker gets at once while a table is written; long texts make larger batches heavy.
BATCH_ROWS = "1000"
BATCH_SETTING = "spark.sql.execution.arrow.maxRecordsPerBatch"
#: Nobody reads the marker of a working table. On local storage the driver starts a chmod process for it, and a process being
#: started counts the driver's memory a second time.
MARKER_SETTING = "mapreduce.fileoutputcommitter.marksuccessfuljobs"


def written(df: DataFrame, name: str, within: str | None = None) -> DataFrame:
    """Cut the lineage: write df as a Parquet table in the shared folder (or a folder in it) and read it again."""
    spark = df.sparkSession
    path, before = (f"{within}/{name}-{uuid.uuid4().hex[:12]}" if within else scratch(spark, name)), spark.conf.get(BATCH_SETTING)
    spark.conf.set(BATCH_SETTING, BATCH_ROWS)
    try:
        df.write.option(MARKER_SETTING, "false").parquet(path)
    finally:
        spark.conf.set(BATCH_SETTING, before)
    return spark.read.schema(df.schema).parquet(path)


def removed(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


class Working:
    """Working tables of one run in a folder of their own. What the result still reads is written outside it; the folder
    goes when the run is over."""

    def __init__(self, spark: SparkSession, name: str):
        self.spark, self.path = spark, scratch(spark, name)

    def written(self, df: DataFrame, name: str) -> DataFrame:
        return written(df, name, self.path)

    def done(self) -> None:
        removed(self.spark, self.path)


def fresh(df: DataFrame, name: str) -> str:
    """A column name that df does not have yet; names clash without regard to case."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name = f"{name}_"
    return name


def hash60(*cols: Column) -> Column:
    """A hash of 60 bits as a long of zero or more; nulls hash as absent values do."""
    return F.shiftrightunsigned(F.xxhash64(*cols), 64 - HASH_BITS)


def bucket_bits(spark: SparkSession, per: int = 1) -> int:
    """Bits of the range buckets that split one group over tasks; more tasks, more buckets."""
    return max(5, min(16, math.ceil(math.log2(max(1, per * int(spark.conf.get("spark.sql.shuffle.partitions")))))))


def with_offsets(df: DataFrame, group: list[str], place: str, ties: list[str], value: str, out: str) -> DataFrame:
    """Add `out`: the sum of `value` over the rows before this one in its group.

    No group column may be null. Rows of a group stand in order of (place, ties), place being a long of HASH_BITS bits. A group of
    any size is spread over range buckets of place, so the order and the result do not depend on the
    number of buckets or partitions: sums by bucket first, then running sums inside each bucket.
    """
    bits = bucket_bits(df.sparkSession, 2)
    b, s, before = fresh(df, "range_bucket"), fresh(df, "bucket_sum"), fresh(df, "bucket_before")
    keys = [*group, b]
    rows = df.withColumn(b, F.shiftright(F.col(place), HASH_BITS - bits).cast("int"))
    sums = rows.groupBy(*keys).agg(F.sum(value).alias(s))
    ahead = Window.partitionBy(*group).orderBy(b).rowsBetween(Window.unboundedPreceding, -1)
    starts = sums.select(*keys, F.coalesce(F.sum(s).over(ahead), F.lit(0)).cast("long").alias(before))
    inside = Window.partitionBy(*keys).orderBy(place, *ties).rowsBetween(Window.unboundedPreceding, 0)
    rows = rows.withColumn(out, F.sum(value).over(inside) - F.col(value))
    return rows.join(starts, keys).withColumn(out, (F.col(out) + F.col(before)).cast("long")).select(*df.columns, out)


def cut_at(df: DataFrame, key: str, k: int, fan: int = 4096) -> tuple[int | None, int]:
    """(t, left): exactly k - left rows have key > t and at least `left` rows have key = t (key: long, no nulls).

    Digit by digit over histograms of at most `fan` rows, so the driver holds no more however long df
    is. t is None if k covers all rows.
    """
    low, high, n = df.agg(F.min(key), F.max(key), F.count(key)).first()
    if k >= n:
        return None, 0
    if k <= 0:
        return high, 0
    left = k
    while low < high:
        width = -(-(high - low + 1) // fan)
        part = df.where(F.col(key).between(low, high)).groupBy(F.expr(f"(`{key}` - ({low}L)) div {width}L").alias("d"))
        for d, c in sorted(((int(r[0]), int(r[1])) for r in part.count().collect()), reverse=True):
            if c >= left:
                low, high = low + d * width, min(high, low + (d + 1) * width - 1)
                break
            left -= c
    return low, left
