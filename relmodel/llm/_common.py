"""Shared helpers of the text operators: reading, word splitting, written intermediate tables."""

from __future__ import annotations

import atexit
import gc
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from relmodel.session import importable, shared_folder

#: The six ASCII white-space characters that separate words.
SPACE_CHARS = " \t\n\x0b\x0c\r"
SPACE_PATTERN = r"[\x20\x09-\x0D]+"

#: Rows from which on a side of a join is not left to Spark, which sizes it by its compressed file.
MOST_SENT = 200_000

_written: list[tuple[SparkSession, str]] = []


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    importable(spark)
    return spread(spark.read.parquet(f"{sf_dir}/{name}.parquet"))


def spread(df: DataFrame) -> DataFrame:
    """A table of fewer scan tasks than cores (one small file) is dealt out once, as texts cost far more
    to work on than to move; a table of many files is read as it lies, without a shuffle."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(cores) if df.rdd.getNumPartitions() < cores else df


def text_of(col: Column | str) -> Column:
    """The text as a string; null counts as empty."""
    return F.coalesce((F.col(col) if isinstance(col, str) else col).cast("string"), F.lit(""))


def words_of(col: Column | str) -> Column:
    """array<string> of the words of a text, split at ASCII white space only."""
    t = F.btrim(text_of(col), F.lit(SPACE_CHARS))
    return F.when(t == "", F.array().cast("array<string>")).otherwise(F.split(t, SPACE_PATTERN))


def work_path(spark: SparkSession) -> str:
    """A new path in the folder that the session's executors share."""
    return f"{shared_folder(spark)}/relmodel-{uuid.uuid4().hex}"


def written(df: DataFrame) -> DataFrame:
    """Cuts lineage: the rows as a Parquet table in the shared folder, read again.

    Shuffle files that only the finished job needed can go afterwards, so memory and disk stay
    bounded by one step. Tables are removed when the driver ends, or earlier by ``drop_written``.
    """
    spark, path = df.sparkSession, work_path(df.sparkSession)
    df.write.option("compression", "zstd").parquet(path)
    _written.append((spark, path))
    out = spark.read.schema(df.schema).parquet(path)
    out._relmodel_path = path
    del df
    free(spark)
    return out


def free(spark: SparkSession) -> None:
    """Lets Spark's cleaner drop the shuffle files of plans that nothing refers to any more."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def apart(df: DataFrame, rows: int) -> DataFrame:
    """A side of a join that is not broadcast from ``MOST_SENT`` rows on."""
    return df.hint("merge") if rows >= MOST_SENT else df


def drop_written(*frames: DataFrame) -> None:
    """Removes tables of ``written`` whose rows have been consumed by a later written table."""
    for df in frames:
        if path := getattr(df, "_relmodel_path", None):
            _remove(df.sparkSession, path)


def _remove(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


@atexit.register
def _clean() -> None:
    for spark, path in _written:
        try:
            if spark.sparkContext._jsc is not None:
                _remove(spark, path)
        except Exception:  # the session may have ended before; its folder is temporary
            return


def components(links: DataFrame) -> DataFrame:
    """(node, component) of an undirected graph of (a, b) links; component = smallest node reachable.

    Alternates two contractions, each a minimum per node with map-side combination and a join back,
    so a hub never comes together in one task's memory. Rounds grow with the logarithm of a path.
    """
    edges = written(links.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct())
    mark = None
    while True:
        now = edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if now == mark or not now[0]:
            return edges.select(F.col("u").alias("node"), F.col("v").alias("component")).union(edges.select("v", "v")).distinct()
        mark, both = now, edges.union(edges.select("v", "u"))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(apart(least, now[0]), "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(apart(low, now[0]), "u").select(F.col("v").alias("u"), F.col("m").alias("v")).union(low).where("u <> v").distinct()
        old, edges = edges, written(small)
        drop_written(old)
