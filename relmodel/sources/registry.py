"""Model registry and ledger as tables, and a Python data source over the registry."""

from __future__ import annotations

import json
import pickle
from datetime import datetime, timezone
from itertools import product

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

REGISTRY = "model_id string, version long, grp string, kind string, params binary, n_params long, config string, created_ts string"


def save_model(spark: SparkSession, path: str, model_id: str, kind: str, grp: str, params: dict, config: dict) -> int:
    """Appends a version; weights of a model are a few megabytes at most."""
    from relmodel.nn.relational import param_count

    version = next_version(spark, path, model_id)
    row = (model_id, version, grp, kind, pickle.dumps(params), param_count(params), json.dumps(config), datetime.now(timezone.utc).isoformat())
    spark.createDataFrame([row], REGISTRY).write.mode("append").parquet(path)
    return version


def next_version(spark: SparkSession, path: str, model_id: str) -> int:
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    if not p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(p):
        return 1
    return (spark.read.schema(REGISTRY).parquet(path).where(F.col("model_id") == model_id).agg(F.max("version")).first()[0] or 0) + 1


def list_models(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(REGISTRY).parquet(path).groupBy("model_id", "grp", "kind").agg(F.max("version").alias("version"), F.max_by("n_params", "version").alias("n_params"))


def load_model(spark: SparkSession, path: str, model_id: str, version: int | None = None) -> tuple[dict, dict]:
    own = spark.read.schema(REGISTRY).parquet(path).where(F.col("model_id") == model_id)
    row = (own.where(F.col("version") == version) if version else own.orderBy(F.desc("version"))).first()
    return pickle.loads(row.params), json.loads(row.config)


class GridSource(DataSource):
    """``spark.read.format("model_grid").option("widths", "32,64").option("depths", "1,2").load()``:
    the candidates of an architecture space as rows, every layer with a width of its own (T12)."""

    @classmethod
    def name(cls):
        return "model_grid"

    def schema(self):
        return "model_id string, widths string, depth int"

    def reader(self, schema):
        return GridReader(self.options)


class GridReader(DataSourceReader):
    def __init__(self, options):
        self.widths = options.get("widths", "32,64,128,256,512").split(",")
        self.depths = [int(x) for x in options.get("depths", "1,2,3").split(",")]

    def partitions(self):
        return [InputPartition((w, d)) for d in self.depths for w in self.widths]

    def read(self, partition):
        first, depth = partition.value
        for rest in product(self.widths, repeat=depth - 1):
            widths = "-".join((first, *rest))
            yield (f"w{widths}", widths, depth)


def bucketed(df: DataFrame, table: str, key: str, buckets: int, path: str | None = None) -> None:
    """A table whose joins on ``key`` need no shuffle; one file a bucket."""
    out = df.repartition(buckets, key).write.mode("overwrite").bucketBy(buckets, key).sortBy(key)
    (out.option("path", path) if path else out).saveAsTable(table)
