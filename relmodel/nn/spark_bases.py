"""Standalone tabular models by the engine's own library (B1, B2) on prepared features."""

from __future__ import annotations

from pyspark.ml import Pipeline
from pyspark.ml.classification import GBTClassifier, LogisticRegression, RandomForestClassifier
from pyspark.ml.feature import Imputer, OneHotEncoder, StandardScaler, StringIndexer, VectorAssembler
from pyspark.ml.functions import vector_to_array
from pyspark.ml.regression import GBTRegressor, LinearRegression, RandomForestRegressor
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def prepare(numerical: list[str], categorical: list[str]) -> list:
    out = [Imputer(inputCols=numerical, outputCols=[f"{c}_i" for c in numerical])] if numerical else []
    out += [StringIndexer(inputCol=c, outputCol=f"{c}_s", handleInvalid="keep") for c in categorical]
    if categorical:
        out.append(OneHotEncoder(inputCols=[f"{c}_s" for c in categorical], outputCols=[f"{c}_o" for c in categorical]))
    parts = [f"{c}_i" for c in numerical] + [f"{c}_o" for c in categorical]
    return out + [VectorAssembler(inputCols=parts, outputCol="raw"), StandardScaler(inputCol="raw", outputCol="features")]


def fit_predict(train: DataFrame, test: DataFrame, numerical, categorical, kind: str, task: str, seed: int = 0) -> DataFrame:
    """test with ``score``; kinds: linear, forest, boosted (a cross-check of ours)."""
    numerical, categorical = list(numerical), list(categorical)
    made = {
        ("linear", "binary"): lambda: LogisticRegression(labelCol="y", maxIter=30), ("linear", "regression"): lambda: LinearRegression(labelCol="y", maxIter=30),
        ("forest", "binary"): lambda: RandomForestClassifier(labelCol="y", numTrees=20, seed=seed), ("forest", "regression"): lambda: RandomForestRegressor(labelCol="y", numTrees=20, seed=seed),
        ("boosted", "binary"): lambda: GBTClassifier(labelCol="y", maxIter=10, seed=seed), ("boosted", "regression"): lambda: GBTRegressor(labelCol="y", maxIter=10, seed=seed),
    }[kind, task]()
    cast = lambda df: df.select("*", *(F.col(c).cast("double").alias(f"{c}__d") for c in numerical))
    model = Pipeline(stages=[*prepare([f"{c}__d" for c in numerical], categorical), made]).fit(cast(train))
    out = model.transform(cast(test))
    return out.withColumn("score", vector_to_array("probability")[1] if task == "binary" else F.col("prediction")).select(*test.columns, "score")
