"""Flat tables under the classifiers of pyspark.ml; trees and the like have no gradient, so they cannot be row blocks."""

from __future__ import annotations

import time

from pyspark.ml import Pipeline
from pyspark.ml.classification import FMClassifier, GBTClassifier, LogisticRegression, MultilayerPerceptronClassifier
from pyspark.ml.feature import StandardScaler, StringIndexer, VectorAssembler
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .metrics import RunReport, auc
from .schema import Task
from .train import flat_task

HEADS = {
    "logistic": lambda n: LogisticRegression(maxIter=30, regParam=1e-4),
    "fm": lambda n: FMClassifier(stepSize=0.05, maxIter=60, factorSize=4, seed=0),
    "gbt": lambda n: GBTClassifier(maxIter=15, maxDepth=4, seed=0),
    "mlp": lambda n: MultilayerPerceptronClassifier(layers=[n, 16, 2], maxIter=60, seed=0),
}


def fit_ml(task: Task, flat: DataFrame, head: str) -> RunReport:
    """Train on part train of a flat table and report the AUC of part test.  Nulls become zero or a class of their own."""
    began, one = time.time(), flat_task(task, flat)
    spec, df = one.catalog.specs[task.target], one.catalog.frame(task.target)
    rows = df.join(one.rows().select(*[F.col(k).alias(f"_{k}") for k in task.keys], "part"), [F.col(k) == F.col(f"_{k}") for k in task.keys])
    rows = rows.fillna(0.0, list(spec.numeric)).fillna("", list(spec.categorical)).withColumn("label", F.col(task.label).cast("double"))
    rows = rows.persist()  # every iteration of the library's trainers reads it
    index = [StringIndexer(inputCol=c, outputCol=f"{c}_i", handleInvalid="keep") for c in spec.categorical]
    inputs = [*spec.numeric, *(f"{c}_i" for c in spec.categorical)]
    stages = [*index, VectorAssembler(inputCols=inputs, outputCol="raw"), StandardScaler(inputCol="raw", outputCol="features"), HEADS[head](len(inputs))]
    model = Pipeline(stages=stages).fit(rows.filter("part = 'train'"))
    got = model.transform(rows.filter("part = 'test'")).select(_second("probability").alias("score"), F.col("label").cast("int").alias("label"))
    measure = auc(got, "score", "label").first()["auc"]
    rows.unpersist()
    return RunReport(task.name, f"roll-up + ml {head}", 0, 0, measure, time.time() - began, n_features=len(inputs))


def _second(column: str):
    from pyspark.ml.functions import vector_to_array

    return F.get(vector_to_array(F.col(column)), F.lit(1))
