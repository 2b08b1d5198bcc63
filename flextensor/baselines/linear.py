"""Click-rate baselines: logistic regression and linear SVM on one-hot indices."""

from __future__ import annotations

from pyspark.ml import Pipeline
from pyspark.ml.classification import LinearSVC, LogisticRegression
from pyspark.ml.feature import OneHotEncoder, VectorAssembler
from pyspark.ml.functions import vector_to_array
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def one_hot(modes: list[str]) -> list:
    return [OneHotEncoder(inputCols=modes, outputCols=[f"{m}_hot" for m in modes], handleInvalid="keep", dropLast=False), VectorAssembler(inputCols=[f"{m}_hot" for m in modes], outputCol="features")]


def _fit(train: DataFrame, test: DataFrame, modes: list[str], model) -> DataFrame:
    cast = lambda df: df.select(*df.columns, F.col("y").cast("double").alias("label"))
    fitted = Pipeline(stages=[*one_hot(modes), model]).fit(cast(train))
    raw = fitted.transform(test).withColumn("score", vector_to_array("rawPrediction")[1])
    return raw.select(*test.columns, "score")


def ctr_logreg(train: DataFrame, test: DataFrame, modes: list[str], penalty: float = 1e-3, iterations: int = 50) -> DataFrame:
    return _fit(train, test, modes, LogisticRegression(regParam=penalty, maxIter=iterations))


def ctr_svm(train: DataFrame, test: DataFrame, modes: list[str], penalty: float = 1e-3, iterations: int = 50) -> DataFrame:
    return _fit(train, test, modes, LinearSVC(regParam=penalty, maxIter=iterations))
