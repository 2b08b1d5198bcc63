"""Accuracy and cost measures as DataFrame aggregates."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .functions.special import student_p


def mse(df: DataFrame, y: str = "y", pred: str = "mean", by: list[str] | None = None) -> DataFrame:
    return df.groupBy(*(by or [])).agg(F.avg((F.col(y) - F.col(pred)) ** 2).alias("mse"))


def auc(df: DataFrame, y: str = "y", score: str = "score", by: list[str] | None = None) -> DataFrame:
    """Area under the ROC curve with half credit for ties; null where a class is missing. Scores are merged to distinct values before they are sorted."""
    by = by or []
    d = df.groupBy(*by, F.col(score).alias("s")).agg(F.sum((F.col(y) > 0).cast("long")).alias("p"), F.sum((F.col(y) <= 0).cast("long")).alias("n"))
    below = F.coalesce(F.sum("n").over(Window.partitionBy(*by).orderBy("s").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return d.withColumn("w", F.col("p") * (below + F.col("n") / 2)).groupBy(*by).agg((F.sum("w") / F.expr("nullif(sum(p) * sum(n), 0)")).alias("auc"))


def auc_binned(df: DataFrame, y: str = "y", score: str = "score", bins: int = 1_000_000) -> DataFrame:
    """(auc, error_bound) from a histogram of scores in [0, 1]: one bounded aggregate, no global sort. The error is half the pair mass that shares a bin."""
    d = df.withColumn("b", F.least(F.lit(bins - 1), F.floor(F.col(score) * bins).cast("int")))
    d = d.groupBy("b").agg(F.sum((F.col(y) > 0).cast("long")).alias("p"), F.sum((F.col(y) <= 0).cast("long")).alias("n"))
    below = F.coalesce(F.sum("n").over(Window.orderBy("b").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    pairs = F.expr("nullif(sum(p) * sum(n), 0)")
    return d.withColumn("w", F.col("p") * (below + F.col("n") / 2)).groupBy().agg((F.sum("w") / pairs).alias("auc"), (F.sum(F.col("p") * F.col("n") / 2) / pairs).alias("error_bound"))


def fold_stats(df: DataFrame, value: str, by: list[str]) -> DataFrame:
    """Mean, SD and standard error over folds."""
    return df.groupBy(*by).agg(F.avg(value).alias("mean"), F.stddev(value).alias("sd"), (F.stddev(value) / F.sqrt(F.count(value))).alias("se"), F.count(value).alias("folds"))


def paired_t(df: DataFrame, method: str, against: str, value: str = "value") -> DataFrame:
    """(t, df, p) of the paired test over folds of two methods in (method, fold, value)."""
    a, b = df.where(F.col("method") == method).select("fold", F.col(value).alias("a")), df.where(F.col("method") == against).select("fold", F.col(value).alias("b"))
    d = a.join(b, "fold").select((F.col("a") - F.col("b")).alias("d"))
    r = d.agg(F.avg("d").alias("m"), F.stddev("d").alias("s"), F.count("*").alias("n")).first()
    t = float("nan") if not r.n or r.n < 2 or not r.s else r.m / (r.s / r.n**0.5)
    p = student_p(t, r.n - 1) if t == t else None
    return df.sparkSession.createDataFrame([(method, against, t, int(r.n) - 1, p)], "method string, against string, t double, df int, p double")


def t_statistic(a: Column, b: Column) -> Column:
    return F.avg(a - b) / (F.stddev(a - b) / F.sqrt(F.count("*")))


def relative_gain(ours: Column, theirs: Column) -> Column:
    return ours / theirs - 1


def log_predictive(df: DataFrame, y: str = "y", prob: str = "prob") -> DataFrame:
    p = F.least(F.lit(1 - 1e-12), F.greatest(F.lit(1e-12), F.col(prob)))
    return df.agg(F.avg(F.when(F.col(y) > 0, F.log(p)).otherwise(F.log(1 - p))).alias("log_likelihood"))


def calibration(df: DataFrame, y: str = "y", prob: str = "prob", bins: int = 10) -> DataFrame:
    b = F.least(F.lit(bins - 1), F.floor(F.col(prob) * bins).cast("int")).alias("bin")
    return df.groupBy(b).agg(F.count("*").alias("n"), F.avg(prob).alias("mean_prob"), F.avg(y).alias("rate"))
