"""Accuracy measures over predicted and true labels, all as aggregations."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def label_confusion(pred: DataFrame, truth: DataFrame, labels: DataFrame | None = None) -> DataFrame:
    """(label, tp, fp, fn) from distinct (v, label) rows; labels (label) adds those that neither side has."""
    both = pred.select("v", "label", F.lit(1).alias("p")).join(truth.select("v", "label", F.lit(1).alias("t")), ["v", "label"], "full").na.fill(0)
    found = both.groupBy("label").agg(F.sum(F.col("p") * F.col("t")).alias("tp"), F.sum(F.col("p") * (1 - F.col("t"))).alias("fp"), F.sum((1 - F.col("p")) * F.col("t")).alias("fn"))
    if labels is not None:
        found = labels.select("label").distinct().join(found, "label", "full").na.fill(0)
    return found


def _ratio(a: Column, b: Column) -> Column:
    return F.when(b > 0, a / b).otherwise(0.0)


def f1(tp: Column, fp: Column, fn: Column) -> Column:
    """Harmonic mean of precision and recall; 0 where it is undefined."""
    return _ratio(2 * tp, 2 * tp + fp + fn)


def per_label(confusion: DataFrame) -> DataFrame:
    tp, fp, fn = F.col("tp"), F.col("fp"), F.col("fn")
    return confusion.select("label", "tp", "fp", "fn", _ratio(tp, tp + fp).alias("precision"), _ratio(tp, tp + fn).alias("recall"), f1(tp, fp, fn).alias("f1"))


def macro_f1(confusion: DataFrame, labels: str = "all") -> DataFrame:
    """Mean F1 over labels; 'seen' leaves out labels without a true vertex."""
    rows = confusion if labels == "all" else confusion.where("tp + fn > 0")
    return rows.agg(F.coalesce(F.avg(f1(F.col("tp"), F.col("fp"), F.col("fn"))), F.lit(0.0)).alias("macro_f1"))


def pooled_f1(confusion: DataFrame) -> DataFrame:
    """F1 of counts summed over labels."""
    s = confusion.agg(*[F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in ("tp", "fp", "fn")])
    return s.select(f1(F.col("tp"), F.col("fp"), F.col("fn")).alias("pooled_f1"))


def score_gap(score: float, against: float) -> dict[str, float]:
    """Difference of two scores in points and relative to the second."""
    return {"points": score - against, "relative": (score - against) / against if against else 0.0}


def f1_summary_udf():
    """Grouped pandas aggregate twin of f1 over summed counts."""

    @F.pandas_udf("double")
    def f1_of(tp: pd.Series, fp: pd.Series, fn: pd.Series) -> float:
        a = 2.0 * tp.sum()
        b = a + fp.sum() + fn.sum()
        return float(a / b) if b else 0.0

    return f1_of
