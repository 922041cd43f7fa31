"""Losses of linear models: value and derivative by the prediction, as Columns and as SQL."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def value_and_slope(loss: str, p: Column, y: Column) -> tuple[Column, Column]:
    """squared: y real. logistic: y 0 or 1. hinge and perceptron: y -1 or 1."""
    if loss == "squared":
        return (p - y) * (p - y) / 2, p - y
    if loss == "logistic":
        m = F.when(y > 0, -p).otherwise(p)
        return F.greatest(m, F.lit(0.0)) + F.log1p(F.exp(-F.abs(m))), F.lit(1.0) / (F.lit(1.0) + F.exp(-p)) - y
    if loss == "hinge":
        return F.greatest(F.lit(0.0), F.lit(1.0) - y * p), F.when(y * p < 1, -y).otherwise(F.lit(0.0))
    if loss == "perceptron":
        return F.greatest(F.lit(0.0), -y * p), F.when(y * p <= 0, -y).otherwise(F.lit(0.0))
    raise ValueError(loss)


SLOPE_SQL = {"squared": "({p} - {y})", "logistic": "(1.0/(1.0+exp(-({p}))) - {y})", "hinge": "(case when {y}*({p}) < 1 then -{y} else 0.0 end)", "perceptron": "(case when {y}*({p}) <= 0 then -{y} else 0.0 end)"}
VALUE_SQL = {"squared": "(({p} - {y})*({p} - {y})/2)", "logistic": "(ln(1.0+exp(case when {y} > 0 then -({p}) else ({p}) end)))", "hinge": "greatest(0.0, 1.0-{y}*({p}))", "perceptron": "greatest(0.0, -{y}*({p}))"}
