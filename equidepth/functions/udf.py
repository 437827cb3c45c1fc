"""Functions in Python where built-ins cannot say it: predictions of very large models, grouped measures, table functions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..plans.cdf_model import CdfModel


def predict_udf(model: CdfModel, f: int | None = None):
    """Vector prediction: the quantile, or with f the slice. For models too large for a literal."""
    if f is None:

        @F.pandas_udf("double")
        def cdf(x: pd.Series) -> pd.Series:
            y = model.cdf_np(x.fillna(0.0).to_numpy())
            return pd.Series(y).where(x.notna().to_numpy())

        return cdf

    @F.pandas_udf("int")
    def pid(x: pd.Series) -> pd.Series:
        return pd.Series(model.pid_np(x.fillna(0.0).to_numpy(), f)).where(x.notna().to_numpy()).astype("Int32")

    return pid


@F.pandas_udf(T.DoubleType())
def bin_cv(sizes: pd.Series) -> float:
    """Coefficient of variation of slice sizes."""
    return float(sizes.std(ddof=0) / sizes.mean()) if len(sizes) and sizes.mean() else 0.0


@F.udtf(returnType=T.StructType().add("slice", T.IntegerType()).add("low", T.DoubleType()).add("high", T.DoubleType()))
class QuantileSlices:
    """The quantile bounds of n slices."""

    def eval(self, n: int):
        for i in range(n):
            yield i, i / n, (i + 1) / n


@F.udtf(returnType=T.StructType().add("key", T.StringType()).add("payload", T.StringType()))
class SplitFixed:
    """Key and payload of a fixed-width record."""

    def eval(self, record: str, width: int):
        if record is not None:
            yield record[:width], record[width:]


def register_all(spark: SparkSession, model: CdfModel | None = None, f: int = 16) -> list[str]:
    """Names under which SQL finds them."""
    spark.udtf.register("quantile_slices", QuantileSlices)
    spark.udtf.register("split_fixed", SplitFixed)
    spark.udf.register("bin_cv", bin_cv)
    names = ["quantile_slices", "split_fixed", "bin_cv"]
    if model is not None:
        spark.udf.register("model_cdf", predict_udf(model))
        spark.udf.register("model_pid", predict_udf(model, f))
        names += ["model_cdf", "model_pid"]
    return names


def cdf_table(model: CdfModel, points: int = 101) -> pd.DataFrame:
    """The model's curve between its first and last centre."""
    x = np.linspace(float(model.centre.min()), float(model.centre.max()), points)
    return pd.DataFrame({"x": x, "cdf": model.cdf_np(x)})
