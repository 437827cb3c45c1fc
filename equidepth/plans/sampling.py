"""Samples of key codes for training."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class SampleSpec:
    """A fraction with a cap, and a floor so that small tables do not drown in sampling noise.

    method: "bernoulli" over all splits; "first_batch" of the first split only (biased where the file is
    clustered); "systematic", rows whose `pk` is a multiple of `every`; "files", whole files.
    """

    frac: float = 0.01
    cap: int = 10_000_000
    floor: int = 2_000
    method: str = "bernoulli"
    batch_rows: int = 100_000
    pk: str | None = None
    every: int = 10
    seed: int = 42

    def rate(self, rows: int) -> float:
        if rows <= 0:
            return 1.0
        return min(1.0, max(min(self.frac, self.cap / rows), self.floor / rows))


def sample_frame(df: DataFrame, code: Column, spec: SampleSpec, rows: int) -> DataFrame:
    """The sampled non-null codes as one column `code`; only the key column is read."""
    rate = spec.rate(rows)
    if spec.method == "systematic":
        if spec.pk is None:
            raise ValueError("a systematic sample needs pk")
        picked = df.filter(F.col(spec.pk) % spec.every == 0).select(code.alias("code"))
    elif spec.method == "first_batch":
        first = df.select(code.alias("code")).filter(F.spark_partition_id() == 0).limit(spec.batch_rows)
        picked = first if rate >= 1 else first.sample(False, min(1.0, max(rate, spec.floor / spec.batch_rows)), spec.seed)
    elif spec.method == "files":
        names = sorted(df.inputFiles())
        step = max(1, int(1 / max(rate, 1e-9)))
        chosen = names[::step] or names
        picked = df.filter(F.input_file_name().isin(chosen)).select(code.alias("code")) if len(chosen) < len(names) else df.select(code.alias("code"))
    elif spec.method == "bernoulli":
        slim = df.select(code.alias("code"))
        picked = slim if rate >= 1 else slim.sample(False, rate, spec.seed)
    else:
        raise ValueError(f"no sample method {spec.method}")
    return picked.filter(F.col("code").isNotNull())


def draw_sample(df: DataFrame, code: Column, spec: SampleSpec, rows: int) -> np.ndarray:
    """The sample on the driver, at most about `cap` doubles."""
    table = sample_frame(df, code.cast("double"), spec, rows).toArrow()
    return table.column(0).to_numpy() if table.num_rows else np.zeros(0)
