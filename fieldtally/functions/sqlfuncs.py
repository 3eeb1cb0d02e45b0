"""SQL surface: scalar helpers, an estimating aggregate and table functions, for users of spark.sql."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from ..plans import primes
from ..plans.sketch_plan import SketchPlan
from . import calibrate
from .algebra import field_of_order


@udtf(returnType="p: bigint")
class PrimePool:
    """prime_pool(linf, eps): the primes of the small-prime scheme."""

    def eval(self, linf: float, eps: float):
        for p in primes.pool_by_max(float(linf), float(eps)):
            yield (p,)


@udtf(returnType="psi_mean: double, psi_var: double, factor: double, error: double")
class FieldConstants:
    """field_constants(order): the large-m constants of a field."""

    def eval(self, order: int):
        field_of_order(int(order))
        mean, variance = calibrate.log_moments(int(order))
        yield mean, variance, 2**-mean, calibrate.error_constant(int(order))


def estimator(plan: SketchPlan):
    """A grouped aggregate over (row, level) of live cells."""
    m, factor = plan.rows, plan.factor
    empty = 1 - 1 / calibrate.survival(plan.field.order)
    offsets = np.array(plan.row_offsets())

    def run(row: pd.Series, level: pd.Series) -> float:
        tops = np.full(m, empty)
        top = level.groupby(row).max()
        tops[top.index.to_numpy()] = top.to_numpy()
        return float(factor * 2 ** np.mean(tops + offsets)) if len(top) else 0.0

    run.__annotations__ = {"row": pd.Series, "level": pd.Series, "return": float}
    return F.pandas_udf(run, "double")


def register(spark: SparkSession, plan: SketchPlan) -> None:
    """Makes prime_pool, field_constants and field_estimate (for sketches of the plan) known to SQL."""
    spark.udtf.register("prime_pool", PrimePool)
    spark.udtf.register("field_constants", FieldConstants)
    spark.udf.register("field_estimate", estimator(plan))
