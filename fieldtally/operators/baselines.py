"""Baselines: insert-only bit tables, HyperLogLog, the earlier turnstile estimator, and ablations."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import calibrate
from ..functions.algebra import prime_field
from ..functions.hashing import placed
from ..plans import primes
from ..plans.sketch_plan import SketchPlan
from .cells import sketch

#: Constant of the first-zero rule for levels from 1 (fixed value from the literature: 1 / (2 * 0.77351)).
FIRST_ZERO_FACTOR = 1 / (2 * 0.77351)


def bit_table(inserts: DataFrame, keys: list[str], plan: SketchPlan, by: list[str] | None = None) -> DataFrame:
    """(by..., row, level): which bits are set.  Deltas, if any, are ignored: a bit can't be unset."""
    by = by or []
    names = [f"_k{i}" for i in range(len(keys))]
    rows = inserts.select(*by, *[F.col(k).alias(n) for k, n in zip(keys, names, strict=True)]).dropna(subset=names)
    found = placed(rows, names, plan).groupBy(*by, "row", "level").agg(F.count(F.lit(1)).alias("_n"))
    # As in cells.folded: a condition on the level alone would have it hashed twice.
    return found.where(F.when(F.col("level") <= plan.levels, F.col("_n")).otherwise(0) > 0).drop("_n")


def row_masks(bits: DataFrame) -> DataFrame:
    """(row, mask): the levels of a row as bits 0, 1, ... of a LONG."""
    return bits.groupBy("row").agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), F.col("level") - 1)).alias("mask"))


def bit_estimate(bits: DataFrame, plan: SketchPlan, rule: str = "first_zero") -> DataFrame:
    """(estimate): by the first missing level of each row, or by the highest set one."""
    m = plan.rows
    if rule == "first_zero":
        # The lowest clear bit is the lowest set bit of the complement.
        clear = F.bitwise_not("mask")
        first = F.bit_count(clear.bitwiseAND(-clear) - 1) + 1
        rows, factor, empty = row_masks(bits).select(first.alias("top")), FIRST_ZERO_FACTOR * m, 1.0
    elif rule == "highest":
        rows, factor, empty = bits.groupBy("row").agg(F.max("level").alias("top")).select("top"), calibrate.asymptotic_factor(m, math.inf), 0.0
    else:
        raise ValueError(f"no rule {rule!r}")
    mean = (F.coalesce(F.sum("top"), F.lit(0)) + (F.lit(m) - F.count("*")) * F.lit(empty)) / F.lit(m)
    return rows.agg((F.lit(factor) * F.pow(F.lit(2.0), mean)).alias("estimate"))


def hll_estimate(updates: DataFrame, keys: list[str]) -> DataFrame:
    """(estimate): Spark's HyperLogLog over the keys; deletions don't count."""
    return updates.agg(F.hll_sketch_estimate(F.hll_sketch_agg(F.xxhash64(*keys), F.lit(12))).cast("double").alias("estimate"))


def prior_l0(updates: DataFrame, keys: list[str], delta: str, eps: float, linf: float, seed: int = 0, levels: int = 40, hash: str = "fast") -> DataFrame:
    """(estimate): the earlier turnstile estimator, as the literature of 2010 has it: levels by low-order bits, about
    1/eps^2 buckets in each, a counter sum(x * coefficient) mod a prime from a wide range, and the inversion of the
    occupied-bucket count at the deepest level that is still a good part full."""
    plan = prior_plan(eps, linf, seed, levels, hash)
    live = sketch(updates, keys, delta, plan)
    full = live.groupBy("level").agg(F.count("*").alias("t"))
    # A level's own elements are a 2^-level share; the fullest level under 0.6 of its buckets is inverted.
    k = F.lit(float(plan.rows))
    sized = full.where(F.col("t") < 0.6 * k).withColumn("n", F.log1p(-F.col("t") / k) / F.log1p(-1 / k) * F.pow(F.lit(2.0), F.col("level")))
    return sized.agg(F.coalesce(F.max_by("n", F.struct(F.col("t"), -F.col("level"))), F.lit(0.0)).alias("estimate"))


def prior_plan(eps: float, linf: float, seed: int = 0, levels: int = 40, hash: str = "fast") -> SketchPlan:
    """Its shape: 1/eps^2 buckets at each level, over the field of a prime from the wide range."""
    prime = primes.draw_between(*primes.wide_range(linf, eps), seed)
    return SketchPlan(max(16, math.ceil(1 / eps**2)), prime_field(prime), levels=levels, seed=seed, hash=hash)


def sql_prior_l0(cells: str, plan: SketchPlan) -> str:
    """The same for DuckDB, from a subquery of cells."""
    sized = f"SELECT level, t, ln(1 - t / {float(plan.rows)}) / ln(1 - 1 / {float(plan.rows)}) * pow(2.0, level) AS n FROM (SELECT level, count(*) AS t FROM ({cells}) GROUP BY level) WHERE t < 0.6 * {plan.rows}"
    return f"SELECT coalesce((SELECT n FROM ({sized}) ORDER BY t DESC, level LIMIT 1), 0.0) AS estimate"
