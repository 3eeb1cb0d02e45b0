"""From cells to estimates: highest non-zero level of each row, their mean, a power of two and a factor."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import calibrate
from ..plans.sketch_plan import SketchPlan


def empty_value(plan: SketchPlan, rule: str) -> float:
    """What a row without live cells counts as: the expected top if the levels below were saturated, or 0."""
    if rule not in ("expected", "zero"):
        raise ValueError(f"no rule {rule!r}")
    return 1 - 1 / calibrate.survival(plan.field.order) if rule == "expected" else 0.0


def row_tops(cells: DataFrame, plan: SketchPlan, by: list[str] | None = None, rule: str = "expected") -> DataFrame:
    """(by..., row, top, is_empty) with all rows of every group that has a cell (or of the one sketch)."""
    by = by or []
    spark = cells.sparkSession
    offset = F.get(F.array(*[F.lit(o) for o in plan.row_offsets()]), F.col("row"))
    tops = cells.groupBy(*by, "row").agg(F.max("level").alias("top"))
    rows = spark.range(plan.rows).select(F.col("id").cast("int").alias("row"))
    every = cells.select(*by).distinct().join(F.broadcast(rows)) if by else rows
    joined = every.join(tops, [*by, "row"], "left")
    top = F.coalesce(F.col("top").cast("double"), F.lit(empty_value(plan, rule))) + offset
    return joined.select(*by, "row", top.alias("top"), F.col("top").isNull().alias("is_empty"))


def estimate(cells: DataFrame, plan: SketchPlan, by: list[str] | None = None, factor: str = "finite", rule: str = "expected", spread: float = 2.0) -> DataFrame:
    """(by..., estimate, rse, lo, hi, empty_rows, in_range), one row for each group.

    No second exchange of rows * levels cells is needed for the row completion: a group's sum of
    tops is that of its present rows plus the constant share of the absent ones."""
    by = by or []
    scale = {"finite": calibrate.finite_factor, "asymptotic": calibrate.asymptotic_factor}[factor](plan.rows, plan.field.order)
    error = plan.relative_error
    offsets = plan.row_offsets()
    tops = cells.groupBy(*by, "row").agg(F.max("level").alias("top"))
    total = F.coalesce(F.sum("top"), F.lit(0)) + F.lit(sum(offsets)) + (F.lit(plan.rows) - F.count("row")) * F.lit(empty_value(plan, rule))
    out = (tops.groupBy(*by) if by else tops.groupBy()).agg((total / F.lit(plan.rows)).alias("_mean"), (F.lit(plan.rows) - F.count("row")).cast("int").alias("empty_rows"))
    value = F.when(F.col("empty_rows") == plan.rows, F.lit(0.0)).otherwise(F.lit(scale) * F.pow(F.lit(2.0), F.col("_mean")))
    out = out.withColumn("estimate", value)
    least = 8 if rule == "expected" else 128
    return out.select(
        *by, "estimate", F.lit(error).alias("rse"), F.greatest(F.lit(0.0), F.col("estimate") * (1 - spread * error)).alias("lo"), (F.col("estimate") * (1 + spread * error)).alias("hi"),
        "empty_rows", ((F.col("estimate") >= least * plan.rows) & (F.col("estimate") <= 2.0 ** (plan.levels - 4) * plan.rows)).alias("in_range"),
    )


def sql_estimate(cells: str, plan: SketchPlan, by: list[str] | None = None, rule: str = "expected", digits: int = 3, factor: float | None = None) -> str:
    """The same (by..., estimate, empty_rows) for DuckDB, from a subquery of cells."""
    by = by or []
    head = "".join(f"{b}, " for b in by)
    group = f"GROUP BY {', '.join(by)}" if by else ""
    scale = plan.factor if factor is None else factor
    mean = f"(coalesce(sum(top), 0) + {sum(plan.row_offsets())!r} + ({plan.rows} - count(row)) * {empty_value(plan, rule)!r}) / {plan.rows}"
    return f"SELECT {head}round(CASE WHEN count(row) = 0 THEN 0.0 ELSE {scale!r} * pow(2.0, {mean}) END, {digits}) AS estimate, ({plan.rows} - count(row))::INTEGER AS empty_rows FROM (SELECT {head}row, max(level) AS top FROM ({cells}) GROUP BY {head}row) {group}"
