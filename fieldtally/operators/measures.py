"""Accuracy and cost measures over replicated sketches."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import calibrate
from ..functions.algebra import field_of_order
from ..functions.hashing import hash_parts, placed
from ..plans.sketch_plan import SketchPlan
from .cells import sketch
from .estimate import empty_value, estimate
from .exact import exact_support, states
from .l0 import replicated


def accuracy(updates: DataFrame, keys: list[str], delta: str, plan: SketchPlan, replicates: int, eps: float = 0.2, rule: str = "expected") -> DataFrame:
    """(replicates, bias, rse, rse_const, predicted_const, fail_rate) of the estimates under several seeds, against the exact support."""
    found = estimate(replicated(updates, keys, delta, plan, replicates), plan, ["replicate"], rule=rule)
    truth = exact_support(updates, keys, delta, plan.field).select("l0")
    found = found.join(F.broadcast(truth))  # one row
    error = F.col("estimate") / F.col("l0") - 1
    out = found.agg(F.count("*").alias("replicates"), F.avg(error).alias("bias"), F.stddev_samp(error).alias("rse"), F.avg((F.abs(error) > eps).cast("int")).alias("fail_rate"))
    root = math.sqrt(plan.rows)
    return out.select("replicates", F.round("bias", 6).alias("bias"), F.round("rse", 6).alias("rse"), F.round(F.col("rse") * root, 6).alias("rse_const"), F.lit(round(plan.relative_error * root, 6)).alias("predicted_const"), F.round("fail_rate", 6).alias("fail_rate"))


def cell_law(cells: DataFrame, plan: SketchPlan, truth: DataFrame, replicates: int) -> DataFrame:
    """(level, live, expected): share of cells of each level that are live, beside the law.  truth: one row, l0."""
    shares = cells.groupBy("level").agg((F.count("*") / F.lit(plan.rows * replicates)).alias("live")).join(F.broadcast(truth.select("l0")))
    expected = (1 - F.exp(-F.col("l0") * F.pow(F.lit(2.0), -F.col("level")) / F.lit(plan.rows))) * F.lit(calibrate.survival(plan.field.order))
    return shares.select("level", F.round("live", 6).alias("live"), F.round(expected, 6).alias("expected"))


def register_law(spark: SparkSession, supports: list[int], plan: SketchPlan, levels: int = 20) -> DataFrame:
    """(support, level, probability) that a register is non-zero, from its law."""
    rows = [(n, i, round(calibrate.cell_nonzero_probability(n, i, 0.0, plan.rows, plan.field.order), 9)) for n in supports for i in range(1, levels + 1)]
    return spark.createDataFrame(rows, "support long, level int, probability double")


def cell_uniformity(cells: DataFrame, plan: SketchPlan) -> DataFrame:
    """(val, n): how often each non-zero value stands in a live cell."""
    return cells.groupBy("val").agg(F.count("*").alias("n"))


def chi_square(cells: DataFrame, plan: SketchPlan) -> DataFrame:
    """(cells, chi_square, degrees) of the non-zero values against the even distribution; values that never occur count."""
    counts = cell_uniformity(cells, plan)
    n, kinds = F.sum("n"), plan.field.order - 1
    return counts.agg(n.alias("cells"), F.round(F.sum(F.col("n") * F.col("n")) * F.lit(float(kinds)) / n - n, 6).alias("chi_square"), F.lit(kinds - 1).alias("degrees"))


def coupled_view(updates: DataFrame, keys: list[str], delta: str, plan: SketchPlan) -> DataFrame:
    """(level, touched, live): cells that some live element falls in, and those that the sketch shows as non-zero."""
    live = states(updates, keys, delta, plan.field).where("x <> 0")
    names = [f"_k{i}" for i in range(len(keys))]
    touched = placed(live.select(*[F.col(k).alias(n) for k, n in zip(keys, names, strict=True)]), names, plan).where(F.col("level") <= plan.levels).select("row", "level").distinct()
    shown = sketch(updates, keys, delta, plan).select("row", "level", F.lit(1).alias("live"))
    return touched.join(shown, ["row", "level"], "left").groupBy("level").agg(F.count("*").alias("touched"), F.count("live").alias("live"))


def engine_costs(updates: DataFrame, keys: list[str], delta: str, plan: SketchPlan) -> DataFrame:
    """(updates, keys, cells, cell_limit): what an exact count shuffles (a row a key) beside what a sketch leaves, and its limit for a task."""
    counted = updates.where(F.col(delta).isNotNull()).agg(F.count("*").alias("updates"))
    seen = states(updates, keys, delta, plan.field).agg(F.count("*").alias("keys"))
    left = sketch(updates, keys, delta, plan).agg(F.count("*").alias("cells"))
    return counted.join(F.broadcast(seen)).join(F.broadcast(left)).withColumn("cell_limit", F.lit(plan.rows * plan.levels).cast("long"))


def position_law(shifts: DataFrame, orders: list[float], low: int = -40, high: int = 80) -> DataFrame:
    """(field_order, shift, position, mass) and the other columns of ``shifts``: the law of a row's highest non-zero position without
    offset, for a support of 2^shift elements a row; from the register law alone.  Infinity as order 0.  One row for each."""
    kinds = shifts.sparkSession.createDataFrame([(0 if math.isinf(q) else int(q), calibrate.survival(q)) for q in orders], "field_order long, r double")
    grid = shifts.join(F.broadcast(kinds)).join(F.broadcast(shifts.sparkSession.range(low, high + 1).select(F.col("id").cast("int").alias("position"))))
    live = F.col("r") * (1 - F.exp(-F.pow(F.lit(2.0), F.col("shift") - F.col("position"))))
    above = Window.partitionBy("field_order", *shifts.columns).orderBy(F.col("position").desc()).rowsBetween(Window.unboundedPreceding, -1)
    # A cell that is surely live ends the product; its logarithm is bounded.
    out = grid.withColumn("live", live).withColumn("_log", F.log(F.greatest(1 - F.col("live"), F.lit(1e-300))))
    return out.select("field_order", *shifts.columns, "position", (F.col("live") * F.exp(F.coalesce(F.sum("_log").over(above), F.lit(0.0)))).alias("mass"))


def periodic_part(supports: DataFrame, orders: list[float]) -> DataFrame:
    """(field_order, support, parts, excess): the mean highest position less log2 of the support, for every support a row that
    the parts' streams have.  Were the error free of a periodic part, it would be the same for all; supports that are a power of
    two apart have the same one."""
    law = position_law(supports.withColumn("shift", F.log2(F.col("support").cast("double"))), orders)
    return law.groupBy("field_order", "support", "parts", "shift").agg(F.sum(F.col("position") * F.col("mass")).alias("mean")).select("field_order", "support", "parts", F.round(F.col("mean") - F.col("shift"), 7).alias("excess"))


def moment_identity(supports: DataFrame, orders: list[float], exponents: list[float], steps: int = 16) -> DataFrame:
    """(field_order, t, parts, observed, expected): E 2^(t (W - log2 n)) over the parts, n lines a row for a part of n, and over
    even offsets, beside base2_moment(t)."""
    known = supports.sparkSession.createDataFrame([(0 if math.isinf(q) else int(q), t, round(calibrate.base2_moment(t, calibrate.survival(q)), 6)) for q in orders for t in exponents], "field_order long, t double, expected double")
    # An offset thins the support by its power of two, and is added to the position: a lesser shift.
    offsets = supports.sparkSession.range(steps).select((F.col("id") / F.lit(float(steps))).alias("offset"))
    moved = supports.join(F.broadcast(offsets)).select("support", "parts", (F.log2(F.col("support").cast("double")) - F.col("offset")).alias("shift"))
    law = position_law(moved, orders).join(F.broadcast(known), "field_order")
    means = law.groupBy("field_order", "t", "expected", "support", "shift", "parts").agg(F.sum(F.pow(F.lit(2.0), F.col("t") * (F.col("position") - F.col("shift"))) * F.col("mass")).alias("m"))
    total = F.sum("parts")
    return means.groupBy("field_order", "t", "expected").agg((total / steps).cast("long").alias("parts"), F.round(F.sum(F.col("m") * F.col("parts")) / total, 6).alias("observed")).select("field_order", "t", "parts", "observed", "expected")


def constants_table(spark: SparkSession, orders: list[tuple[float, int]]) -> DataFrame:
    """(field_order, psi_mean, psi_var, factor, error, n_groups) for each order and its number of groups; infinity as 0."""
    rows = []
    for q, n in orders:
        mean, variance = calibrate.log_moments(q)
        rows.append((0 if math.isinf(q) else int(q), round(mean, 4), round(variance, 4), round(2**-mean, 4), round(calibrate.error_constant(q), 4), n))
    return spark.createDataFrame(rows, "field_order long, psi_mean double, psi_var double, factor double, error double, n_groups long")


def sweep_shapes(orders: list[int], rows: list[int]) -> list[tuple]:
    """(field_order, m, factor, value of an empty row, predicted constant) of every combination."""
    plans = [SketchPlan(m, field_of_order(q)) for q in orders for m in rows]
    return [(p.field.order, p.rows, p.factor, empty_value(p, "expected"), round(p.relative_error * math.sqrt(p.rows), 6)) for p in plans]


def order_sweep(updates: DataFrame, keys: list[str], orders: list[int], rows: list[int], replicates: int, hash: str = "fast") -> DataFrame:
    """(field_order, m, bias, rse_const, predicted_const): distinct keys inserted once, under every order and size.

    One pass: a key is hashed once for each seed, and one aggregate serves all fields of a characteristic: sums
    of coefficients by digit, or their exclusive or."""
    base = SketchPlan(max(rows), field_of_order(2), hash=hash)
    seen = updates.select(*keys).dropna().distinct()
    truth = seen.agg(F.count("*").alias("l0"))
    hashed = hash_parts(seen.withColumn("replicate", F.explode(F.sequence(F.lit(1), F.lit(replicates)))), keys, base, F.col("replicate"))
    sized = hashed.withColumn("m", F.explode(F.array(*[F.lit(m) for m in rows]))).select("replicate", "m", F.pmod("row_hash", "m").cast("int").alias("row"), "level", "coef_hash").where(F.col("level") <= base.levels)
    fields = [field_of_order(q) for q in orders]
    odd = {f.order: [F.sum(F.pmod(F.floor(F.pmod("coef_hash", F.lit(f.order)) / F.lit(f.p**i)), F.lit(f.p))).alias(f"s{f.order}_{i}") for i in range(f.k)] for f in fields if f.p > 2}
    cells = sized.groupBy("m", "replicate", "row", "level").agg(F.bit_xor("coef_hash").alias("x"), *[c for part in odd.values() for c in part])
    live = [F.when((F.col("x").bitwiseAND(F.lit(f.order - 1)) != 0) if f.p == 2 else F.greatest(*[F.pmod(f"s{f.order}_{i}", F.lit(f.p)) for i in range(f.k)], F.lit(0)) != 0, F.lit(f.order).cast("long")) for f in fields]
    found = cells.select("m", "replicate", "row", "level", F.explode(F.array_compact(F.array(*live))).alias("field_order"))
    tops = found.groupBy("field_order", "m", "replicate", "row").agg(F.max("level").alias("top")).groupBy("field_order", "m", "replicate").agg(F.sum("top").alias("tops"), F.count("*").alias("present"))
    shapes = updates.sparkSession.createDataFrame(sweep_shapes(orders, rows), "field_order long, m int, factor double, empty double, predicted_const double")
    value = F.col("factor") * F.pow(F.lit(2.0), (F.col("tops") + (F.col("m") - F.col("present")) * F.col("empty")) / F.col("m"))
    error = tops.join(F.broadcast(shapes), ["field_order", "m"]).join(F.broadcast(truth)).withColumn("e", value / F.col("l0") - 1)
    return error.groupBy("field_order", "m", "predicted_const").agg(F.round(F.avg("e"), 6).alias("bias"), F.round(F.stddev_samp("e") * F.sqrt(F.col("m").cast("double")), 6).alias("rse_const")).select("field_order", "m", "bias", "rse_const", "predicted_const")


def simulate_ideal(spark: SparkSession, elements: int, plan: SketchPlan, replicates: int = 1, low: int = -8) -> DataFrame:
    """ideal_cells of so many elements that are made up."""
    return ideal_cells(spark.range(elements), plan, replicates, low)


def ideal_cells(elements: DataFrame, plan: SketchPlan, replicates: int = 1, low: int = -8) -> DataFrame:
    """(replicate, row, level, val): the idealised construction, for validating the analysis on few elements (``id``, distinct).

    Every element falls in every cell of every row on its own, with probability 1 - exp(-2^(-level-offset) / m) and its own coefficient;
    levels also run below 1."""
    pairs = elements.select("id", F.explode(F.sequence(F.lit(1), F.lit(replicates))).alias("replicate"))
    pairs = pairs.select("id", "replicate", F.explode(F.sequence(F.lit(0), F.lit(plan.rows - 1))).alias("row"))
    pairs = pairs.select("*", F.explode(F.sequence(F.lit(low), F.lit(plan.levels))).alias("level"))
    offset = F.get(F.array(*[F.lit(o) for o in plan.row_offsets()]), F.col("row"))
    u = F.pmod(F.xxhash64(F.lit(f"ideal/{plan.seed}"), "id", "replicate", "row", "level"), F.lit(1 << 52)) / F.lit(float(1 << 52))
    hit = u < 1 - F.exp(-F.pow(F.lit(2.0), -F.col("level") - offset) / F.lit(plan.rows))
    value = F.pmod(F.xxhash64(F.lit(f"value/{plan.seed}"), "id", "replicate", "row", "level"), F.lit(plan.field.order))
    from ..functions.algebra import fold

    return pairs.where(hit).select("replicate", "row", "level", value.alias("val")).groupBy("replicate", "row", "level").agg(fold(F.col("val"), plan.field).alias("val")).where("val <> 0")
