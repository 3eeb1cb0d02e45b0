"""The field sketch as a small table of cells (row, level, val), val never zero.

A sketch is linear in the state vector: sketches of one plan are added, subtracted, scaled
and rolled up cell by cell, in any order.  Partial aggregation leaves at most rows * levels
rows a task (and group) for the exchange, whatever the number of updates and however skewed their keys.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.algebra import embed, fold, negated, with_product
from ..functions.hashing import placed
from ..plans.sketch_plan import SketchPlan

_EXACT = (T.ByteType, T.ShortType, T.IntegerType, T.LongType)


def check_updates(frame: DataFrame, keys: list[str], delta: str) -> None:
    """Deltas must be whole numbers, and keys hashable."""
    kinds = {f.name: f.dataType for f in frame.schema.fields}
    for name in (*keys, delta):
        if name not in kinds:
            raise ValueError(f"no column {name!r}")
    whole = isinstance(kinds[delta], _EXACT) or (isinstance(kinds[delta], T.DecimalType) and kinds[delta].scale == 0)
    if not whole:
        raise ValueError(f"deltas must be whole numbers, not {kinds[delta].simpleString()}; cast them first")
    for k in keys:
        if isinstance(kinds[k], T.MapType):
            raise ValueError(f"maps can't be hashed: {k!r}")


def sketch(updates: DataFrame, keys: list[str], delta: str, plan: SketchPlan, by: list[str] | None = None, seed=None) -> DataFrame:
    """(by..., row, level, val).  Null keys and null deltas are no updates; zero deltas are dropped before any hash."""
    check_updates(updates, keys, delta)
    by = by or []
    names = [f"_k{i}" for i in range(len(keys))]
    rows = updates.select(*by, *[F.col(k).alias(n) for k, n in zip(keys, names, strict=True)], embed(F.col(delta), plan.field, isinstance(updates.schema[delta].dataType, T.DecimalType)).alias("_delta"))
    present = F.col("_delta") != 0
    for n in names:
        present = present & F.col(n).isNotNull()
    rows = with_product(placed(rows.where(present), names, plan, seed), "_delta", "coef", "_val", plan.field)
    # Pushed into a chain of projections, a condition on its end would be written out with 2^k terms; folded() drops zeros too.
    rows = rows if plan.field.chained else rows.where("_val <> 0")
    return folded(rows.select(*by, "row", "level", F.col("_val").alias("val")), plan, by)


def folded(cells: DataFrame, plan: SketchPlan, by: list[str] | None = None) -> DataFrame:
    by = by or []
    added = cells.groupBy(*by, "row", "level").agg(fold(F.col("val"), plan.field).alias("val"))
    # One condition on both, lest the cap alone be pushed below the hashes and have them computed twice.
    return added.where(F.when(F.col("level") <= plan.levels, F.col("val")).otherwise(0) != 0)


def merge(a: DataFrame, b: DataFrame, plan: SketchPlan, by: list[str] | None = None) -> DataFrame:
    """The sketch of both streams together."""
    return folded(a.unionByName(b), plan, by)


def negate(cells: DataFrame, plan: SketchPlan) -> DataFrame:
    return cells.withColumn("val", negated(F.col("val"), plan.field))


def difference(a: DataFrame, b: DataFrame, plan: SketchPlan, by: list[str] | None = None) -> DataFrame:
    """The sketch of the difference of states: over the two-element field, of the symmetric difference of sets."""
    return merge(a, negate(b, plan), plan, by)


def scale(cells: DataFrame, factor: int, plan: SketchPlan) -> DataFrame:
    """Every state times a field element; a non-zero one leaves the pattern of live cells as it is."""
    kept = [c for c in cells.columns if c != "val"]
    if factor == 0:
        return cells.where(F.lit(False))
    # A field has no zero divisors.
    out = with_product(cells.withColumn("_c", F.lit(factor).cast("long")), "val", "_c", "_product", plan.field)
    return out.select(*kept, F.col("_product").alias("val"))


def roll_up(cells: DataFrame, plan: SketchPlan, by: list[str] | None = None) -> DataFrame:
    """Adds up grouped sketches to coarser groups, which are some of their columns or none."""
    return folded(cells.select(*(by or []), "row", "level", "val"), plan, by)


def sliding(cells: DataFrame, plan: SketchPlan, pane: str, width: int) -> DataFrame:
    """Panes (numbered by a whole column) added up over the last ``width`` of them: each cell is replicated
    to the windows it is in, not each update."""
    windows = F.explode(F.sequence(F.col(pane), F.col(pane) + F.lit(width - 1)))
    return folded(cells.withColumn("window_end", windows).select("window_end", "row", "level", "val"), plan, ["window_end"])


def pack(cells: DataFrame, by: list[str] | None = None) -> DataFrame:
    """One row for each sketch: the cells as an array in (row, level) order, at most rows * levels entries."""
    return cells.groupBy(*(by or [])).agg(F.sort_array(F.collect_list(F.struct("row", "level", "val"))).alias("cells"))


def unpack(packed: DataFrame) -> DataFrame:
    kept = [c for c in packed.columns if c != "cells"]
    return packed.select(*kept, F.explode("cells").alias("c")).select(*kept, "c.row", "c.level", "c.val")


def save(cells: DataFrame, plan: SketchPlan, path: str, mode: str = "append", **labels) -> None:
    """Cells as Parquet under the plan's fingerprint and any labels (a day, a batch), which become partitions."""
    out = cells.withColumn("plan", F.lit(plan.fingerprint))
    for name, value in labels.items():
        out = out.withColumn(name, F.lit(value))
    out.coalesce(1).write.mode(mode).option("partitionOverwriteMode", "dynamic").partitionBy("plan", *labels).parquet(path)


def load(spark: SparkSession, plan: SketchPlan, path: str) -> DataFrame:
    """The saved cells of this plan only; other plans' partitions aren't read."""
    return spark.read.parquet(path).where(F.col("plan") == plan.fingerprint).drop("plan")


def pack_bits(cells: DataFrame, plan: SketchPlan, by: list[str] | None = None) -> DataFrame:
    """(by..., bits): each sketch as BINARY, rows * levels registers of as many bits as an element needs, row by row."""
    by, width = by or [], plan.field.bits
    known = cells.groupBy(*by, "row").agg(F.map_from_entries(F.collect_list(F.struct("level", "val"))).alias("_m"))
    register = lambda v: F.lpad(F.conv(F.coalesce(v, F.lit(0)).cast("string"), 10, 2), width, "0")
    line = F.array_join(F.transform(F.sequence(F.lit(1), F.lit(plan.levels)), lambda i: register(F.element_at("_m", i))), "")
    lines = known.select(*by, F.struct(F.col("row").alias("row"), line.alias("line")).alias("_l")).groupBy(*by).agg(F.map_from_entries(F.collect_list("_l")).alias("_l"))
    blank = F.lit("0" * (plan.levels * width))
    text = F.array_join(F.transform(F.sequence(F.lit(0), F.lit(plan.rows - 1)), lambda r: F.coalesce(F.element_at("_l", r), blank)), "")
    size = -(-plan.memory_bits // 8)
    text = F.rpad(text, size * 8, "0")
    octets = F.transform(F.sequence(F.lit(0), F.lit(size - 1)), lambda i: F.lpad(F.conv(F.substring(text, i * 8 + 1, F.lit(8)), 2, 16), 2, "0"))
    return lines.select(*by, F.unhex(F.array_join(octets, "")).alias("bits"))


def unpack_bits(packed: DataFrame, plan: SketchPlan) -> DataFrame:
    """The live cells of :func:`pack_bits`."""
    kept, width = [c for c in packed.columns if c != "bits"], plan.field.bits
    octets = F.transform(F.sequence(F.lit(0), F.length("bits") - 1), lambda i: F.lpad(F.conv(F.substring(F.hex("bits"), i * 2 + 1, F.lit(2)), 16, 2), 8, "0"))
    text = packed.select(*kept, F.array_join(octets, "").alias("_t"))
    places = text.select(*kept, "_t", F.explode(F.sequence(F.lit(0), F.lit(plan.rows * plan.levels - 1))).alias("_i"))
    value = F.conv(F.substring(F.col("_t"), F.col("_i") * width + 1, F.lit(width)), 2, 10).cast("long")
    return places.select(*kept, F.floor(F.col("_i") / plan.levels).cast("int").alias("row"), (F.col("_i") % plan.levels + 1).cast("int").alias("level"), value.alias("val")).where("val <> 0")
