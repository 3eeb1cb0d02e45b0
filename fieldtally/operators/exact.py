"""Exact counterparts: states, support, norms, residue supports.  These shuffle every key; they are what the sketches save."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.algebra import FieldSpec, embed, fold
from .cells import check_updates

#: Bits by which magnitudes of one power of two are classed further.
_FINE = 6

def _total(updates: DataFrame, delta: str) -> Column:
    """Aggregate: the integer sum of deltas, which can't overflow.  LONG deltas are summed as two halves in LONG,
    which 2^31 rows of a key don't overflow, and put together once for each key."""
    kind = dict(updates.dtypes)[delta]
    if kind.startswith("decimal"):
        return F.sum(F.col(delta).cast("decimal(38,0)"))
    if kind != "bigint":
        return F.sum(delta).cast("decimal(38,0)")
    high, low = F.sum(F.shiftright(delta, 32)), F.sum(F.col(delta).bitwiseAND(F.lit((1 << 32) - 1)))
    return (high.cast("decimal(28,0)") * F.lit(1 << 32).cast("decimal(10,0)") + low).cast("decimal(38,0)")


def states(updates: DataFrame, keys: list[str], delta: str, field: FieldSpec | None = None, by: list[str] | None = None) -> DataFrame:
    """(by..., keys..., x): the sum of a key's deltas, in the integers (DECIMAL) or a field (LONG).  Null keys and deltas are no updates."""
    check_updates(updates, keys, delta)
    present = F.col(delta).isNotNull()
    for k in keys:
        present = present & F.col(k).isNotNull()
    x = _total(updates, delta) if field is None else fold(embed(F.col(delta), field, dict(updates.dtypes)[delta].startswith("decimal")), field)
    return updates.where(present).groupBy(*(by or []), *keys).agg(x.alias("x"))


def exact_support(updates: DataFrame, keys: list[str], delta: str, field: FieldSpec | None = None, by: list[str] | None = None) -> DataFrame:
    """(by..., n_keys, l0)."""
    found = states(updates, keys, delta, field, by)
    return (found.groupBy(*by) if by else found.groupBy()).agg(F.count("*").alias("n_keys"), F.count_if(F.col("x") != 0).alias("l0"))


def exact_norms(updates: DataFrame, keys: list[str], delta: str) -> DataFrame:
    """(n_keys, l0, l1, linf, mean): mean is l1 / l0; l1 and linf are DECIMAL."""
    size = F.abs("x")
    out = states(updates, keys, delta).agg(F.count("*").alias("n_keys"), F.count_if(F.col("x") != 0).alias("l0"), F.coalesce(F.sum(size), F.lit(0)).alias("l1"), F.coalesce(F.max(size), F.lit(0)).alias("linf"))
    return out.withColumn("mean", F.round(F.col("l1").cast("double") / F.nullif(F.col("l0"), F.lit(0)), 6))


def power_mean(updates: DataFrame, keys: list[str], delta: str, exponent: float) -> DataFrame:
    """(power_mean): the mean of |x|^g over live elements, to the power 1/g, 0 < g < 1."""
    if not 0 < exponent < 1:
        raise ValueError("the exponent must be between 0 and 1")
    live = states(updates, keys, delta).where("x <> 0")
    return live.agg(F.round(F.pow(F.avg(F.pow(F.abs("x").cast("double"), F.lit(exponent))), F.lit(1 / exponent)), 6).alias("power_mean"))


def discounted_norms(updates: DataFrame, keys: list[str], delta: str, eps: float) -> DataFrame:
    """(cut, l0, l1, linf) without the floor(eps * l0 / 2) entries of largest magnitude.

    No global sort, and no task that sees all magnitudes: they are counted; the counts of their classes (a
    power of two and the next _FINE bits) tell in which class the cut falls; and only that class is ranked."""
    sizes = states(updates, keys, delta).where("x <> 0").groupBy(F.abs("x").alias("size")).agg(F.count("*").alias("n"))
    power = F.floor(F.log2(F.col("size").cast("double")))
    sizes = sizes.withColumn("class", power * F.lit(1 << _FINE) + F.floor((F.col("size").cast("double") / F.pow(F.lit(2.0), power) - 1) * F.lit(1 << _FINE)))
    # At most 126 * 2^_FINE classes.
    above = Window.orderBy(F.col("class").desc()).rowsBetween(Window.unboundedPreceding, -1)
    classes = sizes.groupBy("class").agg(F.sum("n").alias("_n")).withColumn("_above", F.coalesce(F.sum("_n").over(above), F.lit(0)))
    classes = classes.withColumn("cut", F.floor(F.sum("_n").over(Window.partitionBy(F.lit(1))) * F.lit(eps) / 2)).withColumn("_split", (F.col("_above") < F.col("cut")) & (F.col("_above") + F.col("_n") > F.col("cut")))
    marked = sizes.join(F.broadcast(classes), "class")
    ranked = marked.where("_split").withColumn("_above", F.col("_above") + F.coalesce(F.sum("n").over(Window.partitionBy("class").orderBy(F.col("size").desc()).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    whole = marked.where("not _split").withColumn("n", F.when(F.col("_above") >= F.col("cut"), F.col("n")).otherwise(0)).withColumn("_above", F.col("cut"))
    left = ranked.unionByName(whole).withColumn("kept", F.greatest(F.lit(0), F.least(F.col("n"), F.col("n") + F.col("_above") - F.col("cut"))))
    return left.agg(F.max("cut").alias("cut"), F.sum("kept").alias("l0"), F.sum(F.col("kept") * F.col("size")).cast("decimal(38,0)").alias("l1"), F.max(F.when(F.col("kept") > 0, F.col("size"))).alias("linf"))


def residue_support(updates: DataFrame, keys: list[str], delta: str, primes: list[int]) -> DataFrame:
    """(l0, l0_mod_<p>...): live elements, and those whose state the prime doesn't divide: never more."""
    found = states(updates, keys, delta)
    return found.agg(F.count_if(F.col("x") != 0).alias("l0"), *[F.count_if(F.pmod("x", F.lit(p).cast("decimal(20,0)")) != 0).alias(f"l0_mod_{p}") for p in primes])


def gap_table(updates: DataFrame, keys: list[str], delta: str, pool: list[int], eps: float) -> DataFrame:
    """(p, l0, l0_mod, gap, bad) for every prime of a pool.

    States are first counted by magnitude, so the pool meets distinct magnitudes, not elements."""
    spark = updates.sparkSession
    sizes = states(updates, keys, delta).where("x <> 0").groupBy(F.abs("x").alias("size")).agg(F.count("*").alias("n"))
    primes = spark.createDataFrame([(int(p),) for p in pool], "p long")
    pairs = sizes.crossJoin(F.broadcast(primes))
    out = pairs.groupBy("p").agg(F.sum("n").alias("l0"), F.sum(F.when(F.pmod(F.col("size"), F.col("p").cast("decimal(20,0)")) != 0, F.col("n")).otherwise(0)).alias("l0_mod"))
    out = out.withColumn("gap", F.round((F.col("l0") - F.col("l0_mod")) / F.col("l0"), 9))
    return out.withColumn("bad", ((F.col("l0") - F.col("l0_mod")) > F.lit(eps) * F.col("l0")).cast("int"))


def bad_prime_share(updates: DataFrame, keys: list[str], delta: str, pool: list[int], eps: float) -> DataFrame:
    """(pool, bad, share): how many primes of the pool lose more than eps of the support."""
    gaps = gap_table(updates, keys, delta, pool, eps)
    return gaps.agg(F.count("*").alias("pool"), F.sum("bad").alias("bad"), F.round(F.avg("bad"), 9).alias("share"))
