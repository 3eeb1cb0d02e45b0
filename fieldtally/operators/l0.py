"""Counting integers with insertions and deletions: the field sketch over a randomly drawn prime field."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import calibrate
from ..functions.algebra import prime_field
from ..plans import primes
from ..plans.sketch_plan import SketchPlan, space_bound
from .cells import sketch
from .estimate import estimate
from .exact import states

#: Of the failure probability 1/3, a tenth goes to the draw of the prime and the rest to the sketch.
DRAW_FAILURE, SKETCH_FAILURE = 0.1, 1 / 3 - 0.1


@dataclass(frozen=True)
class Choice:
    """A scheme's outcome: the prime, the pool it came from, and the sketch's rows."""

    scheme: str
    prime: int
    pool: int
    rows: int
    eps_sketch: float
    eps_prime: float


def bounds(updates: DataFrame, delta: str = "delta") -> float:
    """Sum of |delta|: bounds l1 and linf from above, in one scan without a shuffle of keys."""
    return float(updates.agg(F.coalesce(F.sum(F.abs(F.col(delta).cast("decimal(38,0)"))), F.lit(0)).alias("s")).first()["s"])


def choose(scheme: str, eps: float, seed: int, linf: float | None = None, mean: float | None = None, power_mean: float | None = None, rows: int | None = None) -> Choice:
    """Draw a prime by 'small' (needs linf), 'above_max' (linf), 'above_mean' (mean), 'above_power_mean' (power_mean),
    'wide' (linf) or 'toggle'; with 'discount_' before it, the bounds are those without the top eps/2 share."""
    half, base = eps / 2, scheme.removeprefix("discount_")
    part = half / 2 if scheme != base else half
    pools = {
        "small": lambda: primes.pool_by_max(linf, part),
        "above_max": lambda: [primes.above_max(int(linf))],
        "above_mean": lambda: primes.pool_by_mean(mean, part),
        "above_power_mean": lambda: primes.pool_by_power_mean(power_mean, part),
        "wide": lambda: range(*primes.wide_range(linf, part)),
        "toggle": lambda: [2],
    }
    if base not in pools:
        raise ValueError(f"no scheme {scheme!r}")
    pool = pools[base]()
    if base == "wide":
        # A range is drawn from, its primes are only counted.
        prime, size = primes.draw_between(pool.start, pool.stop, seed), primes.count_between(pool.start, pool.stop)
    else:
        prime, size = primes.draw(pool, seed), len(pool)
    return Choice(scheme, prime, size, rows or calibrate.rows_for(half, prime, SKETCH_FAILURE), half, half)


def l0_estimate(updates: DataFrame, keys: list[str], delta: str, choice: Choice, seed: int = 0, hash: str = "fast", by: list[str] | None = None) -> DataFrame:
    """The estimate, with the prime, pool and memory it came from."""
    plan = SketchPlan(choice.rows, prime_field(choice.prime), seed=seed, hash=hash)
    found = estimate(sketch(updates, keys, delta, plan, by), plan, by)
    return found.withColumns({"scheme": F.lit(choice.scheme), "prime": F.lit(choice.prime), "pool": F.lit(choice.pool), "rows": F.lit(choice.rows), "memory_bits": F.lit(plan.memory_bits).cast("long")})


def two_pass(updates: DataFrame, keys: list[str], delta: str, eps: float, seed: int = 0) -> DataFrame:
    """A pilot estimate by the small-prime scheme gives the mean frequency for the mean scheme."""
    total = bounds(updates, delta)
    pilot = l0_estimate(updates, keys, delta, choose("small", 0.5, seed, linf=total), seed).first()["estimate"]
    return l0_estimate(updates, keys, delta, choose("above_mean", eps, seed + 1, mean=max(2.0, 2 * total / max(pilot, 1.0))), seed + 1)


def replicated(updates: DataFrame, keys: list[str], delta: str, plan: SketchPlan, replicates: int, by: list[str] | None = None) -> DataFrame:
    """(by..., replicate, row, level, val): sketches under several seeds in one pass.

    States are summed first, as sketches are linear in them, so that a key is hashed once for each seed and not each update."""
    state = states(updates, keys, delta, plan.field, by).where("x <> 0")
    spread = state.withColumn("replicate", F.explode(F.sequence(F.lit(1), F.lit(replicates))))
    return sketch(spread, keys, "x", plan, [*(by or []), "replicate"], seed=F.col("replicate"))


def median_estimate(updates: DataFrame, keys: list[str], delta: str, plan: SketchPlan, replicates: int = 9) -> DataFrame:
    """The median over several seeds: failure falls geometrically with their number."""
    found = estimate(replicated(updates, keys, delta, plan, replicates), plan, ["replicate"])
    return found.agg(F.median("estimate").alias("estimate"), F.count("*").alias("replicates"))


def guarantee(updates: DataFrame, keys: list[str], delta: str, choices: list[Choice], hash: str = "fast") -> DataFrame:
    """(draw, prime, estimate, l0) for several draws of a scheme, each with its own prime and hash seed.  States are summed once."""
    state = states(updates, keys, delta).where("x <> 0")
    truth = state.agg(F.count("*").alias("l0"))
    out = None
    for n, choice in enumerate(choices, 1):
        one = l0_estimate(state, keys, "x", choice, seed=n, hash=hash).select(F.lit(n).alias("draw"), F.col("prime").cast("long").alias("prime"), "estimate")
        out = one if out is None else out.unionByName(one)
    return out.join(F.broadcast(truth))


__all__ = ["Choice", "bounds", "choose", "guarantee", "l0_estimate", "median_estimate", "replicated", "space_bound", "two_pass"]
