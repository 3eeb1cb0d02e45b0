"""Placement of elements: row, level, coefficient and thinning, each from its own hash.

'fast' takes xxhash64 with four seeds; 'portable' 60 bits of an md5 of a tag and the key's
text, which other engines compute alike.  Levels start at 1: level j has probability 2^-j.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.sketch_plan import SketchPlan

_POSITIVE = (1 << 63) - 1


def key_text(keys: list[str]) -> Column:
    return F.concat_ws("|", *[F.col(k).cast("string") for k in keys])


def _hash(tag: str, keys: list[str], plan: SketchPlan, seed: Column | None) -> Column:
    if plan.hash == "fast":
        salt = F.lit(f"{tag}/{plan.seed}")
        return F.xxhash64(salt, *([seed] if seed is not None else []), *[F.col(k) for k in keys]).bitwiseAND(F.lit(_POSITIVE))
    name = tag if plan.seed == 0 else f"{tag}{plan.seed}"
    head = F.lit(f"{name}|") if seed is None else F.concat(F.lit(name), seed.cast("string"), F.lit("|"))
    return F.conv(F.substring(F.md5(F.concat(head, key_text(keys))), 1, 15), 16, 10).cast("long")


def _sql_hash(tag: str, key: str, plan: SketchPlan, seed: str | None) -> str:
    name = tag if plan.seed == 0 else f"{tag}{plan.seed}"
    head = f"'{name}|'" if seed is None else f"'{name}' || {seed} || '|'"
    return f"('0x' || substr(md5({head} || {key}), 1, 15))::BIGINT"


def level_of(h: Column, plan: SketchPlan) -> Column:
    """One more than the zeros at the end of the hash; a hash of zero falls beyond every cap."""
    return F.when(h == 0, F.lit(61)).otherwise(F.bit_count(h.bitwiseAND(-h) - 1) + 1)


def placed(frame: DataFrame, keys: list[str], plan: SketchPlan, seed: Column | None = None) -> DataFrame:
    """Adds row, level and coef; drops what is thinned away by its row's offset.  Levels beyond the cap are the caller's to drop, behind its aggregation."""
    out = frame.withColumns({
        "row": F.pmod(_hash("row", keys, plan, seed), F.lit(plan.rows)).cast("int"),
        "level": level_of(_hash("lev", keys, plan, seed), plan).cast("int"),
        "coef": F.pmod(_hash("coef", keys, plan, seed), F.lit(plan.field.order)).cast("long"),
    })
    if plan.offsets:
        kept = F.get(F.array(*[F.lit(t).cast("long") for t in plan.thresholds()]), F.col("row"))
        out = out.where(_hash("thin", keys, plan, seed).bitwiseAND(F.lit((1 << 52) - 1)) < kept)
    return out


def hash_parts(frame: DataFrame, keys: list[str], plan: SketchPlan, seed: Column | None = None) -> DataFrame:
    """Adds row_hash, level and coef_hash: what a row and a coefficient are the remainders of, for several sizes and fields at once."""
    return frame.withColumns({
        "row_hash": _hash("row", keys, plan, seed),
        "level": level_of(_hash("lev", keys, plan, seed), plan).cast("int"),
        "coef_hash": _hash("coef", keys, plan, seed),
    })


def sql_placed(source: str, keys: list[str], plan: SketchPlan, carried: str = "", seed: str | None = None) -> str:
    """The same for DuckDB, over a subquery ``source`` with the keys, delta and the carried columns."""
    if plan.hash != "portable":
        raise ValueError("only the portable hash has a counterpart in SQL")
    key = "concat_ws('|', " + ", ".join(f"{k}::VARCHAR" for k in keys) + ")"
    head = f"{carried}, " if carried else ""
    thin = f" AND ({_sql_hash('thin', 'k', plan, seed)} & {(1 << 52) - 1}) < ({plan.thresholds()})[row + 1]" if plan.offsets else ""
    inner = f"SELECT {head}delta, {key} AS k FROM ({source})"
    middle = f"SELECT {head}delta, k, {_sql_hash('row', 'k', plan, seed)} % {plan.rows} AS row, {_sql_hash('lev', 'k', plan, seed)} AS lh, {_sql_hash('coef', 'k', plan, seed)} % {plan.field.order} AS coef FROM ({inner}) WHERE k IS NOT NULL"
    return f"SELECT {head}delta, row::INTEGER AS row, (CASE WHEN lh = 0 THEN 61 ELSE bit_count((lh & -lh) - 1) + 1 END)::INTEGER AS level, coef FROM ({middle}) WHERE (CASE WHEN lh = 0 THEN 61 ELSE bit_count((lh & -lh) - 1) + 1 END) <= {plan.levels}{thin}"
