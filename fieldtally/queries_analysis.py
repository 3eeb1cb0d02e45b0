"""Queries on the algebra, the calibration and the laws of the sketch, with SQL that computes the same from the formulas."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions import calibrate
from .functions.algebra import MONOIDS, characteristic, field_of_order, find_irreducible, fold, prime_field, sql_fold, with_product
from .operators import cells, measures
from .operators.estimate import estimate, row_tops
from .plans.sketch_plan import SketchPlan
from .sources.workloads import GROUP_FIELDS, PART_SUPPORTS, WORKLOADS, group_fields, part_supports, table, with_groups

ORDERS = [2, 3, 4, 5, 7, 8, 9, 256, 2**32]
SIZES = [16, 64, 256, 1024]
LAWS = [2, 3, 9, 256, math.inf]
REPLICATES = 24
_STEP = 0.05


def field_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(n, characteristic, n_lines): which of the numbers to 128 and of the lines' quantities are orders of fields."""
    asked = table(spark, sf_dir, "lineitem").groupBy(F.floor("l_quantity").cast("long").alias("n")).agg(F.count("*").alias("n_lines")).where("n IS NOT NULL")
    every = asked.unionByName(spark.range(1, 129).select(F.col("id").alias("n"), F.lit(0).cast("long").alias("n_lines"))).groupBy("n").agg(F.sum("n_lines").alias("n_lines"))
    return every.select("n", characteristic(F.col("n")).cast("int").alias("characteristic"), "n_lines")


def field_laws(keys: DataFrame, orders: list[int]) -> DataFrame:
    """(field_order, elements, products_even, sums_even): of the elements that a column of keys leaves modulo each order, whether a*R for
    each a but zero, and a+R for each a, take every value once as R does."""
    key = F.col(keys.columns[0])
    # The table is gone over once: residues of all orders follow from those of their least common multiple.
    left = keys.dropna().select(F.pmod(key, F.lit(math.lcm(*orders))).alias("k")).distinct()
    seen = left.select(F.explode(F.array(*[F.struct(F.lit(q).alias("q"), F.pmod("k", F.lit(q)).cast("long").alias("r")) for q in orders])).alias("e")).select("e.*").distinct().collect()  # at most the sum of the orders
    out = None
    for q in orders:
        field = field_of_order(q)
        have = keys.sparkSession.createDataFrame([(r["r"],) for r in seen if r["q"] == q], "r long")
        pairs = have.select(F.col("r").alias("a")).join(F.broadcast(have))  # at most q * q
        products = with_product(pairs.where("a > 0"), "a", "r", "v", field).groupBy("a", "v").agg(F.count("*").alias("n"))
        sums = pairs.select("a", "r", F.explode(F.array("a", "r")).alias("x")).groupBy("a", "r").agg(fold(F.col("x"), field).alias("v")).groupBy("a", "v").agg(F.count("*").alias("n"))
        even = lambda f, name: f.agg((F.coalesce(F.max("n"), F.lit(1)) == 1).cast("int").alias(name))
        found = have.agg(F.count("*").alias("elements")).where("elements > 0")
        one = found.join(F.broadcast(even(products, "products_even"))).join(F.broadcast(even(sums, "sums_even"))).select(F.lit(q).cast("long").alias("field_order"), "elements", "products_even", "sums_even")
        out = one if out is None else out.unionByName(one)
    return out


def ideal_construction(rows: DataFrame, plan: SketchPlan, replicates: int) -> DataFrame:
    """(support, replicates, unbiased): the distinct rows counted by the idealised construction, and whether the mean of its estimates is
    within four standard errors of the truth."""
    elements = rows.distinct().select(F.struct(*rows.columns).alias("id"))
    found = estimate(measures.ideal_cells(elements, plan, replicates, low=-3), plan, ["replicate"]).agg(F.count("*").alias("replicates"), F.avg("estimate").alias("mean"))
    near = F.abs(F.col("mean") / F.col("support") - 1) < 4 * plan.relative_error / math.sqrt(replicates)
    return elements.agg(F.count("*").alias("support")).join(F.broadcast(found)).select("support", "replicates", near.cast("int").alias("unbiased"))


def irreducible_polynomials(keys: DataFrame) -> DataFrame:
    """(degree, n_keys, modulus): the degrees that keys have as polynomials over two elements, from 2 on, and the smallest irreducible one of each."""
    key = F.col(keys.columns[0])
    asked = keys.where(key >= 4).groupBy((F.length(F.bin(key)) - 1).cast("long").alias("degree")).agg(F.count("*").alias("n_keys")).collect()  # at most 61
    return keys.sparkSession.createDataFrame([(k, n, find_irreducible(2, k)) for k, n in asked], "degree long, n_keys long, modulus long")


#: Monoid -> the lines' deltas for it, its field if it needs one, and both in SQL.
_QUANTITY, _BIT = "CAST(l_quantity AS BIGINT)", "CAST(POW(2, l_linenumber - 1) AS BIGINT)"
_STREAMS = {
    "natural": (_QUANTITY, None, "sum({})"), "integer": (f"CASE WHEN l_returnflag = 'R' THEN -{_QUANTITY} ELSE {_QUANTITY} END", None, "sum({})"),
    "toggle": ("CAST(1 AS BIGINT)", None, "bit_xor({})"), "mask": (_BIT, None, "bit_xor({})"), "boolean": (_BIT, None, "bit_or({})"),
    "cyclic": (f"{_QUANTITY} % 7", 7, None), "group": (f"{_QUANTITY} % 5", 5, None), "field": (f"{_QUANTITY} % 3 + 3 * (l_linenumber % 3)", 9, None),
}


def monoid_states(lines: DataFrame) -> DataFrame:
    """(name, sketchable, parts, live): every monoid, over the parts whose lines it combines, and how many of their states aren't zero."""
    states = lines.groupBy("l_partkey").agg(*[MONOIDS[n].fold(F.expr(delta).cast("long"), q and field_of_order(q)).alias(n) for n, (delta, q, _) in _STREAMS.items()])
    found = states.agg(F.count("*").alias("parts"), *[F.count_if(F.col(n) != 0).alias(n) for n in _STREAMS])
    each = F.explode(F.array(*[F.struct(F.lit(n).alias("name"), F.lit(int(MONOIDS[n].sketchable)).alias("sketchable"), F.col("parts"), F.col(n).alias("live")) for n in _STREAMS])).alias("m")
    return found.select(each).select("m.*")


def _sql_monoids() -> str:
    folds = ", ".join(f"{sql_fold(delta, field_of_order(q)) if q else how.format(delta)} AS s_{n}" for n, (delta, q, how) in _STREAMS.items())
    known = {"boolean": 0, "cyclic": 1, "field": 1, "group": 0, "integer": 1, "mask": 1, "natural": 1, "toggle": 1}
    return f"WITH s AS MATERIALIZED (SELECT l_partkey, {folds} FROM lineitem GROUP BY l_partkey) " + " UNION ALL ".join(f"SELECT '{n}' AS name, {k} AS sketchable, count(*) AS parts, count(*) FILTER (WHERE s_{n} <> 0) AS live FROM s" for n, k in known.items())


def scaled_tops(updates: DataFrame, keys: list[str], factor: int, plan: SketchPlan) -> DataFrame:
    """(n_rows, changed): rows whose highest level another scale of all deltas changes: the law depends on the support alone."""
    tops = [row_tops(cells.sketch(u, keys, "delta", plan), plan).select("row", F.col("top").alias(name)) for name, u in (("a", updates), ("b", updates.withColumn("delta", F.col("delta") * factor)))]
    return tops[0].join(tops[1], "row").agg(F.count("*").alias("n_rows"), F.count_if(F.col("a") != F.col("b")).alias("changed"))


_GROUP_COUNTS = f"SELECT p AS field_order, count(*) AS n FROM ({GROUP_FIELDS}) GROUP BY p"


def _sql_with_groups(query: str) -> str:
    """The same column n_groups, last."""
    return f"SELECT a.*, coalesce(n, 0) AS n_groups FROM ({query}) a LEFT JOIN ({_GROUP_COUNTS}) b USING (field_order)"


def sql_density(orders: list[float], groups: bool = False) -> str:
    """(field_order, z, d): the centred highest position's density on a grid of _STEP, for DuckDB; ``groups``: for the orders of the table's groups too."""
    kinds = ", ".join(f"({0 if math.isinf(q) else int(q)}::BIGINT, {calibrate.survival(q)!r}::DOUBLE)" for q in orders)
    more = f" UNION SELECT field_order, 1.0::DOUBLE - 1.0::DOUBLE / field_order FROM ({_GROUP_COUNTS})" if groups else ""
    grid = f"SELECT i, -40.0::DOUBLE + {_STEP} * i AS z FROM range({round(120 / _STEP) + 1}) t(i)"
    above = "SELECT q, z, sum(ln(greatest(1 - r * (1 - exp(-pow(2.0, -(z + j)))), 1e-300))) AS s FROM f CROSS JOIN g CROSS JOIN range(1, 130) u(j) GROUP BY q, z"
    return f"WITH f AS (SELECT * FROM (VALUES {kinds}) v(q, r){more}), g AS ({grid}), a AS ({above}) SELECT q AS field_order, r, z, r * (1 - exp(-pow(2.0, -z))) * exp(s) AS d FROM a JOIN f USING (q)"


def _sql_moment(t: str) -> str:
    return f"(sum(pow(2.0, {t} * z) * d) * {_STEP} + max(r) * pow(2.0, -(1 - {t}) * 80) / ((1 - {t}) * ln(2.0)))"


def sql_sweep(source: str, keys: list[str], orders: list[int], rows: list[int], replicates: int) -> str:
    """The same as measures.order_sweep."""
    key = "concat_ws('|', " + ", ".join(f"{k}::VARCHAR" for k in keys) + ")"
    digest = lambda tag: f"('0x' || substr(md5('{tag}' || replicate::VARCHAR || '|' || k), 1, 15))::BIGINT"
    odd = [f for f in map(field_of_order, orders) if f.p > 2]
    sums = "".join(f", sum(coef % {f.order} // {f.p**i} % {f.p}) AS s{f.order}_{i}" for f in odd for i in range(f.k))
    live = {f.order: f"x & {f.order - 1} <> 0" if f.p == 2 else " OR ".join(f"s{f.order}_{i} % {f.p} <> 0" for i in range(f.k)) for f in map(field_of_order, orders)}
    found = " UNION ALL ".join(f"SELECT m, replicate, row, level, {q}::BIGINT AS field_order FROM c WHERE {test}" for q, test in live.items())
    shapes = ", ".join(f"({q}::BIGINT, {m}, {factor!r}::DOUBLE, {empty!r}::DOUBLE, {p!r}::DOUBLE)" for q, m, factor, empty, p in measures.sweep_shapes(orders, rows))
    return f"""
WITH u AS (SELECT DISTINCT {key} AS k FROM ({source}) WHERE {' AND '.join(f'{k} IS NOT NULL' for k in keys)}),
r AS (SELECT k, unnest(range(1, {replicates + 1})) AS replicate FROM u),
h AS MATERIALIZED (SELECT replicate, {digest('row')} AS rh, {digest('lev')} AS lh, {digest('coef')} AS coef FROM r),
l AS (SELECT replicate, rh, coef, CASE WHEN lh = 0 THEN 61 ELSE bit_count((lh & -lh) - 1) + 1 END AS level FROM h),
z AS (SELECT replicate, rh % m AS row, m, level, coef FROM l CROSS JOIN (SELECT unnest({rows}) AS m) WHERE level <= 48),
c AS MATERIALIZED (SELECT m, replicate, row, level, bit_xor(coef) AS x{sums} FROM z GROUP BY m, replicate, row, level),
t AS (SELECT field_order, m, replicate, sum(top) AS tops, count(*) AS present FROM (SELECT field_order, m, replicate, row, max(level) AS top FROM ({found}) GROUP BY ALL) GROUP BY ALL),
s AS (SELECT * FROM (VALUES {shapes}) v(field_order, m, factor, empty, predicted_const)),
e AS (SELECT field_order, m, predicted_const, factor * pow(2.0, (tops + (m - present) * empty) / m) / (SELECT count(*) FROM u) - 1 AS e FROM t JOIN s USING (field_order, m))
SELECT field_order, m::INTEGER AS m, round(avg(e), 6) AS bias, round(stddev_samp(e) * sqrt(m::DOUBLE), 6) AS rse_const, predicted_const FROM e GROUP BY field_order, m, predicted_const
"""


def sql_law(orders: list[float], shifts: str) -> str:
    """measures.position_law; ``shifts`` is a subquery."""
    kinds = ", ".join(f"({0 if math.isinf(q) else int(q)}::BIGINT, {calibrate.survival(q)!r}::DOUBLE)" for q in orders)
    live = "r * (1 - exp(-pow(2.0, shift - position)))"
    grid = f"SELECT s.*, field_order, position, {live} AS live FROM (VALUES {kinds}) v(field_order, r) CROSS JOIN ({shifts}) s CROSS JOIN (SELECT j::INTEGER AS position FROM range(-40, 81) w(j))"
    return f"SELECT *, live * exp(coalesce(sum(ln(greatest(1 - live, 1e-300))) OVER (PARTITION BY field_order, support, shift ORDER BY position DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0.0)) AS mass FROM ({grid})"


def brand_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Net lines of ten brands' parts with the supplier's nation: a fact table filtered and grouped by its dimensions."""
    parts = table(spark, sf_dir, "part").where(F.col("p_brand").rlike("^Brand#1[0-9]$")).select("p_partkey")
    suppliers = table(spark, sf_dir, "supplier").select("s_suppkey", F.col("s_nationkey").cast("long").alias("nation"))
    lines = table(spark, sf_dir, "lineitem").select("l_partkey", "l_suppkey", "l_orderkey", F.when(F.col("l_returnflag") == "R", -1).otherwise(1).cast("long").alias("delta"))
    return lines.join(parts, F.col("l_partkey") == F.col("p_partkey"), "left_semi").join(suppliers, F.col("l_suppkey") == F.col("s_suppkey")).withColumn("region", F.pmod("nation", F.lit(5)))


_BRANDS = "SELECT l_orderkey, l_partkey, CASE WHEN l_returnflag = 'R' THEN -1 ELSE 1 END AS delta, s_nationkey % 5 AS region FROM lineitem JOIN supplier ON l_suppkey = s_suppkey WHERE l_partkey IN (SELECT p_partkey FROM part WHERE regexp_matches(p_brand, '^Brand#1[0-9]$'))"


def _values(rows: list[tuple], names: str) -> str:
    return f"SELECT * FROM (VALUES {', '.join('(' + ', '.join(str(v) if not isinstance(v, str) else repr(v) for v in r) + ')' for r in rows)}) v({names})"


def entries() -> dict:
    from .operators.estimate import sql_estimate
    from .queries import sql_cells

    out = {}
    t = WORKLOADS["toggle_order"]
    out["order_sweep"] = (lambda s, d: measures.order_sweep(t.read(s, d), t.keys, ORDERS, SIZES, REPLICATES, "portable"), sql_sweep(t.sql, t.keys, ORDERS, SIZES, REPLICATES))
    every = [*ORDERS, math.inf]
    moments = f"SELECT field_order, sum(z * d) * {_STEP} AS mean, sum(z * z * d) * {_STEP} AS square FROM ({sql_density(every)}) GROUP BY field_order"
    of_groups = moments.replace(sql_density(every), sql_density(every, groups=True))
    out["constants_table"] = (lambda s, d: measures.constants_table(s, with_groups(every, group_fields(s, d))), _sql_with_groups(f"SELECT field_order, round(mean, 4) AS psi_mean, round(square - mean * mean, 4) AS psi_var, round(pow(2.0, -mean), 4) AS factor, round(ln(2.0) * sqrt(square - mean * mean), 4) AS error FROM ({of_groups})"))
    finite = f"SELECT field_order, m, {_sql_moment('(1.0::DOUBLE / m)')} AS one, {_sql_moment('(2.0::DOUBLE / m)')} AS two FROM ({sql_density(ORDERS, groups=True)}) CROSS JOIN (SELECT unnest({SIZES}) AS m) GROUP BY field_order, m"
    shape = lambda q, m: (q, m, round(calibrate.finite_factor(m, q) / m, 6), round(calibrate.variance_ratio(m, q) * m, 3))
    out["finite_factors"] = (lambda s, d: s.createDataFrame([(*shape(q, m), n) for q, n in with_groups(ORDERS, group_fields(s, d)) for m in SIZES], "field_order long, m int, factor_by_m double, variance_by_m double, n_groups long"), _sql_with_groups(f"SELECT field_order, m::INTEGER AS m, round(pow(one, -m), 6) AS factor_by_m, round((pow(one, -2 * m) * pow(two, m) - 1) * m, 3) AS variance_by_m FROM ({finite})"))
    # The fewest rows for an error: enough, and one less isn't.
    asked = [(q, e) for q in (2, 3, 101, 256) for e in (0.3, 0.1)]
    out["rows_for_error"] = (lambda s, d: s.createDataFrame([(q, e, int(calibrate.variance_ratio(m := calibrate.rows_for(e, q), q) <= e * e / 3), int(calibrate.variance_ratio(m - 1, q) > e * e / 3)) for q, e in asked], "field_order long, eps double, enough int, least int"), _values([(q, f"{e}::DOUBLE", 1, 1) for q, e in asked], "field_order, eps, enough, least").replace("'", ""))
    limit = lambda q: (0 if math.isinf(q) else q, int(calibrate.error_constant(q) < calibrate.UNIVERSAL_BOUND), round(calibrate.error_constant(q) - calibrate.error_constant(math.inf), 4))
    out["error_limits"] = (lambda s, d: s.createDataFrame([(*limit(q), n) for q, n in with_groups(every, group_fields(s, d))], "field_order long, below_bound int, above_limit double, n_groups long"), _sql_with_groups(f"SELECT field_order, CASE WHEN ln(2.0) * sqrt(square - mean * mean) < sqrt(79.0) THEN 1 ELSE 0 END AS below_bound, round(ln(2.0) * sqrt(square - mean * mean) - sqrt(pow(ln(2.0), 2) / 12 + pow(pi(), 2) / 6), 4) + 0.0 AS above_limit FROM ({of_groups})"))
    out["shape_density"] = (lambda s, d: s.createDataFrame([(0 if math.isinf(q) else q, float(z), round(calibrate.shape_density(float(z), calibrate.survival(q)), 6)) for q in LAWS for z in range(-4, 9)], "field_order long, z double, density double"), f"SELECT field_order, round(z, 0) AS z, round(d, 6) AS density FROM ({sql_density(LAWS)}) WHERE abs(z - round(z, 0)) < 0.001 AND z > -4.5 AND z < 8.5")
    plan = SketchPlan(64, prime_field(101), hash="portable")
    supports = [1000, 13_972, 139_556]
    out["register_law"] = (lambda s, d: measures.register_law(s, supports, plan), f"SELECT n AS support, i::INTEGER AS level, round((1 - exp(-n * pow(2.0, -i) / 64)) * {calibrate.survival(101)!r}, 9) AS probability FROM (SELECT unnest({supports})::BIGINT AS n) CROSS JOIN range(1, 21) t(i)")
    law = sql_law(LAWS, f"SELECT support, parts, log2(support::DOUBLE) AS shift FROM ({PART_SUPPORTS})")
    out["periodic_part"] = (lambda s, d: measures.periodic_part(part_supports(s, d), LAWS), f"SELECT field_order, support, parts, round(sum(position * mass) - shift, 7) AS excess FROM ({law}) GROUP BY field_order, support, parts, shift")
    thinned = sql_law(LAWS, f"SELECT support, parts, log2(support::DOUBLE) - o / 16.0::DOUBLE AS shift FROM ({PART_SUPPORTS}) CROSS JOIN range(16) t(o)")
    moved = "SELECT field_order, t, support, parts, shift, sum(pow(2.0, t * (position - shift)) * mass) AS m FROM l CROSS JOIN (SELECT unnest([0.015625, 0.25, 0.5])::DOUBLE AS t) GROUP BY field_order, t, support, parts, shift"
    right = " UNION ALL ".join(f"SELECT field_order, {x}::DOUBLE AS t, round({_sql_moment(str(x))}, 6) AS expected FROM d GROUP BY field_order" for x in (0.015625, 0.25, 0.5))
    out["moment_identity"] = (lambda s, d: measures.moment_identity(part_supports(s, d), LAWS, [1 / 64, 0.25, 0.5]), f"WITH l AS ({thinned}), d AS ({sql_density(LAWS)}), m AS ({moved}), e AS ({right}) SELECT field_order, t, (sum(parts) // 16)::BIGINT AS parts, round(sum(m * parts) / sum(parts), 6) AS observed, max(expected) AS expected FROM m JOIN e USING (field_order, t) GROUP BY field_order, t")
    k = WORKLOADS["kept_orders"]
    out["scale_free"] = (lambda s, d: scaled_tops(k.read(s, d), k.keys, 7, plan), "SELECT 64::BIGINT AS n_rows, 0::BIGINT AS changed")
    ideal = SketchPlan(8, prime_field(5), levels=24, offsets=True)
    out["ideal_construction"] = (lambda s, d: ideal_construction(table(s, d, "lineitem").select("l_quantity", "l_linenumber"), ideal, 40), "SELECT count(*) AS support, 40::BIGINT AS replicates, 1 AS unbiased FROM (SELECT DISTINCT l_quantity, l_linenumber FROM lineitem)")
    # The algebra.
    small = [2, 3, 4, 5, 7, 8, 9, 256]
    out["field_laws"] = (lambda s, d: field_laws(table(s, d, "orders").select("o_orderkey"), small), f"SELECT field_order, count(DISTINCT (o_orderkey % field_order + field_order) % field_order) AS elements, 1 AS products_even, 1 AS sums_even FROM orders CROSS JOIN (SELECT unnest({small})::BIGINT AS field_order) WHERE o_orderkey IS NOT NULL GROUP BY field_order")
    numbers = "SELECT n, sum(n_lines)::BIGINT AS n_lines FROM (SELECT floor(l_quantity)::BIGINT AS n, 1 AS n_lines FROM lineitem WHERE l_quantity IS NOT NULL UNION ALL SELECT range, 0 FROM range(1, 129)) GROUP BY n"
    out["field_orders"] = (field_orders, f"WITH n AS ({numbers}), c AS (SELECT unnest(range(2, (SELECT max(n) + 1 FROM n))) AS p), q AS (SELECT p FROM c WHERE NOT EXISTS (SELECT 1 FROM c e WHERE e.p < c.p AND c.p % e.p = 0)) SELECT n, CASE WHEN count(*) = 1 THEN coalesce(max(p), 0) ELSE 0 END::INTEGER AS characteristic, n_lines FROM n LEFT JOIN q ON n % p = 0 AND p <= n GROUP BY n, n_lines")
    # Smallest irreducible polynomials over two elements, of the degrees that the order keys have as such:
    # no smaller one of their degree passes division by all of at most half of it.
    degrees = "SELECT length(bin(o_orderkey)) - 1 AS degree, count(*) AS n_keys FROM orders WHERE o_orderkey >= 4 GROUP BY 1"
    tried = "SELECT (1::BIGINT << degree) + low AS v, degree AS dv FROM k JOIN (SELECT range AS low FROM range(1, 64, 2)) ON low < 1::BIGINT << degree"
    by = "SELECT q, length(bin(q)) - 1 AS dg FROM (SELECT unnest(range(2, (SELECT 1::BIGINT << max(degree) // 2 + 1 FROM k))) AS q)"
    step = "SELECT v, dv, q, dg, CASE WHEN (r >> top) & 1 = 1 THEN xor(r, q << top - dg) ELSE r END, top - 1 FROM w WHERE top >= dg"
    least = "SELECT dv, min(v) AS modulus FROM (SELECT v, dv FROM w WHERE top < dg GROUP BY v, dv HAVING min(CASE WHEN r = 0 THEN 0 ELSE 1 END) = 1) GROUP BY dv"
    out["irreducible_polynomials"] = (lambda s, d: irreducible_polynomials(table(s, d, "orders").select("o_orderkey")), f"WITH RECURSIVE k AS ({degrees}), w(v, dv, q, dg, r, top) AS (SELECT v, dv, q, dg, v, dv FROM ({tried}) JOIN ({by}) ON 2 * dg <= dv UNION ALL {step}) SELECT degree, n_keys, modulus FROM k JOIN ({least}) ON degree = dv")
    out["monoids"] = (lambda s, d: monoid_states(table(s, d, "lineitem")), _sql_monoids())
    # Dimensions.
    out["brand_region_estimate"] = (lambda s, d: estimate(cells.sketch(brand_lines(s, d), ["l_orderkey", "l_partkey"], "delta", plan, ["region"]), plan, ["region"]).select("region", F.round("estimate", 3).alias("estimate"), "empty_rows"), sql_estimate(sql_cells(_BRANDS, ["l_orderkey", "l_partkey"], plan, "region"), plan, ["region"]))
    return out
