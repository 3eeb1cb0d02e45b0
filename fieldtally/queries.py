"""Every method, variant, baseline and measure as a query, with its SQL where SQL can express it."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions import calibrate
from .functions.algebra import binary_field, field_of_order, prime_field, sql_embed, sql_fold, sql_product
from .functions.hashing import sql_placed
from .operators import baselines, cells, exact, l0, measures
from .operators.estimate import estimate, sql_estimate
from .plans import primes
from .plans.sketch_plan import SketchPlan, space_bound
from .sources.workloads import GROUP_FIELDS, WORKLOADS, change_log, group_fields, table, with_groups

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def _plan(q: int, m: int = 64, **more) -> SketchPlan:
    return SketchPlan(m, field_of_order(q), hash="portable", **more)


def sql_cells(source: str, keys: list[str], plan: SketchPlan, by: str = "") -> str:
    """Cells for DuckDB from a subquery of updates."""
    head = f"{by}, " if by else ""
    embedded = f"SELECT * REPLACE ({sql_embed('delta', plan.field)} AS delta) FROM ({source})"
    values = f"SELECT {head}row, level, {sql_product('delta', 'coef', plan.field)} AS v FROM ({sql_placed(embedded, keys, plan, by)}) WHERE delta <> 0"
    return f"SELECT * FROM (SELECT {head}row, level, {sql_fold('v', plan.field)} AS val FROM ({values}) GROUP BY {head}row, level) WHERE val <> 0"


def sql_cells_large(source: str, keys: list[str], plan: SketchPlan, delta_bits: int) -> str:
    """Cells over a binary field without tables, for deltas of few bits: the coefficient's multiples by powers of x, column by column."""
    k = plan.field.k
    low = plan.field.modulus - (1 << k)
    rows = f"SELECT *, coef AS c0 FROM ({sql_placed(source, keys, plan)}) WHERE delta <> 0"
    for i in range(1, delta_bits):
        rows = f"SELECT *, xor((c{i - 1} & {(1 << k - 1) - 1}) << 1, (c{i - 1} >> {k - 1}) * {low}) AS c{i} FROM ({rows})"
    value = "0::BIGINT"
    for i in range(delta_bits):
        value = f"xor({value}, ((delta >> {i}) & 1) * c{i})"
    return f"SELECT * FROM (SELECT row, level, bit_xor({value}) AS val FROM ({rows}) GROUP BY row, level) WHERE val <> 0"


def _rounded(found: DataFrame, by: tuple[str, ...] = (), digits: int = 3) -> DataFrame:
    return found.select(*by, F.round("estimate", digits).alias("estimate"), "empty_rows")


def _narrow(frame: DataFrame, *names: str) -> DataFrame:
    """Exact DECIMAL results as LONG, which the given tables' are."""
    return frame.withColumns({n: F.col(n).cast("long") for n in names})


def _states_sql(w, field=None) -> str:
    keys = ", ".join(w.keys)
    value = "sum(delta)" if field is None else sql_fold(sql_embed("delta", field), field)
    return f"SELECT {keys}, {value} AS x FROM ({w.sql}) WHERE {' AND '.join(f'{k} IS NOT NULL' for k in w.keys)} GROUP BY {keys}"


def _add(name: str, run, sql: str | None = None) -> None:
    QUERIES[name] = run
    if sql:
        ORACLES[name] = sql


def _exact() -> None:
    for w in WORKLOADS.values():
        field = None if w.algebra == "integer" else field_of_order(w.algebra)
        _add(f"exact_{w.name}", lambda s, d, w=w, f=field: exact.exact_support(w.read(s, d), w.keys, "delta", f), f"SELECT count(*) AS n_keys, coalesce(sum(CASE WHEN x <> 0 THEN 1 ELSE 0 END), 0)::BIGINT AS l0 FROM ({_states_sql(w, field)})")
        _add(f"norms_{w.name}", lambda s, d, w=w: _narrow(exact.exact_norms(w.read(s, d), w.keys, "delta"), "l1", "linf"), f"SELECT count(*) AS n_keys, sum(CASE WHEN x <> 0 THEN 1 ELSE 0 END)::BIGINT AS l0, sum(abs(x))::BIGINT AS l1, max(abs(x))::BIGINT AS linf, round(sum(abs(x)) / nullif(sum(CASE WHEN x <> 0 THEN 1 ELSE 0 END), 0), 6) AS mean FROM ({_states_sql(w)})")
    for name, work in (("part", "part_qty"), ("words", "word_diff")):
        w = WORKLOADS[work]
        _add(f"power_mean_{name}", lambda s, d, w=w: exact.power_mean(w.read(s, d), w.keys, "delta", 0.5), f"SELECT round(pow(avg(pow(abs(x)::DOUBLE, 0.5)), 2.0), 6) AS power_mean FROM ({_states_sql(w)}) WHERE x <> 0")
    for name in ("word_diff", "net_qty"):
        w = WORKLOADS[name]
        ranked = f"SELECT abs(x) AS s, row_number() OVER (ORDER BY abs(x) DESC) AS i, floor(count(*) OVER () * 0.05 / 2)::BIGINT AS cut FROM ({_states_sql(w)}) WHERE x <> 0"
        _add(f"discounted_norms_{name}", lambda s, d, w=w: _narrow(exact.discounted_norms(w.read(s, d), w.keys, "delta", 0.05), "l1", "linf"), f"SELECT max(cut) AS cut, sum(CASE WHEN i > cut THEN 1 ELSE 0 END)::BIGINT AS l0, sum(CASE WHEN i > cut THEN s ELSE 0 END)::BIGINT AS l1, max(CASE WHEN i > cut THEN s END)::BIGINT AS linf FROM ({ranked})")


_GRID = [2, 3, 5, 7, 11, 101]


def _primes() -> None:
    grid = ", ".join(f"sum(CASE WHEN x % {p} <> 0 THEN 1 ELSE 0 END)::BIGINT AS l0_mod_{p}" for p in _GRID)
    for name in ("net_qty", "part_qty", "kept_orders", "pair_net", "word_diff", "adversarial"):
        w = WORKLOADS[name]
        _add(f"residue_support_{name}", lambda s, d, w=w: exact.residue_support(w.read(s, d), w.keys, "delta", _GRID), f"SELECT sum(CASE WHEN x <> 0 THEN 1 ELSE 0 END)::BIGINT AS l0, {grid} FROM ({_states_sql(w)})")
    # Pools are drawn from bounds that hold for every size of the given tables, so that both engines see the same primes.
    for name, linf, mean, eps in (("net_qty", 1000, 60, 0.1), ("part_qty", 3000, 800, 0.05), ("word_diff", 20_000, 4, 0.05), ("adversarial", 30_000, 1800, 0.05)):
        w = WORKLOADS[name]
        for scheme, pool in (("max", primes.pool_by_max(linf, eps)), ("mean", primes.pool_by_mean(mean, eps))):
            listed = f"(SELECT unnest({pool}) AS p)"
            gaps = f"SELECT p, count(*) AS l0, sum(CASE WHEN x % p <> 0 THEN 1 ELSE 0 END)::BIGINT AS l0_mod FROM ({_states_sql(w)}) CROSS JOIN {listed} WHERE x <> 0 GROUP BY p"
            _add(f"bad_prime_share_{scheme}_{name}", lambda s, d, w=w, p=pool, e=eps: exact.bad_prime_share(w.read(s, d), w.keys, "delta", p, e), f"SELECT count(*) AS pool, sum(CASE WHEN l0 - l0_mod > {eps} * l0 THEN 1 ELSE 0 END)::BIGINT AS bad, round(avg(CASE WHEN l0 - l0_mod > {eps} * l0 THEN 1 ELSE 0 END), 9) AS share FROM ({gaps})")
            if name == "net_qty":
                _add(f"gap_table_{scheme}_{name}", lambda s, d, w=w, p=pool, e=eps: exact.gap_table(w.read(s, d), w.keys, "delta", p, e), f"SELECT p, l0, l0_mod, round((l0 - l0_mod) / l0, 9) AS gap, CASE WHEN l0 - l0_mod > {eps} * l0 THEN 1 ELSE 0 END AS bad FROM ({gaps})")
    sieve = "WITH n AS (SELECT range AS n FROM range(2, {top})), q AS (SELECT n FROM n WHERE NOT EXISTS (SELECT 1 FROM range(2, {root}) d WHERE d.range < n AND n % d.range = 0)) SELECT n AS p FROM q WHERE n >= {least} ORDER BY n LIMIT {count}"
    pools = {"max": (primes.pool_by_max(344, 0.2), 2), "mean": (primes.pool_by_mean(53.7, 0.1), 53.7), "power": (primes.pool_by_power_mean(31.4, 0.1), 31.4)}
    for name, (pool, least) in pools.items():
        _add(f"prime_pool_{name}", lambda s, d, p=pool: s.createDataFrame([(x,) for x in p], "p long"), sieve.format(top=pool[-1] + 100, root=math.isqrt(pool[-1] + 100) + 2, least=least, count=len(pool)))
    _add("prime_pool_above_max", lambda s, d: s.createDataFrame(group_fields(s, d), "l_returnflag string, l_linenumber int, linf long, p long"), GROUP_FIELDS)


def _sketches() -> None:
    shapes = {"p2": ("toggle_order", 2, 256), "p3": ("kept_orders", 3, 64), "p101": ("kept_orders", 101, 64), "gf32": ("mask_order", 32, 64), "gf128": ("mask_part", 128, 64), "gf256": ("mask_user_day", 256, 64), "gf4": ("label_mask", 4, 16), "gf9": ("gf9_order", 9, 64), "p7_pairs": ("pair_net", 7, 64), "p11_words": ("word_diff", 11, 64), "p5_embedding": ("embedding_cells", 11, 64)}
    for name, (work, q, m) in shapes.items():
        w, plan = WORKLOADS[work], _plan(q, m)
        made = sql_cells(w.sql, w.keys, plan)
        _add(f"field_cells_{name}", lambda s, d, w=w, p=plan: cells.sketch(w.read(s, d), w.keys, "delta", p), made)
        _add(f"field_estimate_{name}", lambda s, d, w=w, p=plan: _rounded(estimate(cells.sketch(w.read(s, d), w.keys, "delta", p), p)), sql_estimate(made, plan))
    w, plan = WORKLOADS["mask_order"], _plan(2**32, 64)
    made = sql_cells_large(w.sql, w.keys, plan, 5)
    _add("field_cells_gf2_32", lambda s, d, w=w, p=plan: cells.sketch(w.read(s, d), w.keys, "delta", p), made)
    _add("field_estimate_gf2_32", lambda s, d, w=w, p=plan: _rounded(estimate(cells.sketch(w.read(s, d), w.keys, "delta", p), p)), sql_estimate(made, plan))
    # A prime beyond 2^31: products and sums in DECIMAL.
    w = WORKLOADS["net_qty"]
    plan = SketchPlan(64, prime_field(primes.above_max(10**12)), hash="portable")
    _add("field_cells_large_prime", lambda s, d, w=w, p=plan: cells.sketch(w.read(s, d), w.keys, "delta", p), sql_cells(w.sql, w.keys, plan))
    w = WORKLOADS["kept_orders"]
    plan = _plan(101, 64)
    bounds = f"SELECT estimate, round(estimate, 3) AS e FROM ({sql_estimate(sql_cells(w.sql, w.keys, plan), plan, digits=9)})"
    _add("field_estimate_bounds", lambda s, d, w=w, p=plan: estimate(cells.sketch(w.read(s, d), w.keys, "delta", p), p).select(*[F.round(c, 3).alias(c) for c in ("estimate", "lo", "hi")], F.round("rse", 6).alias("rse")), f"SELECT e AS estimate, round(greatest(0.0, estimate * {1 - 2 * plan.relative_error!r}), 3) AS lo, round(estimate * {1 + 2 * plan.relative_error!r}, 3) AS hi, round({plan.relative_error!r}::DOUBLE, 6) AS rse FROM ({bounds})")
    packed = lambda s, d, w=w, p=plan: cells.pack_bits(cells.sketch(w.read(s, d), w.keys, "delta", p), p)
    _add("pack_bits_round_trip", lambda s, d, p=plan, f=packed: cells.unpack_bits(f(s, d), p), sql_cells(w.sql, w.keys, plan))
    _add("pack_bits_size", lambda s, d, p=plan, f=packed: f(s, d).select(F.octet_length("bits").cast("long").alias("octets")), f"SELECT {64 * 48 * 7 // 8}::BIGINT AS octets")
    plan = _plan(101, 64, offsets=True)
    _add("field_estimate_offsets", lambda s, d, p=plan: _rounded(estimate(cells.sketch(w.read(s, d), w.keys, "delta", p), p)), sql_estimate(sql_cells(w.sql, w.keys, plan), plan))
    plan = _plan(101, 64)
    asymptotic = calibrate.asymptotic_factor(64, 101)
    _add("field_estimate_asymptotic", lambda s, d, p=plan: _rounded(estimate(cells.sketch(w.read(s, d), w.keys, "delta", p), p, factor="asymptotic")), sql_estimate(sql_cells(w.sql, w.keys, plan), plan, factor=asymptotic))
    plan2 = _plan(2, 256)
    t = WORKLOADS["toggle_order"]
    _add("field_estimate_zero_rule", lambda s, d, p=plan2: _rounded(estimate(cells.sketch(t.read(s, d), t.keys, "delta", p), p, rule="zero")), sql_estimate(sql_cells(t.sql, t.keys, plan2), plan2, rule="zero"))
    c = WORKLOADS["cancelled"]
    _add("cancelled_stream", lambda s, d, p=plan: cells.sketch(c.read(s, d), c.keys, "delta", p).agg(F.count("*").alias("cells")), "SELECT 0::BIGINT AS cells")
    for name in ("page_hosts", "sign_toggle"):
        g = WORKLOADS[name]
        small = _plan(2 if g.algebra == 2 else 101, 64)
        _add(f"empty_row_guard_{name}", lambda s, d, g=g, p=small: estimate(cells.sketch(g.read(s, d), g.keys, "delta", p), p).select("empty_rows", F.col("in_range").cast("int").alias("in_range")), f"SELECT empty_rows, CASE WHEN estimate >= {8 * 64} THEN 1 ELSE 0 END AS in_range FROM ({sql_estimate(sql_cells(g.sql, g.keys, small), small)})")
    # Linear operations.
    y = WORKLOADS["year_diff"]
    plan = _plan(101, 16)
    year = lambda s, d, n: y.read(s, d).where(F.col("delta") == (1 if n == 1997 else -1)).withColumn("delta", F.lit(1).cast("long"))
    both = lambda s, d: [cells.sketch(year(s, d, n), y.keys, "delta", plan) for n in (1997, 1998)]
    _add("merge_cells", lambda s, d: cells.merge(*both(s, d), plan), sql_cells(WORKLOADS["union"].sql, y.keys, plan))
    _add("difference_cells", lambda s, d: cells.difference(*both(s, d), plan), sql_cells(y.sql, y.keys, plan))
    _add("difference_estimate", lambda s, d: _rounded(estimate(cells.difference(*both(s, d), plan), plan)), sql_estimate(sql_cells(y.sql, y.keys, plan), plan))
    _add("scale_cells", lambda s, d: cells.scale(both(s, d)[0], 7, plan), sql_cells(f"SELECT o_custkey, 7 * delta AS delta FROM ({y.sql}) WHERE delta = 1", y.keys, plan))
    _add("pack_unpack", lambda s, d: cells.unpack(cells.pack(cells.difference(*both(s, d), plan))), sql_cells(y.sql, y.keys, plan))
    two, x = _plan(2, 16), WORKLOADS["symdiff"]
    _add("symmetric_difference_estimate", lambda s, d: _rounded(estimate(cells.sketch(x.read(s, d), x.keys, "delta", two), two)), sql_estimate(sql_cells(x.sql, x.keys, two), two))
    _grouped(plan)
    _schemes()


def _grouped(plan: SketchPlan) -> None:
    joined = f"SELECT o_custkey, c_mktsegment, n_name, r_name, CASE WHEN year(o_orderdate) = 1997 THEN 1 ELSE -1 END AS delta FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey WHERE o_orderdate >= TIMESTAMP '1997-01-01' AND o_orderdate < TIMESTAMP '1999-01-01'"

    def rows(s: SparkSession, d: str) -> DataFrame:
        # 25 nations and 5 regions, fixed; customers are joined as the optimizer sees fit.
        nation = table(s, d, "nation").join(F.broadcast(table(s, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
        customer = table(s, d, "customer").join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "c_mktsegment", "n_name", "r_name")
        return WORKLOADS["year_diff"].read(s, d).join(customer, F.col("o_custkey") == F.col("c_custkey"))

    keys = ["o_custkey"]
    _add("grouped_estimate_segment", lambda s, d: _rounded(estimate(cells.sketch(rows(s, d), keys, "delta", plan, ["c_mktsegment"]), plan, ["c_mktsegment"]), ("c_mktsegment",)), sql_estimate(sql_cells(joined, keys, plan, "c_mktsegment"), plan, ["c_mktsegment"]))
    _add("rollup_region_estimate", lambda s, d: _rounded(estimate(cells.roll_up(cells.sketch(rows(s, d), keys, "delta", plan, ["n_name", "r_name"]), plan, ["r_name"]), plan, ["r_name"]), ("r_name",)), sql_estimate(sql_cells(joined, keys, plan, "r_name"), plan, ["r_name"]))

    def cube(s, d):
        fine = cells.sketch(rows(s, d), keys, "delta", plan, ["c_mktsegment", "r_name"])
        every = fine.cube("c_mktsegment", "r_name", "row", "level").agg(F.pmod(F.sum("val"), F.lit(plan.field.p)).alias("val"), F.grouping_id().alias("g")).where("g % 4 = 0 AND val <> 0")
        named = every.select(F.coalesce("c_mktsegment", F.lit("all")).alias("segment"), F.coalesce("r_name", F.lit("all")).alias("region"), "row", "level", "val")
        return _rounded(estimate(named, plan, ["segment", "region"]), ("segment", "region"))

    spread = f"SELECT o_custkey, delta, unnest([c_mktsegment, 'all']) AS segment, r_name FROM ({joined})"
    spread = f"SELECT o_custkey, delta, segment, unnest([r_name, 'all']) AS region FROM ({spread})"
    grouped = sql_cells(f"SELECT o_custkey, delta, segment || '/' || region AS g FROM ({spread})", keys, plan, "g")
    _add("cube_estimate", cube, f"SELECT split_part(g, '/', 1) AS segment, split_part(g, '/', 2) AS region, estimate, empty_rows FROM ({sql_estimate(grouped, plan, ['g'])})")
    k = WORKLOADS["kept_orders"]
    year_sql = "SELECT l_orderkey, year(l_shipdate) AS y, CASE WHEN l_returnflag = 'R' THEN 0 ELSE 1 END AS delta FROM lineitem"
    p64 = _plan(101, 64)
    years = lambda s, d: table(s, d, "lineitem").select("l_orderkey", F.year("l_shipdate").cast("long").alias("y"), F.when(F.col("l_returnflag") == "R", 0).otherwise(1).cast("long").alias("delta"))
    _add("grouped_estimate_ship_year", lambda s, d: _rounded(estimate(cells.sketch(years(s, d), k.keys, "delta", p64, ["y"]), p64, ["y"]), ("y",)), sql_estimate(sql_cells(year_sql, k.keys, p64, "y"), p64, ["y"]))
    panes = "SELECT user_id, strftime(ts, '%Y-%m-%d %H') AS hour, date_diff('day', DATE '2024-01-01', ts::DATE) AS pane, 1 AS delta FROM events"
    days = lambda s, d: table(s, d, "events").select("user_id", F.date_format("ts", "yyyy-MM-dd HH").alias("hour"), F.datediff(F.to_date("ts"), F.lit("2024-01-01").cast("date")).cast("long").alias("pane"), F.lit(1).cast("long").alias("delta"))
    two = _plan(2, 16)
    slid = sql_cells(f"SELECT user_id, hour, pane + unnest(range(0, 3)) AS window_end, delta FROM ({panes})", ["user_id", "hour"], two, "window_end")
    _add("sliding_pane_estimate", lambda s, d: _rounded(estimate(cells.sliding(cells.sketch(days(s, d), ["user_id", "hour"], "delta", two, ["pane"]), two, "pane", 3), two, ["window_end"]), ("window_end",)), sql_estimate(slid, two, ["window_end"]))

    def session_types(s, d):
        from .sources.workloads import _MASKS

        e = table(s, d, "events").select("user_id", F.col("ts").cast("timestamp").alias("ts"), F.coalesce(*[F.when(F.col("event_type") == k, v) for k, v in _MASKS.items()], F.lit(0)).cast("long").alias("m"))
        found = e.groupBy("user_id", F.session_window("ts", "6 hours").alias("w")).agg(F.bit_xor("m").alias("m"), F.count("*").alias("n_events"))
        return found.groupBy(F.bit_count("m").cast("long").alias("kinds")).agg(F.count("*").alias("sessions"), F.sum("n_events").alias("n_events"))

    mask = "CASE event_type WHEN 'click' THEN 1 WHEN 'view' THEN 2 WHEN 'error' THEN 4 WHEN 'purchase' THEN 8 WHEN 'signup' THEN 16 ELSE 0 END"
    marked = f"SELECT user_id, ts, {mask}::BIGINT AS m, CASE WHEN lag(ts) OVER w IS NULL OR ts >= lag(ts) OVER w + INTERVAL 6 HOUR THEN 1 ELSE 0 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)"
    numbered = f"SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS sid FROM ({marked})"
    _add("session_event_types", session_types, f"SELECT bit_count(m)::BIGINT AS kinds, count(*) AS sessions, sum(n)::BIGINT AS n_events FROM (SELECT bit_xor(m) AS m, count(*) AS n FROM ({numbered}) GROUP BY user_id, sid) GROUP BY 1")
    logged = "SELECT o_custkey AS k, o_orderpriority AS v, lag(o_orderpriority) OVER (PARTITION BY o_custkey ORDER BY o_orderkey, o_orderpriority) AS old FROM orders"
    _add("change_log_lag", lambda s, d: exact.exact_support(change_log(table(s, d, "orders"), "o_custkey", "o_orderkey", "o_orderpriority"), ["o_custkey", "value"], "delta"), f"SELECT count(*) AS n_keys, sum(CASE WHEN x <> 0 THEN 1 ELSE 0 END)::BIGINT AS l0 FROM (SELECT k, v, sum(delta) AS x FROM (SELECT k, v, 1 AS delta FROM ({logged}) UNION ALL SELECT k, old, -1 FROM ({logged}) WHERE old IS NOT NULL) GROUP BY k, v)")


#: Scheme -> (workload, bounds that hold for every size of the given tables, so that both engines draw the same primes).
SCHEMES = {
    "small": ("net_qty", {"linf": 1000}), "above_max": ("net_qty", {"linf": 1000}), "above_mean": ("net_qty", {"mean": 60}), "above_power_mean": ("word_diff", {"power_mean": 3}),
    "toggle": ("toggle_order", {}), "wide": ("net_qty", {"linf": 1000}),
    "discount_small": ("word_diff", {"linf": 4}), "discount_above_max": ("word_diff", {"linf": 4}), "discount_above_mean": ("word_diff", {"mean": 2}), "discount_above_power_mean": ("word_diff", {"power_mean": 2}),
}
EPS, DRAWS = 0.3, 5


def _schemes() -> None:
    for scheme, (work, known) in SCHEMES.items():
        w, choices = WORKLOADS[work], [l0.choose(scheme, EPS, n, **known) for n in range(1, DRAWS + 1)]
        choice, toggled = choices[0], scheme == "toggle"
        plan = SketchPlan(choice.rows, prime_field(choice.prime), hash="portable")
        sql = sql_estimate(sql_cells(w.sql, w.keys, plan), plan)
        _add(f"l0_estimate_{scheme}", lambda s, d, w=w, c=choice: l0.l0_estimate(w.read(s, d), w.keys, "delta", c, hash="portable").select(F.round("estimate", 3).alias("estimate"), "empty_rows", F.col("prime").cast("long").alias("prime"), F.col("pool").cast("long").alias("pool")), f"SELECT estimate, empty_rows, {choice.prime}::BIGINT AS prime, {choice.pool}::BIGINT AS pool FROM ({sql})")
        # How often the estimate is within eps of the truth, with the rows that the guarantee asks for.
        drawn = [sql_estimate(sql_cells(w.sql, w.keys, p), p) for p in (SketchPlan(c.rows, prime_field(c.prime), seed=n, hash="portable") for n, c in enumerate(choices, 1))]
        truth = f"SELECT count(*) AS l0 FROM ({_states_sql(w, prime_field(2) if toggled else None)}) WHERE x <> 0"
        within = lambda s, d, w=w, c=choices, t=toggled: l0.guarantee(_toggles(w.read(s, d), w.keys) if t else w.read(s, d), w.keys, "delta", c, "portable").agg(F.count("*").alias("draws"), F.count_if(F.abs(F.col("estimate") - F.col("l0")) <= EPS * F.col("l0")).alias("within"))
        _add(f"l0_guarantee_{scheme}", within, f"SELECT count(*) AS draws, sum(CASE WHEN abs(estimate - l0) <= {EPS} * l0 THEN 1 ELSE 0 END)::BIGINT AS within FROM ({' UNION ALL '.join(f'SELECT estimate FROM ({x})' for x in drawn)}) CROSS JOIN ({truth})")
    w = WORKLOADS["net_qty"]
    _add("l0_two_pass", lambda s, d: l0.two_pass(w.read(s, d), w.keys, "delta", EPS).join(F.broadcast(exact.exact_support(w.read(s, d), w.keys, "delta"))).select("l0", (F.abs(F.col("estimate") - F.col("l0")) <= EPS * F.col("l0")).cast("int").alias("within")), f"SELECT count(*) AS l0, 1 AS within FROM ({_states_sql(w)}) WHERE x <> 0")
    k, nine = WORKLOADS["kept_orders"], SketchPlan(64, prime_field(101), hash="portable")
    _add("l0_median", lambda s, d: l0.median_estimate(k.read(s, d), k.keys, "delta", nine).select(F.round("estimate", 3).alias("estimate"), "replicates"), f"SELECT round(median(estimate), 3) AS estimate, count(*) AS replicates FROM ({sql_estimate(sql_cells_replicated(k.sql, k.keys, nine, 9), nine, ['replicate'], digits=9)})")


def _toggles(updates: DataFrame, keys: list[str]) -> DataFrame:
    """Interleaved inserts and deletes: each key's toggles as 0 or 1, whose support the two-element field counts exactly."""
    return exact.states(updates, keys, "delta", prime_field(2)).withColumnRenamed("x", "delta")


def _baselines() -> None:
    w = WORKLOADS["en_words"]
    plan = _plan(2, 64)
    bits = f"SELECT DISTINCT row, level FROM ({sql_placed(w.sql, w.keys, plan)})"
    _add("bit_table_cells", lambda s, d: baselines.bit_table(w.read(s, d), w.keys, plan), bits)
    first = f"SELECT row, min(l) AS top FROM (SELECT r.range AS row, l.range AS l FROM range(64) r CROSS JOIN range(1, 50) l) g WHERE NOT EXISTS (SELECT 1 FROM ({bits}) b WHERE b.row = g.row AND b.level = g.l) GROUP BY row"
    _add("bit_table_estimate", lambda s, d: baselines.bit_estimate(baselines.bit_table(w.read(s, d), w.keys, plan), plan).select(F.round("estimate", 3).alias("estimate")), f"SELECT round({baselines.FIRST_ZERO_FACTOR * 64!r} * pow(2.0, sum(top) / 64), 3) AS estimate FROM ({first})")
    highest = calibrate.asymptotic_factor(64, math.inf)
    _add("loglog_estimate", lambda s, d: baselines.bit_estimate(baselines.bit_table(w.read(s, d), w.keys, plan), plan, "highest").select(F.round("estimate", 3).alias("estimate")), f"SELECT round({highest!r} * pow(2.0, sum(top) / 64), 3) AS estimate FROM (SELECT row, max(level) AS top FROM ({bits}) GROUP BY row)")
    k = WORKLOADS["kept_orders"]
    kept = f"SELECT DISTINCT row, level FROM ({sql_placed('SELECT * FROM (' + k.sql + ') WHERE delta > 0', k.keys, plan)})"
    _add("set_semantics_estimate", lambda s, d: baselines.bit_estimate(baselines.bit_table(k.read(s, d).where("delta > 0"), k.keys, plan), plan, "highest").select(F.round("estimate", 3).alias("estimate")), f"SELECT round({highest!r} * pow(2.0, sum(top) / 64), 3) AS estimate FROM (SELECT row, max(level) AS top FROM ({kept}) GROUP BY row)")
    seen = lambda s, d: k.read(s, d).agg(F.countDistinct(*k.keys).alias("inserted"))
    # Its registers are this engine's own affair: both sides tell that it counts what was inserted, and so misses the deletions.
    _add("hll_compare", lambda s, d: baselines.hll_estimate(k.read(s, d), k.keys).join(F.broadcast(seen(s, d))).join(F.broadcast(exact.exact_support(k.read(s, d), k.keys, "delta").select("l0"))).select("inserted", "l0", (F.abs(F.col("estimate") - F.col("inserted")) <= 0.05 * F.col("inserted")).cast("int").alias("counts_inserted")), f"SELECT count(*) AS inserted, sum(CASE WHEN x <> 0 THEN 1 ELSE 0 END)::BIGINT AS l0, 1 AS counts_inserted FROM ({_states_sql(k)})")
    old = baselines.prior_plan(0.05, 1000, hash="portable")
    _add("prior_l0", lambda s, d: baselines.prior_l0(k.read(s, d), k.keys, "delta", 0.05, 1000, hash="portable").select(F.round("estimate", 3).alias("estimate")), f"SELECT round(estimate, 3) AS estimate FROM ({baselines.sql_prior_l0(sql_cells(k.sql, k.keys, old), old)})")


def _measures() -> None:
    k = WORKLOADS["kept_orders"]
    plan = SketchPlan(64, prime_field(101), hash="portable")
    # Replicates for the oracle: the seed is part of the hash's tag.
    many = sql_cells_replicated(k.sql, k.keys, plan, 12)
    _add("replicate_estimates", lambda s, d: _rounded(estimate(l0.replicated(k.read(s, d), k.keys, "delta", plan, 12), plan, ["replicate"]), ("replicate",)), sql_estimate(many, plan, ["replicate"]))
    # The support of states modulo the prime, which no kept line count reaches.
    truth = f"(SELECT count(*) FROM ({_states_sql(k)}) WHERE x <> 0)"
    _add("cell_law", lambda s, d: measures.cell_law(l0.replicated(k.read(s, d), k.keys, "delta", plan, 12), plan, exact.exact_support(k.read(s, d), k.keys, "delta"), 12), f"SELECT level, round(n / (64 * 12), 6) AS live, round((1 - exp(-{truth}::DOUBLE * pow(2.0, -level) / 64)) * {calibrate.survival(101)!r}, 6) AS expected FROM (SELECT level, count(*) AS n FROM ({many}) GROUP BY level)")
    five = SketchPlan(64, prime_field(5), hash="portable")
    values = f"SELECT val, count(*) AS n FROM ({sql_cells_replicated(k.sql, k.keys, five, 12)}) GROUP BY val"
    _add("cell_uniformity", lambda s, d: measures.cell_uniformity(l0.replicated(k.read(s, d), k.keys, "delta", five, 12), five), values)
    _add("chi_square", lambda s, d: measures.chi_square(l0.replicated(k.read(s, d), k.keys, "delta", five, 12), five), f"SELECT sum(n)::BIGINT AS cells, round(sum(n * n) * 4.0::DOUBLE / sum(n) - sum(n), 6) AS chi_square, 3 AS degrees FROM ({values})")
    t, two = WORKLOADS["toggle_order"], _plan(2, 256)
    touched = f"SELECT DISTINCT row, level FROM ({sql_placed('SELECT l_orderkey, 1 AS delta FROM (' + _states_sql(t, binary_field(1)) + ') WHERE x <> 0', t.keys, two)})"
    _add("coupled_view", lambda s, d: measures.coupled_view(t.read(s, d), t.keys, "delta", two), f"SELECT level, count(*) AS touched, count(c.val) AS live FROM ({touched}) t LEFT JOIN ({sql_cells(t.sql, t.keys, two)}) c USING (row, level) GROUP BY level")
    # Tables for four fields and for those of the groups of lines.
    four = "SELECT * FROM (VALUES (2::BIGINT, 1::BIGINT), (9, 4), (101, 7), (256, 8)) f(q, b)"
    both = f"SELECT q, b, coalesce(n, 0) AS n FROM ({four} UNION SELECT p, length(bin(p - 1)) FROM ({GROUP_FIELDS})) LEFT JOIN (SELECT p AS q, count(*) AS n FROM ({GROUP_FIELDS}) GROUP BY p) USING (q)"
    _add("memory_bits", lambda s, d: s.createDataFrame([(q, m, SketchPlan(m, field_of_order(q)).memory_bits, n) for q, n in with_groups([2, 9, 101, 256], group_fields(s, d)) for m in (64, 256)], "field_order long, m long, bits long, n_groups long"), f"SELECT q AS field_order, m, m * 48 * b AS bits, n AS n_groups FROM ({both}) CROSS JOIN (VALUES (64::BIGINT), (256)) s(m)")
    _add("space_bounds", lambda s, d: s.createDataFrame([(x, round(space_bound(x, 0.1, 2.0**40, 1000, 50), 3)) for x in ("small", "above_max", "above_mean", "toggle")], "scheme string, bits double"), "SELECT scheme, round(4000 * f, 3) AS bits FROM (VALUES ('small', log2(10) + log2(log2(1000))), ('above_max', log2(1000)), ('above_mean', greatest(log2(50), log2(10))), ('toggle', 1.0)) v(scheme, f)")
    _add("engine_costs", lambda s, d: measures.engine_costs(k.read(s, d), k.keys, "delta", plan), f"SELECT (SELECT count(*) FROM ({k.sql})) AS updates, (SELECT count(*) FROM ({_states_sql(k)})) AS keys, (SELECT count(*) FROM ({sql_cells(k.sql, k.keys, plan)})) AS cells, {64 * 48}::BIGINT AS cell_limit")
    moved = SketchPlan(64, prime_field(101), hash="portable", offsets=True)
    errors = f"SELECT estimate / {truth} - 1 AS e FROM ({sql_estimate(sql_cells_replicated(k.sql, k.keys, moved, 40), moved, ['replicate'], digits=9)})"
    _add("replicate_accuracy", lambda s, d: measures.accuracy(k.read(s, d), k.keys, "delta", moved, 40), f"SELECT count(*) AS replicates, round(avg(e), 6) AS bias, round(stddev_samp(e), 6) AS rse, round(stddev_samp(e) * 8, 6) AS rse_const, {round(moved.relative_error * 8, 6)!r}::DOUBLE AS predicted_const, round(avg(CASE WHEN abs(e) > 0.2 THEN 1.0 ELSE 0.0 END), 6) AS fail_rate FROM ({errors})")


def sql_cells_replicated(source: str, keys: list[str], plan: SketchPlan, replicates: int) -> str:
    spread = f"SELECT * REPLACE ({sql_embed('delta', plan.field)} AS delta), unnest(range(1, {replicates + 1}))::INTEGER AS replicate FROM ({source})"
    values = f"SELECT replicate, row, level, {sql_product('delta', 'coef', plan.field)} AS v FROM ({sql_placed(spread, keys, plan, 'replicate', 'replicate::VARCHAR')}) WHERE delta <> 0"
    return f"SELECT * FROM (SELECT replicate, row, level, {sql_fold('v', plan.field)} AS val FROM ({values}) GROUP BY replicate, row, level) WHERE val <> 0"


for _part in (_exact, _primes, _sketches, _baselines, _measures):
    _part()


from . import queries_analysis, queries_stream  # noqa: E402

for _more in (queries_analysis, queries_stream):
    for _name, (_run, _sql) in _more.entries().items():
        _add(_name, _run, _sql)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders with something kept, from a stream of lines and returns: the sketch beside the truth."""
    w, plan = WORKLOADS["kept_orders"], SketchPlan(64, prime_field(101), hash="portable")
    found = estimate(cells.sketch(w.read(spark, sf_dir), w.keys, "delta", plan), plan)
    return found.join(F.broadcast(exact.exact_support(w.read(spark, sf_dir), w.keys, "delta")))
