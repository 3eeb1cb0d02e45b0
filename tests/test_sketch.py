from decimal import Decimal

import pytest
from pyspark.sql import functions as F

from fieldtally.functions.algebra import field_of_order, prime_field, with_product
from fieldtally.operators import baselines, cells, exact, l0, measures
from fieldtally.operators.estimate import estimate, row_tops
from fieldtally.plans.sketch_plan import SketchPlan

SF = "/root/testdata/sf0.001"


def updates(spark, rows):
    return spark.createDataFrame(rows, "k string, delta long")


def found(frame):
    return sorted(tuple(r) for r in frame.collect())


@pytest.mark.parametrize("q", [2, 3, 8, 9, 101, 2**16])
def test_products_match_the_driver(spark, q):
    field = field_of_order(q)
    pairs = [(i % q, (i * 7 + 3) % q) for i in range(0, min(q * 3, 400))] + [(q - 1, q - 1), (0, 1)]
    got = with_product(spark.createDataFrame(pairs, "a long, b long"), "a", "b", "c", field).collect()
    assert all(r["c"] == field.multiply(r["a"], r["b"]) for r in got)


def test_small_streams(spark):
    support = lambda rows, q=None: exact.exact_support(updates(spark, rows), ["k"], "delta", q and field_of_order(q)).first()["l0"]
    assert support([("a", 3), ("b", 1), ("a", -3)]) == 1
    assert support([("a", 1), ("a", 1), ("b", 1), ("b", 1), ("b", 1)], 2) == 1
    losses = [("a", 6), ("b", 35), ("c", 11)]
    assert support(losses) == 3 and [support(losses, p) for p in (2, 5, 7, 11, 13)] == [2, 2, 2, 2, 3]
    assert support([("a", 5), ("a", 4), ("a", 1), ("b", 2)], 8) == 1
    assert support([("a", 1), ("a", 2), ("b", 3), ("b", 4)], 9) == 1
    assert support([(None, 1), ("a", None), ("a", 0)]) == 0


@pytest.mark.parametrize("q", [2, 3, 9, 101, 256])
def test_linear_in_the_stream(spark, q):
    plan = SketchPlan(8, field_of_order(q))
    rows = [(f"k{i}", 1 + i % (q - 1 or 1)) for i in range(60)]
    whole = cells.sketch(updates(spark, rows), ["k"], "delta", plan)
    left, right = (cells.sketch(updates(spark, part), ["k"], "delta", plan) for part in (rows[:25], rows[25:]))
    assert found(cells.merge(left, right, plan)) == found(whole)
    assert found(cells.difference(whole, right, plan)) == found(left)
    assert cells.difference(whole, whole, plan).count() == 0
    assert found(cells.unpack(cells.pack(whole))) == found(whole)
    if q > 2:
        live = lambda c: sorted((r["row"], r["level"]) for r in c.collect())
        assert live(cells.scale(whole, 2, plan)) == live(whole)


def test_saved_sketches_are_kept_apart_by_plan(spark, tmp_path):
    a, b = SketchPlan(8, field_of_order(3)), SketchPlan(8, field_of_order(5))
    rows = updates(spark, [(f"k{i}", 1) for i in range(40)])
    for plan in (a, b):
        cells.save(cells.sketch(rows, ["k"], "delta", plan), plan, str(tmp_path))
    assert found(cells.load(spark, a, str(tmp_path)).select("row", "level", "val")) == found(cells.sketch(rows, ["k"], "delta", a))


def test_rejects_what_it_cannot_count(spark):
    plan = SketchPlan(8, field_of_order(2))
    with pytest.raises(ValueError):
        cells.sketch(spark.createDataFrame([("a", 1.5)], "k string, delta double"), ["k"], "delta", plan)
    with pytest.raises(ValueError):
        cells.sketch(spark.createDataFrame([({"a": 1}, 1)], "k map<string,int>, delta long"), ["k"], "delta", plan)


def test_extreme_deltas(spark):
    plan = SketchPlan(8, prime_field(101))
    rows = [("a", 2**63 - 1), ("b", -(2**63)), ("c", -1)]
    states = {r["k"]: r["x"] for r in exact.states(updates(spark, rows), ["k"], "delta", plan.field).collect()}
    assert states == {k: v % 101 for k, v in rows}


def test_exact_sums_never_overflow(spark):
    top = 2**63 - 1
    rows = [("a", top), ("a", top), ("a", top), ("b", -top - 1), ("b", -top - 1), ("c", top), ("c", -top), ("d", 1)]
    out = exact.exact_norms(updates(spark, rows), ["k"], "delta").first()
    assert (out["l0"], int(out["l1"]), int(out["linf"])) == (3, 3 * top + 2**64 + 1, 3 * top)
    huge = spark.createDataFrame([("a", Decimal(10**25)), ("b", Decimal(-(10**25))), ("b", Decimal(10**25))], "k string, delta decimal(38,0)")
    assert exact.exact_support(huge, ["k"], "delta").first()["l0"] == 1
    plan = SketchPlan(8, prime_field(101))
    assert cells.sketch(huge.where("k = 'b'"), ["k"], "delta", plan).count() == 0
    assert {r["k"]: r["x"] for r in exact.states(huge, ["k"], "delta", plan.field).collect()} == {"a": 10**25 % 101, "b": 0}


def test_frequencies_of_a_million_millions(spark):
    from fieldtally.plans import primes

    field = prime_field(primes.above_max(10**12))
    assert field.order > 10**12
    rows = [(f"k{i}", 10**12 - i) for i in range(3000)]
    plan = SketchPlan(64, field)
    whole = cells.sketch(updates(spark, rows), ["k"], "delta", plan)
    assert cells.difference(whole, whole, plan).count() == 0
    assert abs(estimate(whole, plan).first()["estimate"] / 3000 - 1) < 0.6
    pairs = [(field.order - 1, field.order - 2), (10**12, 12345)]
    got = with_product(spark.createDataFrame(pairs, "a long, b long"), "a", "b", "c", field).collect()
    assert all(r["c"] == r["a"] * r["b"] % field.order for r in got)


def test_registers_of_log_q_bits(spark):
    for q in (2, 9, 101):
        plan = SketchPlan(5, field_of_order(q), levels=13)
        made = cells.sketch(updates(spark, [(f"k{i}", 1) for i in range(50)]), ["k"], "delta", plan)
        packed = cells.pack_bits(made, plan)
        assert len(packed.first()["bits"]) == -(-plan.memory_bits // 8)
        assert found(cells.unpack_bits(packed, plan)) == found(made)


def test_unbiased_with_the_predicted_spread(spark):
    rows = spark.range(4000).select(F.col("id").alias("k"), F.lit(1).cast("long").alias("delta"))
    for q in (2, 101):
        out = measures.accuracy(rows, ["k"], "delta", SketchPlan(64, field_of_order(q), offsets=True), 200).first()
        assert abs(out["bias"]) < 4 * out["rse"] / 200**0.5
        assert abs(out["rse_const"] / out["predicted_const"] - 1) < 0.2


def test_idealised_construction(spark):
    plan = SketchPlan(4, prime_field(5), levels=14)
    ideal = measures.simulate_ideal(spark, 200, plan, replicates=40, low=-3)
    mean = estimate(ideal, plan, ["replicate"]).agg(F.avg("estimate")).first()[0]
    assert abs(mean / 200 - 1) < 0.4


def test_out_of_range_is_told(spark):
    plan = SketchPlan(64, prime_field(101))
    out = estimate(cells.sketch(updates(spark, [(f"k{i}", 1) for i in range(10)]), ["k"], "delta", plan), plan).first()
    assert not out["in_range"] and out["empty_rows"] > 0
    none = estimate(cells.sketch(updates(spark, []), ["k"], "delta", plan), plan).first()
    assert none["estimate"] == 0 and none["empty_rows"] == 64
    assert row_tops(cells.sketch(updates(spark, [("a", 1)]), ["k"], "delta", plan), plan).count() == 64


def test_baselines_ignore_deletions(spark):
    plan = SketchPlan(64, prime_field(2))
    rows = updates(spark, [(f"k{i}", d) for i in range(4000) for d in ((1, -1) if i % 2 else (1,))])
    kept = l0.l0_estimate(rows, ["k"], "delta", l0.choose("above_max", 0.3, 1, linf=1, rows=256)).first()["estimate"]
    seen = baselines.bit_estimate(baselines.bit_table(rows, ["k"], plan), plan, "highest").first()["estimate"]
    assert abs(kept / 2000 - 1) < 0.35 and seen > 2800
    assert baselines.hll_estimate(rows, ["k"]).first()["estimate"] > 3600


def test_bad_primes_are_few(spark):
    from fieldtally.plans import primes

    rows = spark.createDataFrame([(i, 30 * (1 + i % 50)) for i in range(2000)], "k long, delta long")
    for pool in (primes.pool_by_max(1500, 0.1), primes.pool_by_mean(765, 0.1)):
        assert exact.bad_prime_share(rows, ["k"], "delta", pool, 0.1).first()["share"] <= 0.1


def test_entry(spark):
    import __spark_entry__ as e

    row = e.entry(spark).first()
    assert row["l0"] == 1395 and abs(row["estimate"] / row["l0"] - 1) < 0.6
    assert set(e.oracle_sql()) <= set(e.queries())


def by_sql(name, sf=SF):
    """A query's rows by its SQL."""
    import duckdb

    import __spark_entry__ as e

    con = duckdb.connect()
    for t in ("lineitem", "orders"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return sorted(con.sql(e.oracle_sql()[name]).fetchall())


def on_a_table(spark, name, tmp_path):
    """A query's rows, equal to its SQL's; other rows are found on a tenth of the table's lines and orders."""
    import __spark_entry__ as e

    got = found(e.queries()[name](spark, SF))
    assert got == by_sql(name)
    for t, test in (("lineitem", "l_orderkey < 150"), ("orders", "o_orderkey < 150")):
        spark.read.parquet(f"{SF}/{t}.parquet").where(test).coalesce(1).write.parquet(f"{tmp_path}/{t}.parquet")
    assert found(e.queries()[name](spark, str(tmp_path))) != got
    return got


def test_primes_above_each_groups_largest_frequency(spark, tmp_path):
    got = on_a_table(spark, "prime_pool_above_max", tmp_path)
    assert len(got) == 21 and all(linf < p <= 2 * linf for _, _, linf, p in got)


def groups(spark):
    """Order of a field -> groups of lines that it counts without loss."""
    import collections

    import __spark_entry__ as e

    return collections.Counter(r["p"] for r in e.queries()["prime_pool_above_max"](spark, SF).collect())


def test_constants_of_the_groups_fields(spark, tmp_path):
    got = on_a_table(spark, "constants_table", tmp_path)
    assert {r[0]: r[-1] for r in got if r[-1]} == groups(spark) and {2, 2**32, 0} <= {r[0] for r in got}


def test_error_limits_of_the_groups_fields(spark, tmp_path):
    got = on_a_table(spark, "error_limits", tmp_path)
    assert {r[0]: r[-1] for r in got if r[-1]} == groups(spark) and all(r[1] == 1 for r in got)


def test_finite_factors_of_the_groups_fields(spark, tmp_path):
    got = on_a_table(spark, "finite_factors", tmp_path)
    assert {r[0]: r[-1] for r in got if r[-1]} == groups(spark) and len(got) == 4 * len({r[0] for r in got})


def test_memory_of_the_groups_fields(spark, tmp_path):
    got = on_a_table(spark, "memory_bits", tmp_path)
    assert {r[0]: r[-1] for r in got if r[-1]} == groups(spark) and (101, 64, 64 * 48 * 7) in {r[:3] for r in got}


def test_periodic_part_at_the_parts_supports(spark, tmp_path):
    got = on_a_table(spark, "periodic_part", tmp_path)
    of = {(q, n): e for q, n, _, e in got}
    assert all(abs(e - of[q, 2 * n]) < 2e-7 for (q, n), e in of.items() if (q, 2 * n) in of)
    assert sum(r[2] for r in got) == 5 * spark.read.parquet(f"{SF}/lineitem.parquet").select("l_partkey").distinct().count()


def test_moment_identity_over_the_parts(spark, tmp_path):
    got = on_a_table(spark, "moment_identity", tmp_path)
    assert len(got) == 15 and all(abs(seen - known) < 2e-6 for *_, seen, known in got)
    assert {r[2] for r in got} == {spark.read.parquet(f"{SF}/lineitem.parquet").select("l_partkey").distinct().count()}


def test_field_laws_on_the_orders_residues(spark, tmp_path):
    got = on_a_table(spark, "field_laws", tmp_path)
    assert got == [(q, q, 1, 1) for q in (2, 3, 4, 5, 7, 8, 9, 256)]


def test_orders_of_fields_among_the_quantities(spark, tmp_path):
    from fieldtally.functions.algebra import characteristic, prime_power

    got = on_a_table(spark, "field_orders", tmp_path)
    assert sum(r[2] for r in got) == spark.read.parquet(f"{SF}/lineitem.parquet").count() and len(got) == 128
    for n, p in spark.range(-2, 1100).select("id", characteristic(F.col("id"))).collect():
        try:
            assert prime_power(n)[0] == p
        except ValueError:
            assert p == 0


def test_ideal_construction_counts_the_lines_kinds(spark, tmp_path):
    (row,) = on_a_table(spark, "ideal_construction", tmp_path)
    assert row == (spark.read.parquet(f"{SF}/lineitem.parquet").select("l_quantity", "l_linenumber").distinct().count(), 40, 1)


def test_irreducible_polynomials_of_the_keys_degrees(spark, tmp_path):
    got = on_a_table(spark, "irreducible_polynomials", tmp_path)
    import __spark_entry__ as e

    assert found(e.queries()["rows_for_error"](spark, SF)) == by_sql("rows_for_error")  # registered before it, from names of its own
    assert [(r[0], r[2]) for r in got][:7] == [(2, 0x7), (3, 0xB), (4, 0x13), (5, 0x25), (6, 0x43), (7, 0x83), (8, 0x11B)]


def test_monoids_over_the_parts_lines(spark, tmp_path):
    from fieldtally.functions.algebra import MONOIDS

    got = {r[0]: r[1:] for r in on_a_table(spark, "monoids", tmp_path)}
    assert {n: r[0] for n, r in got.items()} == {m.name: int(m.sketchable) for m in MONOIDS.values()}
    assert got["natural"][1] == got["natural"][2] == got["boolean"][2] > got["toggle"][2] > 0


def test_stream_equals_batch(spark):
    from fieldtally.queries_stream import stream_vs_batch

    for _ in range(2):  # a second call in one application starts afresh
        a, b = stream_vs_batch(spark, SF).collect()
        assert (a["cells"], a["digest"]) == (b["cells"], b["digest"]) and a["cells"] > 0


def test_windows_of_a_stream_equal_a_batch(spark):
    from fieldtally import queries_stream as q

    events = spark.read.parquet(f"{SF}/events.parquet").withColumn("pane", F.datediff(F.to_date("ts"), F.lit("2024-01-01").cast("date")).cast("long"))
    batch = cells.sketch(q._toggles(events, "pane"), q.KEYS, "delta", q.DAILY, ["pane"])
    assert found(q._panes(spark, SF)) == found(batch)


def test_a_cluster_needs_a_shared_folder(spark):
    from types import SimpleNamespace

    from fieldtally.streaming import stream

    remote = SimpleNamespace(conf=SimpleNamespace(get=lambda *_: None), sparkContext=SimpleNamespace(master="spark://far:7077"))
    with pytest.raises(ValueError):
        stream.shared_folder(remote, "x")


def test_sql_functions(spark):
    from fieldtally.functions.sqlfuncs import register

    plan = SketchPlan(16, prime_field(101))
    register(spark, plan)
    rows = spark.range(3000).select(F.col("id").alias("k"), F.lit(1).cast("long").alias("delta"))
    made = cells.sketch(rows, ["k"], "delta", plan)
    made.createOrReplaceTempView("made")
    assert spark.sql("SELECT field_estimate(row, level) AS e FROM made").first()["e"] == pytest.approx(estimate(made, plan).first()["estimate"])
    assert spark.sql("SELECT count(*) AS n FROM prime_pool(344, 0.1)").first()["n"] == 843
