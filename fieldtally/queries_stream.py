"""Queries that run Structured Streaming over the given events, each with the SQL of the same in one batch.

Every call works in a fresh folder, so a query may be called again in one application.  Files are read one a batch."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions.algebra import prime_field
from .operators import cells
from .operators.estimate import estimate, sql_estimate
from .plans.sketch_plan import SketchPlan
from .sources.workloads import _EVENT_SQL, _MASKS, table
from .streaming import stream

KEYS = ["user_id", "hour"]
PLAN = SketchPlan(64, prime_field(2), hash="portable")
DAILY = SketchPlan(16, prime_field(2), hash="portable")
SIGNED = SketchPlan(64, prime_field(101), hash="portable")
FILES = 3
_SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string"
#: Far behind all events: a row of this time closes every window but its own, which is therefore never written.
_CLOSING = "2100-01-01"


def _hour() -> Column:
    return F.date_format(F.date_trunc("hour", "ts"), "yyyy-MM-dd HH").alias("hour")


def _source(spark: SparkSession, sf_dir: str, root: str, closing: bool = False) -> DataFrame:
    """The events as a stream of FILES files, by their time; with ``closing`` a last one whose only row is late in time."""
    events = table(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type")
    path = f"{root}/events"
    # Ranges of time, one file each, appended in order, as files are read by age.
    bounds = events.agg(F.percentile_approx(F.unix_timestamp(F.col("ts").cast("timestamp")), [i / FILES for i in range(1, FILES)], 1000).alias("b")).first()["b"] or []
    at = F.unix_timestamp(F.col("ts").cast("timestamp"))
    edges = [None, *bounds, None]
    for low, high in zip(edges, edges[1:], strict=False):
        part = events.where(F.lit(True) if low is None else at >= low).where(F.lit(True) if high is None else at < high)
        part.coalesce(1).write.mode("append").parquet(path)
    if closing:
        last = spark.range(1).select(F.lit(-1).cast("long").alias("event_id"), F.lit(_CLOSING).cast("timestamp_ntz").alias("ts"), F.lit(-1).cast("long").alias("user_id"), F.lit("click").alias("event_type"))
        last.coalesce(1).write.mode("append").parquet(path)
    return spark.readStream.schema(_SCHEMA).option("maxFilesPerTrigger", 1).parquet(path)


def _toggles(events: DataFrame, *more) -> DataFrame:
    return events.select("user_id", _hour(), F.lit(1).cast("long").alias("delta"), *more)


def _batches(spark: SparkSession, sf_dir: str, updates, keys: list[str], plan: SketchPlan, by: list[str] | None = None) -> str:
    """Run updates(events) into batches of cells; returns their folder."""
    root = stream.shared_folder(spark, "stream")
    stream.into_batches(updates(_source(spark, sf_dir, root)), keys, "delta", plan, f"{root}/cells", f"{root}/log", by).trigger(availableNow=True).start().awaitTermination()
    return f"{root}/cells"


def unbounded(spark: SparkSession, sf_dir: str) -> DataFrame:
    root = stream.shared_folder(spark, "unbounded")
    return stream.run_to_table(stream.unbounded(_toggles(_source(spark, sf_dir, root)), KEYS, "delta", PLAN), root, "complete")


def _panes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(pane, row, level, val): a sketch of each day, from a stream with a watermark."""
    root = stream.shared_folder(spark, "windows")
    events = stream.event_time(_source(spark, sf_dir, root, closing=True), "ts", "1 hour")
    found = stream.windowed(_toggles(events, "ts"), KEYS, "delta", DAILY, F.window("ts", "1 day"))
    days = stream.run_to_table(found, root)
    return days.select(F.datediff(F.to_date("window.start"), F.lit("2024-01-01").cast("date")).cast("long").alias("pane"), "row", "level", "val")


def tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return estimate(_panes(spark, sf_dir), DAILY, ["pane"]).select("pane", F.round("estimate", 3).alias("estimate"), "empty_rows")


def sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return estimate(cells.sliding(_panes(spark, sf_dir), DAILY, "pane", 3), DAILY, ["window_end"]).select("window_end", F.round("estimate", 3).alias("estimate"), "empty_rows")


def expiring(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The cells of the days from the tenth on: all days' less the earlier ones'."""
    panes = _panes(spark, sf_dir)
    old = panes.where("pane < 10").drop("pane")
    return stream.expired(cells.roll_up(panes, DAILY), cells.folded(old, DAILY), DAILY)


def sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    root = stream.shared_folder(spark, "sessions")
    mask = F.coalesce(*[F.when(F.col("event_type") == k, v) for k, v in _MASKS.items()], F.lit(0)).cast("long")
    events = stream.event_time(_source(spark, sf_dir, root, closing=True), "ts", "1 hour")
    found = stream.run_to_table(stream.sessions(events, "user_id", "ts", "6 hours", mask), root)
    return found.groupBy("kinds").agg(F.count("*").alias("sessions"), F.sum("n_events").alias("n_events"))


def late(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A tenth of the events never reach the stream; their sketch is added to its cells afterwards."""
    archive = table(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type")
    in_time = F.pmod("event_id", F.lit(10)) != 0
    path = _batches(spark, sf_dir, lambda e: _toggles(e.where(in_time)), KEYS, PLAN)
    missed = stream.late_rows(archive, archive.where(in_time), "event_id")
    return stream.corrected(stream.from_batches(spark, path, PLAN), _toggles(missed), KEYS, "delta", PLAN)


def replayed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every batch is processed twice; the second time it overwrites itself."""
    root = stream.shared_folder(spark, "replayed")
    source = _source(spark, sf_dir, root)
    for attempt in range(2):
        stream.into_batches(_toggles(source), KEYS, "delta", PLAN, f"{root}/cells", f"{root}/log{attempt}").trigger(availableNow=True).start().awaitTermination()
    return stream.from_batches(spark, f"{root}/cells", PLAN)


def deduplicated(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every event is delivered twice, and counted once by its id."""
    root = stream.shared_folder(spark, "deduplicated")
    events = stream.event_time(_source(spark, sf_dir, root), "ts", "1 hour")
    twice = events.withColumn("_copy", F.explode(F.array(F.lit(1), F.lit(2)))).drop("_copy")
    stream.into_batches(_toggles(stream.deduplicated(twice, "event_id")), KEYS, "delta", PLAN, f"{root}/cells", f"{root}/log").trigger(availableNow=True).start().awaitTermination()
    return stream.from_batches(spark, f"{root}/cells", PLAN)


def two_streams(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Clicks and views as two streams: the cells of their difference by user and day."""

    def joined(events: DataFrame) -> DataFrame:
        kind = lambda name: events.where(F.col("event_type") == name).select("user_id", F.to_date("ts").alias("day"), F.lit(1).cast("long").alias("delta"))
        return stream.two_streams(kind("click"), kind("view"))

    return stream.from_batches(spark, _batches(spark, sf_dir, joined, ["user_id", "day"], SIGNED), SIGNED)


def stream_vs_batch(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(side, cells, digest): events sketched as a stream of small batches and as one batch."""
    sides = {"stream": stream.from_batches(spark, _batches(spark, sf_dir, _toggles, KEYS, PLAN), PLAN), "batch": cells.sketch(_toggles(table(spark, sf_dir, "events")), KEYS, "delta", PLAN)}
    out = None
    for name, found in sides.items():
        one = found.agg(F.lit(name).alias("side"), F.count("*").alias("cells"), F.sum(F.col("row") * 1009 + F.col("level") * 7 + F.col("val")).cast("long").alias("digest"))
        out = one if out is None else out.unionByName(one)
    return out


def entries() -> dict:
    from .queries import sql_cells

    hourly = "SELECT user_id, strftime(ts, '%Y-%m-%d %H') AS hour, 1 AS delta, date_diff('day', DATE '2024-01-01', ts::DATE) AS pane FROM events"
    whole = sql_cells(hourly, KEYS, PLAN)
    slid = sql_cells(f"SELECT user_id, hour, pane + unnest(range(0, 3)) AS window_end, delta FROM ({hourly})", KEYS, DAILY, "window_end")
    fresh = f"SELECT user_id, ts, {_EVENT_SQL}::BIGINT AS m, CASE WHEN lag(ts) OVER w IS NULL OR ts >= lag(ts) OVER w + INTERVAL 6 HOUR THEN 1 ELSE 0 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)"
    numbered = f"SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS sid FROM ({fresh})"
    balance = "SELECT user_id, ts::DATE AS day, CASE WHEN event_type = 'click' THEN 1 ELSE -1 END AS delta FROM events WHERE event_type IN ('click', 'view')"
    side = lambda name: f"SELECT '{name}' AS side, count(*) AS cells, sum(row * 1009 + level * 7 + val)::BIGINT AS digest FROM ({whole})"
    return {
        "stream_unbounded": (unbounded, whole),
        "stream_tumbling": (tumbling, sql_estimate(sql_cells(hourly, KEYS, DAILY, "pane"), DAILY, ["pane"])),
        "stream_sliding": (sliding, sql_estimate(slid, DAILY, ["window_end"])),
        "stream_expiring": (expiring, sql_cells(f"SELECT * FROM ({hourly}) WHERE pane >= 10", KEYS, DAILY)),
        "stream_sessions": (sessions, f"SELECT bit_count(m)::BIGINT AS kinds, count(*) AS sessions, sum(n)::BIGINT AS n_events FROM (SELECT bit_xor(m) AS m, count(*) AS n FROM ({numbered}) GROUP BY user_id, sid) GROUP BY 1"),
        "stream_late": (late, whole),
        "stream_replayed": (replayed, whole),
        "stream_deduplicated": (deduplicated, whole),
        "stream_difference": (two_streams, sql_cells(balance, ["user_id", "day"], SIGNED)),
        "stream_vs_batch": (stream_vs_batch, f"{side('stream')} UNION ALL {side('batch')}"),
    }
