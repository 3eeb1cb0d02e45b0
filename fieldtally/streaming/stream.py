"""One-pass sketches in Structured Streaming.

Cells are additive, so a batch that is replayed would be added twice (and, over the
two-element field, cancel itself).  :func:`into_batches` therefore keys what it writes by batch id
and overwrites, and :func:`deduplicated` drops replays by event id within the watermark.
"""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.cells import difference, folded, merge, sketch
from ..plans.sketch_plan import SketchPlan


def shared_folder(spark: SparkSession, name: str) -> str:
    """A fresh folder under the one that driver and executors share.  Only a local master may do without such a setting."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        import tempfile

        found = f"file://{tempfile.mkdtemp(prefix='fieldtally-')}"
    return f"{found.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def event_time(stream: DataFrame, column: str, delay: str) -> DataFrame:
    """A watermark; local timestamps are cast first, since watermarks need instants."""
    return stream.withColumn(column, F.col(column).cast("timestamp")).withWatermark(column, delay)


def deduplicated(stream: DataFrame, id_column: str) -> DataFrame:
    return stream.dropDuplicatesWithinWatermark([id_column])


def unbounded(updates: DataFrame, keys: list[str], delta: str, plan: SketchPlan) -> DataFrame:
    """Cells over the whole stream (update or complete mode); the state is rows * levels numbers at most."""
    return sketch(updates, keys, delta, plan)


def windowed(updates: DataFrame, keys: list[str], delta: str, plan: SketchPlan, window: Column) -> DataFrame:
    """(window, row, level, val) of tumbling windows, in append mode once the watermark has passed.

    ``window``: F.window(...).  For sliding windows, sketch panes and add them up with ``cells.sliding``."""
    return sketch(updates.withColumn("window", window), keys, delta, plan, ["window"])


def sessions(stream: DataFrame, user: str, time: str, gap: str, mask: Column) -> DataFrame:
    """(session, user, kinds, n_events): how many kinds of event occurred an odd number of times in each session."""
    found = stream.groupBy(F.session_window(time, gap).alias("session"), user).agg(F.bit_xor(mask).alias("mask"), F.count("*").alias("n_events"))
    return found.select("session", user, F.bit_count("mask").cast("long").alias("kinds"), "n_events")


def two_streams(a: DataFrame, b: DataFrame) -> DataFrame:
    """Updates of a, and those of b with their deltas negated: their sketch counts where the two differ."""
    return a.unionByName(b.withColumn("delta", -F.col("delta")))


def into_batches(updates: DataFrame, keys: list[str], delta: str, plan: SketchPlan, path: str, checkpoint: str, by: list[str] | None = None):
    """Start a query that writes the cells of every batch under its id; a replayed batch overwrites itself."""

    def write(batch: DataFrame, batch_id: int) -> None:
        sketch(batch, keys, delta, plan, by).coalesce(1).write.mode("overwrite").parquet(f"{path}/batch_id={batch_id}")

    return updates.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint)


def from_batches(spark: SparkSession, path: str, plan: SketchPlan, first: int | None = None) -> DataFrame:
    """The sketch of all batches written so far, or of those from ``first`` on: expired ones are left out."""
    cells = spark.read.parquet(path)
    return folded(cells if first is None else cells.where(F.col("batch_id") >= first), plan)


def expired(total: DataFrame, old: DataFrame, plan: SketchPlan) -> DataFrame:
    """The running sketch without what has left the window: the old panes are subtracted, none of the others is read."""
    return difference(total, old, plan)


def late_rows(archive: DataFrame, sketched: DataFrame, id_column: str) -> DataFrame:
    """Archived updates that the stream never counted."""
    return archive.join(sketched.select(id_column), id_column, "left_anti")


def corrected(cells: DataFrame, late: DataFrame, keys: list[str], delta: str, plan: SketchPlan) -> DataFrame:
    """Cells with late updates added: order doesn't matter."""
    return merge(cells, sketch(late, keys, delta, plan), plan)


def run_to_table(stream: DataFrame, root: str, mode: str = "append") -> DataFrame:
    """Run a stream over all that is there, and return what it wrote.  In complete mode the last batch's rows stand alone."""
    out, spark = f"{root}/rows", stream.sparkSession
    if mode == "append":
        query = stream.writeStream.format("parquet").option("path", out).outputMode(mode)
    else:
        query = stream.writeStream.foreachBatch(lambda batch, _: batch.write.mode("overwrite").parquet(out)).outputMode(mode)
    query.option("checkpointLocation", f"{root}/log").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)
