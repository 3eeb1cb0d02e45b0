"""Mixing sources to target weights by iterative proportional fitting, in DataFrame functions only.

Documents fall into cells (source, language, topic).  The cells' token counts are raked,
one marginal after the other, to the target shares of sources, languages and topics; a
document's calibrated probability is the cell's fitted share over its observed share, scaled so
that the expected tokens are ``keep`` of all tokens, with probabilities capped at one and
the rest of the cells scaled up accordingly.  A document is kept if the hash of its id, as
a number in [0, 1), is below its probability.

Targets: tables (value, target) for any of the three columns, or by default the observed
token shares to a power below one, normalised.  Where there is no ``topic`` column, a
document's topic is the form of its text (:func:`form_topic`).

Edge cases: null source, language and text count as empty strings; a null id hashes as an
empty string; repeated ids share one decision; a target for a value that no document has is
left out; cells without tokens keep probability ``keep``; extra columns stay, and columns
named like the computed ones are replaced.  An empty table gives an empty table.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import read_documents, scratch

ROUNDS = 10
KEEP = 0.8
POWERS = {"source": 0.8, "lang": 0.8, "topic": 0.9}
_CELLS_PER_TASK = 200_000
_WORD = "[^\\x20\\x09-\\x0D]+"


def form_topic(text: Column) -> Column:
    """The form of a text: table, listing, symbols, short or prose."""
    size = F.greatest(F.char_length(text), F.lit(1))
    lines = F.regexp_count(text, F.lit("\n"))
    return (
        F.when(F.regexp_count(text, F.lit("[|]")) * 20 > size, F.lit("table"))
        .when(F.regexp_count(text, F.lit("[#$%&*!<>{}=]")) * 20 > size, F.lit("symbols"))
        .when(lines * 60 > size, F.lit("listing"))
        .when(size < 400, F.lit("short"))
        .otherwise(F.lit("prose"))
    )


def uniform(doc_id: Column, seed: str) -> Column:
    """A number in [0, 1) from the id: 52 bits of a digest."""
    digest = F.md5(F.concat(F.lit(f"{seed}|"), F.coalesce(doc_id.cast("string"), F.lit(""))))
    return F.conv(F.substring(digest, 1, 13), 16, 10).cast("double") / F.lit(float(1 << 52))


def _with_targets(cells: DataFrame, column: str, given: DataFrame | None, power: float) -> DataFrame:
    value = Window.partitionBy(column)
    observed = F.sum("tokens").over(value)
    if given is None:
        # The same for each cell of a value; normalised over the values below.
        cells = cells.withColumn("_raw", F.pow(observed.cast("double"), F.lit(power)))
    else:
        # Cells number far fewer than documents, and targets at most one row for each value.
        found = given.groupBy(F.col("value").alias(column)).agg(F.max("target").cast("double").alias("_raw"))
        cells = cells.join(found, column, "left").withColumn("_raw", F.coalesce("_raw", F.lit(0.0)))
    share = F.col("_raw") / F.count("*").over(value)
    total = F.sum("_share").over(Window.partitionBy(F.lit(1)))
    return cells.withColumn("_share", share).withColumn(f"_t_{column}", F.coalesce(F.try_divide("_raw", total), F.lit(0.0))).drop("_raw", "_share")


def fit_cells(cells: DataFrame, targets: dict[str, DataFrame] | None = None, rounds: int = ROUNDS, keep: float = KEEP, powers: dict[str, float] | None = None) -> DataFrame:
    """(source, lang, topic, tokens) -> the same with ``fitted`` (share), ``probability`` and ``marginal_error``: the
    largest gap between a value's fitted share and its target, the same in every row, by which convergence is told."""
    spark, targets, powers = cells.sparkSession, targets or {}, powers or POWERS
    tasks = max(1, -(-cells.count() // _CELLS_PER_TASK))
    one = tasks == 1  # a single task then holds all cells, and no step needs an exchange
    cells = cells.coalesce(1) if one else cells
    for column in POWERS:
        cells = _with_targets(cells, column, targets.get(column), powers[column])
    cells = cells.withColumn("fitted", F.col("tokens").cast("double"))
    if not one:
        cells = scratch(spark, cells, "cells")
    for _ in range(rounds):
        for column in POWERS:
            now = F.sum("fitted").over(Window.partitionBy(column))
            cells = cells.withColumn("fitted", F.when(now > 0, F.col("fitted") * F.col(f"_t_{column}") / now).otherwise(F.lit(0.0)))
        if not one:
            cells = scratch(spark, cells, "cells")
    everything = Window.partitionBy(F.lit(1))
    # How far the fitted shares of any value are from its target after the last round.
    gaps = [F.abs(F.sum("fitted").over(Window.partitionBy(c)) - F.col(f"_t_{c}")) for c in POWERS]
    cells = cells.withColumn("_gap", F.greatest(*gaps)).withColumn("_gap", F.max("_gap").over(everything))
    cells = cells.withColumn("_all", F.sum("tokens").over(everything)).withColumn("_ratio", F.when(F.col("tokens") > 0, F.col("fitted") / F.col("tokens")))
    before = Window.partitionBy(F.lit(1)).orderBy(F.col("_ratio").desc_nulls_last(), "source", "lang", "topic")
    # With the cells of largest ratio saturated, the scale that spends the rest of the token budget on the others.
    cells = cells.withColumn("_full", F.sum("tokens").over(before.rowsBetween(Window.unboundedPreceding, -1))).withColumn("_full", F.coalesce("_full", F.lit(0)))
    cells = cells.withColumn("_open", F.sum("fitted").over(before.rowsBetween(0, Window.unboundedFollowing)))
    scale = F.when(F.col("_open") > 0, (F.lit(keep) * F.col("_all") - F.col("_full")) / F.col("_open"))
    fits = F.when((scale * F.col("_ratio") <= 1.0) & (scale >= 0), scale)
    cells = cells.withColumn("_scale", F.max(fits).over(everything))
    p = F.when(F.col("_ratio").isNull(), F.lit(keep)).otherwise(F.least(F.lit(1.0), F.coalesce(F.col("_scale"), F.lit(1e300)) * F.col("_ratio")))
    return cells.select("source", "lang", "topic", "tokens", "n_documents", F.round(F.col("fitted"), 9).alias("fitted"), F.round(p, 9).alias("probability"), F.round("_gap", 7).alias("marginal_error"))


def _featured(docs: DataFrame) -> DataFrame:
    text = F.coalesce("text", F.lit(""))
    topic = F.coalesce(F.col("topic").cast("string"), F.lit("")) if "topic" in docs.columns else form_topic(text)
    return docs.select("*", F.struct(F.coalesce("source", F.lit("")).alias("source"), F.coalesce("lang", F.lit("")).alias("lang"), topic.alias("topic"), F.regexp_count(text, F.lit(_WORD)).cast("long").alias("tokens")).alias("_cell"))


def mix(docs: DataFrame, targets: dict[str, DataFrame] | None = None, rounds: int = ROUNDS, keep: float = KEEP, seed: str = "mix", powers: dict[str, float] | None = None) -> DataFrame:
    """All rows with ``_mix``: struct(source, lang, topic, tokens, probability, marginal_error, kept)."""
    spark = docs.sparkSession
    rows = _featured(docs)
    cells = rows.groupBy("_cell.source", "_cell.lang", "_cell.topic").agg(F.sum("_cell.tokens").alias("tokens"), F.count("*").alias("n_documents"))
    fitted = scratch(spark, fit_cells(scratch(spark, cells, "cells"), targets, rounds, keep, powers), "fitted")
    key = F.struct("source", "lang", "topic")
    known = fitted.select(key.alias("_key"), "probability", "marginal_error")
    return (
        rows.join(known, F.struct("_cell.source", "_cell.lang", "_cell.topic") == F.col("_key"), "left")
        .withColumn("_mix", F.struct("_cell.source", "_cell.lang", "_cell.topic", "_cell.tokens", "probability", "marginal_error", (uniform(F.col("doc_id"), seed) < F.col("probability")).alias("kept")))
        .drop("_cell", "_key", "probability", "marginal_error")
    )


def sample(docs: DataFrame, **options) -> DataFrame:
    """Only the kept documents, with their own columns."""
    return mix(docs, **options).where("_mix.kept").drop("_mix")


def op10_raking(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_documents(spark, sf_dir).select("doc_id", "text", "lang", "source")
    out = mix(docs)
    return out.select("doc_id", F.col("_mix.source").alias("source"), F.col("_mix.lang").alias("lang"), F.col("_mix.topic").alias("topic"), F.col("_mix.tokens").alias("n_tokens"), F.col("_mix.probability").alias("probability"), F.col("_mix.marginal_error").alias("marginal_error"), F.col("_mix.kept").cast("int").alias("kept"))


def oracle_sql(rounds: int = ROUNDS, keep: float = KEEP, seed: str = "mix", source: str = "documents") -> str:
    """The same computation in DuckDB's SQL, the rounds written out one after the other."""
    count = lambda p: f"len(regexp_extract_all(text, '{p}'))"
    topic = f"CASE WHEN {count('[|]')} * 20 > size THEN 'table' WHEN {count('[#$%&*!<>{}=]')} * 20 > size THEN 'symbols' WHEN {count(chr(10))} * 60 > size THEN 'listing' WHEN size < 400 THEN 'short' ELSE 'prose' END"
    steps = [
        f"d AS (SELECT doc_id, coalesce(text, '') AS text, coalesce(lang, '') AS lang, coalesce(source, '') AS source, greatest(length(coalesce(text, '')), 1) AS size FROM {source})",
        f"r AS MATERIALIZED (SELECT doc_id, source, lang, {topic} AS topic, len(regexp_extract_all(text, '[^\\x20\\x09-\\x0D]+')) AS tokens FROM d)",
        "c AS (SELECT source, lang, topic, sum(tokens) AS tokens FROM r GROUP BY ALL)",
    ]
    for name, power in POWERS.items():
        steps.append(f"m_{name} AS (SELECT {name}, v / sum(v) OVER () AS t FROM (SELECT {name}, pow(sum(tokens)::DOUBLE, {power}) AS v FROM c GROUP BY 1))")
    steps.append("f0 AS MATERIALIZED (SELECT c.*, c.tokens::DOUBLE AS fitted, ms.t AS ts, ml.t AS tl, mt.t AS tt FROM c JOIN m_source ms USING (source) JOIN m_lang ml USING (lang) JOIN m_topic mt USING (topic))")
    at = 0
    for _ in range(rounds):
        for name in POWERS:
            steps.append(f"f{at + 1} AS MATERIALIZED (SELECT * REPLACE (CASE WHEN sum(fitted) OVER (PARTITION BY {name}) > 0 THEN fitted * t{name[0]} / sum(fitted) OVER (PARTITION BY {name}) ELSE 0 END AS fitted) FROM f{at})")
            at += 1
    order = "ORDER BY ratio DESC NULLS LAST, source, lang, topic"
    gaps = ", ".join(f"abs(sum(fitted) OVER (PARTITION BY {name}) - t{name[0]})" for name in POWERS)
    steps += [
        f"g AS (SELECT *, CASE WHEN tokens > 0 THEN fitted / tokens END AS ratio, sum(tokens) OVER () AS al, greatest({gaps}) AS gap FROM f{at})",
        f"h AS (SELECT *, coalesce(sum(tokens) OVER ({order} ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS ful, sum(fitted) OVER ({order} ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS ope FROM g)",
        f"i AS (SELECT *, CASE WHEN ope > 0 THEN ({keep} * al - ful) / ope END AS sc FROM h)",
        "j AS (SELECT *, max(CASE WHEN sc * ratio <= 1.0 AND sc >= 0 THEN sc END) OVER () AS best, max(gap) OVER () AS worst FROM i)",
        f"k AS (SELECT source, lang, topic, round(CASE WHEN ratio IS NULL THEN {keep} ELSE least(1.0, coalesce(best, 1e300) * ratio) END, 9) AS probability, round(worst, 7) AS marginal_error FROM j)",
    ]
    return f"WITH {', '.join(steps)} SELECT doc_id, source, lang, topic, tokens AS n_tokens, probability, marginal_error, CAST((('0x' || substr(md5('{seed}|' || coalesce(doc_id::VARCHAR, '')), 1, 13))::BIGINT)::DOUBLE / {float(1 << 52)} < probability AS INTEGER) AS kept FROM r JOIN k USING (source, lang, topic)"
