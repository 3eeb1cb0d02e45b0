"""Merkle fingerprints of documents, in DataFrame functions only.

A text is cut losslessly: sections at blank lines, paragraphs at line ends, and paragraphs
into leaves (runs of up to 24 characters that don't pass the end of a sentence).  A leaf's
tag is the start of its digest; a paragraph's node digests its leaves' full digests, a
section's node its paragraphs, the root its sections.  The fingerprint is the root followed
by the tags of the leaves in tree order (``.`` between leaves, ``,`` between paragraphs,
``/`` between sections), so that roots test equality and differing branches place an edit.
The likeness of two fingerprints is 1 for equal roots, else the Dice measure of their sets
of leaf tags.

Edge cases: a null text is an empty text, whose fingerprint is a root without tags; two
such fingerprints are equal.  Rows with the same doc_id are ordered by text; a null doc_id
comes last.  With a single row the next document is the row itself.  Columns other than
``doc_id`` and ``text`` are ignored.  An empty table gives an empty table.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import drop_suffix, read_documents

LEAF_PATTERN = "[^.!?]{1,24}|[.!?]+"
TAG = 6
ROWS_PER_BUCKET = 8192
_QUANTILES = 128
_BROADCAST_BUCKETS = 1 << 20


def tree(text: Column) -> Column:
    """sections of paragraphs of leaf digests: array<array<array<string>>>."""
    leaves = lambda p: F.transform(F.regexp_extract_all(p, F.lit(LEAF_PATTERN), F.lit(0)), lambda x: F.md5(x))
    return F.transform(F.split(text, "\n\n", -1), lambda s: F.transform(F.split(s, "\n", -1), leaves))


def _node(children: Column) -> Column:
    return F.md5(F.concat_ws(",", children))


def root(nested: Column) -> Column:
    return _node(F.transform(nested, lambda s: _node(F.transform(s, _node))))


def fingerprint(text: Column) -> Column:
    nested = tree(text)
    tags = F.array_join(F.transform(nested, lambda s: F.array_join(F.transform(s, lambda p: F.array_join(F.transform(p, lambda x: F.substring(x, 1, TAG)), ".")), ",")), "/")
    return F.concat(root(nested), F.lit(":"), tags)


def leaf_tags(print_: Column) -> Column:
    return F.array_distinct(F.regexp_extract_all(F.substring(print_, 34, 1 << 30), F.lit("[0-9a-f]+"), F.lit(0)))


def likeness(a: Column, b: Column) -> Column:
    """1 for equal fingerprints, else the Dice measure of the distinct leaf tags, to 9 digits."""
    x, y = leaf_tags(a), leaf_tags(b)
    both = F.size(F.array_intersect(x, y)) * 2.0
    return F.when(F.substring(a, 1, 32) == F.substring(b, 1, 32), F.lit(1.0)).otherwise(F.round(both / F.greatest(F.size(x) + F.size(y), F.lit(1)), 9))


def differing_paragraphs(a: Column, b: Column) -> Column:
    """Positions (from 0, over all sections) of the paragraphs whose branches differ; extra ones count as differing."""
    cut = lambda p: F.split(F.substring(p, 34, 1 << 30), "[,/]", -1)
    pairs = F.arrays_zip(cut(a).alias("l"), cut(b).alias("r"))
    marked = F.transform(pairs, lambda z, i: F.when(z["l"].eqNullSafe(z["r"]), F.lit(None)).otherwise(i))
    return F.filter(marked, lambda i: i.isNotNull())


def _ordered_buckets(docs: DataFrame) -> tuple[Column, int]:
    """(a bucket number that rises with doc_id and has about ROWS_PER_BUCKET rows, how many there are at most):
    quantiles of the ids, each cut evenly.  Only the id column is read for it."""
    found = docs.agg(F.count("*").alias("n"), F.percentile_approx("doc_id", [i / _QUANTILES for i in range(_QUANTILES + 1)], 2000).alias("q")).first()
    bounds = sorted(set(found["q"] or [0]))
    parts = max(1, -(-found["n"] // (ROWS_PER_BUCKET * max(1, len(bounds) - 1))))
    few = found["n"] <= ROWS_PER_BUCKET * max(1, len(bounds) - 1)
    if few and found["n"]:
        keep = max(1, -(-found["n"] // ROWS_PER_BUCKET))
        bounds = sorted({bounds[i * (len(bounds) - 1) // keep] for i in range(keep + 1)})
    edges = F.array(*[F.lit(int(b)) for b in bounds])
    at = F.greatest(F.size(F.filter(edges, lambda e: e <= F.col("doc_id"))), F.lit(1))
    low = F.element_at(edges, at)
    width = F.element_at(F.array(*[F.lit(float(b - a) or 1.0) for a, b in zip(bounds, [*bounds[1:], bounds[-1] + 1], strict=True)]), at)
    # In DOUBLE: ids of any LONG are ordered alike, and their distances don't overflow.
    inside = F.least(F.floor((F.col("doc_id").cast("double") - low.cast("double")) * F.lit(float(parts)) / width), F.lit(parts - 1))
    found = F.when(F.col("doc_id").isNotNull(), at * F.lit(parts) + F.greatest(inside, F.lit(0))).otherwise(F.lit((len(bounds) + 2) * parts))
    return found.cast("long"), (len(bounds) + 2) * parts


def with_next(docs: DataFrame, carried: list[str]) -> DataFrame:
    """Each row with ``next_<column>`` of the row after it by (doc_id, text), the first one's for the last row.

    Rows meet their successor in buckets of neighbouring ids; each bucket also gets a copy
    of the first row after it, so no global sort and no single task sees all rows."""
    bucket, count = _ordered_buckets(docs)
    # Below the bound the first ids, two numbers for each bucket, are broadcast, and no text moves to find the first rows.
    small = F.broadcast if count <= _BROADCAST_BUCKETS else lambda f: f
    rows = docs.withColumn("bucket", bucket).withColumn("beyond", F.lit(0))
    firsts = rows.groupBy("bucket").agg(F.min("doc_id").alias("doc_id"))
    by_bucket = Window.orderBy("bucket")
    # One row for each bucket, and only numbers: a few MB even for a hundred billion documents.
    links = firsts.select(F.col("bucket").alias("source_bucket"), F.lag("bucket").over(by_bucket).alias("before"), F.max("bucket").over(by_bucket.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("final"))
    links = links.select(F.col("source_bucket"), F.coalesce("before", "final").alias("to_bucket"))
    heads = rows.join(small(firsts.select(F.col("bucket").alias("b"), F.col("doc_id").alias("first"))), (F.col("bucket") == F.col("b")) & F.col("doc_id").eqNullSafe(F.col("first")), "left_semi")
    heads = heads.withColumn("place", F.row_number().over(Window.partitionBy("bucket").orderBy("text"))).where("place = 1").drop("place")
    extra = heads.join(small(links), F.col("bucket") == F.col("source_bucket")).select(*[c for c in docs.columns], F.col("to_bucket").alias("bucket"), F.lit(1).alias("beyond"))
    line = Window.partitionBy("bucket").orderBy("beyond", F.col("doc_id").asc_nulls_last(), "text")
    return rows.unionByName(extra).select("*", *[F.lead(c).over(line).alias(f"next_{c}") for c in carried]).where("beyond = 0").drop("bucket", "beyond")


def fingerprint_documents(docs: DataFrame) -> DataFrame:
    """Fingerprints of every text, of its edited form, and their likenesses to the edited and the next text."""
    rows = drop_suffix(docs, ["doc_id", "text"]).select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    pairs = with_next(rows, ["text"])
    n = F.char_length("text")
    half = F.floor(n / 2).cast("int")
    edited = F.concat(F.substring(F.col("text"), F.lit(1), n - half), F.substring(F.col("next_text"), F.lit(1), half))
    out = pairs.select("doc_id", n.cast("long").alias("n_chars"), edited.alias("edited"), fingerprint(F.col("text")).alias("fingerprint"), fingerprint(F.col("next_text")).alias("next_fingerprint"))
    out = out.select("doc_id", "n_chars", F.sha2(F.col("edited").cast("binary"), 256).alias("edited_sha256"), "fingerprint", fingerprint(F.col("edited")).alias("edited_fingerprint"), "next_fingerprint")
    return out.select("doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", likeness(F.col("fingerprint"), F.col("edited_fingerprint")).alias("near_edited"), likeness(F.col("fingerprint"), F.col("next_fingerprint")).alias("near_next"))


def op9_merkle(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprint_documents(read_documents(spark, sf_dir))


def _sql_print(text: str) -> str:
    leaves = f"list_transform(regexp_extract_all(p, '{LEAF_PATTERN}'), lambda x: md5(x))"
    return f"list_transform(string_split({text}, chr(10) || chr(10)), lambda s: list_transform(string_split(s, chr(10)), lambda p: {leaves}))"


_ROOT = "md5(array_to_string(list_transform(t, lambda s: md5(array_to_string(list_transform(s, lambda p: md5(array_to_string(p, ','))), ','))), ','))"
_TAGS = f"array_to_string(list_transform(t, lambda s: array_to_string(list_transform(s, lambda p: array_to_string(list_transform(p, lambda x: x[1:{TAG}]), '.')), ',')), '/')"


def _sql_like(a: str, b: str) -> str:
    tags = lambda c: f"list_distinct(regexp_extract_all({c}[34:], '[0-9a-f]+'))"
    return f"CASE WHEN {a}[1:32] = {b}[1:32] THEN 1.0 ELSE round(2.0 * len(list_intersect({tags(a)}, {tags(b)})) / greatest(len({tags(a)}) + len({tags(b)}), 1), 9) END"


ORACLE_SQL = f"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS text FROM documents),
n AS (SELECT doc_id, text, coalesce(lead(text) OVER (ORDER BY doc_id, text), first_value(text) OVER (ORDER BY doc_id, text)) AS nxt FROM d),
e AS (SELECT doc_id, length(text) AS n_chars, text, nxt, text[1:length(text) - length(text) // 2] || nxt[1:length(text) // 2] AS edited FROM n),
k AS (SELECT *, {_sql_print('text')} AS ta, {_sql_print('edited')} AS tb, {_sql_print('nxt')} AS tc FROM e),
f AS (SELECT doc_id, n_chars, edited,
  {(_ROOT + " || ':' || " + _TAGS).replace('(t, ', '(ta, ')} AS fa,
  {(_ROOT + " || ':' || " + _TAGS).replace('(t, ', '(tb, ')} AS fb,
  {(_ROOT + " || ':' || " + _TAGS).replace('(t, ', '(tc, ')} AS fc FROM k)
SELECT doc_id, n_chars, sha256(edited) AS edited_sha256, fa AS fingerprint, fb AS edited_fingerprint,
  {_sql_like('fa', 'fb')} AS near_edited, {_sql_like('fa', 'fc')} AS near_next FROM f
"""
