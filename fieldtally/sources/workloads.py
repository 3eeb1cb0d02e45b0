"""Update streams on the given tables: each a DataFrame of keys and ``delta``, and the same in SQL for the exact oracle.

Only the columns a stream needs are read; filters on dates and languages reach the scan.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.primes import above_max

@dataclass(frozen=True)
class Workload:
    name: str
    keys: list[str]
    read: Callable[[SparkSession, str], DataFrame]
    sql: str
    #: 'integer', or the order of the field that its deltas are elements of
    algebra: str | int = "integer"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _long(c: Column) -> Column:
    return c.cast("long")


def _lines(key: list[str], delta: Callable[[], Column]):
    return lambda s, d: table(s, d, "lineitem").select(*key, _long(delta()).alias("delta"))


def _kept(s, d):
    lines = table(s, d, "lineitem")
    back = lines.where("l_returnflag = 'R'")
    return lines.select("l_orderkey", _long(F.lit(1)).alias("delta")).unionByName(back.select("l_orderkey", _long(F.lit(-1)).alias("delta")))


def _quantity(sign: bool = True) -> Column:
    q = _long(F.col("l_quantity"))
    return F.when(F.col("l_returnflag") == "R", -q).otherwise(q) if sign else q


def _years(s, d, delta: Callable[[Column], Column], distinct: bool = False):
    orders = table(s, d, "orders").where((F.col("o_orderdate") >= F.lit("1997-01-01").cast("timestamp_ntz")) & (F.col("o_orderdate") < F.lit("1999-01-01").cast("timestamp_ntz")))
    rows = orders.select("o_custkey", F.year("o_orderdate").alias("y"))
    rows = rows.distinct() if distinct else rows
    return rows.select("o_custkey", _long(delta(F.col("y"))).alias("delta"))


def _words(text: Column) -> Column:
    return F.explode(F.split(F.lower(text), " "))


def _turns(s, d):
    words = F.explode(F.regexp_extract_all(F.lower("text"), F.lit("[^\\s\\.,]+"), F.lit(0)))
    return table(s, d, "conversations").select(_long(F.when(F.col("role") == "user", 1).otherwise(-1)).alias("delta"), words.alias("word"))


def _against_benchmark(s, d):
    own = table(s, d, "documents").where("source = 'src0'").select(_words(F.col("text")).alias("word"), _long(F.lit(1)).alias("delta"))
    return own.unionByName(table(s, d, "benchmark").select(_words(F.col("text")).alias("word"), _long(F.lit(-1)).alias("delta")))


def _line_difference(s, d):
    docs = table(s, d, "documents").select("text", "source")
    first = docs.agg(F.min("source").alias("first"))  # one row
    return docs.join(F.broadcast(first)).select(_long(F.when(F.col("source") == F.col("first"), 1).otherwise(-1)).alias("delta"), F.explode(F.split("text", "\n")).alias("line"))


_MASKS = {"click": 1, "view": 2, "error": 4, "purchase": 8, "signup": 16}


def _event_mask(s, d):
    mask = F.coalesce(*[F.when(F.col("event_type") == k, v) for k, v in _MASKS.items()], F.lit(0))
    return table(s, d, "events").select("user_id", F.to_date("ts").alias("day"), _long(mask).alias("delta"))


def _flag_mask() -> Column:
    flag = F.when(F.col("l_returnflag") == "A", 1).when(F.col("l_returnflag") == "N", 2).otherwise(4)
    return flag.bitwiseXOR(F.when(F.col("l_linestatus") == "F", 8).otherwise(16))


def _coordinates(s, d):
    return table(s, d, "embeddings").select("vec_id", "label", F.posexplode("embedding").alias("dim", "v"))


_TWO_YEARS = "o_orderdate >= TIMESTAMP '1997-01-01' AND o_orderdate < TIMESTAMP '1999-01-01'"
_FLAG_SQL = "xor(CASE l_returnflag WHEN 'A' THEN 1 WHEN 'N' THEN 2 ELSE 4 END, CASE l_linestatus WHEN 'F' THEN 8 ELSE 16 END)"
_EVENT_SQL = "CASE event_type " + " ".join(f"WHEN '{k}' THEN {v}" for k, v in _MASKS.items()) + " ELSE 0 END"
_QTY_SQL = "CASE WHEN l_returnflag = 'R' THEN -(l_quantity::BIGINT) ELSE l_quantity::BIGINT END"

WORKLOADS = {
    w.name: w
    for w in (
        Workload("toggle_order", ["l_orderkey"], _lines(["l_orderkey"], lambda: F.lit(1)), "SELECT l_orderkey, 1 AS delta FROM lineitem", 2),
        Workload("toggle_part", ["l_partkey"], _lines(["l_partkey"], lambda: F.lit(1)), "SELECT l_partkey, 1 AS delta FROM lineitem", 2),
        Workload("mask_order", ["l_orderkey"], _lines(["l_orderkey"], _flag_mask), f"SELECT l_orderkey, {_FLAG_SQL} AS delta FROM lineitem", 32),
        Workload("mask_part", ["l_partkey"], _lines(["l_partkey"], lambda: F.expr("shiftleft(1L, l_linenumber - 1)")), "SELECT l_partkey, (1::BIGINT << (l_linenumber - 1)) AS delta FROM lineitem", 128),
        Workload("mask_user_day", ["user_id", "day"], _event_mask, f"SELECT user_id, ts::DATE AS day, {_EVENT_SQL} AS delta FROM events", 32),
        Workload("kept_orders", ["l_orderkey"], _kept, "SELECT l_orderkey, 1 AS delta FROM lineitem UNION ALL SELECT l_orderkey, -1 FROM lineitem WHERE l_returnflag = 'R'"),
        Workload("net_qty", ["l_orderkey"], _lines(["l_orderkey"], _quantity), f"SELECT l_orderkey, {_QTY_SQL} AS delta FROM lineitem"),
        Workload("part_qty", ["l_partkey"], _lines(["l_partkey"], lambda: _quantity(False)), "SELECT l_partkey, l_quantity::BIGINT AS delta FROM lineitem"),
        Workload("pair_net", ["l_partkey", "l_suppkey"], _lines(["l_partkey", "l_suppkey"], lambda: F.when(F.col("l_returnflag") == "R", -1).otherwise(1)), "SELECT l_partkey, l_suppkey, CASE WHEN l_returnflag = 'R' THEN -1 ELSE 1 END AS delta FROM lineitem"),
        Workload("year_diff", ["o_custkey"], lambda s, d: _years(s, d, lambda y: F.when(y == 1997, 1).otherwise(-1)), f"SELECT o_custkey, CASE WHEN year(o_orderdate) = 1997 THEN 1 ELSE -1 END AS delta FROM orders WHERE {_TWO_YEARS}"),
        Workload("symdiff", ["o_custkey"], lambda s, d: _years(s, d, lambda y: F.lit(1), True), f"SELECT o_custkey, 1 AS delta FROM (SELECT DISTINCT o_custkey, year(o_orderdate) FROM orders WHERE {_TWO_YEARS})", 2),
        Workload("union", ["o_custkey"], lambda s, d: _years(s, d, lambda y: F.lit(1)), f"SELECT o_custkey, 1 AS delta FROM orders WHERE {_TWO_YEARS}"),
        Workload("word_diff", ["word"], _turns, "SELECT unnest(regexp_extract_all(lower(text), '[^\\s\\.,]+')) AS word, CASE WHEN role = 'user' THEN 1 ELSE -1 END AS delta FROM conversations"),
        Workload("doc_bench", ["word"], _against_benchmark, "SELECT unnest(string_split(lower(text), ' ')) AS word, 1 AS delta FROM documents WHERE source = 'src0' UNION ALL SELECT unnest(string_split(lower(text), ' ')), -1 FROM benchmark"),
        Workload("line_diff", ["line"], _line_difference, "SELECT unnest(string_split(text, chr(10))) AS line, CASE WHEN source = (SELECT min(source) FROM documents) THEN 1 ELSE -1 END AS delta FROM documents"),
        Workload("en_words", ["word"], lambda s, d: table(s, d, "documents").where("lang = 'en'").select(_words(F.col("text")).alias("word"), _long(F.lit(1)).alias("delta")), "SELECT unnest(string_split(lower(text), ' ')) AS word, 1 AS delta FROM documents WHERE lang = 'en'"),
        Workload("user_day_balance", ["user_id", "day"], lambda s, d: table(s, d, "events").where("event_type IN ('click', 'view')").select("user_id", F.to_date("ts").alias("day"), _long(F.when(F.col("event_type") == "click", 1).otherwise(-1)).alias("delta")), "SELECT user_id, ts::DATE AS day, CASE WHEN event_type = 'click' THEN 1 ELSE -1 END AS delta FROM events WHERE event_type IN ('click', 'view')"),
        Workload("user_hour_toggle", ["user_id", "hour"], lambda s, d: table(s, d, "events").select("user_id", F.date_format(F.date_trunc("hour", "ts"), "yyyy-MM-dd HH").alias("hour"), _long(F.lit(1)).alias("delta")), "SELECT user_id, strftime(ts, '%Y-%m-%d %H') AS hour, 1 AS delta FROM events", 2),
        Workload("gf9_order", ["l_orderkey"], _lines(["l_orderkey"], lambda: F.pmod(_long(F.col("l_quantity")), F.lit(3)) + 3 * F.pmod(_long(F.col("l_linenumber")), F.lit(3))), "SELECT l_orderkey, (l_quantity::BIGINT % 3) + 3 * (l_linenumber % 3) AS delta FROM lineitem", 9),
        Workload("embedding_cells", ["vec_id", "dim"], lambda s, d: _coordinates(s, d).select("vec_id", "dim", _long(F.round(F.col("v").cast("double") * 10)).alias("delta")), "SELECT vec_id, i - 1 AS dim, round(embedding[i]::DOUBLE * 10)::BIGINT AS delta FROM (SELECT vec_id, embedding, unnest(range(1, len(embedding) + 1)) AS i FROM embeddings)"),
        Workload("sign_toggle", ["label", "dim"], lambda s, d: _coordinates(s, d).where("v > 0").select("label", "dim", _long(F.lit(1)).alias("delta")), "SELECT label, i - 1 AS dim, 1 AS delta FROM (SELECT label, embedding, unnest(range(1, len(embedding) + 1)) AS i FROM embeddings) WHERE embedding[i] > 0", 2),
        Workload("label_mask", ["doc_id"], lambda s, d: table(s, d, "labels").select("doc_id", _long(F.col("quality") + 2 * F.col("toxic")).alias("delta")), "SELECT doc_id, quality + 2 * toxic AS delta FROM labels", 4),
        Workload("page_hosts", ["host"], lambda s, d: table(s, d, "pages").select(F.regexp_extract("url", "https?://([^/]+)", 1).alias("host"), _long(F.lit(1)).alias("delta")), "SELECT regexp_extract(url, 'https?://([^/]+)', 1) AS host, 1 AS delta FROM pages"),
        Workload("adversarial", ["l_orderkey"], _lines(["l_orderkey"], lambda: 30 * _quantity()), f"SELECT l_orderkey, 30 * ({_QTY_SQL}) AS delta FROM lineitem"),
        Workload("cancelled", ["l_orderkey"], lambda s, d: (lambda u: u.unionByName(u.withColumn("delta", -F.col("delta"))))(_lines(["l_orderkey"], _quantity)(s, d)), f"SELECT l_orderkey, {_QTY_SQL} AS delta FROM lineitem UNION ALL SELECT l_orderkey, -({_QTY_SQL}) FROM lineitem"),
    )
}


def line_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(l_returnflag, l_linenumber, linf): the streams of lines with one flag and number, keyed by supplier, and the largest frequency of each."""
    counted = table(spark, sf_dir, "lineitem").groupBy("l_returnflag", "l_linenumber", "l_suppkey").agg(F.count("*").alias("n"))
    return counted.groupBy("l_returnflag", "l_linenumber").agg(F.max("n").alias("linf"))


_LINE_GROUPS = "SELECT l_returnflag, l_linenumber, max(n) AS linf FROM (SELECT l_returnflag, l_linenumber, l_suppkey, count(*) AS n FROM lineitem GROUP BY ALL) GROUP BY ALL"
_GROUP_PRIMES = "SELECT n FROM (SELECT unnest(range(2, (SELECT 2 * max(linf) + 2 FROM g))) AS n) c WHERE NOT EXISTS (SELECT 1 FROM range(2, (SELECT 2 * max(linf) + 2 FROM g)) d WHERE d.range < n AND n % d.range = 0)"
#: group_fields in SQL.
GROUP_FIELDS = f"WITH g AS ({_LINE_GROUPS}) SELECT l_returnflag, l_linenumber, linf, min(n) AS p FROM g JOIN ({_GROUP_PRIMES}) ON n > linf GROUP BY ALL"


def group_fields(spark: SparkSession, sf_dir: str) -> list[tuple[str, int, int, int]]:
    """(l_returnflag, l_linenumber, linf, p) of every group: p is the smallest prime above its largest frequency, so that
    its field counts the group's stream without loss.  The primes are found on the driver, one for each group."""
    return [(*r, above_max(r["linf"])) for r in line_groups(spark, sf_dir).collect()]


def with_groups(orders: list[float], groups: list[tuple]) -> list[tuple[float, int]]:
    """(order, n_groups): the orders asked for, and those of the table's groups with how many groups have each."""
    counted = Counter(p for *_, p in groups)
    return [(q, counted[q]) for q in dict.fromkeys([*orders, *sorted(counted)])]


def part_supports(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(support, parts): how many parts have a stream of so many lines."""
    return table(spark, sf_dir, "lineitem").groupBy("l_partkey").agg(F.count("*").alias("support")).groupBy("support").agg(F.count("*").alias("parts"))


PART_SUPPORTS = "SELECT support, count(*) AS parts FROM (SELECT l_partkey, count(*) AS support FROM lineitem GROUP BY l_partkey) GROUP BY support"


def change_log(frame: DataFrame, key: str, order: str, value: str) -> DataFrame:
    """States over time -> updates (key, value, delta): the old value leaves, the new one enters.

    (key, value) pairs are the elements, so that the number of live ones is that of current values."""
    from pyspark.sql import Window

    before = F.lag(value).over(Window.partitionBy(key).orderBy(order, value))
    images = frame.select(key, F.col(value), before.alias("_old"))
    both = F.explode(F.array(F.struct(F.col("_old").alias("v"), F.lit(-1).cast("long").alias("delta")), F.struct(F.col(value).alias("v"), F.lit(1).cast("long").alias("delta"))))
    return images.select(key, both.alias("u")).select(key, F.col("u.v").alias("value"), F.col("u.delta").alias("delta")).where("value IS NOT NULL")


def signed(frame: DataFrame, keys: list[str], operation: str, inserts: str = "insert") -> DataFrame:
    """Insert/delete flags -> +1 and -1."""
    return frame.select(*keys, F.when(F.col(operation) == inserts, F.lit(1)).otherwise(F.lit(-1)).cast("long").alias("delta"))
