"""Series (var, step, pos, value) derived from the given tables, each with its SQL twin for DuckDB.

pos is the rank of the point's key.  Running sums are kept in cents or whole numbers, so both engines give the same doubles.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ratiobin.operators.relational import cents, dense_positions, densify, month_index
from ratiobin.session import once, small_side
from ratiobin.sources.tables import load_table

LINE_KEY = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate"]
DRIFT_STEPS = 3


def _line_points(spark: SparkSession, sf_dir: str, *more: str) -> DataFrame:
    lines = load_table(spark, sf_dir, "lineitem", *LINE_KEY, *more)
    return lines.join(dense_positions(lines, LINE_KEY), LINE_KEY)


def _stacked(points: DataFrame, var: str, values: list[Column]) -> DataFrame:
    """One row for each point and value expression; step is its place in the list."""
    steps = F.explode(F.array(*[F.struct(F.lit(i).alias("step"), v.alias("value")) for i, v in enumerate(values)]))
    return points.select("pos", steps.alias("s")).select(F.lit(var).alias("var"), "s.step", "pos", "s.value")


def price_states(spark: SparkSession, sf_dir: str) -> DataFrame:
    points = _line_points(spark, sf_dir, "l_extendedprice", "l_discount", "l_tax")
    lower = F.col("l_extendedprice") * (1 - F.col("l_discount"))
    return _stacked(points, "price_states", [F.col("l_extendedprice"), lower, lower * (1 + F.col("l_tax"))])


def drift_factors(t: int) -> tuple[float, float, float]:
    return ((7 * t % 11) - 5) / 10, ((3 * t % 7) - 3) / 10, ((5 * t % 3) - 1) / 50


def drift_field(spark: SparkSession, sf_dir: str, steps: int = DRIFT_STEPS) -> DataFrame:
    points = _line_points(spark, sf_dir, "l_extendedprice", "l_discount", "l_tax", "l_quantity")
    values = [F.col("l_extendedprice")]
    for t in range(1, steps + 1):
        c, d, e = drift_factors(t)
        values.append(values[-1] * (1 + F.col("l_discount") * c + F.col("l_tax") * d + F.col("l_quantity") / 50 * e))
    return _stacked(points, "drift_field", values)


def part_volume(spark: SparkSession, sf_dir: str) -> DataFrame:
    quarter = (F.year("l_shipdate") * 4 + F.quarter("l_shipdate")).alias("q")
    sums = load_table(spark, sf_dir, "lineitem", "l_partkey", "l_shipdate", "l_quantity").groupBy("l_partkey", quarter).agg(F.sum(F.col("l_quantity").cast("long")).alias("sold"))
    steps = dense_positions(sums.select("q"), ["q"], "step").withColumn("step", F.col("step").cast("int"))
    points = dense_positions(load_table(spark, sf_dir, "part", "p_partkey"), ["p_partkey"])
    keyed = sums.join(small_side(steps), "q").join(points, F.col("l_partkey") == F.col("p_partkey")).select("pos", "step", "sold")
    return densify(keyed, points, steps, "sold").select(F.lit("part_volume").alias("var"), "step", "pos", F.col("sold").cast("double").alias("value"))


def customer_balance(spark: SparkSession, sf_dir: str) -> DataFrame:
    sums = load_table(spark, sf_dir, "orders", "o_custkey", "o_orderdate", "o_totalprice").groupBy("o_custkey", month_index(F.col("o_orderdate")).alias("m")).agg(F.sum(cents(F.col("o_totalprice"))).alias("spent"))
    steps = dense_positions(sums.select("m"), ["m"], "step").withColumn("step", F.col("step").cast("int"))
    customers = load_table(spark, sf_dir, "customer", "c_custkey", "c_acctbal")
    points = dense_positions(customers, ["c_custkey"]).join(customers, "c_custkey")
    keyed = sums.join(small_side(steps), "m").join(points, F.col("o_custkey") == F.col("c_custkey")).select("pos", "step", "spent")
    full = densify(keyed, points, steps, "spent").join(points.select("pos", "c_acctbal"), "pos")
    return full.select(F.lit("customer_balance").alias("var"), "step", "pos", ((cents(F.col("c_acctbal")) + F.col("spent")) / 100.0).alias("value"))


def user_activity(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = load_table(spark, sf_dir, "events", "user_id", "event_type", "ts", "value")
    users, kinds = events.select("user_id").distinct(), events.select("event_type").distinct()
    points = dense_positions(users.crossJoin(small_side(kinds)), ["user_id", "event_type"])
    sums = events.groupBy("user_id", "event_type", F.to_date("ts").alias("d")).agg(F.sum(cents(F.col("value"))).alias("spent"))
    steps = dense_positions(sums.select("d"), ["d"], "step").withColumn("step", F.col("step").cast("int"))
    keyed = sums.join(small_side(steps), "d").join(points, ["user_id", "event_type"]).select("pos", "step", "spent")
    return densify(keyed, points, steps, "spent").select(F.lit("user_activity").alias("var"), "step", "pos", (F.col("spent") / 100.0).alias("value"))


def embedding_field(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = load_table(spark, sf_dir, "embeddings", "vec_id", "embedding")
    flat = vectors.select("vec_id", F.posexplode("embedding").alias("dim", "x"))
    return flat.select(
        F.lit("embedding_field").alias("var"), (F.col("vec_id") % 10).cast("int").alias("step"), (F.floor(F.col("vec_id") / 10) * 64 + F.col("dim")).cast("long").alias("pos"), F.col("x").cast("double").alias("value")
    )


def supplier_month(spark: SparkSession, sf_dir: str) -> DataFrame:
    sums = load_table(spark, sf_dir, "lineitem", "l_suppkey", "l_shipdate", "l_extendedprice").groupBy("l_suppkey", month_index(F.col("l_shipdate")).alias("m")).agg(F.sum(cents(F.col("l_extendedprice"))).alias("sold"))
    steps = dense_positions(sums.select("m"), ["m"], "step").withColumn("step", F.col("step").cast("int"))
    points = dense_positions(sums.select("l_suppkey"), ["l_suppkey"])
    return sums.join(small_side(steps), "m").join(points, "l_suppkey").select(F.lit("supplier_month").alias("var"), "step", "pos", (F.col("sold") / 100.0).alias("value"))


def turn_lengths(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = load_table(spark, sf_dir, "conversations", "conv_id", "turn", "text")
    points = dense_positions(turns, ["conv_id"])
    return turns.join(points, "conv_id").select(F.lit("turn_lengths").alias("var"), F.col("turn").cast("int").alias("step"), "pos", F.length("text").cast("double").alias("value"))


BUILDERS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f for f in (price_states, drift_field, part_volume, customer_balance, user_activity, embedding_field, supplier_month, turn_lengths)
}

#: Bytes of an element in the source type.
ELEM_BYTES = {name: 4 if name == "embedding_field" else 8 for name in BUILDERS}


def load_series(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A series, written to the shared folder when it is first asked for and read from there afterwards."""
    return once(spark, ("series", sf_dir, name), lambda: BUILDERS[name](spark, sf_dir))


_LINE = "SELECT *, row_number() OVER (ORDER BY l_orderkey, l_linenumber, l_partkey, l_suppkey, l_shipdate) - 1 AS pos FROM lineitem"


def _drift_sql(steps: int = DRIFT_STEPS) -> str:
    columns, last = ["l_extendedprice AS v0"], "v0"
    nested = f"SELECT pos, l_discount, l_tax, l_quantity, l_extendedprice AS v0 FROM ({_LINE})"
    for t in range(1, steps + 1):
        c, d, e = (f"CAST({x!r} AS DOUBLE)" for x in drift_factors(t))
        nested = f"SELECT *, v{t - 1} * (1 + l_discount * {c} + l_tax * {d} + l_quantity / 50 * {e}) AS v{t} FROM ({nested})"
    return " UNION ALL ".join(f"SELECT 'drift_field' AS var, {t} AS step, pos, v{t} AS value FROM ({nested})" for t in range(steps + 1))


SERIES_SQL = {
    "price_states": f"""SELECT 'price_states' AS var, 0 AS step, pos, l_extendedprice AS value FROM ({_LINE})
        UNION ALL SELECT 'price_states', 1, pos, l_extendedprice * (1 - l_discount) FROM ({_LINE})
        UNION ALL SELECT 'price_states', 2, pos, l_extendedprice * (1 - l_discount) * (1 + l_tax) FROM ({_LINE})""",
    "drift_field": _drift_sql(),
    "part_volume": """SELECT 'part_volume' AS var, step, pos, CAST(sum(coalesce(sold, 0)) OVER (PARTITION BY pos ORDER BY step) AS DOUBLE) AS value FROM
        (SELECT p_partkey, row_number() OVER (ORDER BY p_partkey) - 1 AS pos FROM part) p
        CROSS JOIN (SELECT q, CAST(row_number() OVER (ORDER BY q) - 1 AS INTEGER) AS step FROM (SELECT DISTINCT year(l_shipdate) * 4 + quarter(l_shipdate) AS q FROM lineitem)) t
        LEFT JOIN (SELECT l_partkey, year(l_shipdate) * 4 + quarter(l_shipdate) AS q, sum(CAST(l_quantity AS BIGINT)) AS sold FROM lineitem GROUP BY ALL) s
        ON s.l_partkey = p.p_partkey AND s.q = t.q""",
    "customer_balance": """SELECT 'customer_balance' AS var, step, pos, CAST(CAST(round(c_acctbal * 100) AS BIGINT) + sum(coalesce(spent, 0)) OVER (PARTITION BY pos ORDER BY step) AS DOUBLE) / 100.0 AS value FROM
        (SELECT c_custkey, c_acctbal, row_number() OVER (ORDER BY c_custkey) - 1 AS pos FROM customer) c
        CROSS JOIN (SELECT m, CAST(row_number() OVER (ORDER BY m) - 1 AS INTEGER) AS step FROM (SELECT DISTINCT year(o_orderdate) * 12 + month(o_orderdate) - 1 AS m FROM orders)) t
        LEFT JOIN (SELECT o_custkey, year(o_orderdate) * 12 + month(o_orderdate) - 1 AS m, sum(CAST(round(o_totalprice * 100) AS BIGINT)) AS spent FROM orders GROUP BY ALL) s
        ON s.o_custkey = c.c_custkey AND s.m = t.m""",
    "user_activity": """SELECT 'user_activity' AS var, step, pos, CAST(sum(coalesce(spent, 0)) OVER (PARTITION BY pos ORDER BY step) AS DOUBLE) / 100.0 AS value FROM
        (SELECT user_id, event_type, row_number() OVER (ORDER BY user_id, event_type) - 1 AS pos FROM (SELECT DISTINCT user_id FROM events) CROSS JOIN (SELECT DISTINCT event_type FROM events)) p
        CROSS JOIN (SELECT d, CAST(row_number() OVER (ORDER BY d) - 1 AS INTEGER) AS step FROM (SELECT DISTINCT CAST(ts AS DATE) AS d FROM events)) t
        LEFT JOIN (SELECT user_id, event_type, CAST(ts AS DATE) AS d, sum(CAST(round(value * 100) AS BIGINT)) AS spent FROM events GROUP BY ALL) s
        ON s.user_id = p.user_id AND s.event_type = p.event_type AND s.d = t.d""",
    "embedding_field": """SELECT 'embedding_field' AS var, CAST(vec_id % 10 AS INTEGER) AS step, (vec_id // 10) * 64 + dim - 1 AS pos, CAST(embedding[dim] AS DOUBLE) AS value
        FROM (SELECT vec_id, embedding, unnest(range(1, len(embedding) + 1)) AS dim FROM embeddings)""",
    "supplier_month": """SELECT 'supplier_month' AS var, CAST(dense_rank() OVER (ORDER BY m) - 1 AS INTEGER) AS step, dense_rank() OVER (ORDER BY l_suppkey) - 1 AS pos, CAST(sold AS DOUBLE) / 100.0 AS value
        FROM (SELECT l_suppkey, year(l_shipdate) * 12 + month(l_shipdate) - 1 AS m, sum(CAST(round(l_extendedprice * 100) AS BIGINT)) AS sold FROM lineitem GROUP BY ALL)""",
    "turn_lengths": """SELECT 'turn_lengths' AS var, CAST(turn AS INTEGER) AS step, dense_rank() OVER (ORDER BY conv_id) - 1 AS pos, CAST(length(text) AS DOUBLE) AS value FROM conversations""",
}
