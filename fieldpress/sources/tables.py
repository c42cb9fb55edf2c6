"""Tables as scattered points: field extraction, planted fields, file formats.

All of it is a projection of the scan: only the named columns are read, no shuffle.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..schema import FieldSpec, coords, points_schema


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_points(spark: SparkSession, path: str, d: int, fmt: str = "parquet", **options: str) -> DataFrame:
    """Points kept as Parquet, ORC, CSV or JSON, with an explicit schema."""
    return spark.read.format(fmt).schema(points_schema(d)).options(**options).load(path)


def write_by_axis(df: DataFrame, path: str, column: str = "c1", parts: int = 16, fmt: str = "parquet") -> None:
    """Points or decoded values in folders by bucket of one unit axis (``bucket``), so that a range of the axis reads its own folders only."""
    bucket = F.least(F.floor(F.col(column) * parts), F.lit(parts - 1)).cast("int")
    df.withColumn("bucket", bucket).repartition(F.col("bucket")).write.mode("overwrite").partitionBy("bucket").format(fmt).save(path)


def number_ok(c: Column) -> Column:
    return c.isNotNull() & ~F.isnan(c)


def build_points(df: DataFrame, spec: FieldSpec) -> DataFrame:
    """pt_key, c1..cd, u: rows with a null or NaN coordinate or value are left out (``clean_counts`` counts them)."""
    raw = raw_points(df, spec)
    ok = number_ok(F.col("u"))
    for c in coords(spec.d):
        ok = ok & number_ok(F.col(c))
    return raw.where(ok)


def raw_points(df: DataFrame, spec: FieldSpec) -> DataFrame:
    named = [F.expr(e).cast("double").alias(c) for c, e in zip(coords(spec.d), spec.axes.values())]
    key = F.concat_ws("-", *[F.col(k).cast("string") for k in spec.key])
    base = df.select(key.alias("pt_key"), *named, *[F.col(x) for x in df.columns if x in spec.value])
    return base.select("pt_key", *coords(spec.d), F.expr(spec.value).cast("double").alias("u"))


def clean_counts(df: DataFrame, spec: FieldSpec) -> DataFrame:
    """One row: kept, n_null, n_nan."""
    raw = raw_points(df, spec)
    cols = [F.col(c) for c in (*coords(spec.d), "u")]
    null, nan = F.lit(False), F.lit(False)
    for c in cols:
        null = null | c.isNull()
        nan = nan | F.coalesce(F.isnan(c), F.lit(False))
    bad = F.when(null, 1).when(nan, 2).otherwise(0)
    return raw.agg(*[F.sum((bad == i).cast("long")).alias(n) for i, n in enumerate(("kept", "n_null", "n_nan"))])


def wide_to_long(points: DataFrame, variables: list[str], d: int) -> DataFrame:
    """Several variables on shared coordinates as rows (pt_key, c.., var, u)."""
    return points.unpivot(["pt_key", *coords(d)], variables, "var", "u")


# -- fields over the given tables ------------------------------------------------------------

LINE_KEY = ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber")
#: Coordinates of lineitem, each clamped to [0, 1].
SHIP = "greatest(0.0D, least(1.0D, datediff(l_shipdate, DATE'1995-01-01') / 2500.0D))"
PRICE = "greatest(0.0D, least(1.0D, (l_extendedprice - 900.0D) / 104100.0D))"
QUANTITY = "greatest(0.0D, least(1.0D, l_quantity / 50.0D))"
TOTAL = "greatest(0.0D, least(1.0D, o_totalprice / 500000.0D))"

_SHIP_SQL = "greatest(0.0::DOUBLE, least(1.0::DOUBLE, date_diff('day', DATE '1995-01-01', l_shipdate::DATE) / 2500.0::DOUBLE))"
_PRICE_SQL = "greatest(0.0::DOUBLE, least(1.0::DOUBLE, (l_extendedprice - 900.0::DOUBLE) / 104100.0::DOUBLE))"
_QUANTITY_SQL = "greatest(0.0::DOUBLE, least(1.0::DOUBLE, l_quantity / 50.0::DOUBLE))"
#: The same points in DuckDB: a query with pt_key, c1, c2, c3.
POINTS_SQL = f"SELECT concat_ws('-', l_orderkey, l_partkey, l_suppkey, l_linenumber) AS pt_key, {_SHIP_SQL} AS c1, {_PRICE_SQL} AS c2, {_QUANTITY_SQL} AS c3 FROM lineitem"

#: Planted fields of c1, c2, c3; the same text runs in Spark and in DuckDB.
FRONT3 = "tanh((c1 - 0.5e0 - 0.1e0*sin(2e0*pi()*c2))/0.1e0)*(1e0 + 0.3e0*cos(pi()*c3)) + 0.2e0*sin(4e0*pi()*c1)*exp(-c2)"
FRONT4 = f"({FRONT3})*(1e0 + 0.2e0*cos(2e0*pi()*c4))"
AFFINE = "1e0 + 2e0*c1 - 3e0*c2 + 0.5e0*c3"
PRODUCT = "(1e0 + c1)*(2e0 - c2)*(1e0 + c3)"
#: Eleven variables of differing smoothness on shared coordinates.
ELEVEN = {
    "constant": "2e0",
    "affine": AFFINE,
    "product": PRODUCT,
    "quadratic": "c1*c1 + c2*c3 - 0.5e0*c3*c3 + 1e0",
    "front": FRONT3,
    "sharp_front": "tanh((c1 - 0.5e0 - 0.1e0*sin(2e0*pi()*c2))/0.03e0)*(1e0 + 0.3e0*cos(pi()*c3))",
    "wave": "sin(8e0*pi()*c1)*cos(2e0*pi()*c2)*(1e0 + c3)",
    "short_wave": "sin(32e0*pi()*c1)*cos(2e0*pi()*c2)*(1e0 + c3)",
    "step": "CASE WHEN c1 < 0.5e0 THEN 0e0 ELSE 1e0 + c2 END",
    "separable_sum": "exp(-c1)*c2 + cos(c2)*c3 + c1*sin(3e0*c3)",
    "noise": "c2",
}


def line_points(spark: SparkSession, sf_dir: str, value: str = FRONT3) -> DataFrame:
    """Points of lineitem (ship day, price, quantity) with a planted value."""
    spec = FieldSpec({"day": SHIP, "price": PRICE, "quantity": QUANTITY}, value, LINE_KEY, {"day": "time"})
    return build_points(table(spark, sf_dir, "lineitem"), spec)


def line_points_multi(spark: SparkSession, sf_dir: str, values: dict[str, str] | None = None) -> DataFrame:
    """pt_key, c1, c2, c3 and one column for each variable."""
    values = ELEVEN if values is None else values
    base = line_points(spark, sf_dir, "0e0").drop("u")
    return base.select("*", *[F.expr(e).cast("double").alias(n) for n, e in values.items()])


def order_points(spark: SparkSession, sf_dir: str, value: str = FRONT4) -> DataFrame:
    """Four axes: lineitem joined with orders for the order's total price. Bucket both tables by order key at scale and the join needs no shuffle."""
    line = table(spark, sf_dir, "lineitem").select(*LINE_KEY, "l_shipdate", "l_extendedprice", "l_quantity")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice")
    spec = FieldSpec({"day": SHIP, "price": PRICE, "quantity": QUANTITY, "total": TOTAL}, value, LINE_KEY, {"day": "time"})
    return build_points(line.join(orders, F.col("l_orderkey") == F.col("o_orderkey")), spec)


def event_points(events: DataFrame) -> DataFrame:
    """pt_key, ts, c_time (share of 30 days), type, user bucket (8), value; plain date arithmetic, no time zone."""
    seconds = F.expr("timestampdiff(SECOND, TIMESTAMP_NTZ'2024-01-01 00:00:00', ts)")
    return events.select(F.col("event_id").cast("string").alias("pt_key"), "ts", (seconds / F.lit(30 * 86400.0)).alias("c_time"), "event_type", F.pmod("user_id", F.lit(8)).cast("int").alias("user_bucket"), "value")


PROPS = T.StructType([T.StructField("k", T.LongType())])


def props_axis(events: DataFrame) -> DataFrame:
    """event_id and the integer that the JSON properties hold."""
    return events.select("event_id", F.from_json("props", PROPS)["k"].alias("k"))
