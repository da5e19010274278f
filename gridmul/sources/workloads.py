"""The matrices of the workloads, from the given tables. Values are whole numbers, so sums do not depend on their order."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridmul.operators.blocks import MatrixFrame
from gridmul.plans.topology import MatrixMeta
from gridmul.sources.tables import from_arrays, from_table, load, platforms, quantised

KEYS = 1 << 40  # rows of a matrix whose keys are not known beforehand; sizes it, costs nothing


def square_pair(spark: SparkSession, sf_dir: str, n: int) -> tuple[MatrixFrame, MatrixFrame]:
    """Order by part and part by supplier, all modulo n, summed quantities."""
    lines = load(spark, sf_dir, "lineitem")
    meta = MatrixMeta(n, n)
    q = F.col("l_quantity")
    return from_table(lines, F.col("l_orderkey") % n, F.col("l_partkey") % n, q, meta), from_table(lines, F.col("l_partkey") % n, F.col("l_suppkey") % n, q, meta)


def supplier_part(spark: SparkSession, sf_dir: str, suppliers: int, parts: int) -> MatrixFrame:
    return from_table(load(spark, sf_dir, "lineitem"), F.col("l_suppkey"), F.col("l_partkey"), F.col("l_quantity"), MatrixMeta(suppliers, parts))


def order_part(spark: SparkSession, sf_dir: str) -> MatrixFrame:
    return from_table(load(spark, sf_dir, "lineitem"), F.col("l_orderkey"), F.col("l_partkey"), F.col("l_quantity"), MatrixMeta(KEYS, KEYS))


def part_size(spark: SparkSession, sf_dir: str) -> MatrixFrame:
    return from_table(load(spark, sf_dir, "part"), F.col("p_partkey"), F.col("p_size"), F.lit(1), MatrixMeta(KEYS, 51), "max")


def embeddings(spark: SparkSession, sf_dir: str, rows: int, dim: int = 64) -> MatrixFrame:
    return from_arrays(load(spark, sf_dir, "embeddings"), F.col("vec_id"), quantised(F.col("embedding")), MatrixMeta(rows, dim))


def months(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(month, lines): the order lines shipped in each month, as 202403. The sides of the matrices that schedules and costs are asked for."""
    day = F.col("l_shipdate")
    return load(spark, sf_dir, "lineitem").groupBy((F.year(day) * 100 + F.month(day)).cast("long").alias("month")).agg(F.count("*").alias("lines"))


def month_products(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The published platforms with the product of each month's matrices on them: n is the month's order lines, up to whole blocks."""
    n = F.ceil(F.col("lines") / F.col("b")) * F.col("b")
    return months(spark, sf_dir).crossJoin(F.broadcast(platforms(spark).drop("n"))).withColumn("n", n.cast("double")).drop("lines")  # five platforms


def user_hour_type(spark: SparkSession, sf_dir: str) -> tuple[MatrixFrame, MatrixFrame]:
    """User by hour counts, hour by event type counts; types numbered in alphabetical order."""
    events = load(spark, sf_dir, "events")
    code = F.expr("array_position(array('click', 'error', 'purchase', 'signup', 'view'), event_type)")
    hour = F.hour("ts").cast("long")
    return from_table(events, F.col("user_id"), hour, F.lit(1), MatrixMeta(KEYS, 24), "count"), from_table(events, hour, code, F.lit(1), MatrixMeta(24, 16), "count")
