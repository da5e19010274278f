"""Message schedules of the classic baselines, without data, in the form of one row a message or broadcast:
step, phase, operand, the sender's place, the receiver's place (null for a broadcast), how many receive, how many elements.

Matrices are n x n with blocks that the grid divides; messages a cell would send to itself are left out."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

COLUMNS = ["step", "phase", "operand", "from_row", "from_col", "to_row", "to_col", "receivers", "elements"]


def _cells(spark: SparkSession, p: int, q: int) -> DataFrame:
    return spark.range(p * q).select(F.floor(F.col("id") / q).alias("i"), (F.col("id") % q).alias("j"))


def _rows(df: DataFrame, step: Column, phase: str, operand: str, to: tuple[Column, Column] | None, receivers: int, elements: int | Column) -> DataFrame:
    row, col = to or (F.lit(None), F.lit(None))
    count = elements if isinstance(elements, Column) else F.lit(elements)
    return df.select(step.cast("long").alias("step"), F.lit(phase).alias("phase"), F.lit(operand).alias("operand"), F.col("i").cast("int").alias("from_row"), F.col("j").cast("int").alias("from_col"), row.cast("int").alias("to_row"), col.cast("int").alias("to_col"), F.lit(receivers).cast("long").alias("receivers"), count.cast("long").alias("elements"))


def _steps(spark: SparkSession, first: int, last: int) -> DataFrame:
    return spark.range(first, last).select(F.col("id").alias("step"))


def rotations(spark: SparkSession, n: int, q: int) -> DataFrame:
    """q x q cells: the alignment moves row i of A by i and column j of B by j, then both rotate by one, q - 1 times."""
    cells, block = _cells(spark, q, q), (n // q) ** 2
    i, j = F.col("i"), F.col("j")
    left, up = (i, F.pmod(j - 1, F.lit(q))), (F.pmod(i - 1, F.lit(q)), j)
    out = _rows(cells.where("i > 0"), F.lit(0), "align", "A", (i, F.pmod(j - i, F.lit(q))), 1, block)
    out = out.unionByName(_rows(cells.where("j > 0"), F.lit(0), "align", "B", (F.pmod(i - j, F.lit(q)), j), 1, block))
    turns = cells.crossJoin(_steps(spark, 1, q))  # cells times steps: the schedule itself, no data
    for operand, to in (("A", left), ("B", up)):
        out = out.unionByName(_rows(turns, F.col("step"), "rotate", operand, to, 1, block))
    return out


def broadcast_roll(spark: SparkSession, n: int, q: int) -> DataFrame:
    """q x q cells: at step k the cell k places right of the diagonal broadcasts A along its row; B rolls up between steps."""
    cells, block = _cells(spark, q, q), (n // q) ** 2
    i, j = F.col("i"), F.col("j")
    roots = spark.range(q).select(F.col("id").alias("i")).crossJoin(_steps(spark, 0, q)).withColumn("j", (i + F.col("step")) % q)
    out = _rows(roots, F.col("step"), "broadcast", "A", None, q - 1, block)
    return out.unionByName(_rows(cells.crossJoin(_steps(spark, 1, q)), F.col("step"), "roll", "B", (F.pmod(i - 1, F.lit(q)), j), 1, block))


def lcm_shifts(spark: SparkSession, n: int, p: int, q: int) -> DataFrame:
    """p x q cells, block-cyclic: every class of k modulo lcm(p, q) is one broadcast of B down each column, by the cell that owns
    the class there; A is shifted along the rows q - 1 times, each time all that a cell holds."""
    classes, cells = math.lcm(p, q), _cells(spark, p, q)
    i, j = F.col("i"), F.col("j")
    out = _rows(cells.crossJoin(_steps(spark, 1, q)), F.col("step"), "shift", "A", (i, F.pmod(j - 1, F.lit(q))), 1, n * n // (p * q))
    roots = spark.range(q).select(F.col("id").alias("j")).crossJoin(_steps(spark, 0, classes)).withColumn("i", F.col("step") % p)
    return out.unionByName(_rows(roots, F.col("step"), "broadcast", "B", None, p - 1, n * n // (classes * q)))


def layers(spark: SparkSession, n: int, side: int, c: int, block: int) -> DataFrame:
    """c layers of side x side cells: the blocks of the first layer go to the others, each layer takes its share of the steps, and
    the parts of C are summed back. With c = side every layer has one panel (the 3-D product)."""
    cells, own = _cells(spark, side, side), (n // side) ** 2
    out = None
    for operand in "AB":
        one = _rows(cells, F.lit(0), "replicate", operand, None, c - 1, own)
        out = one if out is None else out.unionByName(one)
    panels = n // block
    roots = spark.range(side).select(F.col("id").alias("line")).crossJoin(_steps(spark, 0, panels))
    owner = F.floor(F.col("step") * block / (n // side))
    a = roots.select("step", F.col("line").alias("i"), owner.alias("j"))
    b = roots.select("step", owner.alias("i"), F.col("line").alias("j"))
    for operand, df in (("A", a), ("B", b)):
        out = out.unionByName(_rows(df, F.floor(F.col("step") / c) + 1, "multiply", operand, None, side - 1, n // side * block))
    return out.unionByName(_rows(cells, F.lit(-(-panels // c) + 1), "reduce", "C", None, c - 1, own))


def sized(plan: DataFrame, sides: DataFrame, times: Column) -> DataFrame:
    """The plan for each row of `sides`: the same messages for matrices `times` as long and as wide, so of times^2 the elements."""
    # a schedule for each size: the product is the result
    return plan.crossJoin(sides.withColumn("times", times.cast("long"))).withColumn("elements", F.col("elements") * F.col("times") * F.col("times")).drop("times")


def totals(plan: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """(*by, phase, operand, messages, deliveries): what every phase sends, in messages and in elements that arrive."""
    return plan.groupBy(*by, "phase", "operand").agg(F.count("*").alias("messages"), F.sum(F.col("receivers") * F.col("elements")).alias("deliveries"))
