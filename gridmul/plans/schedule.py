"""The message schedule of the flat and the grouped product, without data: one row for each broadcast.

step, outer_step, inner_step, operand, level, the root's coordinates, how many receive, how many elements."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from gridmul.plans.topology import GridSpec, MatrixMeta, ceil_div

COLUMNS = ["step", "outer_step", "inner_step", "operand", "level", "root_grp_row", "root_grp_col", "root_in_row", "root_in_col", "receivers", "elements"]


def _axis(spark: SparkSession, n: int, name: str) -> DataFrame:
    return spark.range(n).select(F.col("id").alias(name))


def _rows(steps: DataFrame, roots: DataFrame, operand: str, level: str, place: dict[str, Column], receivers: int, elements: int) -> DataFrame:
    both = steps.crossJoin(roots)  # steps times roots: the schedule itself, no data
    return both.select("step", "outer_step", "inner_step", F.lit(operand).alias("operand"), F.lit(level).alias("level"), *[v.cast("int").alias(k) for k, v in place.items()], F.lit(receivers).cast("long").alias("receivers"), F.lit(elements).cast("long").alias("elements"))


def _place(grp_row: Column, grp_col: Column, in_row: Column, in_col: Column) -> dict[str, Column]:
    return {"root_grp_row": grp_row, "root_grp_col": grp_col, "root_in_row": in_row, "root_in_col": in_col}


def schedule(spark: SparkSession, method: str, a: MatrixMeta, b: MatrixMeta, grid: GridSpec, inner: int, outer: int | None = None) -> DataFrame:
    """Schedule of 'flat' or 'grouped' for contiguous placement; broadcasts without receivers are kept."""
    outer = inner if outer is None else outer
    if method == "flat":
        grid = grid.with_groups(1, 1)
    grid.validate(a, b, inner, outer)
    m, k, n = a.rows, a.cols, b.cols
    rows, cols = grid.inside
    per_row, per_col = ceil_div(m, grid.s), ceil_div(n, grid.t)
    wide_a, wide_b = ceil_div(k, grid.t), ceil_div(k, grid.s)
    fine = _axis(spark, ceil_div(k, inner), "step").select("step", F.floor(F.col("step") * inner / outer).alias("outer_step"), (F.col("step") % (outer // inner)).alias("inner_step"))
    coarse = _axis(spark, ceil_div(k, outer), "outer_step").select((F.col("outer_step") * (outer // inner)).alias("step"), "outer_step", F.lit(0).cast("long").alias("inner_step"))

    def owner(step: str, block: int, width: int) -> Column:
        return F.floor(F.col(step) * block / width)

    i, j = F.col("i"), F.col("j")
    down, across = _axis(spark, grid.s, "i"), _axis(spark, grid.t, "j")
    if method == "flat":
        ca, rb = owner("step", inner, wide_a), owner("step", inner, wide_b)
        zero = F.lit(0)
        one = _rows(fine, down, "A", "flat", _place(zero, zero, i, ca), grid.t - 1, per_row * inner)
        return one.unionByName(_rows(fine, across, "B", "flat", _place(zero, zero, rb, j), grid.s - 1, per_col * inner))
    if method != "grouped":
        raise ValueError("a schedule is flat or grouped")
    ca, rb = owner("outer_step", outer, wide_a), owner("outer_step", outer, wide_b)
    i_place, j_place = (F.floor(i / rows), i % rows), (F.floor(j / cols), j % cols)
    parts = [
        _rows(coarse, down, "A", "between", _place(i_place[0], F.floor(ca / cols), i_place[1], ca % cols), grid.J - 1, per_row * outer),
        _rows(coarse, across, "B", "between", _place(F.floor(rb / rows), j_place[0], rb % rows, j_place[1]), grid.I - 1, per_col * outer),
        # inside, every group has a root in each of its rows (columns): the cell at the owner's place in the group
        _rows(fine, down.crossJoin(_axis(spark, grid.J, "y")), "A", "inside", _place(i_place[0], F.col("y"), i_place[1], ca % cols), cols - 1, per_row * inner),
        _rows(fine, across.crossJoin(_axis(spark, grid.I, "x")), "B", "inside", _place(F.col("x"), j_place[0], rb % rows, j_place[1]), rows - 1, per_col * inner),
    ]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def totals(plan: DataFrame) -> DataFrame:
    """(operand, level, broadcasts, deliveries)."""
    return plan.groupBy("operand", "level").agg(F.count("*").alias("broadcasts"), F.sum(F.col("receivers") * F.col("elements")).alias("deliveries"))


def counted(a: MatrixMeta, b: MatrixMeta, grid: GridSpec) -> dict[tuple[str, str], int]:
    """Deliveries by operand and level in closed form; between and inside add up to flat."""
    m, k, n = a.rows, a.cols, b.cols
    return {("A", "flat"): m * k * (grid.t - 1), ("B", "flat"): k * n * (grid.s - 1), ("A", "between"): m * k * (grid.J - 1), ("B", "between"): k * n * (grid.I - 1), ("A", "inside"): m * k * (grid.t - grid.J), ("B", "inside"): k * n * (grid.s - grid.I)}


def crossings(a: MatrixMeta, b: MatrixMeta, grid: GridSpec) -> dict[tuple[str, str], int]:
    """Elements that leave a group when each receiver is served by the root: the flat method ships t/J (s/I) times as many."""
    m, k, n = a.rows, a.cols, b.cols
    rows, cols = grid.inside
    return {("flat", "A"): m * k * cols * (grid.J - 1), ("flat", "B"): k * n * rows * (grid.I - 1), ("grouped", "A"): m * k * (grid.J - 1), ("grouped", "B"): k * n * (grid.I - 1)}
