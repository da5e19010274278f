"""Who receives which entry: between groups before the exchange, inside a group after it."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gridmul.plans.topology import GridSpec, MatrixMeta


def fan_out(df: DataFrame, name: str, n: int) -> DataFrame:
    """n copies of each row, numbered in column `name`."""
    return df.withColumn(name, F.explode(F.sequence(F.lit(0), F.lit(n - 1))) if n > 1 else F.lit(0))


def operand(df: DataFrame, side: str, meta: MatrixMeta, grid: GridSpec, inner: int, outer: int) -> DataFrame:
    """Entries as (own, k, value) with home coordinates and steps; own is the row of A or the column of B."""
    axis, size = ("row", meta.rows) if side == "a" else ("col", meta.cols)
    own, k = ("row", "col") if side == "a" else ("col", "row")
    base = df.select(F.col(own).alias("own"), F.col(k).alias("k"), "value")
    cell = grid.cell_of(F.col("own"), size, axis, inner)
    placed = base.withColumn("cell", cell)
    return placed.select("own", "k", "value", grid.group_of(F.col("cell"), axis).alias(f"grp_{axis}"), grid.place_in_group(F.col("cell"), axis).alias(f"in_{axis}"), F.floor(F.col("k") / outer).alias("outer_step"), F.floor(F.col("k") / inner).alias("inner_step"))


def group_id(grid: GridSpec) -> Column:
    return (F.col("grp_row") * grid.J + F.col("grp_col")).cast("int")


def route_between(df: DataFrame, side: str, grid: GridSpec) -> DataFrame:
    """A goes to every group of its group row, B to every group of its group column."""
    return fan_out(df, "grp_col", grid.J) if side == "a" else fan_out(df, "grp_row", grid.I)


def exchange_groups(df: DataFrame, grid: GridSpec) -> DataFrame:
    """The one shuffle: partition number grp_id holds the group grp_id and nothing else."""
    return df.withColumn("grp_id", group_id(grid)).repartitionById(grid.groups, F.col("grp_id"))


def route_inside(df: DataFrame, side: str, grid: GridSpec) -> DataFrame:
    """Copies for the cells of the group, made in the task that received the entry; level by level if there are more."""
    rows, cols = grid.inside
    axis, left = ("col", cols) if side == "a" else ("row", rows)
    place: Column = F.lit(0)
    for k, (i, j) in enumerate(grid.levels):
        n = j if axis == "col" else i
        df = fan_out(df, f"level_{k}", n)
        left //= n
        place = place * n + F.col(f"level_{k}")
    df = fan_out(df, "last", left)
    place = place * left + F.col("last")
    out = df.withColumn(f"in_{axis}", place.cast("int"))
    return out.withColumn("cell_row", grid.cell_from(F.col("grp_row"), F.col("in_row"), "row")).withColumn("cell_col", grid.cell_from(F.col("grp_col"), F.col("in_col"), "col")).drop("last", *[f"level_{k}" for k in range(len(grid.levels))])


def route_flat(df: DataFrame, side: str, grid: GridSpec) -> DataFrame:
    """Every entry straight to all cells of its grid row (A) or grid column (B): one exchange by cell."""
    whole = fan_out(df, "other", grid.t if side == "a" else grid.s)
    own = grid.cell_from(F.col("grp_row"), F.col("in_row"), "row") if side == "a" else grid.cell_from(F.col("grp_col"), F.col("in_col"), "col")
    cells = whole.withColumn("cell_row", own if side == "a" else F.col("other")).withColumn("cell_col", F.col("other") if side == "a" else own)
    return cells.withColumn("cell_id", (F.col("cell_row") * grid.t + F.col("cell_col")).cast("int")).repartitionById(grid.cells, F.col("cell_id"))
