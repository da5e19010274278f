"""The virtual grid of cells, its groups, and where entries and steps fall on it."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass(frozen=True)
class MatrixMeta:
    """Dimensions and value type; they travel beside the entries so that no job has to count them."""

    rows: int
    cols: int
    dtype: str = "long"


def divisors(n: int) -> list[int]:
    return [d for d in range(1, n + 1) if n % d == 0]


def ceil_div(a: int, b: int) -> int:
    return -(-a // b)


@dataclass(frozen=True)
class GridSpec:
    """s x t cells in I x J groups.

    placement: 'contiguous' rectangles of the matrix a cell, or 'block_cyclic' with blocks dealt round robin.
    grouping: 'contiguous' neighbouring cells in a group, or 'strided' cells that lie I (J) apart.
    levels: further group grids inside a group, outermost first; each divides what the ones before leave."""

    s: int
    t: int
    I: int = 1  # noqa: E741
    J: int = 1
    levels: tuple[tuple[int, int], ...] = field(default=())
    placement: str = "contiguous"
    grouping: str = "contiguous"

    def __post_init__(self) -> None:
        if min(self.s, self.t, self.I, self.J) < 1:
            raise ValueError("a grid has at least one cell and one group")
        if self.s % self.I or self.t % self.J:
            raise ValueError(f"{self.I} x {self.J} groups do not divide a {self.s} x {self.t} grid")
        if self.placement not in ("contiguous", "block_cyclic") or self.grouping not in ("contiguous", "strided"):
            raise ValueError("unknown placement or grouping")
        rows, cols = self.s // self.I, self.t // self.J
        for i, j in self.levels:
            if rows % i or cols % j:
                raise ValueError(f"level {i} x {j} does not divide the {rows} x {cols} cells left")
            rows, cols = rows // i, cols // j

    @classmethod
    def square(cls, p: int, groups: int) -> GridSpec:
        """sqrt(groups) x sqrt(groups) groups on a sqrt(p) x sqrt(p) grid."""
        side, group = round(p**0.5), round(groups**0.5)
        if side * side != p or group * group != groups:
            raise ValueError("p and the number of groups must be squares")
        return cls(side, side, group, group)

    @property
    def groups(self) -> int:
        return self.I * self.J

    @property
    def cells(self) -> int:
        return self.s * self.t

    @property
    def inside(self) -> tuple[int, int]:
        return self.s // self.I, self.t // self.J

    def with_groups(self, i: int, j: int) -> GridSpec:
        return GridSpec(self.s, self.t, i, j, (), self.placement, self.grouping)

    def validate(self, a: MatrixMeta, b: MatrixMeta, inner: int, outer: int | None = None) -> None:
        """Shapes conform; inner blocks divide outer ones; an outer panel lies in one cell row and one cell column."""
        if a.cols != b.rows:
            raise ValueError(f"{a.rows} x {a.cols} and {b.rows} x {b.cols} do not conform")
        outer = inner if outer is None else outer
        if inner < 1 or outer < inner or outer % inner:
            raise ValueError("the inner block must divide the outer one")
        widest = min(ceil_div(a.cols, self.s), ceil_div(a.cols, self.t))
        if outer > widest:
            raise ValueError(f"an outer block of {outer} is wider than a cell's {widest} columns or rows")

    def frame(self, spark: SparkSession) -> DataFrame:
        """(cell_row, cell_col, grp_row, grp_col, in_row, in_col) of every cell."""
        i, j = F.col("cell_row"), F.col("cell_col")
        grid = spark.range(self.s).select(F.col("id").alias("cell_row")).crossJoin(spark.range(self.t).select(F.col("id").alias("cell_col")))
        return grid.select("cell_row", "cell_col", self.group_of(i, "row").alias("grp_row"), self.group_of(j, "col").alias("grp_col"), self.place_in_group(i, "row").alias("in_row"), self.place_in_group(j, "col").alias("in_col"))

    def _axis(self, axis: str) -> tuple[int, int]:
        return (self.s, self.I) if axis == "row" else (self.t, self.J)

    def cell_of(self, index: Column, size: int, axis: str, block: int) -> Column:
        """The cell row (column) of a matrix row (column)."""
        cells, _ = self._axis(axis)
        if self.placement == "block_cyclic":
            return (F.floor(index / block) % cells).cast("int")
        return F.floor(index / ceil_div(size, cells)).cast("int")

    def group_of(self, cell: Column, axis: str) -> Column:
        cells, groups = self._axis(axis)
        return (cell % groups if self.grouping == "strided" else F.floor(cell / (cells // groups))).cast("int")

    def place_in_group(self, cell: Column, axis: str) -> Column:
        cells, groups = self._axis(axis)
        return (F.floor(cell / groups) if self.grouping == "strided" else cell % (cells // groups)).cast("int")

    def cell_from(self, group: Column, place: Column, axis: str) -> Column:
        cells, groups = self._axis(axis)
        return (place * groups + group if self.grouping == "strided" else group * (cells // groups) + place).cast("int")

    def local_index(self, index: Column, size: int, axis: str, block: int) -> Column:
        """Place of a matrix row (column) in its group's tile."""
        cells, groups = self._axis(axis)
        place = self.place_in_group(self.cell_of(index, size, axis, block), axis)
        if self.placement == "block_cyclic":
            return ((F.floor(index / (block * cells)) * (cells // groups) + place) * block + index % block).cast("int")
        return (place * ceil_div(size, cells) + index % ceil_div(size, cells)).cast("int")

    def global_index(self, local: Column, group: Column, size: int, axis: str, block: int) -> Column:
        """The matrix row (column) at a place of a group's tile: local_index turned round."""
        cells, groups = self._axis(axis)
        per = cells // groups
        if self.placement == "block_cyclic":
            place = F.floor(local / block) % per
            return (F.floor(local / (block * per)) * (block * cells) + self.cell_from(group, place, axis) * block + local % block).cast("long")
        width = ceil_div(size, cells)
        return (self.cell_from(group, F.floor(local / width), axis) * width + local % width).cast("long")

    def tile(self, size: int, axis: str, block: int) -> int:
        """Rows (columns) of a group's tile."""
        cells, groups = self._axis(axis)
        if self.placement == "block_cyclic":
            return ceil_div(size, block * cells) * (cells // groups) * block
        return ceil_div(size, cells) * (cells // groups)


def valid_groupings(s: int, t: int) -> list[tuple[int, int]]:
    return [(i, j) for i in divisors(s) for j in divisors(t)]


def groupings_frame(spark: SparkSession, s: int, t: int) -> DataFrame:
    """(grp_rows, grp_cols, groups) of every valid grouping."""
    i = spark.range(1, s + 1).where(F.lit(s) % F.col("id") == 0).select(F.col("id").alias("grp_rows"))
    j = spark.range(1, t + 1).where(F.lit(t) % F.col("id") == 0).select(F.col("id").alias("grp_cols"))
    return i.crossJoin(j).withColumn("groups", F.col("grp_rows") * F.col("grp_cols"))


def default_grid(spark: SparkSession) -> GridSpec:
    """A near-square grid of at least as many groups as the session has cores, one cell a group row and column of four."""
    side = 1
    while side * side < spark.sparkContext.defaultParallelism:
        side *= 2
    return GridSpec(2 * side, 2 * side, side, side)
