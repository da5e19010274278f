"""The classic parallel products: rotations on a square grid, shifts on any grid, and replicated layers.

Each declares at which step a cell meets a slice of k; the step joins the cell in the keys, and one exchange by cell (or by
cell and layer) does the routing."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gridmul.operators import kernels, routing
from gridmul.operators.blocks import MatrixFrame
from gridmul.operators.multiply import HASH_ENTRIES
from gridmul.plans.topology import GridSpec, MatrixMeta, ceil_div
from gridmul.session import configure


def _out(df: DataFrame, a: MatrixFrame, b: MatrixFrame) -> MatrixFrame:
    return MatrixFrame(df.select("row", "col", "value"), MatrixMeta(a.meta.rows, b.meta.cols, a.meta.dtype))


def _conform(a: MatrixFrame, b: MatrixFrame) -> None:
    if a.meta.cols != b.meta.rows:
        raise ValueError("the operands do not conform")
    configure(a.spark)


def _stepped(a: MatrixFrame, b: MatrixFrame, p: int, q: int, slices: int, step: Column, cyclic: bool = False) -> MatrixFrame:
    """On a p x q grid; k falls into `slices` (contiguous, or dealt round robin); `step` is an expression over i, j, kb."""
    _conform(a, b)
    grid = GridSpec(p, q)

    def side(m: MatrixFrame, own: str, k: str, name: str, n: int, size: int, other: str, others: int) -> DataFrame:
        part = F.col(k) % slices if cyclic else F.floor(F.col(k) / ceil_div(a.meta.cols, slices))
        cell = F.col(own) % n if cyclic else F.floor(F.col(own) / ceil_div(size, n))
        placed = m.df.select(F.col(own).alias("own"), F.col(k).alias("k"), "value", part.cast("int").alias("kb"), cell.cast("int").alias(name))
        both = routing.fan_out(placed, other, others)
        return both.withColumn("step", step).withColumn("cell_id", (F.col("i") * q + F.col("j")).cast("int")).repartitionById(grid.cells, F.col("cell_id"))

    left = side(a, "row", "col", "i", p, a.meta.rows, "j", q)
    right = side(b, "col", "row", "j", q, b.meta.cols, "i", p)
    return _out(kernels.relational(left, right, ["cell_id", "step"], ceil_div(b.meta.rows * b.meta.cols, q) <= HASH_ENTRIES).groupBy("cell_id", "row", "col").agg(F.sum("value").alias("value")), a, b)


def _square(grid: GridSpec | int) -> int:
    if isinstance(grid, GridSpec):
        if grid.s != grid.t:
            raise ValueError("this product needs a square grid")
        return grid.s
    return grid


def cannon_multiply(a: MatrixFrame, b: MatrixFrame, grid: GridSpec | int) -> MatrixFrame:
    """q x q cells; after the alignment, cell (i, j) meets slice kb at rotation (kb - i - j) mod q."""
    q = _square(grid)
    return _stepped(a, b, q, q, q, F.pmod(F.col("kb") - F.col("i") - F.col("j"), F.lit(q)))


def fox_multiply(a: MatrixFrame, b: MatrixFrame, grid: GridSpec | int) -> MatrixFrame:
    """q x q cells; A is broadcast along rows, B rolls up: slice kb comes at step (kb - i) mod q."""
    q = _square(grid)
    return _stepped(a, b, q, q, q, F.pmod(F.col("kb") - F.col("i"), F.lit(q)))


def lcm_shift_multiply(a: MatrixFrame, b: MatrixFrame, p: int, q: int) -> MatrixFrame:
    """Block-cyclic P x Q cells; k falls into lcm(P, Q) classes, each one broadcast and one local product."""
    return _stepped(a, b, p, q, math.lcm(p, q), F.col("kb"), cyclic=True)


def _layered(a: MatrixFrame, b: MatrixFrame, p: int, q: int, layers: int, layer: Column) -> MatrixFrame:
    """Layers of p x q cells, each with its share of k; partial results are summed over the layers by a second exchange."""
    _conform(a, b)

    def side(m: MatrixFrame, own: str, k: str, name: str, n: int, size: int, other: str, others: int) -> DataFrame:
        placed = m.df.select(F.col(own).alias("own"), F.col(k).alias("k"), "value", F.floor(F.col(own) / ceil_div(size, n)).cast("int").alias(name)).withColumn("layer", layer.cast("int"))
        return routing.fan_out(placed, other, others).withColumn("cell_id", ((F.col("layer") * p + F.col("i")) * q + F.col("j")).cast("int")).repartitionById(p * q * layers, F.col("cell_id"))

    left = side(a, "row", "col", "i", p, a.meta.rows, "j", q)
    right = side(b, "col", "row", "j", q, b.meta.cols, "i", p)
    part = kernels.relational(left, right, ["cell_id"], ceil_div(b.meta.rows * b.meta.cols, q * layers) <= HASH_ENTRIES)
    return _out(part.groupBy("row", "col").agg(F.sum("value").alias("value")), a, b)


def multiply_3d(a: MatrixFrame, b: MatrixFrame, q: int) -> MatrixFrame:
    """q^3 cells: cell (i, j, l) multiplies slice l of k once, then the third axis is reduced."""
    return _layered(a, b, q, q, q, F.floor(F.col("k") / ceil_div(a.meta.cols, q)))


def multiply_25d(a: MatrixFrame, b: MatrixFrame, p: int, c: int, block: int) -> MatrixFrame:
    """c layers of sqrt(p / c) x sqrt(p / c) cells, steps dealt over the layers; 1 <= c <= p^(1/3)."""
    side = math.isqrt(p // c) if c else 0
    if c < 1 or c**3 > p or side * side * c != p:
        raise ValueError("2.5D needs 1 <= c <= p^(1/3) and a square number of cells in a layer")
    return _layered(a, b, side, side, c, F.floor(F.col("k") / block) % c)
