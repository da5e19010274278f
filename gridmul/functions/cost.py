"""Closed-form costs as column expressions: literals fold, no Python runs on the executors.

A broadcast of m elements among q processors costs L(q) alpha + m W(q) beta with L(1) = W(1) = 0. A cost here takes
columns, so a frame of platforms crossed with candidates is evaluated at once. Times are seconds where beta is per element;
`element_bytes` scales it where beta is per byte."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from gridmul.plans.topology import GridSpec, MatrixMeta


def col(x: Column | str | float) -> Column:
    return x if isinstance(x, Column) else F.col(x) if isinstance(x, str) else F.lit(float(x))


def lg(x: Column) -> Column:
    return F.log2(x)


@dataclass(frozen=True)
class BroadcastFamily:
    """Latency and bandwidth factors of a broadcast algorithm, with their derivatives where they are known."""

    name: str
    latency: Callable[[Column], Column]
    bandwidth: Callable[[Column], Column]
    d_latency: Callable[[Column], Column] | None = None
    d_bandwidth: Callable[[Column], Column] | None = None


def _tree(q: Column) -> Column:
    return 2 * lg((q + 1) / 2)


def family(name: str, segments: int = 8) -> BroadcastFamily:
    one = F.lit(1.0)
    log_slope = lambda q: one / (q * math.log(2))
    if name == "binomial":
        return BroadcastFamily(name, lg, lg, log_slope, log_slope)
    if name == "scatter_allgather":
        return BroadcastFamily(name, lambda q: lg(q) + q - 1, lambda q: 2 * (q - 1) / q, lambda q: log_slope(q) + 1, lambda q: 2 / (q * q))
    if name in ("flat", "chain"):
        return BroadcastFamily(name, lambda q: q - 1, lambda q: q - 1, lambda q: one + 0 * q, lambda q: one + 0 * q)
    if name == "binary":
        slope = lambda q: 2 / ((q + 1) * math.log(2))
        return BroadcastFamily(name, _tree, _tree, slope, slope)
    if name == "chain_pipelined":
        k = segments
        return BroadcastFamily(name, lambda q: F.when(q > 1, q - 2 + k).otherwise(0.0), lambda q: F.when(q > 1, (q - 2 + k) / k).otherwise(0.0))
    raise ValueError(f"unknown broadcast family {name}")


def family_from(latency: Callable[[float], float], bandwidth: Callable[[float], float], latency_column: Callable[[Column], Column], bandwidth_column: Callable[[Column], Column], name: str = "custom", up_to: int = 1024) -> BroadcastFamily:
    """A family of one's own. Both factors must be 0 at 1, monotone, and have a monotone slope (checked on a sample grid)."""
    for what, f in (("latency", latency), ("bandwidth", bandwidth)):
        if abs(f(1)) > 1e-12:
            raise ValueError(f"{what} factor is not 0 for one processor")
        xs = [1 + (up_to - 1) * i / 64 for i in range(65)]
        steps = [f(b) - f(a) for a, b in zip(xs, xs[1:])]
        bends = [b - a for a, b in zip(steps, steps[1:])]
        for values in (steps, bends):
            if min(values) < -1e-9 and max(values) > 1e-9:
                raise ValueError(f"{what} factor or its slope is not monotone")
    return BroadcastFamily(name, latency_column, bandwidth_column)


def hockney(m, alpha="alpha", beta="beta") -> Column:
    """Point-to-point time of a message of m elements."""
    return col(alpha) + col(m) * col(beta)


def broadcast_time(f: BroadcastFamily, m, q, alpha="alpha", beta="beta") -> Column:
    return f.latency(col(q)) * col(alpha) + col(m) * f.bandwidth(col(q)) * col(beta)


def steps(n="n", b="b") -> Column:
    return col(n) / col(b)


def panel_elements(n="n", b="b", p="p") -> Column:
    """Elements of one operand's panel that a processor sends in a step."""
    return col(n) * col(b) / F.sqrt(col(p))


def compute_cost(n="n", p="p", gamma="gamma", flops_per_update: int = 2, gamma_scope: str = "per_processor") -> Column:
    """flops_per_update n^3 gamma / p; with gamma_scope 'total' the rate is of the whole machine and p does not divide."""
    work = flops_per_update * F.pow(col(n), F.lit(3)) * col(gamma)
    return work / col(p) if gamma_scope == "per_processor" else work


def _sum(latency: Column, bandwidth: Column, row_col: str) -> Column:
    """Row and column broadcasts one after the other ('sum') or at once ('max')."""
    return (2 if row_col == "sum" else 1) * (latency + bandwidth)


def flat_comm(f: BroadcastFamily, n="n", b="b", p="p", alpha="alpha", beta="beta", element_bytes: int = 1, row_col: str = "sum") -> Column:
    n, b, p, side = col(n), col(b), col(p), F.sqrt(col(p))
    return _sum(n / b * f.latency(side) * col(alpha), n * n / side * f.bandwidth(side) * col(beta) * element_bytes, row_col)


def grouped_inner(f: BroadcastFamily, n="n", b="b", p="p", g="g", alpha="alpha", beta="beta", element_bytes: int = 1, row_col: str = "sum") -> Column:
    """Inside the groups: as the flat method on sqrt(p / g) processors a side."""
    n, p, q = col(n), col(p), F.sqrt(col(p) / col(g))
    return _sum(n / col(b) * f.latency(q) * col(alpha), n * n / F.sqrt(p) * f.bandwidth(q) * col(beta) * element_bytes, row_col)


def grouped_outer(f: BroadcastFamily, n="n", outer="b", p="p", g="g", alpha="alpha", beta="beta", element_bytes: int = 1, row_col: str = "sum") -> Column:
    """Between the groups, with the outer block."""
    n, p, q = col(n), col(p), F.sqrt(col(g))
    return _sum(n / col(outer) * f.latency(q) * col(alpha), n * n / F.sqrt(p) * f.bandwidth(q) * col(beta) * element_bytes, row_col)


def grouped_comm(f: BroadcastFamily, n="n", b="b", p="p", g="g", alpha="alpha", beta="beta", outer=None, **options) -> Column:
    """struct(latency, bandwidth, total)."""
    outer = b if outer is None else outer
    parts = [grouped_inner(f, n, b, p, g, x, y, **options) + grouped_outer(f, n, outer, p, g, x, y, **options) for x, y in ((alpha, 0.0), (0.0, beta))]
    return F.struct(parts[0].alias("latency"), parts[1].alias("bandwidth"), (parts[0] + parts[1]).alias("total"))


def rotation_comm(n="n", p="p", alpha="alpha", beta="beta") -> Column:
    """Rotations on a square grid: both operands' blocks move once to be aligned and sqrt(p) - 1 times after."""
    side = F.sqrt(col(p))
    return 2 * side * hockney(col(n) * col(n) / col(p), alpha, beta)


def broadcast_roll_comm(f: BroadcastFamily, n="n", p="p", alpha="alpha", beta="beta") -> Column:
    """sqrt(p) steps, each a broadcast of a block of A along a row and a move of a block of B."""
    side, block = F.sqrt(col(p)), col(n) * col(n) / col(p)
    return side * broadcast_time(f, block, side, alpha, beta) + (side - 1) * hockney(block, alpha, beta)


def lcm_shift_comm(f: BroadcastFamily, rows, cols, classes, n="n", alpha="alpha", beta="beta") -> Column:
    """cols - 1 shifts of all of A, `classes` (the least common multiple of rows and cols) broadcasts of B down the columns."""
    rows, cols, classes, square = col(rows), col(cols), col(classes), col(n) * col(n)
    return (cols - 1) * hockney(square / (rows * cols), alpha, beta) + classes * broadcast_time(f, square / (classes * cols), rows, alpha, beta)


def layered_comm(f: BroadcastFamily, n="n", b="b", p="p", c="c", alpha="alpha", beta="beta") -> Column:
    """c layers of sqrt(p / c) x sqrt(p / c): two replications and a reduction over the layers, and of the flat method's steps the
    c-th part in each layer. With c = p^(1/3) it is the 3-D product."""
    n, p, c = col(n), col(p), col(c)
    side = F.sqrt(p / c)
    over_layers = 3 * broadcast_time(f, n * n / (side * side), c, alpha, beta)
    return over_layers + 2 * n / col(b) / c * broadcast_time(f, n * col(b) / side, side, alpha, beta)


def grouped_at_sqrt(n="n", b="b", p="p", alpha="alpha", beta="beta", as_printed: bool = False) -> Column:
    """Scatter-allgather cost with sqrt(p) groups and one block size.

    The corrected form has fourth roots; as_printed keeps the published square roots, a labelled variant only."""
    n, b, p = col(n), col(b), col(p)
    root = F.sqrt(p) if as_printed else F.pow(p, F.lit(0.25))
    return (lg(p) + 4 * (root - 1)) * n / b * col(alpha) + 8 * (1 - 1 / root) * n * n / F.sqrt(p) * col(beta)


def cost_table(spark: SparkSession, name: str, platforms: DataFrame, groups: Column, outer=None) -> DataFrame:
    """Latency and bandwidth factors inside and between groups and the compute term, one row a platform and method."""
    f = family(name)
    one = F.lit(1.0)
    base = platforms.withColumn("g", groups).withColumn("flat_latency", flat_comm(f, alpha=1.0, beta=0.0)).withColumn("flat_bandwidth", flat_comm(f, alpha=0.0, beta=1.0))
    rows = base.select("platform", "n", "p", "b", "g", compute_cost(gamma=one).alias("compute"), "flat_latency", "flat_bandwidth", grouped_inner(f, alpha=1.0, beta=0.0).alias("latency_inside"), grouped_outer(f, outer=outer or "b", alpha=1.0, beta=0.0).alias("latency_between"), grouped_inner(f, alpha=0.0, beta=1.0).alias("bandwidth_inside"), grouped_outer(f, outer=outer or "b", alpha=0.0, beta=1.0).alias("bandwidth_between"))
    return rows.withColumn("family", F.lit(name))


def d_cost_dg(f: BroadcastFamily, n="n", b="b", p="p", g="g", alpha="alpha", beta="beta") -> Column:
    """Slope of the grouped cost in the number of groups: from the factors' slopes, or by central differences."""
    if f.d_latency and f.d_bandwidth:
        n, b, p, g = col(n), col(b), col(p), col(g)
        q, r = F.sqrt(g), F.sqrt(p / g)

        def part(d: Callable[[Column], Column]) -> Column:
            return d(q) / q - d(r) * r / g

        return n / b * part(f.d_latency) * col(alpha) + n * n / F.sqrt(p) * part(f.d_bandwidth) * col(beta)
    h = col(g) * 1e-4
    return (grouped_comm(f, n, b, p, col(g) + h, alpha, beta)["total"] - grouped_comm(f, n, b, p, col(g) - h, alpha, beta)["total"]) / (2 * h)


def d_cost_dg_scatter_allgather(n="n", b="b", p="p", g="g", alpha="alpha", beta="beta") -> Column:
    """The closed form for scatter-allgather."""
    n, p, g = col(n), col(p), col(g)
    return (g - F.sqrt(p)) / (g * F.sqrt(g)) * (n * col(alpha) / col(b) - 2 * n * n / p * col(beta))


def verdict(n="n", b="b", p="p", alpha="alpha", beta="beta", name: str = "scatter_allgather", element_bytes: int = 1) -> Column:
    """Whether sqrt(p) groups are the best, the worst or as good as any (alpha / beta against 2 n b / p)."""
    if name == "binomial":
        return F.lit("indifferent")
    ratio, bound = col(alpha) / (col(beta) * element_bytes), 2 * col(n) * col(b) / col(p)
    near = F.abs(ratio - bound) <= 1e-9 * bound
    return F.when(near, "indifferent").when(ratio > bound, "min_at_sqrt_p").otherwise("max_at_sqrt_p")


def break_even_p(n="n", b="b", alpha="alpha", beta="beta") -> Column:
    """Processors from which sqrt(p) groups pay."""
    return 2 * col(n) * col(b) * col(beta) / col(alpha)


def exec_time(comm: Column, compute: Column, overlap: bool = False) -> Column:
    """Compute plus communication; with overlap their maximum, a lower bound."""
    return F.greatest(comm, compute) if overlap else comm + compute


def gain(flat: Column, grouped: Column) -> Column:
    return flat / grouped


def copies(method: str, p: int | Column, c: int = 1) -> float | Column:
    """How many copies of the operands a method keeps; a column where p is one and decides."""
    return {"3d": p ** (1 / 3), "25d": float(c)}.get(method, 1.0)


def memory_elements(method: str, a: MatrixMeta, b: MatrixMeta, grid: GridSpec, outer: int = 1, c: int = 1) -> float:
    """Elements that a processor holds: its parts of A, B and C and the panels in flight."""
    m, k, n, p = a.rows, a.cols, b.cols, grid.cells
    own = (m * k + k * n + m * n) / p
    if method in ("flat", "grouped"):
        return own + outer * (m / grid.s + n / grid.t)
    if method == "25d":
        return own * c
    if method == "3d":
        return own * p ** (1 / 3)
    if method == "lcm_shift":  # the largest panels: all of a cell's rows and columns for one class of k
        return own + k / math.lcm(grid.s, grid.t) * (m / grid.s + n / grid.t)
    if method in ("cannon", "fox"):
        return own + (m * k + k * n) / p
    raise ValueError(f"unknown method {method}")
