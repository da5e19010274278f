"""The experiments as runs on real tables: sweeps over groups, cells, blocks and outer blocks, each row one measured product.

Times depend on the machine; shipped rows do not: they are what the schedules predict, and show how each measure moves. Every case
runs REPEATS times; `means` gives the average times, `settled` what does not depend on the machine."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterable
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridmul.operators.blocks import MatrixFrame
from gridmul.operators.multiply import flat_multiply, grouped_multiply
from gridmul.plans.measure import shuffle_stats
from gridmul.plans.topology import GridSpec, valid_groupings
from gridmul.schemas import RUNS


#: Runs of a case; the published figures are means of 30.
REPEATS = 2


def run(method: str, a: MatrixFrame, b: MatrixFrame, grid: GridSpec, inner: int, outer: int | None = None, kernel: str = "relational", repeats: int = REPEATS) -> list[tuple]:
    """Rows of RUNS: `repeats` executions of one product, with the shuffles of each."""
    out = []
    for k in range(repeats):
        product = flat_multiply(a, b, grid, inner) if method == "flat" else grouped_multiply(a, b, grid, inner, outer, kernel)
        began = time.perf_counter()
        stats = shuffle_stats(product.df)
        wall = (time.perf_counter() - began) * 1000
        name = method if kernel == "relational" else f"{method}_{kernel}"
        out.append((name, f"{grid.s}x{grid.t}", grid.groups if method != "flat" else 1, a.meta.rows, inner, outer or inner, k, wall, stats["shuffle_bytes"], stats["shuffle_rows"], stats["spill_bytes"]))
    return out


@contextmanager
def stored(*operands: MatrixFrame):
    """The operands held in memory or on disk, so that runs measure the product and not how its operands are made; then let go."""
    for m in operands:
        m.df.persist().count()
    try:
        yield operands
    finally:
        for m in operands:
            m.df.unpersist()


def means(runs: DataFrame) -> DataFrame:
    """The cases of `runs` with their number of runs and mean time."""
    return runs.groupBy("method", "grid", "groups", "n", "b", "outer_b").agg(F.count("*").alias("runs"), F.avg("wall_ms").alias("wall_ms"), F.max("shuffle_rows").alias("shuffle_rows"))


def settled(runs: DataFrame) -> DataFrame:
    """The cases of `runs` without what depends on the machine; groupings of one size are told apart by what they ship."""
    cases = [F.col(c).cast("long").alias(c) if c in ("groups", "n", "b", "outer_b") else F.col(c) for c in ("method", "grid", "groups", "n", "b", "outer_b")]
    return runs.groupBy(*cases, "shuffle_rows").agg(F.count("*").alias("runs"))


def measured(sweep: Callable[..., DataFrame], spark: SparkSession, pair: tuple[MatrixFrame, MatrixFrame], *args) -> DataFrame:
    """The settled figures of a sweep over stored operands."""
    with stored(*pair) as (a, b):
        return settled(sweep(spark, a, b, *args))


def sweep_of_groups(spark: SparkSession, a: MatrixFrame, b: MatrixFrame, grid: GridSpec, block: int, groupings: Iterable[tuple[int, int]] | None = None) -> DataFrame:
    """The flat product and the grouped one for every grouping: one group and one group a cell tie with flat."""
    rows = run("flat", a, b, grid, block)
    for i, j in groupings or valid_groupings(grid.s, grid.t):
        rows += run("grouped", a, b, grid.with_groups(i, j), block)
    return spark.createDataFrame(rows, RUNS)


def sweep_of_cells(spark: SparkSession, a: MatrixFrame, b: MatrixFrame, grids: Iterable[GridSpec], block: int) -> DataFrame:
    """Flat and grouped as the grid grows, with the largest block: nothing to gain on small grids, more on larger ones."""
    rows = []
    for grid in grids:
        rows += run("flat", a, b, grid, block) + run("grouped", a, b, grid, block)
    return spark.createDataFrame(rows, RUNS)


def sweep_of_blocks(spark: SparkSession, a: MatrixFrame, b: MatrixFrame, grid: GridSpec, blocks: Iterable[int], kernel: str = "panel") -> DataFrame:
    """Block sizes: smaller blocks are more steps for the same rows."""
    rows = []
    for block in blocks:
        rows += run("grouped", a, b, grid, block, kernel=kernel)
    return spark.createDataFrame(rows, RUNS)


def sweep_of_outer_blocks(spark: SparkSession, a: MatrixFrame, b: MatrixFrame, grid: GridSpec, inner: int, factors: Iterable[int] = (1, 2, 4)) -> DataFrame:
    """An outer block of once, twice and four times the inner one ships the same rows."""
    rows = []
    for f in factors:
        rows += run("grouped", a, b, grid, inner, inner * f, "panel")
    return spark.createDataFrame(rows, RUNS)
