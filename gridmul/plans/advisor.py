"""Choosing the number of groups and the block: from the model, from counts, or from a few real steps."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

from gridmul.functions import cost
from gridmul.operators.blocks import MatrixFrame
from gridmul.plans.topology import GridSpec, ceil_div, valid_groupings


def candidates(platforms: DataFrame) -> DataFrame:
    """Platforms with every power of two from 1 to p as g."""
    return platforms.withColumn("g", F.explode(F.transform(F.sequence(F.lit(0), F.floor(F.log2(F.col("p"))).cast("int")), lambda e: F.pow(F.lit(2.0), e))))


def model_costs(platforms: DataFrame, name: str = "scatter_allgather", **options) -> DataFrame:
    f = cost.family(name)
    rows = candidates(platforms)
    return rows.withColumn("flat", cost.flat_comm(f, **options)).withColumn("grouped", cost.grouped_comm(f, **options)["total"]).withColumn("verdict", cost.verdict(name=name))


def advise_groups(platforms: DataFrame, name: str = "scatter_allgather", by: tuple[str, ...] = ("platform",), **options) -> DataFrame:
    """(*by, g, verdict, flat, grouped): the cheapest number of groups of each platform, the smaller on a tie."""
    order = Window.partitionBy(*by).orderBy(F.round(F.col("grouped"), 12), "g")
    return model_costs(platforms, name, **options).withColumn("place", F.row_number().over(order)).where("place = 1").select(*by, F.col("g").cast("long").alias("g"), "verdict", "flat", "grouped")


def advise_groups_spark(nnz_a: int, nnz_b: int, cores: int, task_bytes: int, grid: GridSpec, rows: int, cols: int, per_core: int = 2) -> GridSpec:
    """The grouping that ships least (J |A| + I |B|) among those with enough tasks for the cores and a C tile that fits one.

    In Spark a group is a task, so few groups are cheap to ship and slow to run; this trade stands in for latency."""
    fits = []
    for i, j in valid_groupings(grid.s, grid.t):
        tile = ceil_div(rows, i) * ceil_div(cols, j) * 8
        fits.append((i * j < per_core * cores, tile > task_bytes / 4, j * nnz_a + i * nnz_b, i * j, i, j))
    *_, i, j = min(fits)
    return grid.with_groups(i, j)


def advise_block(k: int, grid: GridSpec, tile_rows: int, tile_cols: int, task_bytes: int) -> int:
    """The largest power of two that an outer panel may have and whose two panels take a quarter of a task's memory at most."""
    limit = min(k // grid.s, k // grid.t)
    block = 1
    while 2 * block <= limit and 2 * block * (tile_rows + tile_cols) * 8 <= task_bytes / 4:
        block *= 2
    return block


def sweep_groups(run: Callable[[GridSpec], DataFrame], grid: GridSpec, options: list[tuple[int, int]] | None = None) -> list[dict]:
    """Time of `run` (grid -> frame, executed by a count) for every grouping: one run a candidate."""
    out = []
    for i, j in options or valid_groupings(grid.s, grid.t):
        began = time.perf_counter()
        rows = run(grid.with_groups(i, j)).count()
        out.append({"grp_rows": i, "grp_cols": j, "groups": i * j, "rows": rows, "wall_ms": (time.perf_counter() - began) * 1000})
    return out


def first_steps(a: MatrixFrame, b: MatrixFrame, steps: int, block: int) -> tuple[MatrixFrame, MatrixFrame]:
    """The operands' first steps only; on stored operands the filter on k reaches the scan and prunes files."""
    return a.filter(cols=F.col("col") < steps * block), b.filter(rows=F.col("row") < steps * block)


def probe_groups(a: MatrixFrame, b: MatrixFrame, grid: GridSpec, inner: int, steps: int = 3, options: list[tuple[int, int]] | None = None) -> tuple[GridSpec, list[dict]]:
    """The grouping that was fastest over a few steps, and all measured candidates."""
    from gridmul.operators.multiply import grouped_multiply

    x, y = first_steps(a, b, steps, inner)
    runs = sweep_groups(lambda g: grouped_multiply(x, y, g, inner).df, grid, options)
    best = min(runs, key=lambda r: (r["wall_ms"], r["groups"]))
    return grid.with_groups(best["grp_rows"], best["grp_cols"]), runs


def runs_frame(spark: SparkSession, runs: list[dict]) -> DataFrame:
    return spark.createDataFrame([(r["grp_rows"], r["grp_cols"], r["groups"], r["rows"], r["wall_ms"]) for r in runs], "grp_rows int, grp_cols int, groups int, rows long, wall_ms double")


def choose_groups(platforms: DataFrame, grid: GridSpec, name: str = "scatter_allgather") -> GridSpec:
    """The valid grouping nearest the model's advice for one platform; one group (the flat method) where grouping does not pay."""
    row = advise_groups(platforms, name).first()
    if row is None or row.g <= 1:
        return grid.with_groups(1, 1)
    i, j = min(valid_groupings(grid.s, grid.t), key=lambda x: (abs(x[0] * x[1] - row.g), abs(x[0] - x[1])))
    return grid.with_groups(i, j)
