"""Grouped and flat products, their special cases and the front door that picks a strategy."""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridmul.operators import kernels, routing
from gridmul.operators.blocks import MatrixFrame
from gridmul.plans import advisor
from gridmul.plans.topology import GridSpec, MatrixMeta, ceil_div, default_grid
from gridmul.session import configure

#: A group's C tile of more entries than this is worked on in parts.
TILE_ENTRIES = 1 << 24
#: Entries of an operand in a task, at most, for which a hash table is made of it; beyond, operands are sorted and can spill.
HASH_ENTRIES = 1 << 21
#: Multiplications and additions of dense panels that take as long as one joined pair of entries.
PANEL_FLOPS = 2000
#: Bytes of a task's memory that the front door plans with.
TASK_BYTES = 1 << 30
#: Rows of an operand up to which it is broadcast; at 24 bytes a row about 100 MB.
BROADCAST_ROWS = 4_000_000
#: Result entries up to which a tall-and-thin product sums partial results instead of routing operands.
THIN_ENTRIES = 1 << 20


def _result(df: DataFrame, a: MatrixFrame, b: MatrixFrame) -> MatrixFrame:
    return MatrixFrame(df.select("row", "col", "value"), MatrixMeta(a.meta.rows, b.meta.cols, a.meta.dtype))


def grouped_multiply(a: MatrixFrame, b: MatrixFrame, grid: GridSpec, inner: int, outer: int | None = None, kernel: str = "relational", routing_form: str = "one_exchange", tile_entries: int = TILE_ENTRIES) -> MatrixFrame:
    """C = A B with the group as the unit of exchange, the cell as that of local work and the step as an order in the task.

    kernel: 'relational' (join and sum), 'panel' (one exchange for both operands, dense panels) or 'hof' (arrays in the JVM).
    routing_form: 'one_exchange', or 'two_exchange', which ships again inside the groups and is kept for comparison."""
    outer = inner if outer is None else outer
    grid.validate(a.meta, b.meta, inner, outer)
    configure(a.spark)
    left = routing.operand(a.df, "a", a.meta, grid, inner, outer)
    right = routing.operand(b.df, "b", b.meta, grid, inner, outer)
    left, right = routing.route_between(left, "a", grid), routing.route_between(right, "b", grid)
    if kernel == "panel":
        return _panel_product(left, right, a, b, grid, inner, outer, tile_entries)
    left, right = (routing.route_inside(routing.exchange_groups(x, grid), side, grid) for x, side in ((left, "a"), (right, "b")))
    keys = ["grp_id", "cell_row", "cell_col"]
    if routing_form == "two_exchange":
        cell = (F.col("cell_row") * grid.t + F.col("cell_col")).cast("int")
        left, right = (x.withColumn("cell_id", cell).repartitionById(grid.cells, F.col("cell_id")) for x in (left, right))
        keys = ["cell_id"]
    elif routing_form != "one_exchange":
        raise ValueError("unknown routing form")
    if kernel == "hof":
        return _result(kernels.hof(left, right, [*keys, "inner_step"], inner), a, b)
    if kernel != "relational":
        raise ValueError("unknown kernel")
    # a bound from the shapes: what of B one task holds, with its copies for the cells
    held = ceil_div(b.meta.rows * b.meta.cols, grid.J) * (grid.s // grid.I)
    return _result(kernels.relational(left, right, keys, held <= HASH_ENTRIES), a, b)


def _panel_product(left: DataFrame, right: DataFrame, a: MatrixFrame, b: MatrixFrame, grid: GridSpec, inner: int, outer: int, tile_entries: int) -> MatrixFrame:
    """Both operands in one tagged frame and one exchange; copies inside a group are slices of its panels, not rows."""
    rows, cols = grid.tile(a.meta.rows, "row", inner), grid.tile(b.meta.cols, "col", inner)
    one = left.select("grp_row", "grp_col", F.lit(0).alias("op"), grid.local_index(F.col("own"), a.meta.rows, "row", inner).alias("local"), "k", "value", "inner_step")
    two = right.select("grp_row", "grp_col", F.lit(1).alias("op"), grid.local_index(F.col("own"), b.meta.cols, "col", inner).alias("local"), "k", "value", "inner_step")
    # a tile too large for a task is cut into stripes of rows there, from panels that were shipped once
    c = kernels.panel(routing.exchange_groups(one.unionByName(two), grid), rows, cols, inner, a.meta.dtype, tile_entries)
    g_row, g_col = F.floor(F.col("grp_id") / grid.J), F.col("grp_id") % grid.J
    return _result(c.select(grid.global_index(F.col("lr"), g_row, a.meta.rows, "row", inner).alias("row"), grid.global_index(F.col("lc"), g_col, b.meta.cols, "col", inner).alias("col"), "value"), a, b)


def flat_multiply(a: MatrixFrame, b: MatrixFrame, grid: GridSpec, block: int, kernel: str = "relational") -> MatrixFrame:
    """The baseline: every entry straight to all cells of its grid row or column; shares the kernels, differs in routing only."""
    flat = grid.with_groups(1, 1)
    flat.validate(a.meta, b.meta, block)
    configure(a.spark)
    left = routing.route_flat(routing.operand(a.df, "a", a.meta, flat, block, block), "a", flat)
    right = routing.route_flat(routing.operand(b.df, "b", b.meta, flat, block, block), "b", flat)
    keys = ["cell_id"]
    return _result(kernels.hof(left, right, [*keys, "inner_step"], block) if kernel == "hof" else kernels.relational(left, right, keys, ceil_div(b.meta.rows * b.meta.cols, grid.t) <= HASH_ENTRIES), a, b)


def multilevel_multiply(a: MatrixFrame, b: MatrixFrame, grid: GridSpec, levels: list[tuple[int, int]], inner: int, outer: int | None = None) -> MatrixFrame:
    """More than two levels: the outermost is the exchange, the others are copies made in the task."""
    first, *rest = levels
    return grouped_multiply(a, b, GridSpec(grid.s, grid.t, *first, tuple(rest), grid.placement, grid.grouping), inner, outer)


def relational_multiply(a: MatrixFrame, b: MatrixFrame) -> MatrixFrame:
    """Join on k, sum by row and col: Catalyst chooses everything."""
    left, right = a.df.select("row", F.col("col").alias("k"), F.col("value").alias("va")), b.df.select(F.col("row").alias("k"), "col", F.col("value").alias("vb"))
    return _result(left.join(right, "k").groupBy("row", "col").agg(F.sum(F.col("va") * F.col("vb")).alias("value")), a, b)


def count_up_to(df: DataFrame, n: int) -> int:
    """Rows of df, counted no further than n + 1."""
    return df.limit(n + 1).count()


def broadcast_multiply(a: MatrixFrame, b: MatrixFrame, max_rows: int = BROADCAST_ROWS) -> MatrixFrame:
    """B to every task, after its size is checked; beyond max_rows the plain relational product is used."""
    if count_up_to(b.df, max_rows) > max_rows:
        return relational_multiply(a, b)
    left, right = a.df.select("row", F.col("col").alias("k"), F.col("value").alias("va")), b.df.select(F.col("row").alias("k"), "col", F.col("value").alias("vb"))
    return _result(left.join(F.broadcast(right), "k").groupBy("row", "col").agg(F.sum(F.col("va") * F.col("vb")).alias("value")), a, b)


def thin_dot_multiply(a: DataFrame, b: DataFrame, rows: int, k: int, cols: int, max_rows: int = BROADCAST_ROWS) -> MatrixFrame:
    """A B for a k of a few dozen: a is (row, v) and b is (col, u) with arrays of k numbers. Every row meets every column, as
    the dense result asks; b goes to every task after its size is checked, and each entry is one dot product in the JVM."""
    if count_up_to(b, max_rows) > max_rows:
        left, right = a.select("row", F.posexplode("v").alias("k", "va")).where("va <> 0"), b.select("col", F.posexplode("u").alias("k", "vb")).where("vb <> 0")
        df = left.join(right, "k").groupBy("row", "col").agg(F.sum(F.col("va") * F.col("vb")).alias("value"))
    else:
        dot = reduce(lambda x, y: x + y, [F.col("v")[i] * F.col("u")[i] for i in range(k)])  # written out, so that it is compiled
        df = a.crossJoin(F.broadcast(b)).select("row", "col", dot.alias("value")).where("value <> 0")
    return MatrixFrame(df, MatrixMeta(rows, cols))


def gram(arrays: DataFrame, column: str, dim: int) -> MatrixFrame:
    """X^T X of rows stored as arrays of whole numbers: each task sums its rows' outer products, then the partial d x d sums add up."""
    schema = pa.schema([("row", pa.int64()), ("col", pa.int64()), ("value", pa.int64())])

    def run(batches):
        total = np.zeros((dim, dim), np.int64)
        seen = False
        for batch in batches:
            x = np.array(batch.column(0).to_pylist(), np.int64).reshape(-1, dim)
            total += kernels.multiply_panels(np.ascontiguousarray(x.T), x)
            seen = seen or len(x) > 0
        if seen:
            r, c = np.indices((dim, dim))
            yield pa.RecordBatch.from_arrays([pa.array(r.ravel()), pa.array(c.ravel()), pa.array(total.ravel())], schema=schema)

    part = arrays.select(column).where(F.col(column).isNotNull()).mapInArrow(run, "row long, col long, value long")
    return MatrixFrame(part.groupBy("row", "col").agg(F.sum("value").alias("value")), MatrixMeta(dim, dim))


def tall_thin_multiply(a: MatrixFrame, b: MatrixFrame, buckets: int = 200) -> MatrixFrame:
    """For a long k and few result entries: both operands are dealt by a bucket of k, each bucket's products are summed where
    they arise, and only the small partial results travel again."""
    configure(a.spark)
    bucket = lambda k: F.pmod(F.xxhash64(k), F.lit(buckets)).cast("int")
    left = a.df.select("row", F.col("col").alias("k"), F.col("value").alias("va")).withColumn("bucket", bucket("k")).repartition(F.col("bucket"))
    right = b.df.select(F.col("row").alias("k"), "col", F.col("value").alias("vb")).withColumn("bucket", bucket("k")).repartition(F.col("bucket"))
    part = left.join(right, ["bucket", "k"]).groupBy("bucket", "row", "col").agg(F.sum(F.col("va") * F.col("vb")).alias("value"))
    return _result(part.groupBy("row", "col").agg(F.sum("value").alias("value")), a, b)


@dataclass(frozen=True)
class Plan:
    """How the front door multiplies: 'flat' where no grouping ships less, the grid, the block and the kernel."""

    method: str
    grid: GridSpec
    inner: int
    kernel: str


def plan_product(nnz_a: int, nnz_b: int, a: MatrixMeta, b: MatrixMeta, cores: int, task_bytes: int = TASK_BYTES) -> Plan:
    """From counts, shapes and memory alone: cells until a group's tile of C fits a quarter of a task and every core has two
    groups, the grouping that ships least among those, the kernel that needs less work for the operands' density."""
    # no more rows or columns than entries, where a shape only bounds the keys
    height, width = min(a.rows, max(nnz_a, 1)), min(b.cols, max(nnz_b, 1))
    side = 1
    while side * side < 2 * cores or ceil_div(height, side) * ceil_div(width, side) * 8 > task_bytes / 4:
        side *= 2
    # cells of a group share its copies; with a k too short to cut once more, a group is a cell
    cells = 2 * side if a.cols >= 2 * side else side
    grid = advisor.advise_groups_spark(nnz_a, nnz_b, cores, task_bytes, GridSpec(cells, cells), height, width)
    rows, cols = ceil_div(height, grid.I), ceil_div(width, grid.J)
    pairs = nnz_a * nnz_b / max(a.cols, 1)
    kernel = "panel" if a.rows * a.cols * b.cols < PANEL_FLOPS * pairs else "relational"
    inner = advisor.advise_block(a.cols, grid, rows, cols, task_bytes)
    flat = grid.J * nnz_a + grid.I * nnz_b >= grid.t * nnz_a + grid.s * nnz_b and kernel == "relational"
    return Plan("flat" if flat else "grouped", grid, max(1, inner), kernel)


def multiply(a: MatrixFrame, b: MatrixFrame, strategy: str = "auto", grid: GridSpec | None = None, inner: int | None = None, groups: str | None = None, **options) -> MatrixFrame:
    """The front door. 'auto' sums partial results where the result is small, broadcasts a small operand, else groups.

    Without a grid, or with groups='auto', operands are counted and `plan_product` settles grid, grouping or none, block and kernel."""
    if a.meta.cols != b.meta.rows:
        raise ValueError("the operands do not conform")
    if groups not in (None, "auto"):
        raise ValueError("groups is 'auto' or given by the grid")
    if strategy == "auto":
        if groups == "auto":
            strategy = "grouped"
        elif a.meta.rows * b.meta.cols <= THIN_ENTRIES and a.meta.cols > 8 * max(a.meta.rows, b.meta.cols):
            strategy = "tall_thin"
        elif b.meta.rows * b.meta.cols <= BROADCAST_ROWS or count_up_to(b.df, BROADCAST_ROWS) <= BROADCAST_ROWS:
            strategy = "broadcast"
        else:
            strategy = "grouped"
    if strategy == "grouped" and (grid is None or groups == "auto"):
        plan = plan_product(a.df.count(), b.df.count(), a.meta, b.meta, a.spark.sparkContext.defaultParallelism)
        if plan.method == "flat":
            return flat_multiply(a, b, plan.grid, inner or plan.inner)
        return grouped_multiply(a, b, plan.grid, inner or plan.inner, **{"kernel": plan.kernel} | options)
    if strategy in ("grouped", "flat"):
        grid = grid or default_grid(a.spark)
        inner = inner or max(1, min(a.meta.cols // grid.s, a.meta.cols // grid.t, 512))
        return grouped_multiply(a, b, grid, inner, **options) if strategy == "grouped" else flat_multiply(a, b, grid, inner, **options)
    simple = {"relational": relational_multiply, "broadcast": broadcast_multiply, "tall_thin": tall_thin_multiply}
    if strategy not in simple:
        raise ValueError(f"unknown strategy {strategy}")
    return simple[strategy](a, b, **options)


def chain_order(dims: list[int]) -> list[tuple[int, int]]:
    """Which neighbours to multiply, in order, for the fewest operations: the classic dynamic programme over intervals."""
    n = len(dims) - 1
    best: dict[tuple[int, int], tuple[int, int]] = {(i, i): (0, i) for i in range(n)}
    for length in range(2, n + 1):
        for i in range(n - length + 1):
            j = i + length - 1
            best[i, j] = min((best[i, m][0] + best[m + 1, j][0] + dims[i] * dims[m + 1] * dims[j + 1], m) for m in range(i, j))
    out: list[tuple[int, int]] = []

    def visit(i: int, j: int) -> None:
        if i < j:
            m = best[i, j][1]
            visit(i, m)
            visit(m + 1, j)
            out.append((i, m + 1))

    visit(0, n - 1)
    return out


def chain(factors: list[MatrixFrame], strategy: str = "relational") -> MatrixFrame:
    """The product of all factors in the cheapest order."""
    if not factors:
        raise ValueError("no factors")
    parts = dict(enumerate(factors))
    for left, right in chain_order([factors[0].meta.rows, *[f.meta.cols for f in factors]]):
        parts[left] = multiply(parts[left], parts.pop(right), strategy)
    return parts[0]


def power(a: MatrixFrame, k: int, strategy: str = "relational") -> MatrixFrame:
    """a^k by repeated squaring."""
    from gridmul.operators.blocks import identity

    out, base = None, a
    if k < 0 or a.meta.rows != a.meta.cols:
        raise ValueError("powers of square matrices, from 0 on")
    while k:
        if k & 1:
            out = base if out is None else multiply(out, base, strategy)
        k >>= 1
        if k:
            base = multiply(base, base, strategy)
    return out or identity(a.spark, a.meta.rows)


def symmetric_product(a: MatrixFrame, full: bool = True) -> MatrixFrame:
    """a a^T from its upper half: half of the sums; the lower half is copied when full."""
    left, right = a.df.select("row", "col", F.col("value").alias("va")), a.df.select(F.col("row").alias("r2"), "col", F.col("value").alias("vb"))
    upper = left.join(right, "col").where("row <= r2").groupBy("row", F.col("r2").alias("c")).agg(F.sum(F.col("va") * F.col("vb")).alias("value")).withColumnRenamed("c", "col")
    if full:
        upper = upper.unionByName(upper.where("row < col").select(F.col("col").alias("row"), F.col("row").alias("col"), "value"))
    return MatrixFrame(upper.select("row", "col", "value"), MatrixMeta(a.meta.rows, a.meta.rows, a.meta.dtype))


def gram_qr(a: MatrixFrame) -> tuple[DataFrame, MatrixFrame]:
    """(Q, R) of a tall matrix with few columns: R is the Cholesky factor of a^T a, whose partial sums alone travel, and Q = a R^-1.

    R has cols x cols entries and is made on the driver; done twice, so that Q's columns are orthogonal to working precision."""
    n = a.meta.cols
    if n * n > THIN_ENTRIES:
        raise ValueError("too many columns for a factor on the driver")
    meta = MatrixMeta(n, n, "double")

    def factor(x: MatrixFrame) -> np.ndarray:
        g = np.zeros((n, n))
        for r in tall_thin_multiply(x.transpose(), x).df.collect():  # cols x cols sums
            g[r.row, r.col] = r.value
        return np.linalg.cholesky(g).T

    def small(m: np.ndarray) -> MatrixFrame:
        return MatrixFrame(a.spark.createDataFrame([(int(i), int(j), float(m[i, j])) for i, j in zip(*np.nonzero(m))], "row long, col long, value double"), meta)

    doubles = MatrixFrame(a.df.select("row", "col", F.col("value").cast("double").alias("value")), MatrixMeta(a.meta.rows, n, "double"))
    r1 = factor(doubles)
    q1 = broadcast_multiply(doubles, small(np.linalg.inv(r1)))
    r2 = factor(q1)
    return broadcast_multiply(q1, small(np.linalg.inv(r2))).df, small(r2 @ r1)


def blocked_lu(a: MatrixFrame, block: int, materialise=None) -> tuple[DataFrame, DataFrame]:
    """(L, U) entries of a small-step factorisation without pivoting, the trailing update by products.

    A panel (block columns by block rows) is factorised at a time; `materialise` (df -> df) cuts lineage between panels."""
    n = a.meta.rows
    rest, lower, upper = a.df.select("row", "col", F.col("value").cast("double").alias("value")), None, None
    meta = MatrixMeta(n, n, "double")
    keep = materialise or (lambda df: df)
    for at in range(0, n, block):
        end = min(at + block, n)
        corner = rest.where((F.col("row") < end) & (F.col("col") < end)).collect()  # one block: block^2 entries
        m = np.zeros((end - at, end - at))
        for r in corner:
            m[r.row - at, r.col - at] = r.value
        lo, up = np.eye(end - at), m.copy()
        for i in range(end - at):
            for j in range(i + 1, end - at):
                lo[j, i] = up[j, i] / up[i, i]
                up[j] -= lo[j, i] * up[i]
        spark = a.spark

        def small(x: np.ndarray, at: int = at) -> MatrixFrame:
            return MatrixFrame(spark.createDataFrame([(at + int(i), at + int(j), float(x[i, j])) for i, j in zip(*np.nonzero(x))], "row long, col long, value double"), meta)

        below = MatrixFrame(rest.where((F.col("row") >= end) & (F.col("col") < end)), meta)
        right = MatrixFrame(rest.where((F.col("row") < end) & (F.col("col") >= end)), meta)
        l_part = relational_multiply(below, small(np.linalg.inv(up)))
        u_part = relational_multiply(small(np.linalg.inv(lo)), right)
        l_all, u_all = small(lo).df.unionByName(l_part.df), small(up).df.unionByName(u_part.df)
        lower, upper = (l_all, u_all) if lower is None else (lower.unionByName(l_all), upper.unionByName(u_all))
        trailing = MatrixFrame(rest.where((F.col("row") >= end) & (F.col("col") >= end)), meta)
        rest = keep(trailing.sub(relational_multiply(l_part, u_part)).df)
    return lower, upper
