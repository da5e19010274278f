"""Products against NumPy, and against each other for every grouping."""

import numpy as np
import pyarrow.parquet as pq
import pytest

from gridmul.operators import baselines, blocks, kernels, multiply
from gridmul.operators.blocks import MatrixFrame
from gridmul.plans import measure
from gridmul.plans.topology import GridSpec, MatrixMeta, valid_groupings
from gridmul.sources.tables import synthetic


def frame(spark, x, dtype="long"):
    rows = [(int(i), int(j), x[i, j].item()) for i, j in zip(*np.nonzero(x))]
    return MatrixFrame(spark.createDataFrame(rows, f"row long, col long, value {dtype}"), MatrixMeta(*x.shape, dtype))


def dense(m):
    out = np.zeros((m.meta.rows, m.meta.cols), np.int64 if m.meta.dtype == "long" else float)
    for r in m.df.collect():
        assert out[r.row, r.col] == 0, "an entry came twice"
        out[r.row, r.col] = r.value
    return out


@pytest.fixture(scope="module")
def pair(spark):
    rng = np.random.default_rng(1)
    x, y = rng.integers(-9, 10, (16, 16)), rng.integers(-9, 10, (16, 16))
    return x, y, frame(spark, x), frame(spark, y)


@pytest.mark.parametrize("groups", valid_groupings(2, 4))
def test_every_grouping_gives_the_product(pair, groups):
    x, y, a, b = pair
    assert (dense(multiply.grouped_multiply(a, b, GridSpec(2, 4, *groups), 2, 4)) == x @ y).all()


@pytest.mark.parametrize("kernel", ["relational", "panel", "hof"])
@pytest.mark.parametrize("placement", ["contiguous", "block_cyclic"])
@pytest.mark.parametrize("grouping", ["contiguous", "strided"])
def test_kernels_and_placements(pair, kernel, placement, grouping):
    x, y, a, b = pair
    grid = GridSpec(4, 4, 2, 2, placement=placement, grouping=grouping)
    assert (dense(multiply.grouped_multiply(a, b, grid, 2, kernel=kernel).prune()) == x @ y).all()


def test_panel_stripes_levels_and_second_exchange(pair):
    x, y, a, b = pair
    grid = GridSpec(4, 4, 2, 2)
    assert (dense(multiply.grouped_multiply(a, b, grid, 2, 4, kernel="panel", tile_entries=16)) == x @ y).all()
    assert (dense(multiply.grouped_multiply(a, b, grid, 4, routing_form="two_exchange")) == x @ y).all()
    assert (dense(multiply.multilevel_multiply(a, b, GridSpec(8, 8), [(2, 2), (2, 1), (1, 2)], 2)) == x @ y).all()


def test_flat_and_baselines(pair):
    x, y, a, b = pair
    z = x @ y
    for c in (
        multiply.flat_multiply(a, b, GridSpec(4, 4), 4),
        baselines.cannon_multiply(a, b, 4),
        baselines.fox_multiply(a, b, 4),
        baselines.lcm_shift_multiply(a, b, 2, 3),
        baselines.multiply_3d(a, b, 2),
        baselines.multiply_25d(a, b, 8, 2, 4),
        multiply.relational_multiply(a, b),
        multiply.broadcast_multiply(a, b),
        multiply.broadcast_multiply(a, b, max_rows=3),
        multiply.tall_thin_multiply(a, b, 4),
        multiply.multiply(a, b),
        multiply.multiply(a, b, "grouped"),
    ):
        assert (dense(c) == z).all()


def test_rectangular_and_not_divisible(spark):
    rng = np.random.default_rng(2)
    x, y = rng.integers(-5, 6, (7, 13)), rng.integers(-5, 6, (13, 5))
    for kernel in ("relational", "panel"):
        assert (dense(multiply.grouped_multiply(frame(spark, x), frame(spark, y), GridSpec(2, 2, 2, 1), 3, kernel=kernel)) == x @ y).all()
    # fewer rows than cells
    u, v = rng.integers(1, 5, (2, 8)), rng.integers(1, 5, (8, 3))
    assert (dense(multiply.grouped_multiply(frame(spark, u), frame(spark, v), GridSpec(4, 4, 2, 2), 1)) == u @ v).all()


def test_edges(spark):
    meta = MatrixMeta(8, 8)
    a = synthetic(spark, 8, 8)
    assert multiply.grouped_multiply(blocks.zeros(spark, meta), a, GridSpec(2, 2, 2, 2), 2).df.count() == 0
    assert multiply.grouped_multiply(blocks.zeros(spark, meta), a, GridSpec(2, 2), 2, kernel="panel").df.count() == 0
    one = np.zeros((8, 8), int)
    one[3, 5] = -4
    assert (dense(multiply.grouped_multiply(frame(spark, one), a, GridSpec(1, 1), 8)) == one @ dense(a)).all()
    column = np.arange(1, 9).reshape(8, 1)
    assert (dense(multiply.grouped_multiply(frame(spark, column.T), frame(spark, column), GridSpec(1, 1), 4)) == column.T @ column).all()


def test_algebra(pair, spark):
    x, y, a, b = pair
    eye = blocks.identity(spark, 16)
    grid = GridSpec(4, 4, 2, 2)
    assert (dense(multiply.grouped_multiply(eye, a, grid, 4)) == x).all()
    ab = multiply.grouped_multiply(a, b, grid, 4)
    assert (dense(ab.transpose()) == dense(multiply.grouped_multiply(b.transpose(), a.transpose(), grid, 4))).all()
    assert (dense(multiply.relational_multiply(a, b.add(eye))) == x @ y + x).all()
    assert (dense(multiply.chain([a, b, a])) == x @ y @ x).all()
    assert (dense(multiply.power(a, 3)) == np.linalg.matrix_power(x, 3)).all()
    assert (dense(multiply.power(a, 0)) == np.eye(16)).all()
    assert (dense(multiply.symmetric_product(a)) == x @ x.T).all()
    assert (dense(a.sub(b)) == x - y).all() and (dense(a.hadamard(b)) == x * y).all()
    assert a.trace().first().value == np.trace(x)
    assert (dense(MatrixFrame.from_blocks(a.to_blocks(6), 6, a.meta)) == x).all()
    assert a.densify().df.count() == 256


def test_double_kernel_within_tolerance(spark):
    rng = np.random.default_rng(3)
    x, y = rng.random((12, 12)), rng.random((12, 12))
    c = multiply.grouped_multiply(frame(spark, x, "double"), frame(spark, y, "double"), GridSpec(2, 2, 2, 2), 3, kernel="panel")
    assert np.allclose(dense(c), x @ y, rtol=1e-9)
    err = measure.errors(c, multiply.relational_multiply(frame(spark, x, "double"), frame(spark, y, "double"))).first()
    assert err.rel_frobenius < 1e-12


def test_large_integers_stay_exact(spark):
    x = np.array([[3_000_000_019, 1], [7, 2_999_999_999]])
    y = np.array([[1_000_003, 5], [11, 1_000_033]])
    c = multiply.grouped_multiply(frame(spark, x), frame(spark, y), GridSpec(1, 1), 2, kernel="panel")
    assert (dense(c) == x @ y).all()
    assert measure.bound_check(frame(spark, x), frame(spark, y))
    huge = np.array([[1 << 40]])
    assert not measure.bound_check(frame(spark, huge), frame(spark, huge))


def test_blocked_lu(spark):
    rng = np.random.default_rng(4)
    x = rng.random((6, 6)) + 6 * np.eye(6)
    lo, up = multiply.blocked_lu(frame(spark, x, "double"), 2)
    meta = MatrixMeta(6, 6, "double")
    left, right = dense(MatrixFrame(lo, meta)), dense(MatrixFrame(up, meta))
    assert np.allclose(np.tril(left), left) and np.allclose(np.triu(right), right)
    assert np.allclose(left @ right, x)


def test_probe_vector_finds_a_wrong_entry(pair, spark):
    x, y, a, b = pair
    z = x @ y
    assert all(r.residual == 0 for r in measure.verify_product(a, b, frame(spark, z)).collect())
    z[3, 4] += 1
    assert all(r.residual == 1 for r in measure.verify_product(a, b, frame(spark, z)).collect())


def test_bad_inputs(pair, spark):
    _, _, a, b = pair
    with pytest.raises(ValueError):
        GridSpec(4, 4, 3, 2)
    with pytest.raises(ValueError):
        multiply.grouped_multiply(a, b, GridSpec(4, 4), 3, 4)
    with pytest.raises(ValueError):
        multiply.grouped_multiply(a, b, GridSpec(4, 4), 4, 2)
    with pytest.raises(ValueError):
        multiply.grouped_multiply(a, b, GridSpec(4, 4), 8)
    with pytest.raises(ValueError):
        multiply.grouped_multiply(a, synthetic(spark, 5, 5), GridSpec(1, 1), 1)
    with pytest.raises(ValueError):
        baselines.cannon_multiply(a, b, GridSpec(2, 4))
    with pytest.raises(ValueError):
        baselines.multiply_25d(a, b, 16, 4, 2)
    with pytest.raises(ValueError):
        GridSpec.square(8, 4)


def test_chain_order():
    assert multiply.chain_order([10, 100, 5, 50]) == [(0, 1), (0, 2)]
    assert multiply.chain_order([5, 25, 1000, 2]) == [(1, 2), (0, 1)]


@pytest.mark.parametrize("tile_entries", [8, 64, 200])
def test_stripes_ship_nothing_twice(pair, tile_entries):
    x, y, a, b = pair
    grid = GridSpec(4, 4, 2, 2)
    shipped = [measure.shuffle_stats(multiply.grouped_multiply(a, b, grid, 2, kernel="panel", tile_entries=t).df)["shuffle_rows"] for t in (tile_entries, 1 << 24)]
    assert shipped[0] == shipped[1] == 2 * (a.df.count() + b.df.count())
    # a step that only one operand has, a whole stripe without entries, and a k of more steps than are multiplied at once
    u, v = x.copy(), y.copy()
    u[:, 4:6], v[8:10], u[2:4] = 0, 0, 0
    for dtype, kind in (("long", np.int64), ("double", float)):
        c = multiply.grouped_multiply(frame(a.spark, u.astype(kind), dtype), frame(a.spark, v.astype(kind), dtype), grid, 2, 4, kernel="panel", tile_entries=tile_entries)
        assert (dense(c) == u @ v).all()


def test_large_product_is_written_in_few_bytes(spark, tmp_path):
    """Many values that all repeat: the files of C are much smaller than those of the same rows by row and column, and whole."""
    rng = np.random.default_rng(5)
    x, y = rng.integers(-300, 300, (2048, 16)), rng.integers(-300, 300, (16, 2048))
    for tile_entries in ((1 << 22) - 1, 1 << 24):
        c = multiply.grouped_multiply(frame(spark, x), frame(spark, y), GridSpec(1, 1), 8, kernel="panel", tile_entries=tile_entries).df
        c.write.mode("overwrite").parquet(f"{tmp_path}/c")
        spark.read.parquet(f"{tmp_path}/c").repartition(1).sortWithinPartitions("row", "col").write.mode("overwrite").parquet(f"{tmp_path}/by_place")
        size = {n: sum(p.stat().st_size for p in (tmp_path / n).glob("*.parquet")) for n in ("c", "by_place")}
        assert size["c"] < 0.85 * size["by_place"], size
        t = pq.read_table(tmp_path / "c")
        row, col, value = (t[n].to_numpy() for n in ("row", "col", "value"))
        assert len(np.unique(row * 2048 + col)) == len(row) == np.count_nonzero(x @ y)
        z = np.zeros((2048, 2048), np.int64)
        z[row, col] = value
        assert (z == x @ y).all()


@pytest.mark.parametrize("tile", [np.zeros((3, 4), np.int64), np.arange(-5, 7).reshape(3, 4), np.array([[2**63 - 1, 0], [-(2**63), 5]]), np.array([[0.5, np.nan], [np.inf, -0.0]]), np.tile(np.array([[7, -7, 0, 9, 2**62]]), (40, 1)), np.tile(np.array([[0.25, -1e300, 0]]), (9, 1))])
@pytest.mark.parametrize("dictionary", [0, 1 << 17])
@pytest.mark.parametrize("batch", [3, 1 << 16])
def test_file_order_keeps_every_entry(tile, dictionary, batch, monkeypatch):
    monkeypatch.setattr(kernels, "DICTIONARY", dictionary)
    monkeypatch.setattr(kernels, "BATCH", batch)
    parts = list(kernels.in_file_order(tile))
    assert all(0 < len(p) == len(v) <= batch for p, v in parts)
    got = np.zeros_like(tile)
    for p, v in parts:
        got.ravel()[p] = v
    np.testing.assert_array_equal(got, tile)
    assert sum(len(p) for p, _ in parts) == np.count_nonzero(tile)
