"""Physical plans, schedules, costs and advice."""

import math

import pytest
from pyspark.sql import functions as F

from gridmul.functions import cost
from gridmul.operators import multiply
from gridmul.plans import advisor, measure, schedule
from gridmul.plans.topology import GridSpec, MatrixMeta, valid_groupings
from gridmul.sources.tables import platforms, read_triplets, synthetic, write_matrix


@pytest.mark.parametrize("aqe", ["true", "false"])
def test_product_has_two_exchanges_or_one(spark, aqe):
    before = spark.conf.get("spark.sql.adaptive.enabled")
    spark.conf.set("spark.sql.adaptive.enabled", aqe)
    try:
        a, b = synthetic(spark, 16, 16), synthetic(spark, 16, 16)
        grid = GridSpec(4, 4, 2, 2)
        assert measure.exchanges(multiply.grouped_multiply(a, b, grid, 2).df) == 2
        assert measure.exchanges(multiply.grouped_multiply(a, b, grid, 2, kernel="panel").df) == 1
        plan = measure.executed_plan(multiply.grouped_multiply(a, b, grid, 2).df)
        assert "Cartesian" not in plan and "NestedLoop" not in plan
        # copies for the cells are made above the exchange
        assert plan.index("Generate") < plan.index("Exchange")
    finally:
        spark.conf.set("spark.sql.adaptive.enabled", before)


def test_scan_reads_only_what_it_needs(spark):
    from gridmul.sources import workloads

    a, _ = workloads.square_pair(spark, "/root/testdata/sf0.001", 64)
    plan = measure.executed_plan(a.df)
    assert "l_orderkey" in plan and "l_extendedprice" not in plan


def test_each_group_has_its_own_partition(spark):
    from gridmul.operators import routing

    a = synthetic(spark, 16, 16)
    grid = GridSpec(4, 4, 4, 2)
    sent = routing.exchange_groups(routing.route_between(routing.operand(a.df, "a", a.meta, grid, 2, 2), "a", grid), grid)
    rows = sent.groupBy(F.spark_partition_id().alias("p"), "grp_id").count().collect()
    assert len(rows) == 8 and all(r.p == r.grp_id for r in rows)


def test_one_exchange_ships_fewer_copies(spark):
    a, b = synthetic(spark, 32, 32), synthetic(spark, 32, 32)
    grid = GridSpec(8, 8, 2, 2)
    grouped = measure.shuffle_stats(multiply.grouped_multiply(a, b, grid, 4).df)["shuffle_rows"]
    flat = measure.shuffle_stats(multiply.flat_multiply(a, b, grid, 4).df)["shuffle_rows"]
    n = a.df.count() + b.df.count()
    assert (grouped, flat) == (2 * n, 8 * n)


def test_groups_of_the_six_by_six_grid(spark):
    rows = GridSpec(6, 6, 3, 3).frame(spark).collect()
    groups = {}
    for r in rows:
        groups.setdefault((r.grp_row, r.grp_col), set()).add((r.cell_row, r.cell_col))
    assert len(groups) == 9 and all(len(g) == 4 for g in groups.values())
    assert groups[0, 0] == {(0, 0), (0, 1), (1, 0), (1, 1)}


def test_between_groups_goes_to_the_same_inner_place(spark):
    meta = MatrixMeta(12, 12)
    plan = schedule.schedule(spark, "grouped", meta, meta, GridSpec(6, 6, 3, 3), 1, 1)
    a = plan.where("operand = 'A' AND level = 'between' AND step = 1").collect()
    # the second block lies in the first cell column: first group column, first place
    assert {(r.root_grp_col, r.root_in_col, r.receivers) for r in a} == {(0, 0, 2)}
    b = plan.where("operand = 'B' AND level = 'between' AND step = 1").collect()
    assert {(r.root_grp_row, r.root_in_row, r.receivers) for r in b} == {(0, 0, 2)}


def test_outer_block_has_four_inner_steps(spark):
    meta = MatrixMeta(16, 16)
    plan = schedule.schedule(spark, "grouped", meta, meta, GridSpec(4, 4, 2, 2), 1, 4)
    inside = plan.where("outer_step = 1 AND level = 'inside' AND operand = 'A'").select("step", "inner_step").distinct().collect()
    assert sorted((r.step, r.inner_step) for r in inside) == [(4, 0), (5, 1), (6, 2), (7, 3)]


@pytest.mark.parametrize("shape", [(96, 192, 48), (96, 96, 96)])
@pytest.mark.parametrize("groups", [(1, 1), (3, 3), (2, 3), (6, 6)])
def test_deliveries_are_those_of_the_flat_method(spark, shape, groups):
    m, k, n = shape
    a, b = MatrixMeta(m, k), MatrixMeta(k, n)
    grid = GridSpec(6, 6, *groups)
    want = schedule.counted(a, b, grid)
    got = {(r.operand, r.level): r.deliveries for r in schedule.totals(schedule.schedule(spark, "grouped", a, b, grid, 4, 8)).collect()}
    flat = {r.operand: r.deliveries for r in schedule.totals(schedule.schedule(spark, "flat", a, b, grid, 4)).collect()}
    for op in "AB":
        assert got[op, "between"] == want[op, "between"] and got[op, "inside"] == want[op, "inside"]
        assert got[op, "between"] + got[op, "inside"] == flat[op] == want[op, "flat"]


def value(spark, column, **cols):
    return spark.range(1).select(*[F.lit(float(v)).alias(k) for k, v in cols.items()]).select(column.alias("x")).first().x


EXA = {"n": 2**22, "p": 2**20, "b": 256, "alpha": 5e-7, "beta": 1e-11}
SUPER = {"n": 65536, "p": 16384, "b": 256, "alpha": 3e-6, "beta": 1e-9}


@pytest.mark.parametrize("name", ["binomial", "scatter_allgather", "flat", "binary", "chain_pipelined"])
def test_one_group_and_p_groups_cost_as_the_flat_method(spark, name):
    f = cost.family(name)
    flat = value(spark, cost.flat_comm(f), **SUPER)
    for g in (1, SUPER["p"]):
        assert math.isclose(value(spark, cost.grouped_comm(f)["total"], g=g, **SUPER), flat, rel_tol=1e-12)


def test_anchor_values(spark):
    f = cost.family("scatter_allgather")
    assert round(value(spark, cost.flat_comm(f), **EXA), 6) == 17.611196
    assert round(value(spark, cost.grouped_comm(f)["total"], g=1024, **EXA), 6) == 2.511088
    assert round(value(spark, cost.grouped_at_sqrt(), **EXA), 6) == 2.511088
    assert round(value(spark, cost.grouped_at_sqrt(as_printed=True), **EXA), 6) == 35.058551
    assert round(value(spark, cost.flat_comm(f), **SUPER), 6) == 0.338993
    assert round(value(spark, cost.grouped_comm(f)["total"], g=128, **SUPER), 6) == 0.287145


def test_slope_changes_its_sign_at_sqrt_p(spark):
    f = cost.family("scatter_allgather")
    for g, sign in ((4, -1), (64, -1), (256, 1), (8192, 1)):
        general = value(spark, cost.d_cost_dg(f), g=g, **SUPER)
        closed = value(spark, cost.d_cost_dg_scatter_allgather(), g=g, **SUPER)
        assert math.isclose(general, closed, rel_tol=1e-9) and general * sign > 0
    assert abs(value(spark, cost.d_cost_dg(f), g=128, **SUPER)) < 1e-18
    # where the condition fails the signs turn round; the binomial family has no slope
    assert value(spark, cost.d_cost_dg(f), g=4, **(SUPER | {"p": 2048})) > 0
    assert abs(value(spark, cost.d_cost_dg(cost.family("binomial")), g=4, **SUPER)) < 1e-15
    piped = cost.family("chain_pipelined")
    assert value(spark, cost.d_cost_dg(piped), g=4, **SUPER) < 0


def test_verdicts_and_advice(spark):
    rows = {r.platform: r for r in advisor.advise_groups(platforms(spark)).collect()}
    assert rows["supercomputer"].g == 128 and rows["supercomputer_2048"].g == 1
    assert rows["cluster"].g == 8 and rows["cluster_large_block"].g == 8
    assert rows["exascale"].g == 1024 and round(rows["exascale"].flat / rows["exascale"].grouped, 2) == 7.01
    assert rows["supercomputer_2048"].verdict == "max_at_sqrt_p"
    assert advisor.choose_groups(platforms(spark).where("platform = 'supercomputer_2048'"), GridSpec(4, 4)).groups == 1


def test_own_family_is_checked(spark):
    ok = cost.family_from(lambda q: q - 1, lambda q: q - 1, lambda q: q - 1, lambda q: q - 1)
    assert math.isclose(value(spark, cost.flat_comm(ok), **SUPER), value(spark, cost.flat_comm(cost.family("flat")), **SUPER))
    with pytest.raises(ValueError):
        cost.family_from(lambda q: q, lambda q: q - 1, lambda q: q, lambda q: q - 1)
    with pytest.raises(ValueError):
        cost.family_from(lambda q: math.sin(q - 1), lambda q: q - 1, lambda q: q, lambda q: q - 1)


def test_overlap_units_and_memory(spark):
    assert value(spark, cost.exec_time(F.lit(3.0), F.lit(2.0), overlap=True)) == 3.0
    f = cost.family("scatter_allgather")
    assert value(spark, cost.flat_comm(f, row_col="max"), **SUPER) * 2 == pytest.approx(value(spark, cost.flat_comm(f), **SUPER))
    m, grid = MatrixMeta(4096, 4096), GridSpec(8, 8)
    flat = cost.memory_elements("flat", m, m, grid, 64)
    assert cost.memory_elements("grouped", m, m, grid, 64) == flat < cost.memory_elements("lcm_shift", m, m, grid)
    assert round(cost.copies("3d", 10**6)) == 100


def test_groupings_block_and_spark_advice():
    assert len(valid_groupings(8, 16)) == 20
    grid = advisor.advise_groups_spark(10**9, 10**9, 32, 1 << 30, GridSpec(16, 16), 4096, 4096)
    assert grid.groups >= 64 and grid.I == grid.J
    assert advisor.advise_block(8192, GridSpec(8, 16), 1024, 512, 1 << 30) == 512
    assert advisor.advise_block(8192, GridSpec(8, 16), 1 << 20, 1 << 20, 1 << 26) == 1


def test_probe_and_filter_push_down(spark, tmp_path):
    a, b = synthetic(spark, 16, 16), synthetic(spark, 16, 16)
    grid, runs = advisor.probe_groups(a, b, GridSpec(2, 2), 4, steps=1)
    assert len(runs) == 4 and grid.groups in {r["groups"] for r in runs}
    write_matrix(a, str(tmp_path / "a"))
    stored = read_triplets(spark, str(tmp_path / "a"), "parquet", a.meta)
    probe, _ = advisor.first_steps(stored, b, 1, 4)
    assert "LessThan(col,4)" in measure.executed_plan(probe.df)


@pytest.mark.parametrize("fmt", ["parquet", "orc", "json", "csv", "text"])
def test_sources_and_sinks(spark, tmp_path, fmt):
    a = synthetic(spark, 8, 8)
    write_matrix(a, str(tmp_path / fmt), fmt, block=4 if fmt == "parquet" else None)
    back = read_triplets(spark, str(tmp_path / fmt), fmt, a.meta)
    assert back.df.exceptAll(a.df).count() == 0 and a.df.exceptAll(back.df).count() == 0


def test_sweeps_move_as_the_schedules_say(spark):
    from gridmul.plans import experiments

    a, b = synthetic(spark, 16, 16), synthetic(spark, 16, 16)
    n = a.df.count()
    runs = {(r.method, r.groups): r.shuffle_rows for r in experiments.sweep_of_groups(spark, a, b, GridSpec(4, 4), 2, [(1, 1), (2, 2), (4, 4)]).collect()}
    assert runs == {("flat", 1): 8 * n, ("grouped", 1): 2 * n, ("grouped", 4): 4 * n, ("grouped", 16): 8 * n}
    outer = experiments.sweep_of_outer_blocks(spark, a, b, GridSpec(4, 4, 2, 2), 1, (1, 2, 4)).collect()
    assert {r.shuffle_rows for r in outer} == {4 * n} and [(r.outer_b, r.repeat) for r in outer] == [(f, k) for f in (1, 2, 4) for k in range(experiments.REPEATS)]


def test_block_sums(spark):
    from gridmul.operators.blocks import sum_blocks

    df = spark.createDataFrame([(1, [1.0, 2.0, 3.0]), (1, [10.0, 20.0, 30.0]), (2, [5.0, 5.0, 5.0])], "k int, data array<double>")
    assert {r.k: r.data for r in sum_blocks(df, ["k"]).collect()} == {1: [11.0, 22.0, 33.0], 2: [5.0, 5.0, 5.0]}


def test_front_door_plans_from_sizes():
    from gridmul.operators.multiply import plan_product
    from gridmul.plans.topology import MatrixMeta

    giga = 1 << 30
    small = plan_product(60_000, 60_000, MatrixMeta(256, 256), MatrixMeta(256, 256), 8)
    assert small.method == "grouped" and small.kernel == "panel" and small.grid.groups >= 16
    # terabytes: as many groups as tiles of C that fit a quarter of a task, not as cores
    dense = plan_product(1 << 40, 1 << 40, MatrixMeta(1 << 20, 1 << 20), MatrixMeta(1 << 20, 1 << 20), 4000, giga)
    assert -(-(1 << 20) // dense.grid.I) * -(-(1 << 20) // dense.grid.J) * 8 <= giga / 4 and dense.grid.groups >= 8000
    assert dense.kernel == "panel" and 2 * dense.inner * (1 << 20) // dense.grid.I * 8 <= giga / 4
    sparse = plan_product(10**9, 10**9, MatrixMeta(1 << 30, 1 << 30), MatrixMeta(1 << 30, 1 << 30), 4000, giga)
    assert sparse.kernel == "relational" and sparse.grid.groups >= 8000
    # keys of unknown range count by their entries
    assert plan_product(1000, 1000, MatrixMeta(1 << 40, 64), MatrixMeta(64, 1 << 40), 8).grid.s <= 64
    # a k that cannot be cut once more leaves a cell a group: nothing is saved, so the flat product is taken
    assert plan_product(10, 10, MatrixMeta(10**6, 1), MatrixMeta(1, 10**6), 2).method == "flat"


def test_baselines_send_what_is_published(spark):
    import math

    from gridmul.plans import baseline_schedules

    for p, q in ((2, 3), (4, 6), (3, 3)):
        plan = baseline_schedules.lcm_shifts(spark, 72, p, q)
        steps = {(r.phase): r.n for r in plan.groupBy("phase").agg(F.countDistinct("step").alias("n")).collect()}
        assert steps == {"shift": q - 1, "broadcast": math.lcm(p, q)}
    for q in (2, 3, 4):
        # after the alignment every cell has met every slice of k: simulate the places of A's and B's blocks
        plan = baseline_schedules.rotations(spark, 12, q).collect()
        a = {(i, j): (i, j) for i in range(q) for j in range(q)}
        b = dict(a)
        met = {c: set() for c in a}
        for step in range(q):
            moves = [r for r in plan if r.step == step]
            for own, name in ((a, "A"), (b, "B")):
                new = {(r.to_row, r.to_col): own[r.from_row, r.from_col] for r in moves if r.operand == name}
                own.update(new)
            for c in a:
                assert a[c][1] == b[c][0]
                met[c].add(a[c][1])
        assert all(len(x) == q for x in met.values())


def test_qr_of_a_tall_matrix(spark):
    import numpy as np

    from gridmul.operators.blocks import MatrixFrame
    from gridmul.operators.multiply import gram_qr
    from gridmul.plans.topology import MatrixMeta

    x = np.random.default_rng(4).integers(-5, 6, (60, 4)).astype(float)
    df = spark.createDataFrame([(i, j, float(x[i, j])) for i in range(60) for j in range(4)], "row long, col long, value double")
    q, r = gram_qr(MatrixFrame(df, MatrixMeta(60, 4, "double")))
    dense = lambda f, shape: np.array([[{(e.row, e.col): e.value for e in f}.get((i, j), 0.0) for j in range(shape[1])] for i in range(shape[0])])
    qm, rm = dense(q.collect(), (60, 4)), dense(r.df.collect(), (4, 4))
    assert np.allclose(qm @ rm, x) and np.allclose(qm.T @ qm, np.eye(4), atol=1e-12) and np.allclose(rm, np.triu(rm))
