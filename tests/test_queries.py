"""Every registered core query against its SQL, on the smallest tables; streams against batches."""

import glob
import os

import duckdb
import pytest
from pyspark.sql import functions as F

import gridmul.queries as core
from gridmul.operators import multiply
from gridmul.plans import measure
from gridmul.sources.tables import load, synthetic
from gridmul.streaming import products

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for path in glob.glob(f"{SF}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(path)[:-8]} AS SELECT * FROM '{path}'")
    return con


@pytest.mark.parametrize("name", sorted(core.ORACLES))
def test_query_equals_sql(spark, duck, name):
    df = core.QUERIES[name](spark, SF)
    columns = sorted(df.columns)
    got = sorted(repr(tuple(r[c] for c in columns)) for r in df.collect())
    want = duck.execute(core.ORACLES[name])
    names = [x[0] for x in want.description]
    assert sorted(names) == columns
    order = [names.index(c) for c in columns]
    assert got == sorted(repr(tuple(r[i] for i in order)) for r in want.fetchall())


def test_entry_module(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() > 0
    assert set(e.oracle_sql()) <= set(e.queries())


#: Schedules and costs of matrices whose sides are counted in a table.
OF_A_TABLE = [
    "baseline_deliveries",
    "best_groups",
    "break_even",
    "copies_by_method",
    "cost_baselines",
    "cost_binary",
    "cost_binomial",
    "cost_chain_pipelined",
    "cost_flat_tree",
    "cost_scatter_allgather",
    "cost_sqrt_corrected",
    "cost_sqrt_printed",
]


@pytest.mark.parametrize("name", OF_A_TABLE)
def test_schedules_and_costs_read_their_sizes_from_a_table(spark, name):
    df = core.QUERIES[name](spark, SF)
    assert [os.path.basename(f) for f in df.inputFiles()] == ["lineitem.parquet"]
    shipped = load(spark, SF, "lineitem").select((F.year("l_shipdate") * 100 + F.month("l_shipdate")).cast("long").alias("month")).distinct()
    assert {r.month for r in df.select("month").distinct().collect()} == {r.month for r in shipped.collect()}


def test_windows_sessions_and_late_rows(spark, tmp_path):
    events = load(spark, SF, "events")
    entries = products.event_entries(events)
    weights = synthetic(spark, 6, 6)
    hourly = products.stream_product(entries, weights, "2 hours", "1 hour")
    assert hourly.agg(F.sum("value")).first()[0] == 2 * products.stream_product(entries, weights).agg(F.sum("value")).first()[0]
    assert products.session_product(entries, weights).count() > 0
    events.coalesce(1).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(events.schema).parquet(str(tmp_path / "in"))
    path = str(tmp_path / "out")
    products.accumulate(spark, products.event_entries(stream), weights, path, str(tmp_path / "check"))
    batch = entries.join(weights.df.select(F.col("row").alias("col"), F.col("col").alias("out"), F.col("value").alias("vb")), "col").groupBy("row", F.col("out").alias("col")).agg(F.sum(F.col("value") * F.col("vb")).alias("value"))
    assert products.product_of(spark, path).exceptAll(batch.select("row", "col", "value")).count() == 0
    assert products.deduplicated(entries).isStreaming is False


def test_windows_are_summed_over_batches_without_state(spark, tmp_path):
    events = load(spark, SF, "events")
    events.repartition(3).write.parquet(str(tmp_path / "in"))
    weights = synthetic(spark, 6, 6)
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    path, check = str(tmp_path / "parts"), str(tmp_path / "check")
    products.accumulate_windows(products.event_entries(stream), weights, path, check)
    assert len(glob.glob(f"{path}/batch=*")) == 3 and not os.path.exists(f"{check}/state")
    got, want = products.window_product_of(spark, path), products.stream_product(products.event_entries(events), weights)
    assert got.count() == want.count() and got.exceptAll(want).count() == 0
    # what has arrived since is added; what has not is not read again
    more = events.limit(100)
    more.write.mode("append").parquet(str(tmp_path / "in"))
    products.accumulate_windows(products.event_entries(stream), weights, path, check)
    want = products.stream_product(products.event_entries(events.unionByName(more)), weights)
    assert products.window_product_of(spark, path).exceptAll(want).count() == 0


def test_stream_product_keeps_no_table_on_the_driver(spark):
    before = {t.name for t in spark.catalog.listTables()}
    assert core.QUERIES["stream_product"](spark, SF).count() > 0
    assert {t.name for t in spark.catalog.listTables()} == before


def test_change_of_both_operands(spark):
    a, b = synthetic(spark, 8, 8), synthetic(spark, 8, 8).transpose()
    da, db = synthetic(spark, 8, 8, F.col("row") - F.col("col")), synthetic(spark, 8, 8, F.col("row") % 3)
    after = multiply.relational_multiply(a.add(da), b.add(db))
    step = multiply.relational_multiply(a, b).add(products.change_of_both(a, b, da, db))
    assert measure.compare(after.prune(), step.prune()).count() == 0
