"""Sources and sinks of matrices."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from gridmul.operators.blocks import MatrixFrame
from gridmul.plans.topology import MatrixMeta
from gridmul.schemas import ENTRIES, ENTRIES_DOUBLE, PLATFORMS


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def from_table(df: DataFrame, row: Column, col: Column, value: Column, meta: MatrixMeta, agg: str = "sum") -> MatrixFrame:
    """Entries aggregated from rows; only the columns in the expressions are read."""
    picked = df.select(row.cast("long").alias("row"), col.cast("long").alias("col"), value.alias("value"))
    fold = {"sum": F.sum, "max": F.max, "min": F.min, "count": F.count}[agg]
    return MatrixFrame(picked.groupBy("row", "col").agg(fold("value").cast(meta.dtype).alias("value")), meta)


def from_arrays(df: DataFrame, row: Column, array: Column, meta: MatrixMeta) -> MatrixFrame:
    """A row of entries from each array; zeros are left out."""
    e = df.select(row.cast("long").alias("row"), F.posexplode(array).alias("col", "value"))
    return MatrixFrame(e.where("value <> 0").select("row", F.col("col").cast("long").alias("col"), F.col("value").cast(meta.dtype).alias("value")), meta)


def quantised(array: Column, scale: int = 1000) -> Column:
    """Floats as whole numbers, once and the same everywhere."""
    return F.transform(array, lambda x: F.round(x.cast("double") * scale).cast("long"))


def synthetic(spark: SparkSession, rows: int, cols: int, value: Column | None = None) -> MatrixFrame:
    """Dense, from an expression over row and col; by default (7 row + 3 col) mod 11 - 5. Zeros are left out."""
    value = (7 * F.col("row") + 3 * F.col("col")) % 11 - 5 if value is None else value
    grid = spark.range(rows * cols).select(F.floor(F.col("id") / cols).cast("long").alias("row"), (F.col("id") % cols).alias("col"))
    return MatrixFrame(grid.withColumn("value", value.cast("long")).where("value <> 0"), MatrixMeta(rows, cols))


def platforms(spark: SparkSession) -> DataFrame:
    """Published platform parameters; gamma is the time of a floating-point operation on one processor."""
    rows = [("cluster", 1e-4, 1e-9, 1e-10, 8192, 128, 64), ("cluster_large_block", 1e-4, 1e-9, 1e-10, 8192, 128, 512), ("supercomputer", 3e-6, 1e-9, 1e-10, 65536, 16384, 256), ("supercomputer_2048", 3e-6, 1e-9, 1e-10, 65536, 2048, 256), ("exascale", 5e-7, 1e-11, 1e-18, 4194304, 1048576, 256)]
    return spark.createDataFrame(rows, PLATFORMS)


def read_triplets(spark: SparkSession, path: str, fmt: str, meta: MatrixMeta, one_based: bool = False) -> MatrixFrame:
    """Entries from parquet, orc, json, csv, or text lines `row col value` (lines from % on are comments)."""
    schema = ENTRIES if meta.dtype == "long" else ENTRIES_DOUBLE
    if fmt == "text":
        parts = F.split(F.trim("value"), r"\s+")
        df = spark.read.text(path).where(~F.col("value").startswith("%") & (F.trim("value") != "")).select(parts[0].cast("long").alias("row"), parts[1].cast("long").alias("col"), parts[2].cast(meta.dtype).alias("value"))
    else:
        reader = spark.read.schema(schema)
        df = reader.option("header", True).csv(path) if fmt == "csv" else reader.format(fmt).load(path)
    if one_based:
        df = df.select((F.col("row") - 1).alias("row"), (F.col("col") - 1).alias("col"), "value")
    return MatrixFrame(df.select("row", "col", "value"), meta)


def write_matrix(m: MatrixFrame, path: str, fmt: str = "parquet", block: int | None = None) -> None:
    """Entries, partitioned by block row where a block side is given, so that panels and probes prune files."""
    if fmt == "text":
        m.df.select(F.concat_ws(" ", "row", "col", "value").alias("value")).write.mode("overwrite").text(path)
        return
    df = m.df
    if block:
        df = df.withColumn("block_row", F.floor(F.col("row") / block).cast("int")).repartition("block_row").sortWithinPartitions("block_row", "col", "row")
        df.write.mode("overwrite").partitionBy("block_row").format(fmt).save(path)
    else:
        writer = df.write.mode("overwrite")
        (writer.option("header", True) if fmt == "csv" else writer).format(fmt).save(path)


def save_bucketed(m: MatrixFrame, name: str, buckets: int, by: str = "row") -> None:
    """A table bucketed by row or col, for operands that are joined again and again."""
    m.df.write.mode("overwrite").bucketBy(buckets, by).sortBy(by).saveAsTable(name)


def save_runs(runs: DataFrame, path: str) -> None:
    runs.write.mode("append").partitionBy("method").parquet(path)
