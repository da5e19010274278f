"""Matrices as frames of entries or of blocks, and the operations a user needs around products. All of them are lazy."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from gridmul.plans.topology import MatrixMeta, ceil_div


@dataclass(frozen=True)
class MatrixFrame:
    """Entries (row, col, value); an absent entry is zero. Every (row, col) occurs once."""

    df: DataFrame
    meta: MatrixMeta

    @property
    def spark(self) -> SparkSession:
        return self.df.sparkSession

    def _like(self, df: DataFrame, rows: int | None = None, cols: int | None = None) -> MatrixFrame:
        return MatrixFrame(df.select("row", "col", "value"), MatrixMeta(rows or self.meta.rows, cols or self.meta.cols, self.meta.dtype))

    def transpose(self) -> MatrixFrame:
        return self._like(self.df.select(F.col("col").alias("row"), F.col("row").alias("col"), "value"), self.meta.cols, self.meta.rows)

    def scale(self, c: int | float) -> MatrixFrame:
        return self._like(self.df.withColumn("value", F.col("value") * F.lit(c)))

    def _same_shape(self, other: MatrixFrame) -> None:
        if (self.meta.rows, self.meta.cols) != (other.meta.rows, other.meta.cols):
            raise ValueError("shapes differ")

    def add(self, other: MatrixFrame) -> MatrixFrame:
        self._same_shape(other)
        return self._like(self.df.unionByName(other.df).groupBy("row", "col").agg(F.sum("value").alias("value")))

    def sub(self, other: MatrixFrame) -> MatrixFrame:
        return self.add(other.scale(-1))

    def hadamard(self, other: MatrixFrame) -> MatrixFrame:
        self._same_shape(other)
        right = other.df.withColumnRenamed("value", "other")
        return self._like(self.df.join(right, ["row", "col"]).withColumn("value", F.col("value") * F.col("other")))

    def row_sums(self) -> DataFrame:
        return self.df.groupBy("row").agg(F.sum("value").alias("value"))

    def col_sums(self) -> DataFrame:
        return self.df.groupBy("col").agg(F.sum("value").alias("value"))

    def trace(self) -> DataFrame:
        return self.df.where("row = col").agg(F.coalesce(F.sum("value"), F.lit(0).cast(self.meta.dtype)).alias("value"))

    def filter(self, rows: Column | None = None, cols: Column | None = None) -> MatrixFrame:
        """Entries whose row and col fit the conditions; the shape stays."""
        df = self.df if rows is None else self.df.where(rows)
        return self._like(df if cols is None else df.where(cols))

    def prune(self) -> MatrixFrame:
        return self._like(self.df.where("value <> 0"))

    def densify(self) -> MatrixFrame:
        """Every entry, zeros included."""
        spark = self.spark
        grid = spark.range(self.meta.rows).select(F.col("id").alias("row")).crossJoin(spark.range(self.meta.cols).select(F.col("id").alias("col")))
        return self._like(grid.join(self.df, ["row", "col"], "left").withColumn("value", F.coalesce("value", F.lit(0).cast(self.meta.dtype))))

    def to_blocks(self, b: int) -> DataFrame:
        """(block_row, block_col, n_rows, n_cols, data): row-major tiles; blocks without entries are absent."""
        place = self.df.select(F.floor(F.col("row") / b).cast("int").alias("block_row"), F.floor(F.col("col") / b).cast("int").alias("block_col"), (F.col("row") % b).cast("int").alias("r"), (F.col("col") % b).cast("int").alias("c"), "value")
        height, width = F.least(F.lit(b), F.lit(self.meta.rows) - F.col("block_row") * b).cast("int"), F.least(F.lit(b), F.lit(self.meta.cols) - F.col("block_col") * b).cast("int")
        tiles = place.withColumn("n_rows", height).withColumn("n_cols", width).groupBy("block_row", "block_col", "n_rows", "n_cols").agg(F.map_from_entries(F.collect_list(F.struct(F.col("r") * F.col("n_cols") + F.col("c"), F.col("value").cast("double")))).alias("m"))
        return tiles.select("block_row", "block_col", "n_rows", "n_cols", F.transform(F.sequence(F.lit(0), F.col("n_rows") * F.col("n_cols") - 1), lambda i: F.coalesce(F.try_element_at(F.col("m"), i), F.lit(0.0))).alias("data"))

    @staticmethod
    def from_blocks(blocks: DataFrame, b: int, meta: MatrixMeta) -> MatrixFrame:
        """Entries of tiles of side b; zeros are left out."""
        e = blocks.select("block_row", "block_col", "n_cols", F.posexplode("data").alias("at", "value")).where("value <> 0")
        return MatrixFrame(e.select((F.col("block_row") * b + F.floor(F.col("at") / F.col("n_cols"))).cast("long").alias("row"), (F.col("block_col") * b + F.col("at") % F.col("n_cols")).cast("long").alias("col"), F.col("value").cast(meta.dtype).alias("value")), meta)

    def to_entries(self) -> DataFrame:
        return self.df

    def to_row_maps(self) -> DataFrame:
        """(row, entries): sparse rows as maps from column to value."""
        return self.df.groupBy("row").agg(F.map_from_entries(F.collect_list(F.struct("col", "value"))).alias("entries"))

    def pad(self, s: int) -> MatrixFrame:
        """The same entries in a shape whose sides s divides."""
        return self._like(self.df, ceil_div(self.meta.rows, s) * s, ceil_div(self.meta.cols, s) * s)


def identity(spark: SparkSession, n: int) -> MatrixFrame:
    return MatrixFrame(spark.range(n).select(F.col("id").alias("row"), F.col("id").alias("col"), F.lit(1).cast("long").alias("value")), MatrixMeta(n, n))


def zeros(spark: SparkSession, meta: MatrixMeta) -> MatrixFrame:
    return MatrixFrame(spark.createDataFrame([], f"row long, col long, value {meta.dtype}"), meta)


def matvec(a: MatrixFrame, v: DataFrame) -> DataFrame:
    """(row, value) of a v; v: (row, value)."""
    return a.df.join(v.select(F.col("row").alias("col"), F.col("value").alias("x")), "col").groupBy("row").agg(F.sum(F.col("value") * F.col("x")).alias("value"))


def add_row_maps(a: DataFrame, b: DataFrame) -> DataFrame:
    """Sum of two frames of sparse row maps; a row of one side alone stays as it is."""
    both = a.withColumnRenamed("entries", "x").join(b.withColumnRenamed("entries", "y"), "row", "full_outer")
    zero = F.lit(0).cast("long")
    return both.select("row", F.when(F.col("x").isNull(), F.col("y")).when(F.col("y").isNull(), F.col("x")).otherwise(F.map_zip_with("x", "y", lambda k, p, q: F.coalesce(p, zero) + F.coalesce(q, zero))).alias("entries"))


def prune_operands(a: MatrixFrame, b: MatrixFrame) -> tuple[MatrixFrame, MatrixFrame]:
    """Leave out columns of a that no row of b meets, and the other way round, before they are shipped anywhere."""
    in_b, in_a = b.df.select(F.col("row").alias("col")).distinct(), a.df.select(F.col("col").alias("row")).distinct()
    return MatrixFrame(a.df.join(in_b, "col", "left_semi").select("row", "col", "value"), a.meta), MatrixFrame(b.df.join(in_a, "row", "left_semi").select("row", "col", "value"), b.meta)


def sum_blocks(blocks: DataFrame, keys: list[str], data: str = "data") -> DataFrame:
    """(keys, data): arrays of one length that share keys, summed element by element; partial sums are made before the exchange."""
    each = blocks.select(*keys, F.posexplode(data).alias("at", "x")).groupBy(*keys, "at").agg(F.sum("x").alias("x"))
    return each.groupBy(*keys).agg(F.array_sort(F.collect_list(F.struct("at", "x"))).alias("s")).select(*keys, F.transform("s", lambda e: e["x"]).alias(data))
