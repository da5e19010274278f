"""What the operators share: tables in the shared folder, Arrow batches, small helpers."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from gridmul.session import shared_folder

#: Rows of one Arrow batch; bounds what a Python worker holds at once.
BATCH_ROWS = 512

#: Files a core, at most, of a narrow table (ids, hashes, counts), and of a table with texts, as long as each is smaller than FILE_BYTES.
NARROW_FILES = 4
TEXT_FILES = 16
#: Bytes of input for which a written table has one file more.
FILE_BYTES = 256 << 20


_written: list[str] = []


def release(spark: SparkSession) -> int:
    """Delete the tables that this driver has written so far; frames that still read them end. Gives their number."""
    paths = [spark._jvm.org.apache.hadoop.fs.Path(p) for p in _written]
    for p in paths:
        p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)
    _written.clear()
    return len(paths)


def input_bytes(df: DataFrame) -> int:
    """Bytes of all tables that df reads, as its optimised plan tells."""
    leaves = df._jdf.queryExecution().optimizedPlan().collectLeaves()
    return sum(int(str(leaves.apply(i).stats().sizeInBytes())) for i in range(leaves.size()))


def few_files(df: DataFrame, per_core: int = TEXT_FILES) -> DataFrame:
    """df in few partitions, so that small shuffle partitions do not become small files: so many a core, more with the bytes read."""
    cores = max(1, df.sparkSession.sparkContext.defaultParallelism)
    return df.coalesce(min(max(per_core * cores, input_bytes(df) // FILE_BYTES), 1 << 30))


def fresh(df: DataFrame, name: str) -> str:
    """name, or with underscores after it, so that no column of df has it (in any case of letters)."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def materialise(df: DataFrame, label: str, narrow: bool = False) -> DataFrame:
    """Write df as a table in the shared folder and read it back: lineage is cut and survives lost executors.

    narrow: a table much smaller than the texts; it gets a few files a core instead of one for every shuffle partition."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/tables/{label}-{uuid.uuid4().hex}"
    if narrow:
        df = few_files(df, NARROW_FILES)
    df.write.parquet(path)
    _written.append(path)
    return spark.read.schema(df.schema).parquet(path)


def small_batches(spark: SparkSession) -> None:
    """Bound the Arrow batches by rows (a runtime setting, in effect for the plans made from now on)."""
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(BATCH_ROWS))


def map_rows(df: DataFrame, columns: list[Column], schema: T.StructType | str, rows: Callable[[Iterable[tuple]], Iterable[tuple]]) -> DataFrame:
    """mapInArrow over the given columns: `rows` turns an iterator of tuples into tuples of the schema, batch by batch."""
    small_batches(df.sparkSession)
    schema = T.StructType.fromDDL(schema) if isinstance(schema, str) else schema
    from pyspark.sql.pandas.types import to_arrow_schema

    arrow = to_arrow_schema(schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def source():
            for batch in batches:
                yield from zip(*(c.to_pylist() for c in batch.columns))

        held = []
        size = 0
        for row in rows(source()):
            held.append(row)
            size += 1
            if size >= BATCH_ROWS:
                yield pa.RecordBatch.from_arrays([pa.array(c, t.type) for c, t in zip(zip(*held), arrow)], schema=arrow)
                held, size = [], 0
        if held:
            yield pa.RecordBatch.from_arrays([pa.array(c, t.type) for c, t in zip(zip(*held), arrow)], schema=arrow)

    return df.select(*columns).mapInArrow(run, schema)


def sample_rows(df: DataFrame, n: int) -> DataFrame:
    """About n rows, n + n / 5 + 50 at most, picked by a hash of the row's short columns: the same rows on every run."""
    total = df.count()
    if total <= n:
        return df
    keys = [c for c, kind in df.dtypes if kind in ("bigint", "int")] or df.columns[:1]
    return df.where(F.pmod(F.xxhash64(*keys), F.lit(1_000_003)) < F.lit(int(1_000_003 * n / total) + 1)).limit(n + n // 5 + 50)


def text_of(name: str = "text") -> Column:
    """The text as a string; null counts as empty."""
    return F.coalesce(F.col(name).cast("string"), F.lit(""))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
