"""What a run cost and whether its result is right."""

from __future__ import annotations

import random
import re
import time
import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridmul.operators.blocks import MatrixFrame

#: A prime below 2^31: products of residues fit 64 bits.
PRIME = 2_147_483_629


def executed_plan(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def exchanges(df: DataFrame) -> int:
    """Shuffle exchanges in the planned (not yet run) query."""
    return len(re.findall(r"(?<!Broadcast)\bExchange\b", executed_plan(df)))


def shuffle_stats(df: DataFrame) -> dict:
    """Rows and bytes of all shuffles of one execution of df, from its operators' metrics."""
    spark = df.sparkSession
    context, tag = spark.sparkContext, f"gridmul-{uuid.uuid4().hex}"
    before = context.getLocalProperty("spark.job.description")
    context.setJobDescription(tag)  # by which this execution is told from others of the session
    try:
        df.write.format("noop").mode("overwrite").save()
    finally:
        context.setLocalProperty("spark.job.description", before)
    store = spark._jsparkSession.sharedState().statusStore()
    listed = store.executionsList()
    run = next(x for x in (listed.apply(k) for k in reversed(range(listed.size()))) if x.description() == tag)
    values = store.executionMetrics(run.executionId())
    out = {"shuffle_bytes": 0, "shuffle_rows": 0, "spill_bytes": 0}
    metrics = run.metrics()
    seen = set()
    for k in range(metrics.size()):
        m = metrics.apply(k)
        got = values.get(m.accumulatorId())
        if got.isEmpty() or m.accumulatorId() in seen:  # a plan that was changed while it ran lists a metric again
            continue
        seen.add(m.accumulatorId())
        text = got.get()
        name = m.name()
        if name == "shuffle bytes written":
            out["shuffle_bytes"] += _bytes(text)
        elif name == "shuffle records written":
            out["shuffle_rows"] += int(re.sub(r"\D", "", text.split("\n")[-1].split("(")[0]) or 0)
        elif name == "spill size":
            out["spill_bytes"] += _bytes(text)
    return out


def _bytes(text: str) -> int:
    m = re.search(r"([\d.]+) (B|KiB|MiB|GiB|TiB)", text)
    return int(float(m[1]) * 1024 ** ["B", "KiB", "MiB", "GiB", "TiB"].index(m[2])) if m else 0


def measure_run(df: DataFrame, repeats: int = 3) -> dict:
    """Mean wall time of `repeats` executions, with the shuffles of one more."""
    times = []
    for _ in range(repeats):
        began = time.perf_counter()
        df.write.format("noop").mode("overwrite").save()
        times.append((time.perf_counter() - began) * 1000)
    return {"wall_ms": sum(times) / len(times), "repeats": repeats} | shuffle_stats(df)


def _residues(df: DataFrame, key: str, out: str, vector: DataFrame) -> DataFrame:
    """(row, value) of a matrix times a vector, modulo PRIME; every product is reduced before it is summed."""
    product = F.pmod(F.pmod(F.col("value"), F.lit(PRIME)) * F.col("x"), F.lit(PRIME))
    return df.join(vector, key).groupBy(out).agg(F.pmod(F.sum(product), F.lit(PRIME)).alias("y"))


def verify_product(a: MatrixFrame, b: MatrixFrame, c: MatrixFrame, rounds: int = 2, seed: int = 7) -> DataFrame:
    """(round, rows, residual): rows in which C v and A (B v) differ for pseudo-random v, whole numbers modulo a prime.

    Costs a product with a vector, so it holds where no oracle can run."""
    rng = random.Random(seed)
    out = None
    for k in range(rounds):
        salt = rng.randrange(1 << 31)
        x = F.pmod(F.xxhash64(F.col("col"), F.lit(salt)), F.lit(PRIME))
        weight = lambda df, x=x: df.withColumn("x", x)
        bv = weight(b.df).groupBy("row").agg(F.pmod(F.sum(F.pmod(F.pmod(F.col("value"), F.lit(PRIME)) * F.col("x"), F.lit(PRIME))), F.lit(PRIME)).alias("x")).select(F.col("row").alias("col"), "x")
        left = _residues(a.df, "col", "row", bv)
        right = weight(c.df).groupBy("row").agg(F.pmod(F.sum(F.pmod(F.pmod(F.col("value"), F.lit(PRIME)) * F.col("x"), F.lit(PRIME))), F.lit(PRIME)).alias("z"))
        both = left.join(right, "row", "full_outer")
        one = both.agg(F.lit(k).alias("round"), F.count("*").alias("rows"), F.count(F.when(F.coalesce("y", F.lit(0)) != F.coalesce("z", F.lit(0)), 1)).alias("residual"))
        out = one if out is None else out.unionByName(one)
    return out


def compare(x: MatrixFrame, y: MatrixFrame) -> DataFrame:
    """Entries of one product that the other lacks, either way; empty where they agree."""
    return x.df.exceptAll(y.df).withColumn("only_in", F.lit("first")).unionByName(y.df.exceptAll(x.df).withColumn("only_in", F.lit("second")))


def errors(x: MatrixFrame, y: MatrixFrame) -> DataFrame:
    """(max_abs_err, rel_frobenius) of x against y."""
    both = x.df.join(y.df.withColumnRenamed("value", "other"), ["row", "col"], "full_outer").select(F.coalesce("value", F.lit(0.0)).cast("double").alias("v"), F.coalesce("other", F.lit(0.0)).cast("double").alias("w"))
    return both.agg(F.max(F.abs(F.col("v") - F.col("w"))).alias("max_abs_err"), (F.sqrt(F.sum(F.pow(F.col("v") - F.col("w"), F.lit(2)))) / F.sqrt(F.sum(F.pow(F.col("w"), F.lit(2))))).alias("rel_frobenius"))


def bound_check(a: MatrixFrame, b: MatrixFrame) -> bool:
    """Whether every entry of the product is sure to fit 64 bits: max|a| max|b| k < 2^63."""
    x, y = (m.df.agg(F.max(F.abs("value"))).first()[0] or 0 for m in (a, b))
    return int(x) * int(y) * a.meta.cols < 1 << 63
