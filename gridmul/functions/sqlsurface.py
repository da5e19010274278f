"""The cost model, the valid groupings and the matrices for SQL users."""

from __future__ import annotations

from pyspark.sql import SparkSession

from gridmul.operators.blocks import MatrixFrame

#: Broadcast factors as SQL over q.
_FACTORS = {"binomial": ("log2(q)", "log2(q)"), "scatter_allgather": ("log2(q) + q - 1", "2 * (q - 1) / q")}


def register(spark: SparkSession, matrices: dict[str, MatrixFrame] | None = None) -> None:
    """Temporary functions flat_comm, grouped_comm (scatter-allgather), their *_binomial forms, break_even_p, and the table
    functions valid_groups and grid_cells; temporary views of the given matrices. All are inlined by the optimiser."""
    args = "n DOUBLE, b DOUBLE, p DOUBLE, alpha DOUBLE, beta DOUBLE"
    for name, (latency, bandwidth) in _FACTORS.items():
        suffix = "" if name == "scatter_allgather" else f"_{name}"
        at = lambda f, q: "(" + f.replace("log2(q)", f"log2({q})").replace("q - 1", f"{q} - 1").replace("/ q", f"/ {q}").replace("+ q", f"+ {q}") + ")"

        def comm(q: str, block: str) -> str:
            return f"2 * (n / {block} * {at(latency, q)} * alpha + n * n / sqrt(p) * {at(bandwidth, q)} * beta)"

        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION flat_comm{suffix}({args}) RETURNS DOUBLE RETURN {comm('sqrt(p)', 'b')}")
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION grouped_comm{suffix}({args}, g DOUBLE) RETURNS DOUBLE RETURN {comm('sqrt(p / g)', 'b')} + {comm('sqrt(g)', 'b')}")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION break_even_p(n DOUBLE, b DOUBLE, alpha DOUBLE, beta DOUBLE) RETURNS DOUBLE RETURN 2 * n * b * beta / alpha")
    spark.sql("""CREATE OR REPLACE TEMPORARY FUNCTION valid_groups(s INT, t INT) RETURNS TABLE (grp_rows INT, grp_cols INT) RETURN
        SELECT i, j FROM (SELECT explode(filter(sequence(1, s), x -> s % x = 0)) AS i) CROSS JOIN (SELECT explode(filter(sequence(1, t), x -> t % x = 0)) AS j)""")
    spark.sql("""CREATE OR REPLACE TEMPORARY FUNCTION grid_cells(s INT, t INT, gi INT, gj INT) RETURNS TABLE (cell_row INT, cell_col INT, grp_row INT, grp_col INT) RETURN
        SELECT r, c, CAST(r DIV CAST(s / gi AS INT) AS INT), CAST(c DIV CAST(t / gj AS INT) AS INT) FROM (SELECT explode(sequence(0, s - 1)) AS r) CROSS JOIN (SELECT explode(sequence(0, t - 1)) AS c)""")
    for name, m in (matrices or {}).items():
        m.df.createOrReplaceTempView(name)
