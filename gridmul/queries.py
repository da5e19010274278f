"""Every method, variant, baseline, measure and workload as a query, with the SQL that gives the same rows."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

from gridmul.functions import cost, sqlsurface
from gridmul.operators import baselines, blocks, kernels, multiply, routing
from gridmul.operators.blocks import MatrixFrame
from gridmul.plans import advisor, baseline_schedules, experiments, measure, schedule, topology
from gridmul.plans.topology import GridSpec, MatrixMeta
from gridmul.session import configure, shared_folder
from gridmul.sources import tables, workloads
from gridmul.streaming import products

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}

N = 64
GRID = GridSpec(4, 4, 2, 2)
WIDE = GridSpec(4, 8, 2, 4)


def query(sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


# ---------------------------------------------------------------- products

PRODUCT = 'SELECT a.r AS "row", b.c AS "col", CAST(sum(a.v * b.v) AS BIGINT) AS "value" FROM a JOIN b ON a.c = b.r GROUP BY 1, 2'


def _square_ctes(n: int = N) -> str:
    one = lambda r, c: f"SELECT CAST({r} % {n} AS BIGINT) AS r, CAST({c} % {n} AS BIGINT) AS c, CAST(sum(l_quantity) AS BIGINT) AS v FROM lineitem GROUP BY 1, 2"
    return f"WITH a AS ({one('l_orderkey', 'l_partkey')}), b AS ({one('l_partkey', 'l_suppkey')}) "


SQUARE_SQL = _square_ctes() + PRODUCT
_SUPPLIER = "SELECT CAST(l_suppkey AS BIGINT) AS r, CAST(l_partkey AS BIGINT) AS c, CAST(sum(l_quantity) AS BIGINT) AS v FROM lineitem GROUP BY 1, 2"
SUPPLIER_CTES = f"WITH a AS ({_SUPPLIER}), b AS (SELECT c AS r, r AS c, v FROM a) "
_VECTORS = "SELECT vec_id AS r, CAST(generate_subscripts(embedding, 1) - 1 AS BIGINT) AS c, CAST(ROUND(CAST(unnest(embedding) AS DOUBLE) * 1000) AS BIGINT) AS v FROM embeddings"


def _pair(spark: SparkSession, d: str, n: int = N) -> tuple[MatrixFrame, MatrixFrame]:
    configure(spark)
    return workloads.square_pair(spark, d, n)


def _largest(df: DataFrame, name: str) -> int:
    return (df.agg(F.max(name)).first()[0] or 0) + 1


def _supplier(spark: SparkSession, d: str) -> MatrixFrame:
    configure(spark)
    lines = tables.load(spark, d, "lineitem")
    up = lambda n, k: -(-n // k) * k
    return workloads.supplier_part(spark, d, up(_largest(lines, "l_suppkey"), 8), up(_largest(lines, "l_partkey"), 8))


def _stored(m: MatrixFrame) -> MatrixFrame:
    """Written to the shared folder and read back: an operand that is used more than once is made once."""
    path = f"{shared_folder(m.spark)}/tables/operand-{uuid.uuid4().hex}"
    m.df.write.parquet(path)
    return MatrixFrame(m.spark.read.schema(m.df.schema).parquet(path), m.meta)


def _vectors(spark: SparkSession, d: str) -> MatrixFrame:
    """Vectors by dimensions, quantised; as many rows as the ids need, a multiple of 1024 so that blocks divide them."""
    configure(spark)
    return workloads.embeddings(spark, d, -(-_largest(tables.load(spark, d, "embeddings"), "vec_id") // 1024) * 1024)


@query(SQUARE_SQL)
def grouped_square(spark, d):
    return multiply.grouped_multiply(*_pair(spark, d), GRID, 8).df


@query(SQUARE_SQL)
def front_door_groups(spark, d):
    """Grid, grouping or none, block and kernel from the operands' counts."""
    return multiply.multiply(*_pair(spark, d), groups="auto").df


@query(SQUARE_SQL)
def block_product(spark, d):
    """Blocks that meet on k, multiplied by cogrouped Arrow tables, then summed by their place."""
    a, b = _pair(spark, d)
    parts = kernels.block_kernel(a.to_blocks(16), b.to_blocks(16))
    summed = blocks.sum_blocks(parts.select("block_row", "block_col", "data"), ["block_row", "block_col"]).select("block_row", "block_col", F.posexplode("data").alias("spot", "value")).where("value <> 0")
    return summed.select((F.col("block_row") * 16 + F.floor(F.col("spot") / 16)).cast("long").alias("row"), (F.col("block_col") * 16 + F.col("spot") % 16).cast("long").alias("col"), F.col("value").cast("long").alias("value"))


@query(SQUARE_SQL)
def grouped_two_block(spark, d):
    return multiply.grouped_multiply(*_pair(spark, d), GRID, 8, 16).df


@query(SQUARE_SQL)
def grouped_panel(spark, d):
    return multiply.grouped_multiply(*_pair(spark, d), GRID, 8, 16, kernel="panel").df


@query(SQUARE_SQL)
def grouped_panel_tiles(spark, d):
    """The panel kernel with C tiles cut into stripes, as for tiles larger than a task."""
    return multiply.grouped_multiply(*_pair(spark, d), GRID, 8, kernel="panel", tile_entries=256).df


@query(SQUARE_SQL)
def grouped_hof(spark, d):
    return multiply.grouped_multiply(*_pair(spark, d), GRID, 8, kernel="hof").df


@query(SQUARE_SQL)
def grouped_two_exchange(spark, d):
    return multiply.grouped_multiply(*_pair(spark, d), GRID, 8, routing_form="two_exchange").df


@query(SQUARE_SQL)
def grouped_square_groups(spark, d):
    return multiply.grouped_multiply(*_pair(spark, d), GridSpec.square(16, 4), 16).df


@query(SQUARE_SQL)
def grouped_one_group(spark, d):
    return multiply.grouped_multiply(*_pair(spark, d), GRID.with_groups(1, 1), 8).df


@query(SQUARE_SQL)
def grouped_p_groups(spark, d):
    return multiply.grouped_multiply(*_pair(spark, d), GRID.with_groups(4, 4), 8).df


@query(SQUARE_SQL)
def flat_square(spark, d):
    return multiply.flat_multiply(*_pair(spark, d), GRID, 8).df


@query(SQUARE_SQL)
def grouped_nonsquare_grid(spark, d):
    return multiply.grouped_multiply(*_pair(spark, d), WIDE, 4, 8).df


@query(SQUARE_SQL)
def grouped_strided(spark, d):
    return multiply.grouped_multiply(*_pair(spark, d), GridSpec(4, 8, 2, 4, grouping="strided"), 4).df


@query(SQUARE_SQL)
def grouped_block_cyclic(spark, d):
    return multiply.grouped_multiply(*_pair(spark, d), GridSpec(4, 4, 2, 2, placement="block_cyclic"), 4, kernel="panel").df


@query(SQUARE_SQL)
def multilevel_square(spark, d):
    return multiply.multilevel_multiply(*_pair(spark, d), GridSpec(8, 8), [(2, 2), (2, 2)], 8).df


@query(SQUARE_SQL)
def grouped_auto_groups(spark, d):
    """The number of groups comes from the model; one group where grouping does not pay."""
    grid = advisor.choose_groups(tables.platforms(spark).where("platform = 'supercomputer'"), GridSpec(8, 8))
    return multiply.grouped_multiply(*_pair(spark, d), grid, 8).df


@query(SQUARE_SQL)
def multiply_auto(spark, d):
    return multiply.multiply(*_pair(spark, d)).df


@query(SQUARE_SQL)
def tall_thin_square(spark, d):
    return multiply.tall_thin_multiply(*_pair(spark, d), buckets=16).df


@query(SQUARE_SQL)
def pruned_square(spark, d):
    return multiply.grouped_multiply(*blocks.prune_operands(*_pair(spark, d)), GRID, 8).df


@query(SQUARE_SQL)
def cannon_square(spark, d):
    return baselines.cannon_multiply(*_pair(spark, d), GridSpec(4, 4)).df


@query(SQUARE_SQL)
def fox_square(spark, d):
    return baselines.fox_multiply(*_pair(spark, d), GridSpec(4, 4)).df


@query(SQUARE_SQL)
def lcm_shift_square(spark, d):
    return baselines.lcm_shift_multiply(*_pair(spark, d), 4, 6).df


@query(SQUARE_SQL)
def three_d_square(spark, d):
    return baselines.multiply_3d(*_pair(spark, d), 3).df


@query(SQUARE_SQL)
def layered_25d_square(spark, d):
    return baselines.multiply_25d(*_pair(spark, d), 32, 2, 8).df


@query(SQUARE_SQL)
def relational_square(spark, d):
    return multiply.relational_multiply(*_pair(spark, d)).df


@query(SQUARE_SQL)
def broadcast_square(spark, d):
    return multiply.broadcast_multiply(*_pair(spark, d)).df


@query(SUPPLIER_CTES + PRODUCT)
def grouped_rect_supplier(spark, d):
    """Stored once, then planned by the front door from its counts, as both operands are made from one table."""
    s = _stored(_supplier(spark, d))
    return multiply.multiply(s, s.transpose(), groups="auto").df


@query(SUPPLIER_CTES + PRODUCT)
def symmetric_supplier(spark, d):
    return multiply.symmetric_product(_supplier(spark, d)).df


@query(f"WITH e AS ({_VECTORS}), a AS (SELECT c AS r, r AS c, v FROM e), b AS (SELECT * FROM e) " + PRODUCT)
def grouped_gram_dim(spark, d):
    e = _vectors(spark, d)
    return multiply.grouped_multiply(e.transpose(), e, GRID, 64, 256).df


@query(f"WITH e AS ({_VECTORS}), a AS (SELECT c AS r, r AS c, v FROM e), b AS (SELECT * FROM e) " + PRODUCT)
def gram_partial_sums(spark, d):
    """The tall-and-thin form: partial sums of outer products, no routing of operands."""
    arrays = tables.load(spark, d, "embeddings").select(tables.quantised(F.col("embedding")).alias("x"))
    return multiply.gram(arrays, "x", 64).df


@query(f"WITH a AS ({_VECTORS}), b AS (SELECT c AS r, r AS c, v FROM a) " + PRODUCT + " HAVING sum(a.v * b.v) <> 0")
def grouped_gram_rows(spark, d):
    e = _vectors(spark, d)
    return multiply.grouped_multiply(e, e.transpose(), GridSpec(4, 4, 2, 2), 8, kernel="panel").df


_CODE = "CASE event_type WHEN 'click' THEN 1 WHEN 'error' THEN 2 WHEN 'purchase' THEN 3 WHEN 'signup' THEN 4 WHEN 'view' THEN 5 ELSE 0 END"


@query(f"WITH a AS (SELECT user_id AS r, CAST(hour(ts) AS BIGINT) AS c, count(*) AS v FROM events GROUP BY 1, 2), b AS (SELECT CAST(hour(ts) AS BIGINT) AS r, CAST({_CODE} AS BIGINT) AS c, count(*) AS v FROM events GROUP BY 1, 2) " + PRODUCT)
def grouped_event_user(spark, d):
    a, b = workloads.user_hour_type(spark, d)
    users = MatrixMeta(-(-_largest(tables.load(spark, d, "events"), "user_id") // 4) * 4, 24)
    return multiply.grouped_multiply(MatrixFrame(a.df, users), b, GRID, 3, 6).df


@query("WITH b AS (SELECT user_id AS r, CAST(hour(ts) AS BIGINT) AS c, count(*) AS v FROM events GROUP BY 1, 2), a AS (SELECT c AS r, r AS c, v FROM b) " + PRODUCT)
def event_user_gram(spark, d):
    """Hours by hours, over the users they share."""
    u, _ = workloads.user_hour_type(spark, d)
    u = MatrixFrame(u.df, MatrixMeta(-(-_largest(tables.load(spark, d, "events"), "user_id") // 32) * 32, 24))
    return multiply.grouped_multiply(u.transpose(), u, GRID, 8).df


_SEGMENTS = ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"]
_SEGMENT_SQL = "CASE c_mktsegment " + " ".join(f"WHEN '{s}' THEN {i}" for i, s in enumerate(_SEGMENTS)) + " END"


@query(f"""SELECT CAST(n_regionkey AS BIGINT) AS "row", CAST({_SEGMENT_SQL} AS BIGINT) AS "col", CAST(sum(CAST(round(o_totalprice * 100) AS BIGINT)) AS BIGINT) AS "value"
    FROM region JOIN nation ON n_regionkey = r_regionkey JOIN customer ON c_nationkey = n_nationkey JOIN orders ON o_custkey = c_custkey GROUP BY 1, 2""")
def chain_geo(spark, d):
    nation, customer, orders = (tables.load(spark, d, x) for x in ("nation", "customer", "orders"))
    one = F.lit(1)
    r = tables.from_table(nation, F.col("n_regionkey"), F.col("n_nationkey"), one, MatrixMeta(5, 25), "max")
    n = tables.from_table(customer, F.col("c_nationkey"), F.col("c_custkey"), one, MatrixMeta(25, workloads.KEYS), "max")
    paid = customer.join(orders, F.col("c_custkey") == F.col("o_custkey"))
    c = tables.from_table(paid, F.col("c_custkey"), F.expr(_SEGMENT_SQL), F.round(F.col("o_totalprice") * 100).cast("long"), MatrixMeta(workloads.KEYS, 5))
    return multiply.chain([r, n, c]).df


@query('WITH a AS (SELECT l_orderkey AS r, l_partkey AS c, CAST(sum(l_quantity) AS BIGINT) AS v FROM lineitem GROUP BY 1, 2), b AS (SELECT p_partkey AS r, CAST(p_size AS BIGINT) AS c, CAST(1 AS BIGINT) AS v FROM part) ' + PRODUCT)
def orders_by_size(spark, d):
    return multiply.relational_multiply(workloads.order_part(spark, d), workloads.part_size(spark, d)).df


_LANG = "CASE lang WHEN 'de' THEN 0 WHEN 'en' THEN 1 WHEN 'es' THEN 2 WHEN 'fr' THEN 3 END"
_SOURCE = "CAST(substr(source, 4) AS BIGINT)"


@query(f"WITH a AS (SELECT doc_id AS r, {_SOURCE} AS c, count(*) AS v FROM documents GROUP BY 1, 2), b AS (SELECT {_SOURCE} AS r, CAST({_LANG} AS BIGINT) AS c, count(*) AS v FROM documents GROUP BY 1, 2) " + PRODUCT)
def doc_source_lang(spark, d):
    docs = tables.load(spark, d, "documents")
    source, lang = F.expr(_SOURCE), F.expr(_LANG)
    a = tables.from_table(docs, F.col("doc_id"), source, F.lit(1), MatrixMeta(workloads.KEYS, 20), "count")
    b = tables.from_table(docs, source, lang, F.lit(1), MatrixMeta(20, 4), "count")
    return multiply.broadcast_multiply(a, b).df


@query(f"SELECT CAST(quality * 2 + toxic AS BIGINT) AS \"row\", CAST({_LANG} AS BIGINT) AS \"col\", count(*) AS \"value\" FROM labels JOIN documents USING (doc_id) GROUP BY 1, 2")
def label_class_lang(spark, d):
    docs, labels = tables.load(spark, d, "documents"), tables.load(spark, d, "labels")
    one = F.lit(1)
    a = tables.from_table(labels, F.col("quality") * 2 + F.col("toxic"), F.col("doc_id"), one, MatrixMeta(4, workloads.KEYS), "count")
    b = tables.from_table(docs, F.col("doc_id"), F.expr(_LANG), one, MatrixMeta(workloads.KEYS, 4), "count")
    return multiply.tall_thin_multiply(a, b, 16).df


def _lengths_sql(table: str, key: str) -> str:
    return f"SELECT k AS r, CAST(length(w) % 16 AS BIGINT) AS c, count(*) AS v FROM (SELECT {key} AS k, unnest(string_split(text, ' ')) AS w FROM {table}) GROUP BY 1, 2"


@query(f"WITH a AS ({_lengths_sql('documents', 'doc_id')}), t AS ({_lengths_sql('benchmark', 'item_id')}), b AS (SELECT c AS r, r AS c, v FROM t) " + PRODUCT)
def token_overlap(spark, d):
    def lengths(name: str, key: str, row: str, v: str) -> DataFrame:
        words = tables.load(spark, d, name).select(F.col(key).alias(row), F.explode(F.split("text", " ")).alias("w")).select(row, (F.length("w") % 16).alias("n"))
        # sixteen counts a text, summed before anything is shuffled
        return words.groupBy(row).agg(F.array(*[F.count_if(F.col("n") == i) for i in range(16)]).alias(v))

    return multiply.thin_dot_multiply(lengths("documents", "doc_id", "row", "v"), lengths("benchmark", "item_id", "col", "u"), workloads.KEYS, 16, workloads.KEYS).df


_ROLE = "CASE {} WHEN 'assistant' THEN 0 WHEN 'system' THEN 1 WHEN 'user' THEN 2 END"


@query(f"WITH s AS (SELECT {_ROLE.format('role')} AS r, {_ROLE.format('nxt')} AS c FROM (SELECT role, lead(role) OVER (PARTITION BY conv_id ORDER BY turn) AS nxt FROM conversations) WHERE nxt IS NOT NULL), a AS (SELECT CAST(r AS BIGINT) AS r, CAST(c AS BIGINT) AS c, count(*) AS v FROM s GROUP BY 1, 2), b AS (SELECT * FROM a) " + PRODUCT)
def role_two_step(spark, d):
    turns = tables.load(spark, d, "conversations").withColumn("nxt", F.lead("role").over(Window.partitionBy("conv_id").orderBy("turn"))).where("nxt IS NOT NULL")
    m = tables.from_table(turns, F.expr(_ROLE.format("role")), F.expr(_ROLE.format("nxt")), F.lit(1), MatrixMeta(3, 3), "count")
    return multiply.power(m, 2).df


@query("""WITH a AS (SELECT host AS r, length(h) % 16 AS c, count(*) AS v FROM (SELECT regexp_extract(url, '://([^/?#]+)', 1) AS host, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS h FROM pages) GROUP BY 1, 2), b AS (SELECT c AS r, r AS c, v FROM a) """ + PRODUCT)
def web_overlap(spark, d):
    links = tables.load(spark, d, "pages").select(F.regexp_extract("url", "://([^/?#]+)", 1).alias("row"), F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("h"))
    m = MatrixFrame(links.groupBy("row", (F.length("h") % 16).alias("col")).agg(F.count("*").alias("value")), MatrixMeta(workloads.KEYS, 16))
    return multiply.relational_multiply(m, m.transpose()).df


# ---------------------------------------------------------------- operators around products

_A = f"SELECT r AS \"row\", c AS \"col\", v AS \"value\" FROM a"


@query(_square_ctes() + _A)
def block_roundtrip(spark, d):
    a, _ = _pair(spark, d)
    return MatrixFrame.from_blocks(a.to_blocks(24), 24, a.meta).df


@query(_square_ctes() + 'SELECT c AS "row", r AS "col", v AS "value" FROM a')
def transpose(spark, d):
    return _pair(spark, d)[0].transpose().df


@query(_square_ctes() + 'SELECT r AS "row", c AS "col", CAST(sum(v) AS BIGINT) AS "value" FROM (SELECT * FROM a UNION ALL SELECT * FROM b) GROUP BY 1, 2')
def add(spark, d):
    a, b = _pair(spark, d)
    return a.add(b).df


@query(_square_ctes() + 'SELECT r AS "row", c AS "col", CAST(sum(v) AS BIGINT) AS "value" FROM (SELECT * FROM a UNION ALL SELECT r, c, -v FROM b) GROUP BY 1, 2 HAVING sum(v) <> 0')
def subtract(spark, d):
    a, b = _pair(spark, d)
    return a.sub(b).prune().df


@query(_square_ctes() + 'SELECT a.r AS "row", a.c AS "col", a.v * b.v AS "value" FROM a JOIN b ON a.r = b.r AND a.c = b.c')
def hadamard(spark, d):
    a, b = _pair(spark, d)
    return a.hadamard(b).df


@query(_square_ctes() + 'SELECT r AS "row", c AS "col", v * 3 AS "value" FROM a')
def scale(spark, d):
    return _pair(spark, d)[0].scale(3).df


@query(_square_ctes() + 'SELECT r AS "row", CAST(sum(v) AS BIGINT) AS "value" FROM a GROUP BY 1')
def row_sums(spark, d):
    return _pair(spark, d)[0].row_sums()


@query(_square_ctes() + 'SELECT c AS "col", CAST(sum(v) AS BIGINT) AS "value" FROM a GROUP BY 1')
def col_sums(spark, d):
    return _pair(spark, d)[0].col_sums()


@query(_square_ctes() + 'SELECT CAST(sum(v) AS BIGINT) AS "value" FROM a WHERE r = c')
def trace(spark, d):
    return _pair(spark, d)[0].trace()


@query(_square_ctes() + _A)
def identity_left(spark, d):
    a, _ = _pair(spark, d)
    return multiply.grouped_multiply(blocks.identity(spark, N), a, GRID, 8).df


@query(_square_ctes() + f'SELECT i.range AS "row", j.range AS "col", CAST(coalesce(v, 0) AS BIGINT) AS "value" FROM range({N}) i CROSS JOIN range({N}) j LEFT JOIN a ON a.r = i.range AND a.c = j.range')
def densify(spark, d):
    return _pair(spark, d)[0].densify().df


@query(_square_ctes() + 'SELECT r AS "row", CAST(sum(v * (c + 1)) AS BIGINT) AS "value" FROM a GROUP BY 1')
def matvec(spark, d):
    a, _ = _pair(spark, d)
    return blocks.matvec(a, spark.range(N).select(F.col("id").alias("row"), (F.col("id") + 1).alias("value")))


@query(_square_ctes() + f"""SELECT a.r AS "row", b.c AS "col", CAST(sum(a.v * b.v) AS BIGINT) AS "value" FROM a JOIN b ON a.c = b.r WHERE a.r < 8 AND b.c BETWEEN 8 AND 15 GROUP BY 1, 2""")
def panel_filter(spark, d):
    a, b = _pair(spark, d)
    return multiply.grouped_multiply(a.filter(rows=F.col("row") < 8), b.filter(cols=F.col("col").between(8, 15)), GRID, 8).df


@query(_square_ctes() + 'SELECT r AS "row", c AS "col", CAST(sum(v) AS BIGINT) AS "value" FROM (SELECT * FROM a UNION ALL SELECT * FROM b) GROUP BY 1, 2')
def sparse_row_maps(spark, d):
    a, b = _pair(spark, d)
    return blocks.add_row_maps(a.to_row_maps(), b.to_row_maps()).select("row", F.explode("entries").alias("col", "value"))


@query("""WITH q AS (SELECT vec_id AS id, list_transform(embedding, lambda x: CAST(ROUND(CAST(x AS DOUBLE) * 1000) AS BIGINT)) AS x FROM embeddings),
    w AS (SELECT j.range AS j, list((7 * k.range + 3 * j.range) % 11 - 5 ORDER BY k.range) AS y FROM range(4) j CROSS JOIN range(64) k GROUP BY 1)
    SELECT id AS "row", j AS "col", CAST(list_sum(list_transform(list_zip(x, y), lambda z: z[1] * z[2])) AS BIGINT) AS "value" FROM q, w""")
def hof_dot(spark, d):
    """Every vector times a 64 x 4 matrix held as four column arrays, in array functions only."""
    columns = F.lit([[(7 * k + 3 * j) % 11 - 5 for k in range(64)] for j in range(4)])
    vectors = tables.load(spark, d, "embeddings").select(F.col("vec_id").alias("row"), tables.quantised(F.col("embedding")).alias("x"))
    return vectors.select("row", "x", F.posexplode(columns).alias("col", "y")).select("row", F.col("col").cast("long").alias("col"), kernels.dot(F.col("x"), F.col("y")).alias("value"))


# ---------------------------------------------------------------- schedules

_DIM = MatrixMeta(96, 96)
_SIX = GridSpec(6, 6, 3, 3)
_INNER, _OUTER = 4, 8

_FLAT_SCHEDULE = f"""
    WITH st AS (SELECT range AS step FROM range({96 // _INNER})), ij AS (SELECT CAST(range AS INT) AS i FROM range(6))
    SELECT step, step AS outer_step, CAST(0 AS BIGINT) AS inner_step, 'A' AS operand, 'flat' AS level, 0 AS root_grp_row, 0 AS root_grp_col, i AS root_in_row, CAST(step * {_INNER} // 16 AS INT) AS root_in_col, CAST(5 AS BIGINT) AS receivers, CAST({16 * _INNER} AS BIGINT) AS elements FROM st, ij
    UNION ALL SELECT step, step, 0, 'B', 'flat', 0, 0, CAST(step * {_INNER} // 16 AS INT), i, 5, {16 * _INNER} FROM st, ij"""
_GROUPED_SCHEDULE = f"""
    WITH fine AS (SELECT range AS step, range // 2 AS outer_step, range % 2 AS inner_step, CAST(range // 2 * {_OUTER} // 16 AS INT) AS own FROM range({96 // _INNER})),
    coarse AS (SELECT range * 2 AS step, range AS outer_step, CAST(0 AS BIGINT) AS inner_step, CAST(range * {_OUTER} // 16 AS INT) AS own FROM range({96 // _OUTER})),
    ij AS (SELECT CAST(range AS INT) AS i FROM range(6)), gg AS (SELECT CAST(range AS INT) AS g FROM range(3))
    SELECT step, outer_step, inner_step, 'A' AS operand, 'between' AS level, CAST(i // 2 AS INT) AS root_grp_row, CAST(own // 2 AS INT) AS root_grp_col, CAST(i % 2 AS INT) AS root_in_row, CAST(own % 2 AS INT) AS root_in_col, CAST(2 AS BIGINT) AS receivers, CAST({16 * _OUTER} AS BIGINT) AS elements FROM coarse, ij
    UNION ALL SELECT step, outer_step, inner_step, 'B', 'between', CAST(own // 2 AS INT), CAST(i // 2 AS INT), CAST(own % 2 AS INT), CAST(i % 2 AS INT), 2, {16 * _OUTER} FROM coarse, ij
    UNION ALL SELECT step, outer_step, inner_step, 'A', 'inside', CAST(i // 2 AS INT), g, CAST(i % 2 AS INT), CAST(own % 2 AS INT), 1, {16 * _INNER} FROM fine, ij, gg
    UNION ALL SELECT step, outer_step, inner_step, 'B', 'inside', g, CAST(i // 2 AS INT), CAST(own % 2 AS INT), CAST(i % 2 AS INT), 1, {16 * _INNER} FROM fine, ij, gg"""


def _plan(spark: SparkSession, method: str) -> DataFrame:
    return schedule.schedule(spark, method, _DIM, _DIM, _SIX, _INNER, _INNER if method == "flat" else _OUTER)


@query(_FLAT_SCHEDULE)
def schedule_flat(spark, d):
    return _plan(spark, "flat")


@query(_GROUPED_SCHEDULE)
def schedule_grouped(spark, d):
    return _plan(spark, "grouped")


_BOTH = f"(SELECT * FROM ({_FLAT_SCHEDULE}) UNION ALL SELECT * FROM ({_GROUPED_SCHEDULE}))"


@query(f"SELECT operand, level, count(*) AS broadcasts, CAST(sum(receivers * elements) AS BIGINT) AS deliveries FROM {_BOTH} GROUP BY 1, 2")
def schedule_totals(spark, d):
    return schedule.totals(_plan(spark, "flat").unionByName(_plan(spark, "grouped")))


def _cube_sql(how: str) -> str:
    return f"SELECT operand, level, CAST(sum(receivers * elements) AS BIGINT) AS deliveries FROM ({_GROUPED_SCHEDULE}) GROUP BY {how}"


def _delivered() -> F.Column:
    return F.sum(F.col("receivers") * F.col("elements")).alias("deliveries")


@query(_cube_sql("ROLLUP (operand, level)"))
def schedule_rollup(spark, d):
    return _plan(spark, "grouped").rollup("operand", "level").agg(_delivered())


@query(_cube_sql("CUBE (operand, level)"))
def schedule_cube(spark, d):
    return _plan(spark, "grouped").cube("operand", "level").agg(_delivered())


@query(_cube_sql("GROUPING SETS ((operand), (level))"))
def schedule_sets(spark, d):
    return _plan(spark, "grouped").groupingSets([["operand"], ["level"]], "operand", "level").agg(_delivered()).select("operand", "level", "deliveries")


@query(f"SELECT operand, arg_max(root, deliveries * 1000000 - root) AS root, CAST(max(deliveries) AS BIGINT) AS deliveries FROM (SELECT operand, CAST(((root_grp_row * 3 + root_grp_col) * 2 + root_in_row) * 2 + root_in_col AS BIGINT) AS root, CAST(sum(receivers * elements) AS BIGINT) AS deliveries FROM ({_GROUPED_SCHEDULE}) GROUP BY 1, 2) GROUP BY 1")
def schedule_busiest(spark, d):
    root = (((F.col("root_grp_row") * 3 + F.col("root_grp_col")) * 2 + F.col("root_in_row")) * 2 + F.col("root_in_col")).cast("long")
    per = _plan(spark, "grouped").groupBy("operand", root.alias("root")).agg(_delivered())
    return per.groupBy("operand").agg(F.max_by("root", F.col("deliveries") * 1_000_000 - F.col("root")).alias("root"), F.max("deliveries").alias("deliveries"))


@query(f"SELECT operand, step, CAST(sum(x) OVER (PARTITION BY operand ORDER BY step) AS BIGINT) AS delivered FROM (SELECT operand, step, sum(receivers * elements) AS x FROM ({_GROUPED_SCHEDULE}) GROUP BY 1, 2)")
def schedule_running(spark, d):
    per = _plan(spark, "grouped").groupBy("operand", "step").agg(F.sum(F.col("receivers") * F.col("elements")).alias("x"))
    return per.select("operand", "step", F.sum("x").over(Window.partitionBy("operand").orderBy("step").rowsBetween(Window.unboundedPreceding, 0)).alias("delivered"))


@query("SELECT * FROM (VALUES ('flat', 'A', CAST(96 * 96 * 2 * 2 AS BIGINT)), ('flat', 'B', CAST(96 * 96 * 2 * 2 AS BIGINT)), ('grouped', 'A', CAST(96 * 96 * 2 AS BIGINT)), ('grouped', 'B', CAST(96 * 96 * 2 AS BIGINT))) AS t(method, operand, crossings)")
def group_crossings(spark, d):
    rows = [(m, o, n) for (m, o), n in schedule.crossings(_DIM, _DIM, _SIX).items()]
    return spark.createDataFrame(rows, "method string, operand string, crossings long")


@query('SELECT CAST(i.range AS INT) AS cell_row, CAST(j.range AS INT) AS cell_col, CAST(i.range // 2 AS INT) AS grp_row, CAST(j.range // 2 AS INT) AS grp_col, CAST(i.range % 2 AS INT) AS in_row, CAST(j.range % 2 AS INT) AS in_col FROM range(6) i CROSS JOIN range(6) j')
def grid_frame(spark, d):
    return _SIX.frame(spark).select(*[F.col(c).cast("int").alias(c) for c in ("cell_row", "cell_col", "grp_row", "grp_col", "in_row", "in_col")])


@query("SELECT i.range AS grp_rows, j.range AS grp_cols, i.range * j.range AS groups FROM range(1, 9) i CROSS JOIN range(1, 17) j WHERE 8 % i.range = 0 AND 16 % j.range = 0")
def valid_groupings(spark, d):
    return topology.groupings_frame(spark, 8, 16)


# ---------------------------------------------------------------- costs

#: Published platform parameters, as in tables.platforms.
_PLATFORMS = "(VALUES ('cluster', 1e-4, 1e-9, 8192.0, 128.0, 64.0), ('cluster_large_block', 1e-4, 1e-9, 8192.0, 128.0, 512.0), ('supercomputer', 3e-6, 1e-9, 65536.0, 16384.0, 256.0), ('supercomputer_2048', 3e-6, 1e-9, 65536.0, 2048.0, 256.0), ('exascale', 5e-7, 1e-11, 4194304.0, 1048576.0, 256.0)) AS t(platform, alpha, beta, n, p, b)"
_P = f"(SELECT platform, CAST(alpha AS DOUBLE) AS alpha, CAST(beta AS DOUBLE) AS beta, CAST(n AS DOUBLE) AS n, CAST(p AS DOUBLE) AS p, CAST(b AS DOUBLE) AS b FROM {_PLATFORMS}) AS pl"
#: Order lines by the month they were shipped in, as workloads.months.
_MONTHS = "(SELECT CAST(year(l_shipdate) * 100 + month(l_shipdate) AS BIGINT) AS month, count(*) AS lines FROM lineitem GROUP BY 1) AS months"
#: SQL of the factors over q.
_SQL_FACTORS = {
    "binomial": ("log2({q})", "log2({q})"),
    "scatter_allgather": ("(log2({q}) + {q} - 1)", "(2 * ({q} - 1) / {q})"),
    "flat": ("({q} - 1)", "({q} - 1)"),
    "binary": ("(2 * log2(({q} + 1) / 2))", "(2 * log2(({q} + 1) / 2))"),
    "chain_pipelined": ("(CASE WHEN {q} > 1 THEN {q} + 6 ELSE 0 END)", "(CASE WHEN {q} > 1 THEN ({q} + 6) / 8 ELSE 0 END)"),
}


def _comm_sql(name: str, q: str) -> str:
    latency, bandwidth = (f.format(q=q) for f in _SQL_FACTORS[name])
    return f"2 * (n / b * {latency} * alpha + n * n / sqrt(p) * {bandwidth} * beta)"


def _grouped_sql(name: str) -> str:
    return f"({_comm_sql(name, 'sqrt(p / g)')} + {_comm_sql(name, 'sqrt(g)')})"


def _micro_sql(x: str) -> str:
    return f"CAST(round(({x}) * 1000000) AS BIGINT)"


def _micro(x) -> F.Column:
    return F.round(x * 1_000_000).cast("long")


#: The platforms with each month's product, as workloads.month_products.
_PM = f"(SELECT month, platform, alpha, beta, ceil(lines / b) * b AS n, p, b FROM {_MONTHS} CROSS JOIN {_P}) AS pm"


def _exact_us_sql(x: str) -> str:
    return f"CAST(round(round(({x}) * 1000000, 3)) AS BIGINT)"


def _exact_us(x) -> F.Column:
    """Microseconds; rounded to thousandths first, so that half of one is the same in every engine."""
    return F.round(F.round(x * 1_000_000, 3)).cast("long")


def _cost_sql(name: str) -> str:
    return f"SELECT month, platform, CAST(g AS BIGINT) AS g, {_exact_us_sql(_comm_sql(name, 'sqrt(p)'))} AS flat_us, {_exact_us_sql(_grouped_sql(name))} AS grouped_us FROM {_PM} CROSS JOIN (SELECT CAST(pow(2, range) AS DOUBLE) AS g FROM range(21)) WHERE g <= p"


def _cost_query(name: str) -> Query:
    """Flat and grouped costs of each month's product on each platform, for every number of groups."""

    def run(spark, d):
        return advisor.model_costs(workloads.month_products(spark, d), name).select("month", "platform", F.col("g").cast("long").alias("g"), _exact_us(F.col("flat")).alias("flat_us"), _exact_us(F.col("grouped")).alias("grouped_us"))

    return run


for _name in _SQL_FACTORS:
    _key = f"cost_{_name}" if _name != "flat" else "cost_flat_tree"
    QUERIES[_key], ORACLES[_key] = _cost_query(_name), _cost_sql(_name)


@query("SELECT platform, CAST(g AS BIGINT) AS g, family, CAST(round(flat_latency) AS BIGINT) AS flat_latency, CAST(round(latency_inside) AS BIGINT) AS latency_inside, CAST(round(latency_between) AS BIGINT) AS latency_between, CAST(round(bandwidth_inside) AS BIGINT) AS bandwidth_inside, CAST(round(bandwidth_between) AS BIGINT) AS bandwidth_between FROM ("
       + " UNION ALL ".join(f"SELECT platform, 16.0 AS g, '{f}' AS family, 2 * n / b * {_SQL_FACTORS[f][0].format(q='sqrt(p)')} AS flat_latency, 2 * n / b * {_SQL_FACTORS[f][0].format(q='sqrt(p / 16)')} AS latency_inside, 2 * n / b * {_SQL_FACTORS[f][0].format(q='4.0')} AS latency_between, 2 * n * n / sqrt(p) * {_SQL_FACTORS[f][1].format(q='sqrt(p / 16)')} AS bandwidth_inside, 2 * n * n / sqrt(p) * {_SQL_FACTORS[f][1].format(q='4.0')} AS bandwidth_between FROM {_P}" for f in ("binomial", "scatter_allgather")) + ")")
def cost_tables(spark, d):
    """The two comparison tables as data, at 16 groups."""
    parts = [cost.cost_table(spark, f, tables.platforms(spark), F.lit(16.0)) for f in ("binomial", "scatter_allgather")]
    names = ["flat_latency", "latency_inside", "latency_between", "bandwidth_inside", "bandwidth_between"]
    return parts[0].unionByName(parts[1]).select("platform", F.col("g").cast("long").alias("g"), "family", *[F.round(c).cast("long").alias(c) for c in names])


def _sqrt_sql(root: str) -> str:
    return f"SELECT month, platform, {_exact_us_sql(f'(log2(p) + 4 * ({root} - 1)) * n / b * alpha + 8 * (1 - 1 / {root}) * n * n / sqrt(p) * beta')} AS cost_us FROM {_PM}"


@query(_sqrt_sql("pow(p, 0.25)"))
def cost_sqrt_corrected(spark, d):
    return workloads.month_products(spark, d).select("month", "platform", _exact_us(cost.grouped_at_sqrt()).alias("cost_us"))


@query(_sqrt_sql("sqrt(p)"))
def cost_sqrt_printed(spark, d):
    """The published form, which exceeds the flat cost; a labelled variant only."""
    return workloads.month_products(spark, d).select("month", "platform", _exact_us(cost.grouped_at_sqrt(as_printed=True)).alias("cost_us"))


@query(f"SELECT platform, CASE WHEN alpha / beta > 2 * n * b / p THEN 'min_at_sqrt_p' ELSE 'max_at_sqrt_p' END AS scatter_allgather, 'indifferent' AS binomial, CASE WHEN alpha / (8 * beta) > 2 * n * b / p THEN 'min_at_sqrt_p' ELSE 'max_at_sqrt_p' END AS by_bytes FROM {_P}")
def verdicts(spark, d):
    return tables.platforms(spark).select("platform", cost.verdict().alias("scatter_allgather"), cost.verdict(name="binomial").alias("binomial"), cost.verdict(element_bytes=8).alias("by_bytes"))


_SA = _grouped_sql("scatter_allgather")
_ALL_G = f"(SELECT *, {_SA} AS cost, {_comm_sql('scatter_allgather', 'sqrt(p)')} AS flat FROM {_P} CROSS JOIN (SELECT CAST(pow(2, range) AS DOUBLE) AS g FROM range(21)) WHERE g <= p)"


@query(f"SELECT month, platform, CAST(g AS BIGINT) AS g, {_exact_us_sql('flat')} AS flat_us, {_exact_us_sql('cost')} AS grouped_us FROM (SELECT *, row_number() OVER (PARTITION BY month, platform ORDER BY round(cost, 12), g) AS place FROM {_ALL_G.replace(_P, _PM)}) WHERE place = 1")
def best_groups(spark, d):
    """The cheapest number of groups for each month's product on each platform."""
    best = advisor.advise_groups(workloads.month_products(spark, d), by=("month", "platform"))
    return best.select("month", "platform", "g", _exact_us(F.col("flat")).alias("flat_us"), _exact_us(F.col("grouped")).alias("grouped_us"))


@query(f"SELECT platform, CAST(g AS BIGINT) AS g, CAST(CASE WHEN abs(g - sqrt(p)) < 1e-6 THEN 0 ELSE sign((g - sqrt(p)) * (n * alpha / b - 2 * n * n / p * beta)) END AS INT) AS slope FROM {_ALL_G}")
def derivative_sign(spark, d):
    """Sign of the cost's slope in the number of groups, from the general form."""
    f = cost.family("scatter_allgather")
    rows = advisor.candidates(tables.platforms(spark))
    slope = cost.d_cost_dg(f)
    near = F.abs(F.col("g") - F.sqrt("p")) < 1e-6
    return rows.select("platform", F.col("g").cast("long").alias("g"), F.when(near, 0).otherwise(F.signum(slope)).cast("int").alias("slope"))


@query(f"SELECT month, platform, CAST(round(round(2 * n * b * beta / alpha * 1000, 3)) AS BIGINT) AS p_thousandths FROM {_PM}")
def break_even(spark, d):
    return workloads.month_products(spark, d).select("month", "platform", F.round(F.round(cost.break_even_p() * 1000, 3)).cast("long").alias("p_thousandths"))


@query(f"SELECT CAST(g AS BIGINT) AS g, {_micro_sql('2 * pow(n, 3) * 1e-18 / p + cost')} AS grouped_us, {_micro_sql('2 * pow(n, 3) * 1e-18 / p + flat')} AS flat_us FROM {_ALL_G} WHERE platform = 'exascale'")
def exascale_curve(spark, d):
    """Predicted execution time over 1 to 2^20 groups; the flop time is taken by processor, as in the published curve."""
    rows = advisor.model_costs(tables.platforms(spark).where("platform = 'exascale'"))
    work = cost.compute_cost()
    return rows.select(F.col("g").cast("long").alias("g"), _micro(cost.exec_time(F.col("grouped"), work)).alias("grouped_us"), _micro(cost.exec_time(F.col("flat"), work)).alias("flat_us"))


@query(f"SELECT platform, CAST(n / b AS BIGINT) AS steps, CAST(n / (2 * b) AS BIGINT) AS outer_steps, CAST(2 AS BIGINT) AS inner_steps FROM {_P}")
def steps_table(spark, d):
    return tables.platforms(spark).select("platform", cost.steps().cast("long").alias("steps"), cost.steps(b=F.col("b") * 2).cast("long").alias("outer_steps"), cost.steps(n=F.col("b") * 2).cast("long").alias("inner_steps"))


@query(f"SELECT platform, CAST(round(n * b / sqrt(p)) AS BIGINT) AS panel, {_micro_sql('alpha + n * b / sqrt(p) * beta')} AS message_us FROM {_P}")
def panel_sizes(spark, d):
    m = cost.panel_elements()
    return tables.platforms(spark).select("platform", F.round(m).cast("long").alias("panel"), _micro(cost.hockney(m)).alias("message_us"))


@query("""SELECT * FROM (VALUES ('flat', 3 * 4096 * 4096 // 64 + 64 * 1024), ('grouped', 3 * 4096 * 4096 // 64 + 64 * 1024), ('25d', 2 * 3 * 4096 * 4096 // 64), ('3d', 4 * 3 * 4096 * 4096 // 64), ('lcm_shift', 3 * 4096 * 4096 // 64 + 512 * 1024), ('cannon', 3 * 4096 * 4096 // 64 + 2 * 4096 * 4096 // 64)) AS t(method, elements)""".replace("elements)", "e)").replace("SELECT *", "SELECT method, CAST(e AS BIGINT) AS elements"))
def memory_per_cell(spark, d):
    m, grid = MatrixMeta(4096, 4096), GridSpec(8, 8)
    rows = [(name, round(cost.memory_elements(name, m, m, grid, outer=64, c=2))) for name in ("flat", "grouped", "25d", "3d", "lcm_shift", "cannon")]
    return spark.createDataFrame(rows, "method string, elements long")


@query(f"SELECT month, method, CAST(round(CASE method WHEN '3d' THEN pow(lines, 1.0 / 3) WHEN '25d' THEN 4 ELSE 1 END) AS BIGINT) AS copies FROM {_MONTHS} CROSS JOIN (VALUES ('flat'), ('grouped'), ('3d'), ('25d')) AS t(method)")
def copies_by_method(spark, d):
    """Copies of a month's operands on a processor an order line; the 2.5-D product has four layers."""
    methods = [F.struct(F.lit(m).alias("method"), F.round(cost.col(cost.copies(m, F.col("lines"), 4))).cast("long").alias("copies")) for m in ("flat", "grouped", "3d", "25d")]
    return workloads.months(spark, d).select("month", F.inline(F.array(*methods)))


#: Published measurements (what, flat seconds, grouped seconds).
_MEASURED = [("communication, 16384 cores", 36.46, 6.19), ("execution, 16384 cores", 50.2, 21.26), ("communication, cluster, large block", 4.53, 2.81)]


@query("SELECT what, CAST(round(flat / grouped * 100) AS BIGINT) AS gain_hundredths FROM (VALUES " + ", ".join(f"('{w}', CAST({x} AS DOUBLE), CAST({y} AS DOUBLE))" for w, x, y in _MEASURED) + ") AS t(what, flat, grouped)")
def paper_gains(spark, d):
    return spark.createDataFrame(_MEASURED, "what string, flat double, grouped double").select("what", F.round(cost.gain(F.col("flat"), F.col("grouped")) * 100).cast("long").alias("gain_hundredths"))


@query(f"SELECT platform, {_micro_sql(_comm_sql('scatter_allgather', 'sqrt(p)'))} AS flat_us, {_micro_sql(_grouped_sql('scatter_allgather').replace('sqrt(g)', '4.0').replace('p / g', 'p / 16'))} AS grouped_us FROM {_P}")
def sql_functions(spark, d):
    """The same costs through the SQL surface."""
    sqlsurface.register(spark)
    tables.platforms(spark).createOrReplaceTempView("gridmul_platforms")
    return spark.sql("SELECT platform, CAST(round(flat_comm(n, b, p, alpha, beta) * 1000000) AS BIGINT) AS flat_us, CAST(round(grouped_comm(n, b, p, alpha, beta, 16) * 1000000) AS BIGINT) AS grouped_us FROM gridmul_platforms")


@query("SELECT CAST(i.range AS INT) AS grp_rows, CAST(j.range AS INT) AS grp_cols FROM range(1, 9) i CROSS JOIN range(1, 17) j WHERE 8 % i.range = 0 AND 16 % j.range = 0")
def sql_valid_groups(spark, d):
    sqlsurface.register(spark)
    return spark.sql("SELECT * FROM valid_groups(8, 16)")


# ---------------------------------------------------------------- relational surface

@query(SUPPLIER_CTES + f'SELECT * FROM ({PRODUCT}) ORDER BY "value" DESC, "row", "col" LIMIT 20')
def top_entries(spark, d):
    s = _supplier(spark, d)
    return multiply.relational_multiply(s, s.transpose()).df.orderBy(F.desc("value"), "row", "col").limit(20)


@query(SUPPLIER_CTES + f', p AS ({PRODUCT}) SELECT "row", "col", "value", CAST(place AS INT) AS place FROM (SELECT *, row_number() OVER (PARTITION BY "row" ORDER BY "value" DESC, "col") AS place FROM p) WHERE place <= 3')
def top_per_row(spark, d):
    s = _supplier(spark, d)
    order = Window.partitionBy("row").orderBy(F.desc("value"), "col")
    return multiply.relational_multiply(s, s.transpose()).df.withColumn("place", F.row_number().over(order)).where("place <= 3")


@query(SUPPLIER_CTES + f', p AS ({PRODUCT}), s AS (SELECT "row", CAST(sum("value") AS BIGINT) AS total FROM p GROUP BY 1) SELECT "row", total, CAST(rank() OVER (ORDER BY total DESC) AS INT) AS place, CAST(dense_rank() OVER (ORDER BY total DESC) AS INT) AS dense_place, total - lag(total) OVER (ORDER BY total DESC, "row") AS step FROM s')
def rank_suppliers(spark, d):
    s = _supplier(spark, d)
    sums = multiply.relational_multiply(s, s.transpose()).row_sums().withColumnRenamed("value", "total")
    order = Window.orderBy(F.desc("total"))  # one row for each supplier
    return sums.select("row", "total", F.rank().over(order).alias("place"), F.dense_rank().over(order).alias("dense_place"), (F.col("total") - F.lag("total").over(Window.orderBy(F.desc("total"), "row"))).alias("step"))


@query(_square_ctes() + "SELECT 'A' AS operand, CAST(count(*) * 2 AS BIGINT) AS routed, CAST(count(DISTINCT r // 32) * 2 AS BIGINT) AS groups FROM a UNION ALL SELECT 'B', CAST(count(*) * 2 AS BIGINT), CAST(count(DISTINCT c // 32) * 2 AS BIGINT) FROM b")
def distinct_routes(spark, d):
    a, b = _pair(spark, d)
    parts = []
    for name, side, m in (("A", "a", a), ("B", "b", b)):
        sent = routing.route_between(routing.operand(m.df, side, m.meta, GRID, 8, 8), side, GRID).withColumn("grp_id", routing.group_id(GRID))
        parts.append(sent.agg(F.lit(name).alias("operand"), F.count("*").alias("routed"), F.countDistinct("grp_id").alias("groups")))
    return parts[0].unionByName(parts[1])


@query(_square_ctes() + "SELECT 'intersect' AS what, count(*) AS entries FROM (SELECT r, c FROM a INTERSECT SELECT r, c FROM b) UNION ALL SELECT 'union', count(*) FROM (SELECT r, c FROM a UNION SELECT r, c FROM b) UNION ALL SELECT 'except', count(*) FROM (SELECT r, c FROM a EXCEPT SELECT r, c FROM b)")
def set_ops_entries(spark, d):
    a, b = (m.df.select("row", "col") for m in _pair(spark, d))
    sets = {"intersect": a.intersect(b), "union": a.union(b).distinct(), "except": a.subtract(b)}
    out = None
    for what, s in sets.items():
        one = s.agg(F.lit(what).alias("what"), F.count("*").alias("entries"))
        out = one if out is None else out.unionByName(one)
    return out


@query("SELECT c_custkey AS \"row\" FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)")
def missing_rows(spark, d):
    c, o = tables.load(spark, d, "customer"), tables.load(spark, d, "orders")
    return c.join(o, c.c_custkey == o.o_custkey, "left_anti").select(F.col("c_custkey").alias("row"))


@query("SELECT c_custkey AS \"row\" FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)")
def present_rows(spark, d):
    c, o = tables.load(spark, d, "customer"), tables.load(spark, d, "orders")
    return c.join(o, c.c_custkey == o.o_custkey, "left_semi").select(F.col("c_custkey").alias("row"))


_EDGES = [(0, 0, 91000), (1, 91000, 93500), (2, 93500, 97000), (3, 97000, 10**9)]


@query("SELECT bucket, p_brand, count(*) AS parts FROM (SELECT p_brand, CAST(round(p_retailprice * 100) AS BIGINT) AS cents FROM part) JOIN (VALUES " + ", ".join(map(str, _EDGES)) + ") AS t(bucket, lo, hi) ON lo <= cents AND cents < hi GROUP BY 1, 2")
def nearest_bucket(spark, d):
    parts = tables.load(spark, d, "part").select("p_brand", F.round(F.col("p_retailprice") * 100).cast("long").alias("cents"))
    edges = F.broadcast(spark.createDataFrame(_EDGES, "bucket int, lo long, hi long"))  # four rows
    return parts.join(edges, (F.col("lo") <= F.col("cents")) & (F.col("cents") < F.col("hi"))).groupBy("bucket", "p_brand").agg(F.count("*").alias("parts"))


@query("SELECT o_orderkey, lag(o_orderkey) OVER w AS prev_orderkey, lag(CAST(round(o_totalprice * 100) AS BIGINT)) OVER w AS prev_cents FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
def asof_price(spark, d):
    """The customer's order before each order: the as-of join of a table with itself as one window."""
    before = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return tables.load(spark, d, "orders").select("o_orderkey", F.lag("o_orderkey").over(before).alias("prev_orderkey"), F.lag(F.round(F.col("o_totalprice") * 100).cast("long")).over(before).alias("prev_cents"))


@query("SELECT CAST(n_nationkey AS BIGINT) AS nation, segment, cents FROM (SELECT c_nationkey AS n_nationkey, c_mktsegment AS segment, CAST(sum(CAST(round(o_totalprice * 100) AS BIGINT)) AS BIGINT) AS cents FROM customer JOIN orders ON o_custkey = c_custkey GROUP BY 1, 2)")
def wide_small(spark, d):
    c, o = tables.load(spark, d, "customer"), tables.load(spark, d, "orders")
    cents = c.join(o, c.c_custkey == o.o_custkey).select(F.col("c_nationkey").cast("long").alias("nation"), "c_mktsegment", F.round(F.col("o_totalprice") * 100).cast("long").alias("cents"))
    wide = cents.groupBy("nation").pivot("c_mktsegment", _SEGMENTS).agg(F.sum("cents"))
    return wide.unpivot("nation", _SEGMENTS, "segment", "cents").where("cents IS NOT NULL")


@query("SELECT user_id AS \"row\", CAST(CAST(json_extract_string(props, '$.k') AS BIGINT) % 16 AS BIGINT) AS \"col\", count(*) AS \"value\" FROM events GROUP BY 1, 2")
def json_matrix(spark, d):
    events = tables.load(spark, d, "events")
    return tables.from_table(events, F.col("user_id"), F.get_json_object("props", "$.k").cast("long") % 16, F.lit(1), MatrixMeta(workloads.KEYS, 16), "count").df


def _weights(spark: SparkSession) -> MatrixFrame:
    return tables.synthetic(spark, 6, 6, (F.col("row") * 3 + F.col("col")) % 5)


_DAY_SQL = f"""WITH w AS (SELECT i.range AS r, j.range AS c, CAST((i.range * 3 + j.range) % 5 AS BIGINT) AS v FROM range(6) i CROSS JOIN range(6) j WHERE (i.range * 3 + j.range) % 5 <> 0)
    SELECT CAST(date_diff('day', DATE '1970-01-01', CAST(ts AS DATE)) AS BIGINT) AS day, user_id AS "row", w.c AS "col", CAST(sum(w.v) AS BIGINT) AS "value" FROM events JOIN w ON w.r = {_CODE} GROUP BY 1, 2, 3"""


def _by_day(df: DataFrame) -> DataFrame:
    return df.select(F.unix_date(F.col("start").cast("date")).cast("long").alias("day"), "row", "col", "value")


@query(_DAY_SQL)
def windowed_event_product(spark, d):
    return _by_day(products.stream_product(products.event_entries(tables.load(spark, d, "events")), _weights(spark)))


@query(_DAY_SQL)
def stream_product(spark, d):
    """The same product from a stream of the events, run until its input ends."""
    batch = tables.load(spark, d, "events")
    stream = spark.readStream.schema(batch.schema).parquet(f"{d}/events.parque[t]")  # as a pattern it may be one file
    folder = f"{shared_folder(spark)}/tables/stream-{uuid.uuid4().hex}"
    products.accumulate_windows(products.event_entries(stream), _weights(spark), f"{folder}/parts", f"{folder}/checkpoint")
    return _by_day(products.window_product_of(spark, f"{folder}/parts"))


# ---------------------------------------------------------------- checks and probes

@query(_square_ctes() + 'SELECT CAST(k AS INT) AS round, (SELECT count(DISTINCT r) FROM a JOIN (SELECT DISTINCT r AS rr FROM b) ON c = rr) AS "rows", CAST(0 AS BIGINT) AS residual FROM (VALUES (0), (1)) AS t(k)')
def verify_product(spark, d):
    a, b = _pair(spark, d)
    return measure.verify_product(a, b, multiply.grouped_multiply(a, b, GRID, 8))


@query("SELECT 'grouped against flat' AS what, CAST(0 AS BIGINT) AS entries")
def compare_methods(spark, d):
    a, b = _pair(spark, d)
    return measure.compare(multiply.grouped_multiply(a, b, GRID, 8), multiply.flat_multiply(a, b, GRID, 8)).agg(F.lit("grouped against flat").alias("what"), F.count("*").alias("entries"))


_PROBED = ", ".join(f"({i}, {j})" for i, j in topology.valid_groupings(GRID.s, GRID.t))


@query(_square_ctes() + f"SELECT CAST(i AS INT) AS grp_rows, CAST(j AS INT) AS grp_cols, CAST(i * j AS BIGINT) AS groups, (SELECT count(*) FROM (SELECT DISTINCT a.r, b.c FROM a JOIN b ON a.c = b.r WHERE a.c < 16)) AS rows FROM (VALUES {_PROBED}) AS t(i, j)")
def probe_groups_run(spark, d):
    """Every valid grouping of the grid over the first two steps; the times that decide are left out here."""
    a, b = _pair(spark, d)
    _, runs = advisor.probe_groups(a, b, GRID, 8, steps=2)
    return advisor.runs_frame(spark, runs).select("grp_rows", "grp_cols", F.col("groups").cast("long").alias("groups"), "rows")


# ---------------------------------------------------------------- experiments: measured runs, and what they ship as exact counts

def _shipped_sql(cases: list[tuple[str, int, int, int, int]]) -> str:
    rows = ", ".join(f"('{m}', {s}, {t}, {i}, {j})" for m, s, t, i, j in cases)
    sent = "CASE method WHEN 'flat' THEN t ELSE j END * (SELECT count(*) FROM a) + CASE method WHEN 'flat' THEN s ELSE i END * (SELECT count(*) FROM b)"
    return f"SELECT method, CAST(s AS INT) AS s, CAST(t AS INT) AS t, CAST(i AS INT) AS i, CAST(j AS INT) AS j, CAST({sent} AS BIGINT) AS shipped FROM (VALUES {rows}) AS c(method, s, t, i, j)"


_SWEEP = [("flat", 4, 8, 1, 1), *[("grouped", 4, 8, i, j) for i, j in topology.valid_groupings(4, 8)]]
_SCALE = [(m, s, t, i, j) for s, t, i, j in ((1, 1, 1, 1), (1, 2, 1, 1), (2, 2, 2, 1), (2, 4, 2, 2), (4, 4, 2, 2), (4, 8, 2, 4), (8, 8, 4, 4)) for m in ("flat", "grouped")]


def _shipped(spark: SparkSession, d: str, cases: list[tuple[str, int, int, int, int]]) -> DataFrame:
    """Rows that a product's exchanges carry, counted on the routed operands of every case."""
    a, b = (_stored(m) for m in _pair(spark, d))
    out = None
    for method, s, t, i, j in cases:
        grid = GridSpec(s, t, i, j)
        if method == "flat":
            sent = [routing.fan_out(m.df, "other", n) for m, n in ((a, t), (b, s))]
        else:
            sent = [routing.route_between(routing.operand(m.df, side, m.meta, grid, 8, 8), side, grid) for m, side in ((a, "a"), (b, "b"))]
        one = sent[0].select("value").unionByName(sent[1].select("value")).agg(F.count("*").alias("shipped"))
        one = one.select(F.lit(method).alias("method"), *[F.lit(x).alias(n) for n, x in zip("stij", (s, t, i, j))], "shipped")
        out = one if out is None else out.unionByName(one)
    return out


@query(_square_ctes() + _shipped_sql(_SWEEP))
def shipped_by_groups(spark, d):
    """What each number of groups ships: as much as flat at one group a cell; fewer groups ship less, and are fewer tasks."""
    return _shipped(spark, d, _SWEEP)


@query(_square_ctes() + _shipped_sql(_SCALE))
def shipped_by_cells(spark, d):
    """Flat and grouped as the grid grows."""
    return _shipped(spark, d, _SCALE)


def _experiment_sql(n: int, cases: list[tuple]) -> str:
    """cases: (method, s, t, i, j, groups, b, outer). A flat product ships t copies of A and s of B, a grouped one j and i."""
    rows = ", ".join(f"('{m}', {s}, {t}, {i}, {j}, {g}, {b}, {o})" for m, s, t, i, j, g, b, o in cases)
    sent = "CASE method WHEN 'flat' THEN t ELSE j END * (SELECT count(*) FROM a) + CASE method WHEN 'flat' THEN s ELSE i END * (SELECT count(*) FROM b)"
    return _square_ctes(n) + f"""SELECT method, s || 'x' || t AS grid, CAST(g AS BIGINT) AS groups, CAST({n} AS BIGINT) AS n, CAST(b AS BIGINT) AS b, CAST(o AS BIGINT) AS outer_b, CAST({experiments.REPEATS} * count(*) AS BIGINT) AS runs, CAST({sent} AS BIGINT) AS shuffle_rows FROM (VALUES {rows}) AS c(method, s, t, i, j, g, b, o) GROUP BY ALL"""


def _group_cases(s: int, t: int, block: int, options: list[tuple[int, int]]) -> list[tuple]:
    return [("flat", s, t, 1, 1, 1, block, block)] + [("grouped", s, t, i, j, i * j, block, block) for i, j in options]


_ALL_48, _SOME_48 = [(1, 1), (1, 2), (2, 2), (2, 4), (4, 4), (4, 8)], [(1, 1), (2, 2), (2, 4), (4, 4), (4, 8)]  # one for each number of groups
_SQUARES = [(1, 1), (2, 2), (4, 4), (8, 8)]
_SCALED = [(1, 1, 1, 1), (2, 2, 2, 1), (4, 4, 2, 2), (4, 8, 2, 4), (8, 8, 4, 4)]


@query(_experiment_sql(N, _group_cases(4, 8, 4, _ALL_48)))
def experiment_groups_small_block(spark, d):
    return experiments.measured(experiments.sweep_of_groups, spark, _pair(spark, d), GridSpec(4, 8), 4, _ALL_48)


@query(_experiment_sql(N, _group_cases(4, 8, 8, _SOME_48)))
def experiment_groups_largest_block(spark, d):
    return experiments.measured(experiments.sweep_of_groups, spark, _pair(spark, d), GridSpec(4, 8), 8, _SOME_48)


@query(_experiment_sql(256, _group_cases(8, 8, 16, _SQUARES)))
def experiment_groups_many_cells(spark, d):
    return experiments.measured(experiments.sweep_of_groups, spark, _pair(spark, d, 256), GridSpec(8, 8), 16, _SQUARES)


@query(_experiment_sql(256, _group_cases(4, 4, 16, _SQUARES[:3])))
def experiment_groups_fewer_cells(spark, d):
    """The same matrices and block on a quarter of the cells: the saving shrinks."""
    return experiments.measured(experiments.sweep_of_groups, spark, _pair(spark, d, 256), GridSpec(4, 4), 16, _SQUARES[:3])


@query(_experiment_sql(256, _group_cases(2, 2, 16, _SQUARES[:2])))
def experiment_groups_few_cells(spark, d):
    """On four cells no grouping ships less than flat by more than the one-group form."""
    return experiments.measured(experiments.sweep_of_groups, spark, _pair(spark, d, 256), GridSpec(2, 2), 16, _SQUARES[:2])


@query(_experiment_sql(N, [(m, s, t, i, j, 1 if m == "flat" else i * j, 8, 8) for m, s, t, i, j in _SCALE]))
def experiment_cells(spark, d):
    grids = [GridSpec(s, t, i, j) for m, s, t, i, j in _SCALE if m == "grouped"]
    return experiments.measured(experiments.sweep_of_cells, spark, _pair(spark, d), grids, 8)


@query(_experiment_sql(256, [(m, s, t, i, j, 1 if m == "flat" else i * j, 16, 16) for s, t, i, j in _SCALED for m in ("flat", "grouped")]))
def experiment_cells_scaling(spark, d):
    """More cells for the larger matrices."""
    return experiments.measured(experiments.sweep_of_cells, spark, _pair(spark, d, 256), [GridSpec(*x) for x in _SCALED], 16)


@query(_experiment_sql(N, [("grouped_panel", 4, 4, 2, 2, 4, b, b) for b in (1, 2, 4, 8, 16)]))
def experiment_blocks(spark, d):
    return experiments.measured(experiments.sweep_of_blocks, spark, _pair(spark, d), GRID, (1, 2, 4, 8, 16))


@query(_experiment_sql(N, [("grouped_panel", 4, 4, 2, 2, 4, 4, 4 * f) for f in (1, 2, 4)]))
def experiment_outer_blocks(spark, d):
    return experiments.measured(experiments.sweep_of_outer_blocks, spark, _pair(spark, d), GRID, 4)


# ---------------------------------------------------------------- schedules and costs of the classic baselines

def _cells_sql(p: int, q: int) -> str:
    return f"(SELECT range // {q} AS i, range % {q} AS j FROM range({p * q}))"


def _message_sql(step: str, phase: str, operand: str, source: tuple[str, str], to: tuple[str, str] | None, receivers: int, elements: int, rows: str) -> str:
    row, col = to or ("NULL", "NULL")
    return f"SELECT CAST({step} AS BIGINT) AS step, '{phase}' AS phase, '{operand}' AS operand, CAST({source[0]} AS INT) AS from_row, CAST({source[1]} AS INT) AS from_col, CAST({row} AS INT) AS to_row, CAST({col} AS INT) AS to_col, CAST({receivers} AS BIGINT) AS receivers, CAST({elements} AS BIGINT) AS elements FROM {rows}"


_HERE, _Q4, _Q46 = ("i", "j"), _cells_sql(4, 4), _cells_sql(4, 6)
_TURNS = f"{_Q4} CROSS JOIN (SELECT range AS step FROM range(1, 4))"


@query(" UNION ALL ".join([
    _message_sql("0", "align", "A", _HERE, ("i", "(j - i + 4) % 4"), 1, 256, f"{_Q4} WHERE i > 0"),
    _message_sql("0", "align", "B", _HERE, ("(i - j + 4) % 4", "j"), 1, 256, f"{_Q4} WHERE j > 0"),
    _message_sql("step", "rotate", "A", _HERE, ("i", "(j + 3) % 4"), 1, 256, _TURNS),
    _message_sql("step", "rotate", "B", _HERE, ("(i + 3) % 4", "j"), 1, 256, _TURNS),
]))
def schedule_rotations(spark, d):
    return baseline_schedules.rotations(spark, N, 4)


@query(" UNION ALL ".join([
    _message_sql("step", "broadcast", "A", ("i", "(i + step) % 4"), None, 3, 256, "(SELECT range AS i FROM range(4)) CROSS JOIN (SELECT range AS step FROM range(4))"),
    _message_sql("step", "roll", "B", _HERE, ("(i + 3) % 4", "j"), 1, 256, _TURNS),
]))
def schedule_broadcast_roll(spark, d):
    return baseline_schedules.broadcast_roll(spark, N, 4)


@query(" UNION ALL ".join([
    _message_sql("step", "shift", "A", _HERE, ("i", "(j + 5) % 6"), 1, 96 * 96 // 24, f"{_Q46} CROSS JOIN (SELECT range AS step FROM range(1, 6))"),
    _message_sql("step", "broadcast", "B", ("step % 4", "j"), None, 3, 96 * 96 // 72, "(SELECT range AS j FROM range(6)) CROSS JOIN (SELECT range AS step FROM range(12))"),
]))
def schedule_lcm(spark, d):
    """4 x 6 cells: 5 shifts of A, 12 broadcasts of B in every column."""
    return baseline_schedules.lcm_shifts(spark, 96, 4, 6)


@query(f"SELECT month, method, phase, operand, CAST(messages AS BIGINT) AS messages, CAST(deliveries * pow(ceil(lines / {N}), 2) AS BIGINT) AS deliveries FROM {_MONTHS} CROSS JOIN (VALUES "
       "('rotations', 'align', 'A', 12, 12 * 256), ('rotations', 'align', 'B', 12, 12 * 256), ('rotations', 'rotate', 'A', 48, 48 * 256), ('rotations', 'rotate', 'B', 48, 48 * 256), "
       "('broadcast_roll', 'broadcast', 'A', 16, 48 * 256), ('broadcast_roll', 'roll', 'B', 48, 48 * 256), "
       "('lcm_shifts', 'shift', 'A', 7 * 32, 7 * 64 * 64), ('lcm_shifts', 'broadcast', 'B', 8 * 8, 3 * 64 * 64), "
       "('3d', 'replicate', 'A', 16, 3 * 64 * 64), ('3d', 'replicate', 'B', 16, 3 * 64 * 64), ('3d', 'multiply', 'A', 16, 3 * 64 * 64), ('3d', 'multiply', 'B', 16, 3 * 64 * 64), ('3d', 'reduce', 'C', 16, 3 * 64 * 64), "
       "('25d', 'replicate', 'A', 64, 64 * 64), ('25d', 'replicate', 'B', 64, 64 * 64), ('25d', 'multiply', 'A', 64, 7 * 64 * 64), ('25d', 'multiply', 'B', 64, 7 * 64 * 64), ('25d', 'reduce', 'C', 64, 64 * 64)) AS t(method, phase, operand, messages, deliveries)")  # fmt: skip
def baseline_deliveries(spark, d):
    """What each baseline sends for a month's matrices, as long and as wide as the month has order lines (up to a multiple of 64): 4 x 4
    cells, 4 x 8, four layers of 4 x 4, two layers of 8 x 8."""
    plans = {"rotations": baseline_schedules.rotations(spark, N, 4), "broadcast_roll": baseline_schedules.broadcast_roll(spark, N, 4), "lcm_shifts": baseline_schedules.lcm_shifts(spark, N, 4, 8), "3d": baseline_schedules.layers(spark, N, 4, 4, 16), "25d": baseline_schedules.layers(spark, N, 8, 2, 8)}
    out = None
    for method, plan in plans.items():
        one = plan.withColumn("method", F.lit(method))
        out = one if out is None else out.unionByName(one)
    whole = baseline_schedules.sized(out, workloads.months(spark, d), F.ceil(F.col("lines") / N))
    return baseline_schedules.totals(whole, ("month", "method")).select("month", "method", "phase", "operand", "messages", F.col("deliveries").cast("long").alias("deliveries"))


def _cast_sql(m: str, q: str) -> str:
    latency, bandwidth = (x.format(q=q) for x in _SQL_FACTORS["binomial"])
    return f"({latency} * alpha + ({m}) * {bandwidth} * beta)"


_BLOCK = "n * n / p"
_BASELINE_COSTS = {
    "flat": _comm_sql("binomial", "sqrt(p)"),
    "rotations": f"2 * sqrt(p) * (alpha + {_BLOCK} * beta)",
    "broadcast_roll": f"sqrt(p) * {_cast_sql(_BLOCK, 'sqrt(p)')} + (sqrt(p) - 1) * (alpha + {_BLOCK} * beta)",
    "lcm_shifts": f"(sqrt(p) - 1) * (alpha + {_BLOCK} * beta) + sqrt(p) * {_cast_sql(_BLOCK, 'sqrt(p)')}",
    "25d": f"3 * {_cast_sql('n * n / (p / 4)', '4.0')} + 2 * n / b / 4 * {_cast_sql('n * b / sqrt(p / 4)', 'sqrt(p / 4)')}",
    "3d": f"3 * {_cast_sql('n * n / pow(p, 2.0 / 3)', 'pow(p, 1.0 / 3)')} + 2 * n / b / pow(p, 1.0 / 3) * {_cast_sql('n * b / pow(p, 1.0 / 3)', 'pow(p, 1.0 / 3)')}",
}


@query(" UNION ALL ".join(f"SELECT month, platform, '{m}' AS method, {_exact_us_sql(x)} AS cost_us FROM {_PM}" for m, x in _BASELINE_COSTS.items()))
def cost_baselines(spark, d):
    """Communication of the baselines beside the flat method's, for each month's product, with binomial broadcasts; the 2.5-D product
    has four layers."""
    f, p = cost.family("binomial"), workloads.month_products(spark, d)
    side, cube = F.sqrt(F.col("p").cast("double")), F.pow(F.col("p").cast("double"), F.lit(1.0 / 3))
    found = {"flat": cost.flat_comm(f), "rotations": cost.rotation_comm(), "broadcast_roll": cost.broadcast_roll_comm(f), "lcm_shifts": cost.lcm_shift_comm(f, side, side, side), "25d": cost.layered_comm(f, c=F.lit(4.0)), "3d": cost.layered_comm(f, b="b", c=cube)}
    return p.select("month", "platform", F.inline(F.array(*[F.struct(F.lit(m).alias("method"), _exact_us(x).alias("cost_us")) for m, x in found.items()])))


@query(_square_ctes() + 'SELECT CAST(block_row AS INT) AS block_row, CAST(block_col AS INT) AS block_col, CAST(spot AS INT) AS spot, CAST(sum(v) AS BIGINT) AS "value" FROM (SELECT r // 16 AS block_row, c // 16 AS block_col, (r % 16) * 16 + c % 16 AS spot, v FROM (SELECT * FROM a UNION ALL SELECT * FROM b)) GROUP BY 1, 2, 3')
def block_sums(spark, d):
    """Element-wise sums of blocks that meet: how layers are reduced when they are kept as blocks."""
    a, b = _pair(spark, d)
    both = a.to_blocks(16).unionByName(b.to_blocks(16))
    return blocks.sum_blocks(both, ["block_row", "block_col"]).select("block_row", "block_col", F.posexplode("data").alias("spot", "x")).where("x <> 0").select("block_row", "block_col", "spot", F.col("x").cast("long").alias("value"))


def queries() -> dict[str, Query]:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)
