"""The local update c += a b in three physical forms that give the same result."""

from __future__ import annotations

import tempfile
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Integers up to here are exact in a double, so integer panels within it can use the floating-point product.
EXACT = 1 << 53
#: Entries of C, and numbers of the panels, that a task holds at once where it works in stripes.
STRIPE_ENTRIES = 1 << 23
#: Rows of C that a task gives at a time.
BATCH = 65536
#: Distinct numbers of 8 bytes that fit the dictionary of a Parquet column (1 MB); with more, each number is written out.
DICTIONARY = 1 << 17


def relational(a: DataFrame, b: DataFrame, keys: list[str], hashed: bool = False) -> DataFrame:
    """Join on the keys and k, sum the products by the keys, row and col; reuses the partitioning of the inputs.

    hashed: b is sure to fit a hash table in each task; else it is sorted, and can spill."""
    left = a.select(*keys, "k", F.col("own").alias("row"), F.col("value").alias("va"))
    right = b.select(*keys, "k", F.col("own").alias("col"), F.col("value").alias("vb"))
    return left.join(right.hint("shuffle_hash") if hashed else right, [*keys, "k"]).groupBy(*keys, "row", "col").agg(F.sum(F.col("va") * F.col("vb")).alias("value"))


def dot(x: Column, y: Column) -> Column:
    """Sum of products of two arrays, in the JVM."""
    return F.aggregate(F.zip_with(x, y, lambda p, q: p * q), F.lit(0).cast("long"), lambda acc, v: acc + v.cast("long"))


def hof(a: DataFrame, b: DataFrame, keys: list[str], width: int) -> DataFrame:
    """Rows of A and columns of B as dense arrays of one inner step, multiplied by higher-order functions.

    keys must hold inner_step; the arrays have the width of a step."""

    def arrays(df: DataFrame, name: str) -> DataFrame:
        per = df.groupBy(*keys, "own").agg(F.map_from_entries(F.collect_list(F.struct((F.col("k") % width).cast("int"), "value"))).alias("m"))
        return per.select(*keys, F.col("own").alias(name), F.transform(F.sequence(F.lit(0), F.lit(width - 1)), lambda i: F.coalesce(F.try_element_at(F.col("m"), i), F.lit(0))).alias(f"v_{name}"))

    joined = arrays(a, "row").join(arrays(b, "col"), keys)
    out = [k for k in keys if k != "inner_step"]
    return joined.select(*out, "row", "col", dot(F.col("v_row"), F.col("v_col")).alias("value")).groupBy(*out, "row", "col").agg(F.sum("value").alias("value"))


def block_kernel(a: DataFrame, b: DataFrame, dtype: str = "long") -> DataFrame:
    """(block_row, block_col, n_rows, n_cols, data): the product of two block frames whose blocks meet on k, by cogrouped Arrow tables.

    One task call holds the blocks of one slice of k and gives one row for each pair of them; sums of blocks follow (sum_blocks)."""
    kind = np.int64 if dtype == "long" else np.float64
    element = pa.int64() if dtype == "long" else pa.float64()
    schema = pa.schema([("block_row", pa.int32()), ("block_col", pa.int32()), ("n_rows", pa.int32()), ("n_cols", pa.int32()), ("data", pa.list_(element))])

    def matrices(table: pa.Table, at: str) -> list[tuple[int, np.ndarray]]:
        return [(r[at], np.array(r["data"], kind).reshape(r["n_rows"], r["n_cols"])) for r in table.to_pylist()]

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        rows = [(i, j, multiply_panels(x, y)) for i, x in matrices(left, "block_row") for j, y in matrices(right, "block_col")]
        columns = list(zip(*((i, j, *z.shape, z.ravel().tolist()) for i, j, z in rows))) or [[]] * 5
        return pa.table([pa.array(list(c), f.type) for c, f in zip(columns, schema)], schema=schema)

    ddl = f"block_row int, block_col int, n_rows int, n_cols int, data array<{'long' if dtype == 'long' else 'double'}>"
    return a.groupBy(F.col("block_col").alias("slice")).cogroup(b.groupBy(F.col("block_row").alias("slice"))).applyInArrow(run, ddl)


def multiply_panels(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """x y; integer panels through the floating-point product where that is exact."""
    if x.dtype == np.int64 and x.size and y.size:
        bound = float(np.abs(x).max()) * float(np.abs(y).max()) * x.shape[1]
        if bound < EXACT:
            return (x.astype(np.float64) @ y.astype(np.float64)).astype(np.int64)
    return x @ y


class PanelStore:
    """A group's pairs of panels, step by step, in a file of the task's own, so that a tile of C can be made a stripe at a time.

    Both are dense: (rows + cols) x k numbers in all, however large the tile is."""

    def __init__(self, rows: int, cols: int, width: int, kind: type) -> None:
        self.rows, self.cols, self.width, self.kind, self.steps, self.file = rows, cols, width, np.dtype(kind), 0, tempfile.TemporaryFile()

    def clear(self) -> None:
        self.steps = 0

    def add(self, a: np.ndarray, b: np.ndarray) -> None:
        self.file.seek(self.steps * self.width * (self.rows + self.cols) * self.kind.itemsize)
        self.file.write(a.data)
        self.file.write(b.data)
        self.steps += 1

    def _read(self, step: int, at: int, rows: int, cols: int) -> np.ndarray:
        self.file.seek((step * self.width * (self.rows + self.cols) + at) * self.kind.itemsize)
        return np.frombuffer(self.file.read(rows * cols * self.kind.itemsize), self.kind).reshape(rows, cols)

    def stripes(self, entries: int) -> Iterator[tuple[int, np.ndarray]]:
        """(first row, rows of C) of at most so many entries, or of one row; steps that fit as many again are multiplied at once."""
        height = max(1, min(self.rows, entries // self.cols))
        some = max(1, entries // (self.width * (height + self.cols)))
        for lo in range(0, self.rows, height):
            c, high = None, min(height, self.rows - lo)
            for first in range(0, self.steps, some):
                steps = range(first, min(first + some, self.steps))
                a = np.hstack([self._read(x, lo * self.width, high, self.width) for x in steps])
                if a.any():
                    part = multiply_panels(a, np.vstack([self._read(x, self.rows * self.width, self.width, self.cols) for x in steps]))
                    c = part if c is None else c + part
            if c is not None:
                yield lo, c


def in_file_order(tile: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(places in the flattened tile, values) of all entries but zeros, in parts: by value or by place, whichever files hold in fewer bytes.

    By place, a value is written out where there are too many for a dictionary. By value, a run of equal ones is written once and
    each place is a few bits, which pays where values occur four times on average."""
    flat = tile.ravel()
    places = np.flatnonzero(flat)
    if not len(places):
        return
    v, bits = flat[places], max(1, flat.size - 1).bit_length()
    low = int(v.min()) if v.dtype == np.int64 else 0
    if packed := v.dtype == np.int64 and int(v.max()) - low < 1 << (62 - bits):  # a value and its place in one number sort faster than an index
        v -= low
        v <<= bits
        v |= places
        v.sort()
        distinct = 1 + np.count_nonzero((v[1:] ^ v[:-1]) >> bits)
    else:
        order = np.argsort(v, kind="stable")
        v = v[order]
        distinct = 1 + np.count_nonzero(v[1:] != v[:-1])
    by_value = distinct > DICTIONARY and 4 * distinct <= len(places)
    for at in range(0, len(places), BATCH):
        some = slice(at, at + BATCH)
        if by_value and packed:
            yield v[some] & ((1 << bits) - 1), (v[some] >> bits) + low
        else:
            p = places[order[some]] if by_value else places[some]
            yield p, flat[p]


def panel(tagged: DataFrame, tile_rows: int, tile_cols: int, width: int, dtype: str = "long", tile_entries: int | None = None) -> DataFrame:
    """(grp_id, lr, lc, value): each task streams its group's steps in order, holding one panel of A, one of B and the tile of C.

    tagged: (grp_id, inner_step, op, local, k, value), dealt by group; op 0 is A, 1 is B. A tile of more than tile_entries is worked
    on in stripes of rows: the panels go to a file of the task and are read again for each stripe, so nothing is shipped twice. Within
    a stripe, rows come in the order of `in_file_order`."""
    kind = np.int64 if dtype == "long" else np.float64
    arrow = pa.schema([("grp_id", pa.int32()), ("lr", pa.int32()), ("lc", pa.int32()), ("value", pa.int64() if dtype == "long" else pa.float64())])
    striped = tile_entries is not None and tile_rows * tile_cols > tile_entries
    stripe = min(tile_entries, STRIPE_ENTRIES) if striped else 0

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        state: dict = {"group": None, "step": None}
        store = PanelStore(tile_rows, tile_cols, width, kind) if striped else None

        def clear() -> None:
            state["a"], state["b"], state["used"] = np.zeros((tile_rows, width), kind), np.zeros((width, tile_cols), kind), [False, False]

        def fold() -> None:
            if state["step"] is not None and all(state["used"]):
                if store:
                    store.add(state["a"], state["b"])
                else:
                    state["c"] += multiply_panels(state["a"], state["b"])
            clear()

        def emit() -> Iterator[pa.RecordBatch]:
            if state["group"] is None:
                return
            fold()
            high = max(1, STRIPE_ENTRIES // tile_cols)
            for top, tile in store.stripes(stripe) if store else ((lo, state["c"][lo : lo + high]) for lo in range(0, tile_rows, high)):
                for places, values in in_file_order(tile):
                    i, j = (x.astype(np.int32) for x in np.divmod(places, tile_cols))
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(i), state["group"], np.int32)), pa.array(i + np.int32(top)), pa.array(j), pa.array(values)], schema=arrow)

        for batch in batches:
            g, step, op, local, k, v = (col.to_numpy(zero_copy_only=False) for col in batch.columns)
            cut = np.flatnonzero((g[1:] != g[:-1]) | (step[1:] != step[:-1]) | (op[1:] != op[:-1])) + 1
            for lo, hi in zip([0, *cut.tolist()], [*cut.tolist(), len(g)]):
                if lo == hi:
                    continue
                if g[lo] != state["group"]:
                    yield from emit()
                    state.update(group=int(g[lo]), step=None)
                    if store:
                        store.clear()
                    else:
                        state["c"] = np.zeros((tile_rows, tile_cols), kind)
                    clear()
                if step[lo] != state["step"]:  # a step may span batches, so its value decides
                    fold()
                    state["step"] = step[lo]
                state["used"][op[lo]] = True
                if op[lo] == 0:
                    np.add.at(state["a"], (local[lo:hi], k[lo:hi] % width), v[lo:hi])
                else:
                    np.add.at(state["b"], (k[lo:hi] % width, local[lo:hi]), v[lo:hi])
        yield from emit()

    ordered = tagged.sortWithinPartitions("grp_id", "inner_step", "op").select("grp_id", "inner_step", "op", "local", "k", "value")
    return ordered.mapInArrow(run, f"grp_id int, lr int, lc int, value {'long' if dtype == 'long' else 'double'}")
