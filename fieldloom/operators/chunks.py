"""Chunk rows: assembly from points, messages between chunks, and carry scans.

A chunk is one row; a kernel sees its columns as arrays.  What chunks tell each other (faces, and sums
that prefix sums carry on) moves as messages, one row of an array each.  Messages are grouped by chunk
and joined to the rows that they are for, and those stay as they are stored: a chunk is decoded after
the join, and its points are never shuffled.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType

from fieldloom.model import Layout

CELLS = ["ci", "cj", "ck"]
KEY = ["field", *CELLS]
GRID = ["eps", "d0", "d1", "d2"]
HEAD = "field string, ci int, cj int, ck int, eps double, d0 bigint, d1 bigint, d2 bigint"
MESSAGE = f"{HEAD}, code int, v array<bigint>"
BATCH = 16  # chunk rows that a kernel turns into one Arrow batch
POINTS = 100_000  # points of an Arrow batch
FACE, GHOST = 64, 128  # codes: FACE + side is a neighbour's layer, GHOST * (1 + axis) + set a carry for it
LINE = 4096  # chunks of a one-dimensional field whose carries are summed in one piece


def reader(column: pa.Array) -> Callable[[int], object]:
    """A function from a row number to its value: arrays as numpy views, lists of messages as pairs, structs as dicts."""
    kind = column.type
    if pa.types.is_list(kind):
        ends = np.asarray(column.offsets)
        if pa.types.is_struct(kind.value_type):
            names = [f.name for f in kind.value_type]
            plain = all(pa.types.is_primitive(f.type) for f in kind.value_type)
            if plain:
                parts = [np.asarray(c) for c in column.values.flatten()]
                return lambda i: tuple(p[ends[i] : ends[i + 1]] for p in parts)
            parts = [reader(c) for c in column.values.flatten()]
            return lambda i: [tuple(p(k) for p in parts) for k in range(ends[i], ends[i + 1])] if names else []
        values = np.asarray(column.values)
        return lambda i: values[ends[i] : ends[i + 1]]
    if pa.types.is_struct(kind):
        parts = {f.name: reader(c) for f, c in zip(kind, column.flatten())}
        return lambda i: {n: p(i) for n, p in parts.items()}
    return lambda i: column[i].as_py()


def rows_of(batches) -> Iterator[dict]:
    for b in batches:
        read = {n: reader(b.column(n)) for n in b.schema.names}
        for i in range(b.num_rows):
            yield {n: f(i) for n, f in read.items()}


def kernel(df: DataFrame, run: Callable[[dict], Iterator[dict]], schema: str) -> DataFrame:
    """Map each row (a dict) to rows of ``schema``."""
    arrow = to_arrow_schema(StructType.fromDDL(schema))

    def batches(it):
        held = []
        for row in rows_of(it):
            for out in run(row):
                held.append(out)
                if len(held) >= BATCH:
                    yield pa.RecordBatch.from_pylist(held, schema=arrow)
                    held = []
        if held:
            yield pa.RecordBatch.from_pylist(held, schema=arrow)

    return df.mapInArrow(batches, schema)


def flat_kernel(df: DataFrame, run: Callable[[dict], dict], schema: str) -> DataFrame:
    """Map each row to many: ``run`` gives equally long columns, or masked arrays where there are nulls."""
    arrow = to_arrow_schema(StructType.fromDDL(schema))

    def column(values, s: int, e: int, kind) -> pa.Array:
        if not isinstance(values, np.ndarray):
            return pa.array([values] * (e - s), kind)
        part = values[s:e]
        return pa.array(part.data, kind, mask=np.ma.getmaskarray(part)) if isinstance(part, np.ma.MaskedArray) else pa.array(part, kind)

    def batches(it):
        for row in rows_of(it):
            out = run(row)
            n = max((len(v) for v in out.values() if isinstance(v, np.ndarray)), default=0)
            for s in range(0, n, POINTS):
                e = min(n, s + POINTS)
                yield pa.RecordBatch.from_arrays([column(out[f.name], s, e, f.type) for f in arrow], schema=arrow)

    return df.mapInArrow(batches, schema)


def place(row: dict, layout: Layout) -> tuple[tuple[int, ...], tuple[int, ...], tuple[int, ...]]:
    """(origin, shape, grid extents) of a chunk."""
    dims = tuple(int(row[f"d{a}"]) for a in range(layout.ndim))
    lo = tuple(int(row[CELLS[a]]) * c for a, c in enumerate(layout.chunk))
    return lo, tuple(min(c, d - x) for c, d, x in zip(layout.chunk, dims, lo)), dims


def flatten_grid(points: DataFrame) -> DataFrame:
    """Quantised points as a one-dimensional field in row-major order."""
    g = (F.col("i") * F.col("d1") + F.col("j")) * F.col("d2") + F.col("k")
    zero, one = F.lit(0).cast("bigint"), F.lit(1).cast("bigint")
    return points.select("field", g.cast("bigint").alias("i"), zero.alias("j"), zero.alias("k"), "value", "eps", (F.col("d0") * F.col("d1") * F.col("d2")).alias("d0"), one.alias("d1"), one.alias("d2"), "q")


def to_chunks(points: DataFrame, layout: Layout) -> DataFrame:
    """Chunk rows of quantised points, with ``cells`` of (place in the chunk, integer): the one full shuffle of compression."""
    size = [*layout.chunk, 1, 1][:3]
    at = {c: F.col(c).cast("bigint") for c in "ijk"}
    p = points.withColumns({f"c{c}": F.floor(at[c] / s).cast("int") for c, s in zip("ijk", size)})
    extent = [F.least(F.lit(s).cast("bigint"), F.col(f"d{a}") - F.col(f"c{c}") * s) for a, (c, s) in enumerate(zip("ijk", size))]
    inner = [at[c] - F.col(f"c{c}") * s for c, s in zip("ijk", size)]
    pos = (inner[0] * extent[1] + inner[1]) * extent[2] + inner[2]
    return p.withColumn("pos", pos.cast("int")).groupBy(*KEY).agg(*[F.first(g).alias(g) for g in GRID], F.collect_list(F.struct("pos", "q")).alias("cells"))


def dense(row: dict, layout: Layout) -> np.ndarray:
    """The numbers of a chunk row as an array; a grid with a missing or repeated point is an error."""
    lo, shape, _ = place(row, layout)
    if "data" in row:  # made as a whole
        return row["data"].reshape(shape)
    pos, q = row["cells"]
    n = int(np.prod(shape))
    seen = np.bincount(pos, minlength=n)
    if len(pos) != n or (seen != 1).any():
        raise ValueError(f"field {row['field']}: the chunk at {lo} has {int((seen == 0).sum())} points missing and {int((seen > 1).sum())} repeated")
    out = np.empty(n, q.dtype)
    out[pos] = q
    return out.reshape(shape)


def head(row: dict, cell: list[int] | None = None) -> dict:
    out = {k: row[k] for k in (*KEY, *GRID)}
    return out if cell is None else out | dict(zip(CELLS, cell))


def with_messages(rows: DataFrame, messages: DataFrame) -> DataFrame:
    """``rows`` with ``got``: the (code, array) pairs that were sent to each chunk."""
    return rows.join(messages.groupBy(*KEY).agg(F.collect_list(F.struct("code", "v")).alias("got")), KEY, "left")


def sides(ndim: int) -> list[tuple[int, int, int]]:
    """(code, axis, step) of the 2 * ndim neighbours: the layer that comes from there lies at that end."""
    return [(FACE + 2 * a + (s > 0), a, s) for a in range(ndim) for s in (-1, 1)]


def layer(a: np.ndarray, axis: int, last: bool) -> np.ndarray:
    return a[tuple((slice(-1, None) if last else slice(0, 1)) if b == axis else slice(None) for b in range(a.ndim))]


def faces(rows: DataFrame, layout: Layout, arrays: Callable[[dict], list[np.ndarray]], periodic: bool = False, kind: str = "bigint") -> DataFrame:
    """Messages of each chunk's outer layers, of all ``arrays`` one after another, to its neighbours."""

    def run(row):
        lo, shape, dims = place(row, layout)
        many = [-(-d // c) for d, c in zip(dims, layout.chunk)]
        own = arrays(row)
        for code, a, step in sides(layout.ndim):
            cell = [row[c] for c in CELLS]
            cell[a] -= step
            if periodic:
                cell[a] %= many[a]
            if 0 <= cell[a] < many[a]:
                yield head(row, cell) | {"code": code, "v": np.concatenate([layer(x, a, step < 0).ravel() for x in own])}

    return kernel(rows, run, f"{HEAD}, code int, v array<{kind}>")


def masks(ndim: int, full: bool) -> list[int]:
    """Sets of axes as bits; without ``full`` all but that of all axes."""
    return list(range(1, (1 << ndim) - (0 if full else 1)))


def kept(shape: tuple[int, ...], mask: int) -> tuple[int, ...]:
    return tuple(1 if mask >> a & 1 else s for a, s in enumerate(shape))


def summed(p: np.ndarray, mask: int) -> np.ndarray:
    """``p`` summed over the axes of ``mask`` and prefix-summed over the others."""
    axes = [a for a in range(p.ndim) if mask >> a & 1]
    out = p.sum(axis=tuple(axes), keepdims=True)
    for a in range(p.ndim):
        if a not in axes:
            out = out.cumsum(axis=a)
    return out


def carries(rows: DataFrame, layout: Layout, residuals: Callable[[dict], np.ndarray], full: bool = True, ghosts: bool = False) -> DataFrame:
    """Messages of what earlier chunks add to a chunk's prefix sums, from one pass over ``rows`` for all axes.

    For each set of axes a chunk sums its residuals over the set and prefix-sums them over the rest;
    running sums over the chunks before it along each axis of the set follow.  ``full=False`` leaves out
    the set of all axes, which prefix sums over fewer axes do not need.  With ``ghosts`` a chunk also
    gets the next chunks' first layers and what is carried to them.
    """
    n = layout.ndim
    sets = masks(n, full)

    def run(row):
        _, shape, _ = place(row, layout)
        p = residuals(row)
        for mask in sets:
            yield head(row) | {"code": mask, "v": summed(p, mask).ravel()}
        for a in range(n) if ghosts else ():
            if row[CELLS[a]]:
                cell = [row[c] - (b == a) for b, c in enumerate(CELLS)]
                yield head(row, cell) | {"code": FACE + 2 * a + 1, "v": layer(p, a, False).ravel()}

    out = kernel(rows, run, MESSAGE)
    if not sets:
        return out
    for a in range(n):
        out = running(out, a, n)

    def copies(row):
        yield row
        if row["code"] < FACE:
            _, shape, _ = place(row, layout)
            v = row["v"].reshape(kept(shape, row["code"]))
            for a in range(n):
                if row[CELLS[a]] and not row["code"] >> a & 1:
                    cell = [row[c] - (b == a) for b, c in enumerate(CELLS)]
                    yield head(row, cell) | {"code": GHOST * (1 + a) + row["code"], "v": layer(v, a, False).ravel()}

    return kernel(out, copies, MESSAGE) if ghosts else out


def running(messages: DataFrame, axis: int, ndim: int) -> DataFrame:
    """Carry messages whose set has ``axis``, replaced by the sums of those before them along it; others pass.

    A task holds one array of a line of chunks at a time.  The chunks of a one-dimensional field are one
    line, so there pieces of it are summed first, and then the sums of the pieces.
    """
    at = CELLS[axis]
    line = ["field", "code", *(c for c in CELLS if c != at)]
    rows = messages
    if ndim == 1:
        line.append("piece")
        rows = messages.withColumn("piece", F.floor(F.col(at) / LINE).cast("int"))

    def run(row, state):
        if row["code"] >= FACE or not row["code"] >> axis & 1:
            return row["v"]
        key = [row[c] for c in line]
        if state.get("key") != key:
            state["key"], state["sum"] = key, np.zeros(len(row["v"]), np.int64)
        v = state["sum"]
        state["sum"] = v + row["v"]
        return v

    def scan(batches):
        state: dict = {}
        for b in batches:
            if b.num_rows:
                out = [run(row, state) for row in rows_of([b])]
                ends = np.concatenate([[0], np.cumsum([len(v) for v in out])]).astype(np.int32)
                v = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(out)))
                yield pa.RecordBatch.from_arrays([v if n == "v" else b.column(n) for n in b.schema.names], schema=b.schema)

    schema = StructType([f for f in rows.schema.fields])
    out = rows.repartition(*line).sortWithinPartitions(*line, at).mapInArrow(scan, schema)
    if ndim > 1:
        return out
    sums = rows.where(F.col("code") < FACE).groupBy("field", "code", "piece").agg(F.sum(F.element_at("v", 1)).alias("s"))
    w = Window.partitionBy("field", "code").orderBy("piece").rowsBetween(Window.unboundedPreceding, -1)
    before = sums.select("field", "code", "piece", F.coalesce(F.sum("s").over(w), F.lit(0)).cast("bigint").alias("s"))
    out = out.join(before, ["field", "code", "piece"], "left")
    return out.withColumn("v", F.when(F.col("code") < FACE, F.array(F.element_at("v", 1) + F.col("s"))).otherwise(F.col("v"))).drop("piece", "s")


def carried(row: dict, shape: tuple[int, ...]) -> list[tuple[int, np.ndarray]]:
    """(set, what it adds) of a chunk's carry messages."""
    return [(code, v.reshape(kept(shape, code))) for code, v in row["got"] if code < FACE]


def prefix_with_carry(p: np.ndarray, row: dict) -> np.ndarray:
    """Prefix sums of a chunk's residuals over all axes, from the start of the grid."""
    out = summed(p, 0)
    for _, v in carried(row, p.shape):
        out = out + v
    return out
