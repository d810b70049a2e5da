"""Generic operations on containers: stencils, linear combinations, block aggregates, regions, isosurfaces, halos.

All work on integers and scale once.  Mean codecs answer whole blocks from metadata; what needs
neighbours gets their layers, corners too, as messages.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fieldloom.model import CODECS, META, QUANT, Layout
from fieldloom.operators.chunks import CELLS, HEAD, KEY, flat_kernel, head, kernel, place, with_messages
from fieldloom.operators.codecs import block_order, decoded, integers, partial_decompress, with_carries
from fieldloom.operators.statistics import exact, mean_result, moments, sd_result, whole

POINT = "i bigint, j bigint, k bigint"


def readable(container: DataFrame, codec: str, layout: Layout, anchor: str = "grid") -> tuple[DataFrame, Callable[[dict], np.ndarray]]:
    """Rows that each give their integers on their own, and how."""
    if CODECS[codec].predictor != "difference" or anchor != "grid":
        return container, lambda row: integers(row, layout, anchor)
    return partial_decompress(container, codec, layout, QUANT, anchor), lambda row: row["data"].reshape(place(row, layout)[1])


def surrounded(container: DataFrame, codec: str, layout: Layout, ahead_only: bool = False, anchor: str = "grid") -> tuple[DataFrame, Callable[[dict], np.ndarray]]:
    """Rows with the layers of all chunks around, corners included, and how they give integers with one layer more.

    ``ahead_only`` asks for the chunks after it alone, and the layer is at the high ends alone.
    """
    rows, read = readable(container, codec, layout, anchor)
    n = layout.ndim
    low = 0 if ahead_only else -1
    steps = [s for s in np.ndindex(*(3,) * n) if any(x != 1 for x in s)]
    steps = [tuple(x - 1 for x in s) for s in steps if min(s) - 1 >= low]

    def send(row):
        q = read(row)
        _, _, dims = place(row, layout)
        for code, step in enumerate(steps):  # the chunk that sees this one in the direction ``step``
            cell = [row[c] for c in CELLS]
            cell[:n] = [c - s for c, s in zip(cell, step)]
            if all(0 <= c and c * e < d for c, e, d in zip(cell, layout.chunk, dims)):
                part = q[tuple(slice(None) if s == 0 else slice(0, 1) if s > 0 else slice(-1, None) for s in step)]
                yield head(row, cell) | {"code": code, "v": part.ravel()}

    sent = with_messages(rows, kernel(rows, send, f"{HEAD}, code int, v array<bigint>"))

    def wide(row):
        q = read(row)
        out = np.pad(q, [(-low, 1)] * n)
        for code, v in row["got"]:
            at = tuple(slice(-low, s + 1 if low == 0 else -1) if x == 0 else slice(0, 1) if x < 0 else slice(-1, None) for x, s in zip(steps[code], q.shape))
            at = tuple(slice(0, s) if x == 0 and low == 0 else a for a, x, s in zip(at, steps[code], q.shape))
            out[at] = v.reshape(out[at].shape)
        return out

    return sent, wide


def coordinates(row: dict, layout: Layout) -> tuple[list[np.ndarray], tuple[int, ...]]:
    lo, shape, dims = place(row, layout)
    return [np.broadcast_to(x + o, shape) for x, o in zip(np.indices(shape, sparse=True), lo)], dims


def columns(at: list[np.ndarray], keep: np.ndarray) -> dict:
    zero = np.zeros(int(keep.sum()), np.int64)
    return {c: at[a][keep] if a < len(at) else zero for a, c in enumerate("ijk")}


def stencil(container: DataFrame, codec: str, layout: Layout, weights: dict[tuple[int, ...], int], anchor: str = "grid") -> DataFrame:
    """(field, i, j, k, s, result): the weighted sum of the neighbours at offsets -1, 0 or 1 on each axis.

    Integer weights; ``result`` is the integer sum times twice the bound.  Points that lack a neighbour are left out.
    """
    rows, wide = surrounded(container, codec, layout, anchor=anchor)

    def run(row):
        w = wide(row)
        at, dims = coordinates(row, layout)
        total, keep = 0, np.ones(at[0].shape, bool)
        for offset, weight in weights.items():
            total = total + weight * w[tuple(slice(1 + o, s - 1 + o) for o, s in zip(offset, w.shape))]
            for x, o, d in zip(at, offset, dims):
                keep = keep & (x + o >= 0) & (x + o < d)
        s = total[keep]
        return {"field": row["field"], "s": s, "result": s * (2 * row["eps"])} | columns(at, keep)

    return flat_kernel(rows, run, f"field string, {POINT}, s bigint, result double")


def linear_combination(parts: list[tuple[DataFrame, str, Layout]], weights: list[float]) -> DataFrame:
    """(i, j, k, result) of fields on one grid, met chunk by chunk: integers are added first where bounds are equal and weights whole."""
    joined, reads = None, []
    for n, (container, codec, layout) in enumerate(parts):
        rows = with_carries(container, codec, layout)
        one = rows.select(*CELLS, F.struct(*rows.columns).alias(f"u{n}"))
        joined = one if joined is None else joined.join(one, CELLS)
        reads.append(layout)
    whole_weights = all(float(w).is_integer() for w in weights)

    def run(row):
        own = [row[f"u{n}"] for n in range(len(reads))]
        at, _ = coordinates(own[0], reads[0])
        q = [integers(r, y) for r, y in zip(own, reads)]
        if whole_weights and len({r["eps"] for r in own}) == 1:
            result = sum(int(w) * x for w, x in zip(weights, q)) * (2 * own[0]["eps"])
        else:
            result = sum(w * (x * (2 * r["eps"])) for w, x, r in zip(weights, q, own))
        return {"result": result.ravel()} | columns(at, np.ones(at[0].shape, bool))

    return flat_kernel(joined, run, f"{POINT}, result double")


def block_aggregate(container: DataFrame, codec: str, layout: Layout, anchor: str = "grid") -> DataFrame:
    """(field, bi, bj, bk, n, s, lo, hi): points, sum and extremes of the integers of each block."""
    rows = with_carries(container, codec, layout, anchor)

    def run(row):
        q = integers(row, layout, anchor)
        lo, shape, _ = place(row, layout)
        order, sizes = block_order(shape, layout.block)
        v, starts = q.ravel()[order], np.cumsum(sizes) - sizes
        grid = np.indices([-(-s // b) for s, b in zip(shape, layout.block)])
        at = {f"b{c}": (g + o // b).ravel() for c, g, o, b in zip("ijk", grid, lo, layout.block)}
        zero = np.zeros(len(sizes), np.int64)
        return {"field": row["field"], "n": sizes, "s": np.add.reduceat(v, starts), "lo": np.minimum.reduceat(v, starts), "hi": np.maximum.reduceat(v, starts)} | {f"b{c}": at.get(f"b{c}", zero) for c in "ijk"}

    return flat_kernel(rows, run, "field string, bi bigint, bj bigint, bk bigint, n bigint, s bigint, lo bigint, hi bigint")


def regional(container: DataFrame, codec: str, layout: Layout, boxes: DataFrame, anchor: str = "grid") -> DataFrame:
    """(id, n, s1, mean, sd, lowest, highest) of the points in each of ``boxes`` (id, lo, hi: arrays of first and last places).

    Boxes meet the chunks that they touch by an equal join on chunk numbers; other chunks are not decoded.
    A box without points is absent.
    """
    n = layout.ndim
    touched = boxes
    for a, c in enumerate(CELLS):
        first, last = (F.floor(F.element_at(e, a + 1) / layout.chunk[a]).cast("int") for e in ("lo", "hi")) if a < n else (F.lit(0), F.lit(0))
        touched = touched.withColumn(c, F.explode(F.sequence(F.greatest(first, F.lit(0)), last)))
    asked = touched.groupBy(*CELLS).agg(F.collect_list(F.struct(F.col("id").cast("bigint").alias("id"), F.col("lo").cast("array<bigint>").alias("lo"), F.col("hi").cast("array<bigint>").alias("hi"))).alias("boxes"))
    rows = with_carries(container, codec, layout, anchor).join(asked, CELLS)

    def run(row):
        q = integers(row, layout, anchor)
        origin, shape, _ = place(row, layout)
        for id_, lo, hi in row["boxes"]:
            cut = tuple(slice(max(0, int(a) - o), min(s, int(b) - o + 1)) for a, b, o, s in zip(lo, hi, origin, shape))
            v = q[cut]
            if v.size:
                yield {"id": id_, "eps": row["eps"], "n": v.size, "s1": exact(v), "s2": exact(v, v), "lo": int(v.min()), "hi": int(v.max())}

    part = kernel(rows, run, "id bigint, eps double, n bigint, s1 decimal(38,0), s2 decimal(38,0), lo bigint, hi bigint")
    t = part.groupBy("id", "eps").agg(F.sum("n").alias("n"), whole("s1").alias("s1"), whole("s2").alias("s2"), F.min("lo").alias("lo"), F.max("hi").alias("hi"))
    scale = 2 * F.col("eps")
    return t.select("id", "n", F.col("s1").cast("bigint").alias("s1"), mean_result().alias("mean"), sd_result().alias("sd"), (F.col("lo") * scale).alias("lowest"), (F.col("hi") * scale).alias("highest"))


def isosurface_cells(container: DataFrame, codec: str, layout: Layout, level: float, anchor: str = "grid") -> DataFrame:
    """(field, i, j, k) of the first corners of the grid cells that the level passes through: a test on integers."""
    rows, wide = surrounded(container, codec, layout, ahead_only=True, anchor=anchor)
    n = layout.ndim

    def run(row):
        w = wide(row)
        at, dims = coordinates(row, layout)
        corners = [w[tuple(slice(o, s - 1 + o) for o, s in zip(offset, w.shape))] for offset in np.ndindex(*(2,) * n)]
        cut = np.ceil(level / (2 * row["eps"]))
        keep = (np.minimum.reduce(corners) < cut) & (np.maximum.reduce(corners) >= cut)
        for x, d in zip(at, dims):
            keep &= x < d - 1
        return {"field": row["field"]} | columns(at, keep)

    return flat_kernel(rows, run, f"field string, {POINT}")


def halo_points(container: DataFrame, codec: str, layout: Layout, factor: float, anchor: str = "grid") -> DataFrame:
    """(field, i, j, k, q): points above ``factor`` times the field's mean, which comes from metadata where the codec has any."""
    stage = META if META in CODECS[codec].stages else QUANT
    mean = moments(container, codec, layout, stage, anchor, squares=False).select("field", (F.lit(float(factor)) * F.col("s1").cast("double") / F.col("n")).alias("cut"))
    rows = with_carries(container, codec, layout, anchor).join(F.broadcast(mean), "field")  # one row a field

    def run(row):
        q = integers(row, layout, anchor)
        at, _ = coordinates(row, layout)
        keep = q > row["cut"]
        return {"field": row["field"], "q": q[keep]} | columns(at, keep)

    return flat_kernel(rows, run, f"field string, {POINT}, q bigint")


def symbol_counts(container: DataFrame, layout: Layout) -> DataFrame:
    """(p, c): how often each residual occurs; counted in the chunks first."""

    def run(row):
        p, _, _, _ = decoded(row, layout)
        value, many = np.unique(p, return_counts=True)
        return {"p": value, "c": many}

    return flat_kernel(container, run, "p bigint, c bigint").groupBy("p").agg(F.sum("c").alias("c"))


def run_counts(container: DataFrame, layout: Layout) -> DataFrame:
    """(field, residuals, runs) of a run-length encoder that starts anew in each block."""
    from fieldloom.functions.bitpack import encode_runs

    def run(row):
        p, _, order, shape = decoded(row, layout)
        _, sizes = block_order(shape, layout.block)
        p, ends = p[order], np.cumsum(sizes).tolist()
        yield {"field": row["field"], "residuals": len(p), "runs": sum(len(encode_runs(p[a:b])[0]) for a, b in zip([0, *ends], ends))}

    return kernel(container, run, "field string, residuals bigint, runs bigint").groupBy("field").agg(F.sum("residuals").alias("residuals"), F.sum("runs").alias("runs"))


__all__ = ["KEY", "block_aggregate", "halo_points", "isosurface_cells", "linear_combination", "regional", "run_counts", "stencil", "surrounded", "symbol_counts"]
