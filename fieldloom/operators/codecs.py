"""Compression into containers and staged decompression out of them."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fieldloom.functions.bitpack import decode_fixed, encode_fixed
from fieldloom.functions.quantise import checked, quantised
from fieldloom.model import CODECS, META, QUANT, RESID, VALUE, ErrorBound, Layout, layout_for, require
from fieldloom.operators.chunks import HEAD, KEY, MESSAGE, carries, dense, flatten_grid, head, kernel, place, prefix_with_carry, to_chunks, with_messages

CONTAINER = f"{HEAD}, codec string, n array<bigint>, meta array<bigint>, width array<int>, payload binary"


def block_order(shape: tuple[int, ...], block: tuple[int, ...]) -> tuple[np.ndarray, np.ndarray]:
    """(places of a chunk's points, block by block; points of each block). Blocks at the rim may be smaller."""
    grid = np.indices(shape)
    many = [-(-s // b) for s, b in zip(shape, block)]
    number = np.zeros(shape, np.int64)
    for x, b, m in zip(grid, block, many):
        number = number * m + x // b
    number = number.ravel()
    return np.argsort(number, kind="stable"), np.bincount(number, minlength=int(np.prod(many)))


def half_down(total: np.ndarray, n: np.ndarray) -> np.ndarray:
    """Integer means, nearest with ties down."""
    return -((n - 2 * total) // (2 * n))


def block_meta(predictor: str, q: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """One number a block, of values that lie block by block."""
    starts = np.cumsum(sizes) - sizes
    if predictor == "mean":
        return half_down(np.add.reduceat(q, starts), sizes)
    if predictor == "midrange":
        return (np.maximum.reduceat(q, starts) + np.minimum.reduceat(q, starts)) // 2
    return q[starts]


def in_block_difference(q: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    p = np.diff(q, prepend=0)
    p[np.cumsum(sizes) - sizes] = 0
    return p


def in_block_sum(p: np.ndarray, meta: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    total = np.cumsum(p)
    starts = np.cumsum(sizes) - sizes
    return total - np.repeat(total[starts] - p[starts], sizes) + np.repeat(meta, sizes)


def predict_differences(q: np.ndarray) -> np.ndarray:
    """Inclusion-exclusion residuals of an array with one layer more at the low sides."""
    for axis in range(q.ndim):
        q = np.diff(q, axis=axis)
    return q


def compress_points(points: DataFrame, codec: str, bound: ErrorBound, ndim: int, chunk: tuple[int, ...] | None = None, anchor: str = "grid", on_invalid: str = "error") -> DataFrame:
    """Container of a field given as points (field, i, j, k, value) on a dense grid.

    ``anchor='chunk'`` restarts the prediction of difference codecs in each chunk, so chunks need no
    carries at some cost in ratio; it is told by the codec's name ending in '@chunk'.
    """
    layout = layout_for(codec, ndim, chunk)
    q = quantised(checked(points, on_invalid), bound)
    return compress_chunks(to_chunks(flatten_grid(q) if CODECS[codec].flat else q, layout), codec, layout, anchor)


def compress_chunks(chunks: DataFrame, codec: str, layout: Layout, anchor: str = "grid") -> DataFrame:
    """Container of quantised chunk rows."""
    kind = CODECS[codec]
    name = codec if anchor == "grid" else f"{codec}@chunk"
    chained = kind.predictor == "difference" and anchor == "grid"
    n = layout.ndim
    steps = [s for s in np.ndindex(*(2,) * n) if any(s)]

    def send(row):
        q = dense(row, layout)
        _, _, dims = place(row, layout)
        for code, s in enumerate(steps):  # the last layers go to the chunks after this one
            cell = [row["ci"], row["cj"], row["ck"]]
            cell[:n] = [c + x for c, x in zip(cell, s)]
            if all(c * e < d for c, e, d in zip(cell, layout.chunk, dims)):
                yield head(row, cell) | {"code": code, "v": q[tuple(slice(-1, None) if x else slice(None) for x in s)].ravel()}

    if chained:
        chunks = with_messages(chunks, kernel(chunks, send, MESSAGE))

    def run(row):
        p = dense(row, layout)
        shape = p.shape
        if kind.predictor == "difference":
            p = np.pad(p, [(1, 0)] * n)
            for code, v in row["got"] if chained else ():
                at = tuple(slice(0, 1) if x else slice(1, None) for x in steps[code])
                p[at] = v.reshape(p[at].shape)
            p = predict_differences(p)
        order, sizes = block_order(shape, layout.block)
        p = p.ravel()[order].astype(np.int64)
        meta = np.zeros(0, np.int64)
        if kind.predictor != "difference":
            meta = block_meta(kind.predictor, p, sizes)
            p = in_block_difference(p, sizes) if kind.predictor == "first" else p - np.repeat(meta, sizes)
        width, payload = encode_fixed(p, sizes)
        yield head(row) | {"codec": name, "n": sizes, "meta": meta, "width": width, "payload": payload}

    return kernel(chunks, run, CONTAINER)


def codec_of(name: str):
    return CODECS[name.split("@")[0]]


def decoded(row: dict, layout: Layout) -> tuple[np.ndarray, np.ndarray, np.ndarray, tuple[int, ...]]:
    """(residuals in chunk order, means in chunk order, block order, shape) of a container row."""
    _, shape, _ = place(row, layout)
    order, sizes = block_order(shape, layout.block)
    p = decode_fixed(np.asarray(row["width"], np.int64), sizes, row["payload"])
    back, means = np.empty(len(order), np.int64), np.zeros(len(order), np.int64)
    meta = np.asarray(row["meta"], np.int64)
    if codec_of(row["codec"]).predictor == "first":
        p = in_block_sum(p, meta, sizes)
        meta = meta[:0]
    back[order] = p
    if len(meta):
        means[order] = np.repeat(meta, sizes)
    return back, means, order, shape


def residual_array(row: dict, layout: Layout) -> np.ndarray:
    p, _, _, shape = decoded(row, layout)
    return p.reshape(shape)


def integers(row: dict, layout: Layout, anchor: str = "grid") -> np.ndarray:
    """The quantised integers of a container row, with the carries that it got where its codec needs them."""
    p, means, _, shape = decoded(row, layout)
    p = p.reshape(shape)
    if codec_of(row["codec"]).predictor != "difference":
        return p + means.reshape(shape)
    if anchor == "grid":
        return prefix_with_carry(p, row)
    for a in range(p.ndim):
        p = p.cumsum(axis=a)
    return p


def with_carries(container: DataFrame, codec: str, layout: Layout, anchor: str = "grid") -> DataFrame:
    """Container rows with what integers() needs; the difference codecs' carries take one pass over it."""
    if CODECS[codec].predictor != "difference" or anchor != "grid":
        return container
    return with_messages(container, carries(container, layout, lambda row: residual_array(row, layout)))


def partial_decompress(container: DataFrame, codec: str, layout: Layout, stage: str, anchor: str = "grid") -> DataFrame:
    """The container at ``stage``: META (n, meta), or RESID, QUANT or VALUE chunks in ``data``.

    META never reads payloads.  QUANT of the predecessor baseline is open to the scalar operations on it.
    """
    if stage != QUANT:
        require(codec, stage)
    if stage == META:
        return container.select(*KEY, "eps", "d0", "d1", "d2", "n", "meta")
    if stage == RESID:

        def residuals(row):
            p, means, _, _ = decoded(row, layout)
            yield head(row) | {"data": p, "means": means}

        return kernel(container, residuals, f"{HEAD}, data array<bigint>, means array<bigint>")

    def restore(row):
        q = integers(row, layout, anchor).ravel()
        yield head(row) | {"data": q if stage == QUANT else q.astype(np.float64) * (2 * row["eps"])}

    return kernel(with_carries(container, codec, layout, anchor), restore, f"{HEAD}, data array<{'bigint' if stage == QUANT else 'double'}>")


def to_points(chunks: DataFrame, layout: Layout, dims: tuple[int, ...] | None = None) -> DataFrame:
    """(field, i, j, k, v) of chunk rows; a flat layout is folded back by the extents ``dims``."""
    size = [*layout.chunk, 1, 1][:3]
    extent = [F.least(F.lit(s).cast("bigint"), F.col(f"d{a}") - F.col(f"c{c}") * s) for a, (c, s) in enumerate(zip("ijk", size))]
    p = chunks.select("field", "ci", "cj", "ck", *[e.alias(f"s{a}") for a, e in enumerate(extent)], F.posexplode("data").alias("pos", "v"))
    pos = F.col("pos").cast("bigint")
    k = F.pmod(pos, F.col("s2")) + F.col("ck") * size[2]
    j = F.pmod(F.floor(pos / F.col("s2")), F.col("s1")) + F.col("cj") * size[1]
    i = F.floor(pos / (F.col("s1") * F.col("s2"))) + F.col("ci") * size[0]
    p = p.select("field", i.cast("bigint").alias("i"), j.cast("bigint").alias("j"), k.cast("bigint").alias("k"), "v")
    return p if dims is None else unflatten(p, dims)


def unflatten(points: DataFrame, dims: tuple[int, ...]) -> DataFrame:
    d = [*dims, 1, 1][:3]
    g = F.col("i")
    return points.select("field", F.floor(g / (d[1] * d[2])).cast("bigint").alias("i"), F.pmod(F.floor(g / d[2]), F.lit(d[1])).cast("bigint").alias("j"), F.pmod(g, F.lit(d[2])).cast("bigint").alias("k"), "v")


def region(container: DataFrame, layout: Layout, lo: tuple[int, ...], hi: tuple[int, ...]) -> DataFrame:
    """Only the chunks that a box meets: a predicate on chunk numbers, which Parquet can push down."""
    names = ["ci", "cj", "ck"]
    test = F.lit(True)
    for n, c, a, b in zip(names, layout.chunk, lo, hi):
        test = test & F.col(n).between(a // c, b // c)
    return container.where(test)
