"""A transform codec: orthonormal cosine coefficients of each block, quantised.

A block of n points has a step of 2 * eps / sqrt(n): errors of the coefficients of at most half a step
each have a length of at most eps, which the inverse keeps, so no point is off by more than eps.  The
first coefficient over its step is the block's sum over 2 * eps; it is the block's metadata, from which
the mean is had without a payload.  By the transform's orthogonality the standard deviation comes from
coefficients; a derivative needs the inverse.
"""

from __future__ import annotations

from functools import lru_cache
from itertools import product

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fieldloom.functions.bitpack import decode_fixed, encode_fixed
from fieldloom.functions.quantise import checked, quantised
from fieldloom.model import ErrorBound, Layout
from fieldloom.operators.chunks import HEAD, dense, head, kernel, place, to_chunks
from fieldloom.operators.codecs import CONTAINER, block_order
from fieldloom.operators.statistics import micro

CODEC = "cosine"


@lru_cache(maxsize=64)
def basis(n: int) -> np.ndarray:
    """The orthonormal cosine matrix of n points: a row for each coefficient."""
    k, x = np.indices((n, n))
    out = np.cos(np.pi * (x + 0.5) * k / n) * np.sqrt(2.0 / n)
    out[0] = np.sqrt(1.0 / n)
    return out


def like_blocks(shape: tuple[int, ...], block: tuple[int, ...]):
    """(box, extents of its blocks): the boxes of a chunk that hold blocks of one shape."""
    cuts = [((0, s - s % b, b), (s - s % b, s, s % b)) for s, b in zip(shape, block)]
    for parts in product(*cuts):
        if all(stop > start for start, stop, _ in parts):
            yield tuple(slice(start, stop) for start, stop, _ in parts), tuple(n for _, _, n in parts)


def transformed(v: np.ndarray, block: tuple[int, ...], inverse: bool = False) -> np.ndarray:
    """Each block of an array through the transform along all axes, or back."""
    out = np.empty(v.shape)
    for box, extents in like_blocks(v.shape, block):
        x = v[box]
        for axis, n in enumerate(extents):
            w = np.moveaxis(x, axis, -1)
            turned = w.reshape(*w.shape[:-1], -1, n) @ (basis(n) if inverse else basis(n).T)
            x = np.moveaxis(turned.reshape(w.shape), -1, axis)
        out[box] = x
    return out


def compress_cosine(points: DataFrame, bound: ErrorBound, layout: Layout, on_invalid: str = "error") -> DataFrame:
    """Container of a field given as points (field, i, j, k, value) on a dense grid."""
    values = quantised(checked(points, on_invalid), bound).withColumn("q", F.col("value").cast("double"))

    def run(row):
        v = dense(row, layout)
        order, sizes = block_order(v.shape, layout.block)
        starts = np.cumsum(sizes) - sizes
        step = np.repeat(2 * row["eps"] / np.sqrt(sizes), sizes)
        p = np.floor(transformed(v, layout.block).ravel()[order] / step + 0.5).astype(np.int64)
        meta = np.floor(np.add.reduceat(v.ravel()[order], starts) / (2 * row["eps"]) + 0.5).astype(np.int64)
        p[starts] = 0
        width, payload = encode_fixed(p, sizes)
        yield head(row) | {"codec": CODEC, "n": sizes, "meta": meta, "width": width, "payload": payload}

    return kernel(to_chunks(values, layout), run, CONTAINER)


def coefficients(row: dict) -> tuple[np.ndarray, np.ndarray]:
    """(quantised coefficients block by block, points of each block) of a container row."""
    sizes = np.asarray(row["n"], np.int64)
    p = decode_fixed(np.asarray(row["width"], np.int64), sizes, row["payload"])
    p[np.cumsum(sizes) - sizes] = row["meta"]
    return p, sizes


def cosine_values(container: DataFrame, layout: Layout) -> DataFrame:
    """VALUE chunks, for to_points() and all that takes values."""

    def run(row):
        p, sizes = coefficients(row)
        _, shape, _ = place(row, layout)
        order, _ = block_order(shape, layout.block)
        c = np.empty(len(p))
        c[order] = p * np.repeat(2 * row["eps"] / np.sqrt(sizes), sizes)
        yield head(row) | {"data": transformed(c.reshape(shape), layout.block, inverse=True).ravel()}

    return kernel(container, run, f"{HEAD}, data array<double>")


def cosine_mean(container: DataFrame) -> DataFrame:
    """(field, n, int_num, result): the mean from metadata alone."""
    total = lambda name: F.aggregate(name, F.lit(0).cast("decimal(38,0)"), lambda a, x: (a + x).cast("decimal(38,0)"))
    t = container.select("field", "eps", total("n").alias("n"), total("meta").alias("s")).groupBy("field", "eps").agg(F.sum("n").cast("bigint").alias("n"), F.sum("s").cast("bigint").alias("int_num"))
    return t.select("field", "n", "int_num", (F.col("int_num").cast("double") / F.col("n") * (2 * F.col("eps"))).alias("result"))


def cosine_stddev(container: DataFrame) -> DataFrame:
    """(field, n, result_micro): the sample standard deviation from coefficients, without the inverse.

    Each block's squares about its own mean are those of its other coefficients; block means are combined pairwise.
    """

    def run(row):
        p, sizes = coefficients(row)
        starts = np.cumsum(sizes) - sizes
        p[starts] = 0
        inside = np.add.reduceat((p * np.repeat(2 * row["eps"] / np.sqrt(sizes), sizes)) ** 2, starts).sum()
        means = row["meta"] * (2 * row["eps"]) / sizes
        middle = float((means * sizes).sum() / sizes.sum())
        yield {"field": row["field"], "n": int(sizes.sum()), "mean": middle, "square": float(inside + (sizes * (means - middle) ** 2).sum())}

    part = kernel(container, run, "field string, n bigint, mean double, square double")
    middle = part.groupBy("field").agg((F.sum(F.col("n") * F.col("mean")) / F.sum("n")).alias("middle"))
    t = part.join(F.broadcast(middle), "field").groupBy("field").agg(F.sum("n").alias("n"), F.sum(F.col("square") + F.col("n") * (F.col("mean") - F.col("middle")) ** 2).alias("s"))
    return t.select("field", "n", F.when(F.col("n") > 1, micro(F.sqrt(F.col("s") / (F.col("n") - 1)))).alias("result_micro"))


__all__ = ["CODEC", "compress_cosine", "cosine_mean", "cosine_stddev", "cosine_values"]
