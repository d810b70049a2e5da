"""Derivatives, Laplacian, divergence and curl at RESID, QUANT and VALUE.

Integers first, the scale last.  All stages come down to the steps of the integers from point to point
along each axis.  Mean codecs at RESID add the steps of residuals and of block means; difference codecs
at RESID get the steps along an axis as prefix sums over the other axes, so along the axis itself nothing
is scanned; QUANT takes the differences of integers; VALUE goes on from the doubles of the full flow.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fieldloom.model import CODECS, QUANT, RESID, VALUE, Layout, UnsupportedStage, require
from fieldloom.operators.chunks import CELLS, FACE, GHOST, GRID, HEAD, KEY, carried, carries, faces, flat_kernel, kernel, kept, layer, place, sides, with_messages
from fieldloom.operators.codecs import decoded, integers, partial_decompress, residual_array, with_carries

#: What a derivative is where a neighbour is missing: the point is left out, or the derivative is null, or the missing
#: neighbour equals the point, or is the grid's other end, or the difference to the one neighbour counts twice.
BOUNDARIES = ("interior", "null", "clamp", "periodic", "one_sided")


@dataclass(frozen=True)
class Reading:
    """How a kernel reads prepared chunk rows; ``steps(row)`` gives (integers or None, steps along each axis).

    Steps along an axis are one more than the points there: from the neighbour before the first to the
    first, and so on to the neighbour after the last.  At the rim of the grid they mean nothing.
    """

    layout: Layout
    stage: str
    steps: Callable[[dict], tuple[np.ndarray | None, list[np.ndarray]]]
    boundary: str = "interior"


@dataclass(frozen=True)
class Ready:
    """Chunk rows with what a stencil needs, and how to read them."""

    rows: DataFrame
    how: Reading


def cut(a: np.ndarray, axis: int, start: int | None, stop: int | None) -> np.ndarray:
    return a[tuple(slice(start, stop) if b == axis else slice(None) for b in range(a.ndim))]


def summed_over_others(p: np.ndarray, axis: int) -> np.ndarray:
    for b in range(p.ndim):
        if b != axis:
            p = p.cumsum(axis=b)
    return p


def chained_steps(row: dict, layout: Layout, full: bool) -> tuple[np.ndarray | None, list[np.ndarray]]:
    """Steps of a difference codec's row from its residuals, its carries and the next chunks' first layers."""
    p = residual_array(row, layout)
    got, carry = dict(row["got"]), carried(row, p.shape)
    q = integers(row, layout) if full else None
    out = []
    for a in range(p.ndim):
        shape = kept(p.shape, 1 << a)
        ahead = np.zeros(shape, np.int64)
        if FACE + 2 * a + 1 in got:
            ahead = summed_over_others(got[FACE + 2 * a + 1].reshape(shape), a)
            for code, v in got.items():
                if code // GHOST == a + 1:
                    ahead = ahead + v.reshape(kept(shape, code % GHOST))
        own = [(s, v) for s, v in carry if not s >> a & 1]
        if full:
            first = summed_over_others(layer(p, a, False), a)
            for _, v in own:
                first = first + layer(v, a, False)
            out.append(np.concatenate([first, np.diff(q, axis=a), ahead], axis=a))
        else:
            back = summed_over_others(p, a)
            for _, v in own:
                back = back + np.diff(v, axis=a, prepend=0)
            out.append(np.concatenate([back, ahead], axis=a))
    return q, out


def widened(arrays: list[np.ndarray], row: dict, axis: int) -> list[np.ndarray]:
    """Arrays with the neighbours' layers at both ends of an axis; zeros where there is none."""
    got = dict(row["got"])
    ends = []
    for code in (FACE + 2 * axis, FACE + 2 * axis + 1):
        v = got.get(code)
        ends.append(np.split(v, len(arrays)) if v is not None else [np.zeros(0, x.dtype) for x in arrays])
    out = []
    for x, *around in zip(arrays, *ends):
        shape = kept(x.shape, 1 << axis)
        low, high = (v.reshape(shape) if v.size else np.zeros(shape, x.dtype) for v in around)
        out.append(np.concatenate([low, x, high], axis=axis))
    return out


def faced_steps(arrays: Callable[[dict], list[np.ndarray]], whole: bool):
    """Steps of rows that can be read on their own: those of each of ``arrays`` added up."""

    def steps(row):
        own = arrays(row)
        return own[0] if whole else None, [sum(np.diff(w, axis=a) for w in widened(own, row, a)) for a in range(own[0].ndim)]

    return steps


def prepared(container: DataFrame, codec: str, layout: Layout, stage: str, anchor: str = "grid", boundary: str = "interior", dims: tuple[int, ...] | None = None, work: Layout | None = None) -> Ready:
    """The container, ready for stencils at ``stage``.

    One-dimensional codecs of fields of more dimensions are folded from chunk to chunk into ``work``'s
    boxes of the grid ``dims``.
    """
    if boundary not in BOUNDARIES:
        raise ValueError(f"boundary {boundary!r} is none of {BOUNDARIES}")
    periodic = boundary == "periodic"
    kind = CODECS[codec]
    if kind.flat and dims is not None and len(dims) > 1:
        require(codec, stage, "gradient")
        return folded(container, codec, layout, stage, dims, work, anchor, boundary)
    if not (kind.flat and stage == RESID and kind.predictor == "difference"):  # a field of one dimension has steps at RESID
        require(codec, stage, "gradient")
    chained = kind.predictor == "difference" and anchor == "grid"
    if chained and not periodic:
        full = stage != RESID
        messages = carries(container, layout, lambda row: residual_array(row, layout), full=full, ghosts=True)
        return Ready(with_messages(container, messages), Reading(layout, stage, lambda row: chained_steps(row, layout, full), boundary))
    if kind.predictor == "difference" and stage == RESID:
        raise UnsupportedStage(f"{codec} has no residuals across the rim, or across chunks that start anew")
    if chained:
        rows = partial_decompress(container, codec, layout, QUANT)
        arrays = lambda row: [row["data"].reshape(place(row, layout)[1])]
    elif stage == RESID:
        rows = container

        def arrays(row):
            p, means, _, shape = decoded(row, layout)
            return [p.reshape(shape), means.reshape(shape)]

    else:
        rows = container
        arrays = lambda row: [integers(row, layout, anchor)]
    return Ready(with_messages(rows, faces(rows, layout, arrays, periodic)), Reading(layout, stage, faced_steps(arrays, stage != RESID), boundary))


def folded(container: DataFrame, codec: str, layout: Layout, stage: str, dims: tuple[int, ...], work: Layout, anchor: str, boundary: str) -> Ready:
    """Boxes with one layer around them, from the chunks of a flattened field: each point goes where it is needed, once."""
    n, periodic = len(dims), boundary == "periodic"
    box, extent = np.array(work.chunk, np.int64), np.array(dims, np.int64)
    many = -(-extent // box)

    def send(row):
        q = integers(row, layout, anchor).ravel()
        at = np.array(np.unravel_index(int(row["ci"]) * layout.chunk[0] + np.arange(len(q)), dims), np.int64)
        cell, inner = np.divmod(at, box[:, None])
        found = [(np.arange(len(q)), cell, inner + 1)]
        for a in range(n):
            for step in (-1, 1):  # the point is the layer after the box of the point before it, and the reverse
                y = at[a] + step
                if periodic:
                    y = y % extent[a]
                edge = (y % box[a] == box[a] - 1) | (y == extent[a] - 1) if step < 0 else y % box[a] == 0
                pick = np.flatnonzero(edge & (y >= 0) & (y < extent[a]))
                to, place_ = cell[:, pick].copy(), inner[:, pick] + 1
                to[a], place_[a] = y[pick] // box[a], y[pick] % box[a] + 1 - step
                found.append((pick, to, place_))
        which, to, place_ = (np.concatenate(c, axis=-1) for c in zip(*found))
        sizes = np.minimum(box[:, None], extent[:, None] - to * box[:, None]) + 2
        pos = np.zeros(len(which), np.int64)
        target = np.zeros(len(which), np.int64)
        for a in range(n):
            pos = pos * sizes[a] + place_[a]
            target = target * many[a] + to[a]
        order = np.argsort(target, kind="stable")
        cuts = np.flatnonzero(np.diff(target[order], prepend=-1))
        for s, e in zip(cuts.tolist(), [*cuts[1:].tolist(), len(order)]):
            own = order[s:e]
            at_cell = [int(x) for x in to[:, own[0]]] + [0, 0]
            facts = {"field": row["field"], "eps": row["eps"]} | dict(zip(CELLS, at_cell)) | dict(zip(GRID[1:], [*dims, 1, 1]))
            yield facts | {"pos": pos[own].astype(np.int32), "v": q[which[own]]}

    parts = kernel(with_carries(container, codec, layout, anchor), send, f"{HEAD}, pos array<int>, v array<bigint>")
    rows = parts.groupBy(*KEY).agg(*[F.first(g).alias(g) for g in GRID], F.collect_list(F.struct("pos", "v")).alias("parts"))

    def steps(row):
        _, shape, _ = place(row, work)
        w = np.zeros([s + 2 for s in shape], np.int64)
        for pos, v in row["parts"]:
            w.ravel()[pos] = v
        inside = tuple(slice(1, -1) for _ in shape)
        return w[inside], [np.diff(w[tuple(slice(None) if b == a else slice(1, -1) for b in range(n))], axis=a) for a in range(n)]

    return Ready(rows, Reading(work, stage, steps, boundary))


def local(how: Reading, row: dict, gradient: bool = True, laplacian: bool = True) -> dict:
    """Of one chunk's points with a result, a box: ``lo`` and ``shape``, ``d`` (a derivative for each axis) and ``lap``.

    Integers are differences of both neighbours, times eps the derivative, and the neighbours' sum less
    twice the number of axes times the centre, times twice eps the Laplacian; VALUE gives both as doubles.
    """
    lo, shape, dims = place(row, how.layout)
    q, steps = how.steps(row)
    n, mode = len(shape), how.boundary
    inner = mode == "interior"
    box = [slice(int(inner and o == 0), s - int(inner and o + s == d)) for o, s, d in zip(lo, shape, dims)]
    size = tuple(max(0, b.stop - b.start) for b in box)
    first = [np.arange(b.start, b.start + s) + o == 0 for b, s, o in zip(box, size, lo)]
    last = [np.arange(b.start, b.start + s) + o == d - 1 for b, s, o, d in zip(box, size, lo, dims)]
    d, total, whole = [], None, np.ones(size, bool) if mode == "null" else None
    if how.stage == VALUE:
        scale = 2 * row["eps"]
        q = q[tuple(box)]
        v = q.astype(np.float64) * scale
    for a in range(n):
        along = [slice(b.start, b.start + s) for b, s in zip(box, size)]
        back = steps[a][tuple(along)]
        along[a] = slice(box[a].start + 1, box[a].start + size[a] + 1)
        ahead = steps[a][tuple(along)]
        open_, close = (x.reshape([-1 if b == a else 1 for b in range(n)]) for x in (first[a], last[a]))
        if mode == "clamp":
            back, ahead = np.where(open_, 0, back), np.where(close, 0, ahead)
        elif mode == "one_sided":  # on an axis of one point nothing is to either side
            back, ahead = np.where(open_, np.where(close, 0, ahead), back), np.where(close, np.where(open_, 0, back), ahead)
        if how.stage == VALUE:
            low, high = (q - back).astype(np.float64) * scale, (q + ahead).astype(np.float64) * scale
            one = (high - low) / 2
            if mode == "one_sided":
                one = np.where(open_ & ~close, high - v, np.where(close & ~open_, v - low, one))
                low, high = (np.where(open_ | close, v, x) for x in (low, high))
            across = high + low
        else:
            one = ahead + back if gradient else None
            across = ahead - back if laplacian else 0
        if mode == "null":
            rim = np.broadcast_to(open_ | close, size)
            one, whole = np.ma.MaskedArray(one, rim), whole & ~rim
        d.append(one)
        if laplacian:
            total = across if total is None else total + across
    if laplacian and how.stage == VALUE:
        total = total - 2.0 * n * v
    if laplacian and mode == "null":
        total = np.ma.MaskedArray(total, ~whole)
    return {"lo": [o + b.start for o, b in zip(lo, box)], "shape": size, "d": d, "lap": total}


def places(found: dict) -> dict:
    """Columns i, j, k of the points with a result."""
    size, n = found["shape"], len(found["shape"])
    at = [np.broadcast_to((np.arange(s) + o).reshape([-1 if b == a else 1 for b in range(n)]), size).ravel() for a, (s, o) in enumerate(zip(size, found["lo"]))]
    zero = np.zeros(int(np.prod(size)), np.int64)
    return {c: at[a] if a < n else zero for a, c in enumerate("ijk")}


def stencilled(ready: Ready) -> DataFrame:
    """(field, eps, i, j, k, d0, d1, d2, lap) of local(), point by point."""
    how = ready.how
    kind = "double" if how.stage == VALUE else "bigint"

    def run(row):
        f = local(how, row)
        at = places(f)
        zero = np.zeros(len(at["i"]), np.float64 if kind == "double" else np.int64)
        d = {f"d{a}": f["d"][a].ravel() if a < len(f["d"]) else zero for a in range(3)}
        return {"field": row["field"], "eps": row["eps"], "lap": f["lap"].ravel()} | at | d

    return flat_kernel(ready.rows, run, f"field string, eps double, i bigint, j bigint, k bigint, d0 {kind}, d1 {kind}, d2 {kind}, lap {kind}")


def result_chunks(ready: Ready, operation: str = "gradient") -> DataFrame:
    """The derivatives, or the Laplacian, as chunk rows: (field, ci, cj, ck, eps, lo, shape, d0, d1, d2 or lap).

    Arrays are row-major in the box from ``lo`` on; for large fields, whose results stay arrays.
    """
    how = ready.how
    kind = "double" if how.stage == VALUE else "bigint"
    names = [f"d{a}" for a in range(how.layout.ndim)] if operation == "gradient" else ["lap"]

    def run(row):
        f = local(how, row, operation == "gradient", operation == "laplacian")
        arrays = f["d"] if operation == "gradient" else [f["lap"]]
        yield {k: row[k] for k in (*KEY, "eps")} | {"lo": f["lo"], "shape": f["shape"]} | {n: x.ravel() for n, x in zip(names, arrays)}

    return kernel(ready.rows, run, f"field string, ci int, cj int, ck int, eps double, lo array<bigint>, shape array<int>, {', '.join(f'{n} array<{kind}>' for n in names)}")


def derivatives(container: DataFrame, codec: str, layout: Layout, stage: str, anchor: str = "grid", boundary: str = "interior") -> DataFrame:
    """(field, eps, i, j, k, d0, d1, d2, lap): integers at RESID and QUANT.

    d0 to d2 times eps are the derivatives, lap times 2 eps the Laplacian; axes that the field lacks give 0.
    """
    if stage not in (RESID, QUANT):
        raise UnsupportedStage(f"integers of {codec} have no {stage}; value_derivatives() starts from values")
    return stencilled(prepared(container, codec, layout, stage, anchor, boundary))


def grid_derivatives(container: DataFrame, codec: str, layout: Layout, stage: str, dims: tuple[int, ...], work: Layout, anchor: str = "grid", boundary: str = "interior") -> DataFrame:
    """derivatives() for any codec: one-dimensional codecs are folded into ``dims`` at QUANT."""
    if stage not in (RESID, QUANT):
        raise UnsupportedStage(f"integers of {codec} have no {stage}; value_derivatives() starts from values")
    return stencilled(prepared(container, codec, layout, stage, anchor, boundary, dims if CODECS[codec].flat else None, work))


def scaled(d: DataFrame, names: dict[str, str], factor: int = 1) -> DataFrame:
    """Point rows with integers and their scaled values: result columns are ``factor`` eps times the integers."""
    return d.select("field", "i", "j", "k", *[F.col(c).alias(n) for c, n in names.items()], *[(F.col(c) * (factor * F.col("eps"))).alias(f"{n}_value") for c, n in names.items()])


def gradient(d: DataFrame, ndim: int) -> DataFrame:
    return scaled(d, {f"d{a}": "dx dy dz".split()[a] for a in range(ndim)})


def laplacian(d: DataFrame) -> DataFrame:
    return scaled(d, {"lap": "lap"}, 2)


def value_derivatives(container: DataFrame, codec: str, layout: Layout, dims: tuple[int, ...] | None = None, anchor: str = "grid", work: Layout | None = None, boundary: str = "interior") -> DataFrame:
    """The full flow, down to doubles and then central differences of these: (field, i, j, k, dx, dy, dz, lap)."""
    n = len(dims) if dims else layout.ndim
    d = stencilled(prepared(container, codec, layout, VALUE, anchor, boundary, dims if CODECS[codec].flat else None, work))
    return d.select("field", "i", "j", "k", *[F.col(f"d{a}").alias("dx dy dz".split()[a]) for a in range(n)], "lap")


def vector_kernel(parts: list[Ready], names: list[str], combine: Callable[[list[list[np.ndarray]]], list[np.ndarray]]) -> DataFrame:
    """(i, j, k, *names) of a vector field: ``combine`` sees the scaled derivatives, [component][axis].

    Components meet chunk by chunk, still compressed; each is decoded once and scaled by its own bound.
    """
    joined = None
    for n, p in enumerate(parts):
        one = p.rows.select(*CELLS, F.struct(*p.rows.columns).alias(f"u{n}"))
        joined = one if joined is None else joined.join(one, CELLS)

    hows = [p.how for p in parts]

    def run(row):
        d, out = [], None
        for n, how in enumerate(hows):
            f = local(how, row[f"u{n}"], laplacian=False)
            out = out or places(f)
            d.append([x.ravel() * (1.0 if how.stage == VALUE else row[f"u{n}"]["eps"]) for x in f["d"]])
        return out | dict(zip(names, combine(d)))

    return flat_kernel(joined, run, "i bigint, j bigint, k bigint, " + ", ".join(f"{n} double" for n in names))


def curl_3d(d: list) -> list:
    return [d[2][1] - d[1][2], d[0][2] - d[2][0], d[1][0] - d[0][1]]


def divergence(parts: list[Ready] | list[DataFrame]) -> DataFrame:
    """(i, j, k, result): each component along its own axis, scaled by its own bound before the addition."""

    def total(d):
        out = d[0][0]
        for a in range(1, len(d)):
            out = out + d[a][a]
        return [out]

    return combined(parts, ["result"], total)


def curl(parts: list[Ready] | list[DataFrame], sign: str = "paper") -> DataFrame:
    """(i, j, k, result) in the plane, with the first component along y less the second along x, or its
    negative for ``sign='standard'``; three components give (curl_x, curl_y, curl_z) in standard orientation."""
    if len(parts) == 3:
        return combined(parts, ["curl_x", "curl_y", "curl_z"], curl_3d)
    return combined(parts, ["result"], lambda d: [-(d[0][1] - d[1][0]) if sign == "standard" else d[0][1] - d[1][0]])


def combined(parts: list, names: list[str], combine: Callable) -> DataFrame:
    """vector_kernel() of prepared components, or the same over their derivatives() point by point."""
    if isinstance(parts[0], Ready):
        return vector_kernel(parts, names, combine)
    joined = None
    for n, p in enumerate(parts):
        one = p.select("i", "j", "k", *[(F.col(f"d{a}") * F.col("eps")).alias(f"u{n}_{a}") for a in range(3)])
        joined = one if joined is None else joined.join(one, ["i", "j", "k"])
    made = combine([[F.col(f"u{n}_{a}") for a in range(3)] for n in range(len(parts))])
    return joined.select("i", "j", "k", *[c.alias(name) for name, c in zip(names, made)])
