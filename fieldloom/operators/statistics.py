"""Mean and standard deviation at each stage; integers are summed exactly and scaled once, last."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fieldloom.model import CODECS, META, QUANT, RESID, VALUE, Layout, require
from fieldloom.operators.chunks import kernel, place, rows_of
from fieldloom.operators.codecs import decoded, integers, partial_decompress, residual_array, with_carries

MOMENTS = "field string, eps double, n bigint, s1 decimal(38,0), s2 decimal(38,0), f double"


SAFE = float(1 << 62)  # a bound on sums below which 64 bits hold them


def whole(c: str) -> Column:
    """An exact sum of 38 digits."""
    return F.sum(F.col(c).cast("decimal(38,0)"))


def largest(a: np.ndarray) -> float:
    return max(float(a.max()), -float(a.min())) if a.size else 0.0


def exact(*factors: np.ndarray) -> int:
    """The sum of products of integers: in 64 bits where a bound says that they suffice, in whole numbers else."""
    a = [f.ravel() for f in factors]
    bound = float(a[0].size)
    for f in a:
        bound *= largest(f)
    if bound >= SAFE:
        a = [f.astype(object) for f in a]
    out = a[0]
    for f in a[1:]:
        out = out * f
    return int(out.sum())


def moments(container: DataFrame, codec: str, layout: Layout, stage: str, anchor: str = "grid", squares: bool = True) -> DataFrame:
    """(field, eps, n, s1, s2): count, sum and sum of squares of the quantised integers, seen from ``stage``.

    At RESID the difference codecs weigh residuals for the sum, which needs no scan; squares take
    prefix sums that live only inside the kernel.  VALUE gives sums of doubles in f instead.
    """
    kind = CODECS[codec]
    require(codec, stage, "mean" if not squares else "sd") if stage != QUANT else None
    if stage == META:
        part = container.select("field", "eps", F.aggregate("n", F.lit(0).cast("bigint"), lambda a, x: a + x).alias("n"), F.aggregate(F.zip_with("n", "meta", lambda n, m: n * m), F.lit(0).cast("bigint"), lambda a, x: a + x).alias("s1"))
        return part.groupBy("field", "eps").agg(F.sum("n").alias("n"), whole("s1").alias("s1"))
    if stage == RESID and kind.predictor == "difference" and not squares:

        def sums(row):
            lo, shape, dims = place(row, layout)
            p = residual_array(row, layout)
            # points of the grid that each residual is part of
            weight = [(d - x - np.arange(s)).reshape([-1 if b == a else 1 for b in range(len(shape))]) for a, (x, s, d) in enumerate(zip(lo, shape, dims))]
            if largest(p) * float(np.prod([float(d) for d in dims])) * p.size < SAFE:
                for w in weight:
                    p = p * w
                return p.size, int(p.sum()), 0
            for w in weight:
                p = p.astype(object) * w.astype(object)
            return p.size, int(p.sum()), 0

        rows = container
    elif stage == RESID and kind.predictor != "difference":

        def sums(row):
            p, means, _, _ = decoded(row, layout)
            n, m, w = (np.asarray(row[c], np.int64) for c in ("n", "meta", "width"))
            # a constant block needs no residual: its share follows from its mean
            if not (w > 0).any():
                return len(p), exact(n, m), exact(n, m, m)
            return len(p), exact(p) + exact(n, m), exact(p + means, p + means)

        rows = container
    elif stage in (RESID, QUANT):
        rows = with_carries(container, codec, layout, anchor)

        def sums(row):
            q = integers(row, layout, anchor)
            return q.size, exact(q), exact(q, q)

    else:
        raise ValueError(f"moments of integers have no stage {stage}")

    def run(row):
        n, s1, s2 = sums(row)
        yield {"field": row["field"], "eps": row["eps"], "n": n, "s1": s1, "s2": s2}

    part = kernel(rows, run, "field string, eps double, n bigint, s1 decimal(38,0), s2 decimal(38,0)")
    return part.groupBy("field", "eps").agg(F.sum("n").alias("n"), whole("s1").alias("s1"), whole("s2").alias("s2"))


def mean_result() -> Column:
    return F.col("s1").cast("double") / F.col("n") * (2 * F.col("eps"))


def sd_result() -> Column:
    n = F.col("n").cast("decimal(20,0)")
    numerator = (n * F.col("s2").cast("decimal(30,0)") - F.col("s1").cast("decimal(19,0)") * F.col("s1").cast("decimal(19,0)")).cast("double")
    return F.when(F.col("n") > 1, F.sqrt(numerator / (F.col("n").cast("double") * (F.col("n") - 1).cast("double"))) * (2 * F.col("eps")))


def expansion(values: list[float]) -> list[float]:
    """A few doubles, largest first, whose sum is exactly that of ``values``."""
    out: list[float] = []
    while rest := math.fsum([*values, *(-x for x in out)]):
        out.append(rest)
    return out


def value_sums(chunks: DataFrame) -> DataFrame:
    """(field, n, s): count and sum of the doubles in ``data``; the sum is exact until it is rounded once, last, whatever the order."""

    def part(batches):
        held: dict[str, tuple[int, list[float]]] = {}
        for row in rows_of(batches):
            n, parts = held.get(row["field"], (0, []))
            held[row["field"]] = n + len(row["data"]), expansion(row["data"].tolist() + parts)
        if held:
            yield pa.RecordBatch.from_pylist([{"field": f, "n": n, "parts": parts} for f, (n, parts) in held.items()], schema=pa.schema([("field", pa.string()), ("n", pa.int64()), ("parts", pa.list_(pa.float64()))]))

    def whole_sum(row):
        yield {"field": row["field"], "n": row["n"], "s": math.fsum(row["parts"])}

    each = chunks.select("field", "data").mapInArrow(part, "field string, n bigint, parts array<double>")
    return kernel(each.groupBy("field").agg(F.sum("n").alias("n"), F.flatten(F.collect_list("parts")).alias("parts")), whole_sum, "field string, n bigint, s double")


def micro(value: Column) -> Column:
    """Sums of doubles depend on their order in the last bits: results of VALUE are given in millionths."""
    return F.round(value * 1e6).cast("bigint")


def field_mean(container: DataFrame, codec: str, layout: Layout, stage: str = "auto", anchor: str = "grid") -> DataFrame:
    """(field, n, int_num, result): the mean; VALUE gives (field, n, result_micro)."""
    stage = (META if META in CODECS[codec].stages else RESID if RESID in CODECS[codec].stages else VALUE) if stage == "auto" else stage
    require(codec, stage, "mean") if stage != QUANT else None
    if stage == VALUE:
        return value_sums(partial_decompress(container, codec, layout, VALUE, anchor)).select("field", "n", micro(F.col("s") / F.col("n")).alias("result_micro"))
    m = moments(container, codec, layout, stage, anchor, squares=False)
    return m.select("field", "n", F.col("s1").cast("bigint").alias("int_num"), mean_result().alias("result"))


def field_stddev(container: DataFrame, codec: str, layout: Layout, stage: str = "auto", center: str = "exact", anchor: str = "grid") -> DataFrame:
    """(field, n, result): the sample standard deviation; null for one point.

    ``center='rounded'`` (mean codecs at RESID) takes squares about the mean rounded to an integer.
    """
    stage = (RESID if RESID in CODECS[codec].stages else VALUE) if stage == "auto" else stage
    require(codec, stage, "sd") if stage != QUANT else None
    if stage == VALUE:
        v = partial_decompress(container, codec, layout, VALUE, anchor).select("field", F.explode("data").alias("v"))
        return v.groupBy("field").agg(F.count("v").alias("n"), micro(F.stddev_samp("v")).alias("result_micro"))
    m = moments(container, codec, layout, stage, anchor)
    if center == "rounded":
        middle = moments(container, codec, layout, META, squares=False).select("field", F.ceil(F.col("s1").cast("double") / F.col("n") - 0.5).cast("bigint").alias("mid"))
        m = m.join(F.broadcast(middle), "field")
        mid = F.col("mid").cast("decimal(19,0)")
        square = F.col("s2").cast("decimal(30,0)") - 2 * mid * F.col("s1").cast("decimal(19,0)") + F.col("n").cast("decimal(19,0)") * mid * mid
        return m.select("field", "n", (F.sqrt(square.cast("double") / (F.col("n") - 1)) * (2 * F.col("eps"))).alias("result"))
    return m.select("field", "n", sd_result().alias("result"))


def extremes(container: DataFrame, codec: str, layout: Layout, anchor: str = "grid") -> DataFrame:
    """(field, min_q, max_q, result_min, result_max); mean codecs read residuals, others integers."""
    stage = RESID if CODECS[codec].predictor == "mean" else QUANT
    q = partial_decompress(container, codec, layout, stage, anchor)
    data = F.zip_with("data", "means", lambda p, m: p + m) if stage == RESID else F.col("data")
    e = q.select("field", "eps", F.array_min(data).alias("a"), F.array_max(data).alias("b")).groupBy("field", "eps").agg(F.min("a").alias("min_q"), F.max("b").alias("max_q"))
    return e.select("field", "min_q", "max_q", (F.col("min_q") * (2 * F.col("eps"))).alias("result_min"), (F.col("max_q") * (2 * F.col("eps"))).alias("result_max"))
