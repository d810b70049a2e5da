"""Which stage and which codec: a cost model over stages, and advice by use."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import functions as F

from fieldloom.functions.quantise import grid_facts
from fieldloom.model import CODECS, META, QUANT, RESID, STAGES, VALUE, ErrorBound
from fieldloom.plans import oracle
from fieldloom.sources.fields import FIELDS

REL = 1e-3
ADVISED = ("ord_price2", "ord_price3")
STATISTICS, MOVING = ("mean", "sd"), ("gradient", "laplacian", "divergence", "curl")

# Relative costs a point, in units of reading one encoded byte; calibrate on a cluster.
DECODE, RESTORE, SCAN, SCALE = 1.0, 0.1, 1.2, 0.4
SHUFFLE = 3.0


def supports(codec: str, stage: str, operation: str) -> bool:
    c = CODECS[codec]
    if stage not in c.stages or stage == META and operation != "mean":
        return False
    return not (operation in ("gradient", "laplacian", "divergence", "curl") and c.flat and stage == RESID)


def cost(codec: str, stage: str, operation: str, ndim: int, bytes_per_point: float = 1.0, block: int = 64, face: float = 0.05) -> float:
    """Expected cost a point of an operation at a stage: decompress, operate, and move faces or carries."""
    if stage == META:
        return 5.0 / block
    moving = operation in ("gradient", "laplacian", "divergence", "curl")
    differences = CODECS[codec].predictor == "difference"
    t = bytes_per_point + DECODE
    if stage in (QUANT, VALUE):
        t += SCAN * ndim + SHUFFLE * face if differences else RESTORE
    elif differences and operation != "mean":
        # prefix sums over the other axes only, for each axis that the operation differentiates along
        t += SCAN * (ndim * (ndim - 1) if moving else ndim) + SHUFFLE * face * ((ndim - 1) * 0.8 if moving else 1)
    if stage == VALUE:
        t += SCALE
    if moving:
        t += ndim * 0.5 + SHUFFLE * face * (2 if stage == RESID and not differences else 1)
        t += SCALE if stage == VALUE else 0
    return t


def choose_stage(codec: str, operation: str, ndim: int) -> str:
    """The cheapest stage that supports the operation."""
    return min((s for s in STAGES if supports(codec, s, operation)), key=lambda s: cost(codec, s, operation, ndim))


def recommend_codec(use: str, ndim: int, priority: str = "throughput") -> str:
    """A codec for a class of use: 'statistics', 'differential' or 'vector'."""
    if use == "statistics":
        return "meannd"
    if ndim <= 2 or priority == "ratio":
        return "lorenzo"
    return "meannd"


def stage_support(spark, sf_dir):
    """(codec, operation, stage, eps, points): the support matrix for the plane of orders, with its bound and how many points an operation answers for."""
    rows = [(c, o, s) for c in CODECS for o in (*STATISTICS, *MOVING) for s in STAGES if supports(c, s, o)]
    facts = grid_facts(FIELDS["ord_price2"].points(spark, sf_dir), ErrorBound(REL)).select("eps", "n_points", ((F.col("d0") - 2) * (F.col("d1") - 2)).alias("inner"))
    matrix = spark.createDataFrame(rows, "codec string, operation string, stage string").crossJoin(F.broadcast(facts))
    return matrix.select("codec", "operation", "stage", "eps", F.when(F.col("operation").isin(*MOVING), F.col("inner")).otherwise(F.col("n_points")).alias("points"))


def advise(spark, sf_dir):
    """(field, use, ndim, priority, codec, stage, eps, points): advice for fields of orders by the axes that each has, with its bound and points."""
    facts = [grid_facts(FIELDS[n].points(spark, sf_dir), ErrorBound(REL)) for n in ADVISED]
    facts = reduce(lambda a, b: a.union(b), facts).select("field", sum(F.when(F.col(f"d{a}") > 1, 1).otherwise(0) for a in range(3)).alias("ndim"), "eps", F.col("n_points").alias("points"))
    rows = [(u, n, p, recommend_codec(u, n, p), choose_stage(recommend_codec(u, n, p), {"statistics": "sd", "differential": "gradient", "vector": "curl"}[u], n)) for u in ("statistics", "differential", "vector") for n in (2, 3) for p in ("throughput", "ratio")]
    advice = spark.createDataFrame(rows, "use string, ndim int, priority string, codec string, stage string")
    return facts.join(F.broadcast(advice), "ndim").select("field", "use", "ndim", "priority", "codec", "stage", "eps", "points")


def advice_sql() -> str:
    """The advice written out by axes, use and priority, for the axes that a field of orders has."""
    rows = []
    for priority in ("throughput", "ratio"):
        rows += [(2, "statistics", priority, "meannd", "RESID"), (3, "statistics", priority, "meannd", "RESID")]
        rows += [(2, u, priority, "lorenzo", "RESID") for u in ("differential", "vector")]
        rows += [(3, u, priority, "lorenzo" if priority == "ratio" else "meannd", "QUANT") for u in ("differential", "vector")]
    facts = " UNION ALL ".join(f"SELECT * FROM (WITH {oracle.base(n, REL)} SELECT '{n}' AS field, CAST((d0 > 1) AS INTEGER) + CAST((d1 > 1) AS INTEGER) + CAST((d2 > 1) AS INTEGER) AS ndim, eps, (SELECT count(*) FROM p) AS points FROM e)" for n in ADVISED)
    return f"SELECT field, \"use\", ndim, priority, codec, stage, eps, points FROM ({facts}) JOIN (VALUES {', '.join(map(str, rows))}) t(ndim, \"use\", priority, codec, stage) USING (ndim)"


def support_sql() -> str:
    """The support matrix, written out from the table of stages by codec and operation."""
    rows = []
    for codec in ("chain1d", "lorenzo", "mean1d", "meannd"):
        stat = ["RESID", "QUANT", "VALUE"]
        rows += [(codec, "mean", s) for s in (["META"] if codec.startswith("mean") else []) + stat]
        rows += [(codec, "sd", s) for s in stat]
        rows += [(codec, o, s) for o in ("gradient", "laplacian", "divergence", "curl") for s in (stat if codec in ("lorenzo", "meannd") else stat[1:])]
    rows += [(c, o, "VALUE") for c in ("blockdiff", "midrange") for o in ("mean", "sd", "gradient", "laplacian", "divergence", "curl")]
    matrix = "(VALUES " + ", ".join(map(str, rows)) + ") t(codec, operation, stage)"
    points = "CASE WHEN operation IN ('mean', 'sd') THEN n ELSE (d0 - 2) * (d1 - 2) END"
    return f"WITH {oracle.base('ord_price2', REL)}, f AS (SELECT any_value(eps) AS eps, count(*) AS n, any_value(d0) AS d0, any_value(d1) AS d1 FROM q) SELECT codec, operation, stage, eps, CAST({points} AS BIGINT) AS points FROM {matrix}, f"


QUERIES = {"stage_support": stage_support, "advise_codec": advise}
ORACLES = {"stage_support": support_sql(), "advise_codec": advice_sql()}
