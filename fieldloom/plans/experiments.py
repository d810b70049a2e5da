"""Queries over containers: generic operators, boundary modes, operation errors, bias bounds, and the grid of ratios."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fieldloom.functions.quantise import quantised
from fieldloom.model import BLOCKS, CODECS, META, QUANT, RESID, VALUE, ErrorBound
from fieldloom.operators import differential as dif
from fieldloom.operators import generic
from fieldloom.operators import statistics as sta
from fieldloom.operators.chunks import flatten_grid, to_chunks
from fieldloom.operators.codecs import compress_chunks, compress_points
from fieldloom.plans import measures, oracle
from fieldloom.plans.workloads import REL, derived, packed, ready, short, stages_of
from fieldloom.sources.fields import FIELDS

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
STAGED = ("chain1d", "mean1d", "lorenzo", "meannd")
BOUNDS = (1e-1, 1e-2, 1e-3, 1e-4, 1e-5)
RATIO_FIELDS = ("emb", "ord_price2", "evt_grid", "evt_cube", "part_price3", "line_price", "line_qty", "line_disc", "line_tax", "line_cube_price", "line_cube_qty")


def add(name: str, query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        ORACLES[name] = sql


def union(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def container(name: str, codec: str, spark: SparkSession, sf: str, rel: float = REL):
    """(container, codec, layout) of a field."""
    f = FIELDS[name]
    return packed(f, codec, spark, sf, rel), codec, f.layout(CODECS[codec].flat)


# generic operators

NINE = {(a, b): 1 if a or b else -8 for a in (-1, 0, 1) for b in (-1, 0, 1)}
SEVEN = {(0, 0, 0): 5, (1, 0, 0): 2, (-1, 0, 0): -1, (0, 1, 0): 3, (0, -1, 0): -2, (0, 0, 1): 1, (0, 0, -1): 4}
BOXES = {
    2: ((1, (10, 5), (200, 40)), (2, (0, 0), (7, 7)), (3, (16, 8), (31, 23)), (4, (3, 2), (3, 2)), (5, (5000, 0), (6000, 9))),
    3: ((1, (1, 0, 1), (6, 7, 2)), (2, (0, 0, 0), (3, 3, 3)), (3, (4, 2, 0), (4, 2, 0))),
}


def stencil_sql(name: str, weights: dict) -> str:
    offsets = ", ".join(str((*o, *(0,) * (3 - len(o)), w)) for o, w in weights.items())
    return f"""WITH {oracle.base(name, REL)}, o(di, dj, dk, w) AS (VALUES {offsets}),
s AS (SELECT x.i, x.j, x.k, any_value(x.eps) AS eps, CAST(sum(w * y.q) AS BIGINT) AS s, count(*) AS n FROM q x, o JOIN q y ON y.i = x.i + di AND y.j = x.j + dj AND y.k = x.k + dk GROUP BY x.i, x.j, x.k)
SELECT '{name}' AS field, i, j, k, s, s * (2 * eps) AS result FROM s WHERE n = {len(weights)}"""


def boxes_frame(spark: SparkSession, ndim: int) -> DataFrame:
    return spark.createDataFrame([(i, list(a), list(b)) for i, a, b in BOXES[ndim]], "id bigint, lo array<bigint>, hi array<bigint>")


def regional_sql(name: str) -> str:
    n = FIELDS[name].ndim
    rows = ", ".join(str((i, *a, *(0,) * (3 - n), *b, *(0,) * (3 - n))) for i, a, b in BOXES[n])
    sd = "CASE WHEN count(*) > 1 THEN sqrt(CAST(count(*) * sum(q * q) - sum(q) * sum(q) AS DOUBLE) / (CAST(count(*) AS DOUBLE) * CAST(count(*) - 1 AS DOUBLE))) * (2 * any_value(eps)) END"
    return f"""WITH {oracle.base(name, REL)}, x(id, a0, a1, a2, b0, b1, b2) AS (VALUES {rows})
SELECT CAST(id AS BIGINT) AS id, count(*) AS n, CAST(sum(q) AS BIGINT) AS s1, CAST(sum(q) AS DOUBLE) / count(*) * (2 * any_value(eps)) AS mean, {sd} AS sd,
 min(q) * (2 * any_value(eps)) AS lowest, max(q) * (2 * any_value(eps)) AS highest
FROM x JOIN q ON i BETWEEN a0 AND b0 AND j BETWEEN a1 AND b1 AND k BETWEEN a2 AND b2 GROUP BY id"""


def cells_sql(name: str, level: float) -> str:
    n = FIELDS[name].ndim
    offsets = ", ".join(str((a, b, c)) for a in (0, 1) for b in (0, 1) for c in ((0, 1) if n == 3 else (0,)))
    return f"""WITH {oracle.base(name, REL)}, o(di, dj, dk) AS (VALUES {offsets}),
s AS (SELECT x.i, x.j, x.k, min(y.q) AS lo, max(y.q) AS hi, count(*) AS n, ceil(CAST({level!r} AS DOUBLE) / (2 * any_value(x.eps))) AS cut FROM q x, o JOIN q y ON y.i = x.i + di AND y.j = x.j + dj AND y.k = x.k + dk GROUP BY x.i, x.j, x.k)
SELECT '{name}' AS field, i, j, k FROM s WHERE n = {2**n} AND lo < cut AND hi >= cut"""


def halo_sql(name: str, codec: str, factor: float) -> str:
    if META in CODECS[codec].stages:
        key = oracle.block_key(codec, FIELDS[name].ndim)
        mean = f"m AS (SELECT CAST(sum(x) AS DOUBLE) AS s, CAST(sum(c) AS BIGINT) AS n FROM (SELECT CAST(ceil(CAST(sum(q) AS DOUBLE) / count(*) - 0.5) AS BIGINT) * count(*) AS x, count(*) AS c FROM q GROUP BY {key}))"
    else:
        mean = "m AS (SELECT CAST(sum(q) AS DOUBLE) AS s, count(*) AS n FROM q)"
    return f"WITH {oracle.base(name, REL)}, {mean} SELECT '{name}' AS field, i, j, k, q FROM q, m WHERE q > CAST({factor!r} AS DOUBLE) * s / n"


def block_sql(name: str, codec: str) -> str:
    b = BLOCKS[FIELDS[name].ndim]
    key = [f"CAST({x} // {s} AS BIGINT)" for x, s in zip("ijk", b)] + ["CAST(0 AS BIGINT)"] * (3 - len(b))
    return f"WITH {oracle.base(name, REL)} SELECT '{name}' AS field, {', '.join(f'{e} AS b{x}' for x, e in zip('ijk', key))}, count(*) AS n, CAST(sum(q) AS BIGINT) AS s, min(q) AS lo, max(q) AS hi FROM q GROUP BY 1, 2, 3, 4"


def generic_queries() -> None:
    for codec, name, weights in (("meannd", "emb", NINE), ("lorenzo", "part_price", NINE), ("lorenzo", "evt_cube", SEVEN), ("meannd", "part_price3", SEVEN)):
        add(f"stencil_{len(weights)}pt_{codec}_{name}", lambda s, d, c=codec, n=name, w=weights: generic.stencil(*container(n, c, s, d), w), stencil_sql(name, weights))
    for codec in ("meannd", "lorenzo"):
        sql = f"WITH {oracle.base('emb_u', REL, '0')}, {oracle.base('emb_v', REL, '1')} SELECT i, j, k, CAST(3 AS DOUBLE) * (a.q * (2 * a.eps)) + CAST(-2 AS DOUBLE) * (b.q * (2 * b.eps)) AS result FROM q0 a JOIN q1 b USING (i, j, k)"
        add(f"lincomb_{codec}_uv", lambda s, d, c=codec: generic.linear_combination([container(n, c, s, d) for n in ("emb_u", "emb_v")], [3, -2]), sql)
    for codec, name in (("meannd", "emb"), ("lorenzo", "part_price"), ("lorenzo", "part_price3")):
        add(f"block_agg_{codec}_{name}", lambda s, d, c=codec, n=name: generic.block_aggregate(*container(n, c, s, d)), block_sql(name, codec))
    for codec, name in (("meannd", "emb"), ("lorenzo", "ord_price2"), ("meannd", "evt_cube"), ("lorenzo", "part_price3")):
        add(f"regional_{codec}_{name}", lambda s, d, c=codec, n=name: generic.regional(*container(n, c, s, d), boxes_frame(s, FIELDS[n].ndim)), regional_sql(name))
    for codec, name, level in (("meannd", "emb", 0.1), ("lorenzo", "part_price", 930.0), ("lorenzo", "evt_cube", 60.0)):
        add(f"isosurface_{codec}_{name}", lambda s, d, c=codec, n=name, v=level: generic.isosurface_cells(*container(n, c, s, d), v), cells_sql(name, level))
    for codec, name, factor in (("meannd", "ord_price2", 1.9), ("lorenzo", "part_price", 1.03), ("mean1d", "evt_value", 4.0)):
        add(f"halo_points_{codec}_{name}", lambda s, d, c=codec, n=name, x=factor: generic.halo_points(*container(n, c, s, d), x), halo_sql(name, codec, factor))
    for codec, name in (("chain1d", "ord_price"), ("lorenzo", "part_price")):
        sql = f"WITH {oracle.base(name, REL)}, {oracle.residual(codec, FIELDS[name].ndim)} SELECT p, count(*) AS c FROM r GROUP BY p"

        def counts(s, d, c=codec, n=name):
            box, _, layout = container(n, c, s, d)
            return generic.symbol_counts(box, layout)

        add(f"symbol_counts_{codec}_{name}", counts, sql)
    for codec in CODECS:
        n = FIELDS["part_price"].ndim
        sql = f"WITH {oracle.base('part_price', 1e-1)}, {oracle.residual(codec, n)}, {oracle.widths(codec, n)} SELECT count(*) AS blocks, CAST(sum(CASE WHEN width = 0 THEN 1 ELSE 0 END) AS BIGINT) AS constant FROM w"

        def constant(s, d, c=codec):
            w = measures.width_histogram(container("part_price", c, s, d, 1e-1)[0])
            return w.agg(F.sum("blocks").alias("blocks"), F.sum(F.when(F.col("width") == 0, F.col("blocks")).otherwise(0)).alias("constant"))

        add(f"const_blocks_{codec}_part_price", constant, sql)
    add("sd_constblock_part_price", lambda s, d: sta.field_stddev(*container("part_price", "meannd", s, d, 1e-1), RESID), oracle.sd_sql("part_price", "meannd", RESID, 1e-1))


# boundary modes of derivatives


def boundary_sql(name: str, stage: str, mode: str) -> str:
    n = FIELDS[name].ndim
    cols = []
    for a, x in enumerate("ijk"[:n]):
        w = f"(PARTITION BY {', '.join(b for b in 'ijk' if b != x)} ORDER BY {x} ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)"
        lag, lead = f"lag(v) OVER {w}", f"lead(v) OVER {w}"
        if mode == "periodic":
            lag, lead = f"coalesce({lag}, last_value(v) OVER {w})", f"coalesce({lead}, first_value(v) OVER {w})"
        elif mode == "clamp":
            lag, lead = f"coalesce({lag}, v)", f"coalesce({lead}, v)"
        cols.append(f"{lag} AS l{a}, {lead} AS h{a}")
    v = "CAST(q AS DOUBLE) * (2 * eps)" if stage == VALUE else "q"
    out = []
    for a in range(n):
        both = f"(h{a} - l{a}) / 2" if stage == VALUE else f"h{a} - l{a}"
        if mode == "one_sided":
            k = "" if stage == VALUE else "2 * "
            both = f"CASE WHEN l{a} IS NULL AND h{a} IS NULL THEN 0 WHEN l{a} IS NULL THEN {k}(h{a} - v) WHEN h{a} IS NULL THEN {k}(v - l{a}) ELSE {both} END"
        out.append(f"{both} AS d{'xyz'[a]}" + ("" if stage == VALUE else f", ({both}) * (1 * eps) AS d{'xyz'[a]}_value"))
    return f"WITH {oracle.base(name, REL)}, t AS (SELECT i, j, k, eps, {v} AS v FROM q), s AS (SELECT i, j, k, eps, v, {', '.join(cols)} FROM t) SELECT '{name}' AS field, i, j, k, {', '.join(out)} FROM s"


def boundary_queries() -> None:
    cases = [("meannd", RESID, "evt_grid", m) for m in dif.BOUNDARIES[1:]]
    cases += [("lorenzo", RESID, "part_price", m) for m in ("null", "clamp", "one_sided")] + [("lorenzo", QUANT, "part_price", "periodic")]
    cases += [("mean1d", QUANT, "ord_price2", m) for m in ("periodic", "one_sided")] + [("lorenzo", VALUE, "evt_cube", m) for m in ("clamp", "one_sided")]
    for codec, stage, name, mode in cases:
        f = FIELDS[name]

        def run(s, d, f=f, c=codec, g=stage, m=mode):
            out = derived(f, c, g, s, d, m)
            return out.drop("lap") if g == VALUE else dif.gradient(out, f.ndim)

        add(f"boundary_{mode}_{codec}_{short(stage)}_{name}", run, boundary_sql(name, stage, mode))


# errors of operations against the full flow, the worst over the stages


def worst_scalar(results: list[DataFrame], full: DataFrame) -> DataFrame:
    """(stages, worst_ppm): the largest relative deviation of ``result`` from the full flow's, in millionths."""
    many = union([r.select("field", "result") for r in results])
    error = F.abs(F.col("result") - F.col("full")) / F.abs(F.col("full"))
    return many.join(F.broadcast(full), "field").agg(F.count("*").alias("stages"), F.round(F.max(error) * 1e6).cast("bigint").alias("worst_ppm"))


def worst_field(results: list[DataFrame], full: DataFrame) -> DataFrame:
    """(points, worst_ppm): the largest deviation at any point over the range of the full flow's result, in millionths."""
    span = full.agg((F.max("result") - F.min("result")).alias("span"))
    out = None
    for r in results:
        e = r.join(full.withColumnRenamed("result", "full"), ["i", "j", "k"]).select(F.abs(F.col("result") - F.col("full")).alias("e"))
        out = e if out is None else out.unionAll(e)
    return out.crossJoin(F.broadcast(span)).agg(F.count("*").alias("points"), F.round(F.max(F.col("e") / F.col("span")) * 1e6).cast("bigint").alias("worst_ppm"))


def full_scalar(name: str, codec: str, spark, sf, op: str) -> DataFrame:
    """The statistic of the decompressed doubles, unrounded."""
    from fieldloom.operators.codecs import partial_decompress

    box, _, layout = container(name, codec, spark, sf)
    v = partial_decompress(box, codec, layout, VALUE).select("field", F.explode("data").alias("v"))
    return v.groupBy("field").agg((F.avg("v") if op == "mean" else F.stddev_samp("v")).alias("full"))


def error_of(op: str, codec: str):
    name, plane = "evt_grid", ("emb_u", "emb_v")

    def run(spark: SparkSession, sf: str) -> DataFrame:
        stages = [g for g in stages_of(codec, op if op in ("mean", "sd") else "gradient") if g != VALUE]
        if op in ("mean", "sd"):
            box = container(name, codec, spark, sf)
            if op == "mean":
                out = [sta.field_mean(*box, g) for g in stages]
            else:  # the form with the rounded centre is the one that deviates
                out = [sta.field_stddev(*box, g, "rounded" if g == RESID and CODECS[codec].predictor == "mean" else "exact") for g in stages]
            return worst_scalar(out, full_scalar(name, codec, spark, sf, op)).select(F.lit(op).alias("op"), F.lit(codec).alias("codec"), "*")
        if op in ("gradient", "laplacian"):
            f, column = FIELDS[name], {"gradient": "dx", "laplacian": "lap"}[op]
            make = (lambda x: dif.gradient(x, f.ndim)) if op == "gradient" else dif.laplacian
            out = [make(derived(f, codec, g, spark, sf)).select("i", "j", "k", F.col(f"{column}_value").alias("result")) for g in stages]
            full = derived(f, codec, VALUE, spark, sf).select("i", "j", "k", F.col(column).alias("result"))
        else:
            make = dif.divergence if op == "divergence" else dif.curl
            out = [make([ready(FIELDS[n], codec, g, spark, sf) for n in plane]) for g in stages]
            full = make([ready(FIELDS[n], codec, VALUE, spark, sf) for n in plane])
        return worst_field(out, full).select(F.lit(op).alias("op"), F.lit(codec).alias("codec"), "*")

    return run


def error_sql(op: str, codec: str) -> str:
    name = "evt_grid"
    head = f"SELECT '{op}' AS op, '{codec}' AS codec"
    stages = [g for g in stages_of(codec, op if op in ("mean", "sd") else "gradient") if g != VALUE]
    if op in ("mean", "sd"):
        full = f"WITH {oracle.base(name, REL)} SELECT {'avg' if op == 'mean' else 'stddev_samp'}(CAST(q AS DOUBLE) * (2 * eps)) AS f FROM q"
        sql = {g: oracle.mean_sql(name, codec, g, REL) if op == "mean" else oracle.sd_sql(name, codec, g, REL, g == RESID and CODECS[codec].predictor == "mean") for g in stages}
        each = " UNION ALL ".join(f"SELECT result FROM ({s})" for s in sql.values())
        return f"{head}, count(*) AS stages, CAST(round(max(abs(result - f) / abs(f)) * 1e6) AS BIGINT) AS worst_ppm FROM ({each}), ({full})"
    if op in ("gradient", "laplacian"):
        kind, column = ("grad", "dx") if op == "gradient" else ("lap", "lap")
        one, full = oracle.derivative_sql(name, QUANT, REL, kind), oracle.derivative_sql(name, VALUE, REL, kind)
        one = f"SELECT i, j, k, {column}_value AS result FROM ({one})"
        full = f"SELECT i, j, k, {column} AS f FROM ({full})"
    else:
        kind, plane = ("div", ["emb_u", "emb_v"]) if op == "divergence" else ("curl", ["emb_u", "emb_v"])
        one, full = oracle.vector_sql(plane, REL, kind), f"SELECT i, j, k, result AS f FROM ({oracle.vector_value_sql(plane, REL, kind)})"
    many = len(stages)
    return f"WITH a AS ({one}), b AS ({full}), r AS (SELECT max(f) - min(f) AS span FROM b) {head}, {many} * count(*) AS points, CAST(round(max(abs(result - f) / span) * 1e6) AS BIGINT) AS worst_ppm FROM a JOIN b USING (i, j, k), r"


def bias_bounds(spark: SparkSession, sf: str) -> DataFrame:
    """(check, field, within): what is proved of the mean from metadata and of the deviation about a rounded centre.

    The deviation's bound is the corrected one: squares exceed the exact form's by n / (n - 1) times the
    square of the centre's offset, which is at most one step of twice the bound.
    """
    out = []
    for codec, name in (("mean1d", "ord_price"), ("meannd", "evt_grid"), ("meannd", "part_price")):
        box, _, layout = container(name, codec, spark, sf)
        eps = box.groupBy("field").agg(F.first("eps").alias("eps"))
        meta, exact = sta.field_mean(box, codec, layout, META).select("field", F.col("result").alias("a")), sta.field_mean(box, codec, layout, QUANT).select("field", F.col("result").alias("b"))
        out.append(meta.join(exact, "field").join(eps, "field").select(F.lit("mean from metadata").alias("check"), "field", (F.abs(F.col("a") - F.col("b")) <= F.col("eps")).alias("within")))
        sd = sta.field_stddev(box, codec, layout, RESID, "rounded").select("field", "n", F.col("result").alias("a")).join(sta.field_stddev(box, codec, layout, RESID).select("field", F.col("result").alias("b")), "field").join(eps, "field")
        extra = F.col("n") / (F.col("n") - 1) * F.pow(2 * F.col("eps"), F.lit(2.0))
        out.append(sd.select(F.lit("deviation about a rounded centre").alias("check"), "field", (F.pow("a", F.lit(2.0)) - F.pow("b", F.lit(2.0)) <= extra * (1 + 1e-9)).alias("within")))
    return union(out)


def bias_sql() -> str:
    each = []
    for codec, name in (("mean1d", "ord_price"), ("meannd", "evt_grid"), ("meannd", "part_price")):
        eps = f"(WITH {oracle.base(name, REL)} SELECT eps FROM e)"
        a, b = (oracle.mean_sql(name, codec, g, REL) for g in (META, QUANT))
        each.append(f"SELECT 'mean from metadata' AS \"check\", a.field, abs(a.result - b.result) <= eps AS within FROM ({a}) a, ({b}) b, {eps}")
        a, b = oracle.sd_sql(name, codec, RESID, REL, True), oracle.sd_sql(name, codec, RESID, REL)
        each.append(f"SELECT 'deviation about a rounded centre', a.field, a.result ** 2 - b.result ** 2 <= a.n / (a.n - 1) * (2 * eps) ** 2 * (1 + 1e-9) FROM ({a}) a, ({b}) b, {eps}")
    return " UNION ALL ".join(each)


def curl_of_gradient(spark: SparkSession, sf: str) -> DataFrame:
    """(points, largest): the curl of a field's gradient, whose components are compressed by different codecs."""
    f = FIELDS["part_price"]
    g = derived(f, "meannd", QUANT, spark, sf).select(F.col("i") - 1, F.col("j") - 1, "k", "d0", "d1").toDF("i", "j", "k", "d0", "d1")
    parts = []
    for n, codec in enumerate(("lorenzo", "meannd")):
        pts = g.select(F.lit(f"g{n}").alias("field"), "i", "j", "k", F.col(f"d{n}").cast("double").alias("value"))
        box = compress_points(pts, codec, ErrorBound(0.5, relative=False), 2, f.chunk)
        parts.append(dif.prepared(box, codec, f.layout(), QUANT))
    return dif.curl(parts).agg(F.count("*").alias("points"), F.max(F.abs("result")).alias("largest"))


def measure_queries() -> None:
    for op in ("mean", "sd", "gradient", "laplacian", "divergence", "curl"):
        for codec in STAGED:
            add(f"operr_{op}_{codec}", error_of(op, codec), error_sql(op, codec))
    add("bias_bounds", bias_bounds, bias_sql())
    grad = oracle.derivative_sql("part_price", QUANT, REL, "grad")
    sql = f"WITH g AS ({grad}), c AS (SELECT i, j, lead(dx) OVER a - lag(dx) OVER a - (lead(dy) OVER b - lag(dy) OVER b) AS r FROM g WINDOW a AS (PARTITION BY i ORDER BY j), b AS (PARTITION BY j ORDER BY i)) SELECT count(*) AS points, max(abs(r)) * CAST(0.5 AS DOUBLE) AS largest FROM c WHERE r IS NOT NULL"
    add("curl_of_gradient_zero", curl_of_gradient, sql)


# ratios: every field, six codecs, five bounds


def ratio_grid(name: str):
    f = FIELDS[name]

    def run(spark: SparkSession, sf: str) -> DataFrame:
        out = []
        for rel in BOUNDS:
            q = quantised(f.points(spark, sf), ErrorBound(rel))
            for flat in (False, True):
                chunks = to_chunks(flatten_grid(q) if flat else q, f.layout(flat))
                for codec in (c for c in CODECS if CODECS[c].flat == flat):
                    r = measures.ratio(compress_chunks(chunks, codec, f.layout(flat)), codec)
                    out.append(r.select("field", "codec", F.lit(rel).alias("bound"), "raw_bytes", "bytes", "ratio"))
        return union(out)

    return run


def ratio_grid_sql(name: str) -> str:
    n = FIELDS[name].ndim
    each = []
    for rel in BOUNDS:
        for codec in CODECS:
            part = f"WITH {oracle.base(name, rel)}, {oracle.residual(codec, n)}, {oracle.widths(codec, n)}, c AS (SELECT CAST(sum(s) * 4 AS BIGINT) AS raw_bytes, {oracle.bytes_sql(codec)} AS bytes FROM w)"
            each.append(f"SELECT * FROM ({part} SELECT '{name}' AS field, '{codec}' AS codec, CAST({rel!r} AS DOUBLE) AS bound, raw_bytes, bytes, CAST(raw_bytes AS DOUBLE) / bytes AS ratio FROM c)")
    return " UNION ALL ".join(each)


def ratio_queries() -> None:
    for name in RATIO_FIELDS:
        add(f"ratio_grid_{name}", ratio_grid(name), ratio_grid_sql(name))
    for name in ("poly2d", "poly3d"):  # smooth fields over the orders
        add(f"ratio_grid_{name}", ratio_grid(f"ord_{name}"), ratio_grid_sql(f"ord_{name}"))


# the scalar-operation baseline and the cube of lineitem


def baseline_queries() -> None:
    for name in ("emb", "evt_cube", "line_price", "line_cube_price"):
        for op, make, sql in (("mean", sta.field_mean, oracle.mean_sql), ("sd", sta.field_stddev, oracle.sd_sql)):
            add(f"{op}_quantop_{name}", lambda s, d, n=name, m=make: m(*container(n, "blockdiff", s, d), QUANT), sql(name, "blockdiff", QUANT, REL))
    for codec in ("lorenzo", "meannd"):
        for stage in stages_of(codec, "mean"):
            add(f"mean_{codec}_{short(stage)}_line_cube_price", lambda s, d, c=codec, g=stage: sta.field_mean(*container("line_cube_price", c, s, d), g), oracle.mean_sql("line_cube_price", codec, stage, REL))
        for stage in stages_of(codec, "sd"):
            add(f"sd_{codec}_{short(stage)}_line_cube_price", lambda s, d, c=codec, g=stage: sta.field_stddev(*container("line_cube_price", c, s, d), g), oracle.sd_sql("line_cube_price", codec, stage, REL))


generic_queries()
boundary_queries()
measure_queries()
ratio_queries()
baseline_queries()
