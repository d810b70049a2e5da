"""The experiment workloads on the given tables, one query for each method, variant, baseline and measure."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fieldloom.functions.quantise import dequantise, grid_facts, quantised
from fieldloom.model import CODECS, META, QUANT, RESID, VALUE, ErrorBound
from fieldloom.operators import differential as dif
from fieldloom.operators import statistics as sta
from fieldloom.operators.codecs import compress_points, partial_decompress, to_points
from fieldloom.plans import measures, oracle
from fieldloom.sources.fields import FIELDS, Field

REL = 1e-3
Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def add(name: str, query: Query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        ORACLES[name] = sql


def packed(f: Field, codec: str, spark: SparkSession, sf: str, rel: float = REL, anchor: str = "grid") -> DataFrame:
    return compress_points(f.points(spark, sf), codec, ErrorBound(rel), f.ndim, f.layout(CODECS[codec].flat).chunk, anchor)


def extents(f: Field, spark: SparkSession, sf: str) -> tuple[int, ...]:
    row = grid_facts(f.points(spark, sf), ErrorBound(REL)).first()
    return tuple(row[f"d{a}"] for a in range(f.ndim))


def short(stage: str) -> str:
    return stage.lower()


def stages_of(codec: str, operation: str) -> list[str]:
    if CODECS[codec].stages == (VALUE,):
        return [VALUE]
    if operation == "mean":
        return list(CODECS[codec].stages)
    if operation == "sd":
        return [s for s in CODECS[codec].stages if s != META]
    return [QUANT, VALUE] if CODECS[codec].flat else [RESID, QUANT, VALUE]


def ready(f: Field, codec: str, stage: str, spark: SparkSession, sf: str, boundary: str = "interior") -> dif.Ready:
    flat = CODECS[codec].flat and f.ndim > 1
    dims = extents(f, spark, sf) if flat else None
    return dif.prepared(packed(f, codec, spark, sf), codec, f.layout(CODECS[codec].flat), stage, boundary=boundary, dims=dims, work=f.layout())


def derived(f: Field, codec: str, stage: str, spark: SparkSession, sf: str, boundary: str = "interior") -> DataFrame:
    """Derivatives of a field, point by point; for VALUE as doubles dx, dy, dz, lap."""
    d = dif.stencilled(ready(f, codec, stage, spark, sf, boundary))
    return d if stage != VALUE else d.select("field", "i", "j", "k", *[F.col(f"d{a}").alias("dx dy dz".split()[a]) for a in range(f.ndim)], "lap")


def statistic_queries() -> None:
    flat_fields, grids = ("ord_price", "cust_bal", "evt_value", "line_price"), ("emb", "evt_grid", "evt_cube", "part_price")
    for codecs, fields in ((("chain1d", "mean1d"), flat_fields), (("lorenzo", "meannd"), grids), (("blockdiff", "midrange"), ("ord_price", "emb"))):
        for codec in codecs:
            for name in fields:
                f = FIELDS[name]
                for stage in stages_of(codec, "mean"):
                    add(f"mean_{codec}_{short(stage)}_{name}", lambda s, d, f=f, c=codec, g=stage: sta.field_mean(packed(f, c, s, d), c, f.layout(CODECS[c].flat), g), oracle.mean_sql(name, codec, stage, REL))
                for stage in stages_of(codec, "sd"):
                    add(f"sd_{codec}_{short(stage)}_{name}", lambda s, d, f=f, c=codec, g=stage: sta.field_stddev(packed(f, c, s, d), c, f.layout(CODECS[c].flat), g), oracle.sd_sql(name, codec, stage, REL))
    for codec, name in (("mean1d", "ord_price"), ("meannd", "emb"), ("meannd", "part_price")):
        f = FIELDS[name]
        add(f"sd_rounded_{codec}_{name}", lambda s, d, f=f, c=codec: sta.field_stddev(packed(f, c, s, d), c, f.layout(CODECS[c].flat), RESID, "rounded"), oracle.sd_sql(name, codec, RESID, REL, True))
    # the scalar-operation baseline works on the quantised integers of the predecessor codec
    f = FIELDS["ord_price"]
    add("mean_quantop_ord_price", lambda s, d, f=f: sta.field_mean(packed(f, "blockdiff", s, d), "blockdiff", f.layout(True), QUANT), oracle.mean_sql("ord_price", "blockdiff", QUANT, REL))
    add("sd_quantop_ord_price", lambda s, d, f=f: sta.field_stddev(packed(f, "blockdiff", s, d), "blockdiff", f.layout(True), QUANT), oracle.sd_sql("ord_price", "blockdiff", QUANT, REL))
    for codec, name in (("chain1d", "ord_price"), ("lorenzo", "emb")):
        f = FIELDS[name]
        add(f"mean_{codec}_chunk_anchor_{name}", lambda s, d, f=f, c=codec: sta.field_mean(packed(f, c, s, d, anchor="chunk"), c, f.layout(CODECS[c].flat), VALUE, "chunk"), oracle.mean_sql(name, codec, VALUE, REL))
    for codec, name in (("meannd", "emb"), ("lorenzo", "part_price"), ("mean1d", "cust_bal")):
        f = FIELDS[name]
        sql = f"WITH {oracle.base(name, REL)} SELECT '{name}' AS field, min(q) AS min_q, max(q) AS max_q, min(q) * (2 * any_value(eps)) AS result_min, max(q) * (2 * any_value(eps)) AS result_max FROM q"
        add(f"minmax_{codec}_{name}", lambda s, d, f=f, c=codec: sta.extremes(packed(f, c, s, d), c, f.layout(CODECS[c].flat)), sql)


def differential_queries() -> None:
    cases = [(c, n) for c in ("lorenzo", "meannd") for n in ("emb", "part_price", "part_price3", "evt_cube")] + [(c, "ord_price2") for c in ("chain1d", "mean1d")] + [("blockdiff", "part_price"), ("midrange", "part_price")]
    for codec, name in cases:
        f = FIELDS[name]
        for stage in stages_of(codec, "gradient"):
            run = lambda s, d, f=f, c=codec, g=stage: derived(f, c, g, s, d)
            grad = (lambda s, d, r=run: r(s, d).drop("lap")) if stage == VALUE else (lambda s, d, r=run, f=f: dif.gradient(r(s, d), f.ndim))
            lap = (lambda s, d, r=run: r(s, d).drop("dx", "dy", "dz")) if stage == VALUE else (lambda s, d, r=run: dif.laplacian(r(s, d)))
            add(f"grad_{codec}_{short(stage)}_{name}", grad, oracle.derivative_sql(name, stage, REL, "grad"))
            add(f"lap_{codec}_{short(stage)}_{name}", lap, oracle.derivative_sql(name, stage, REL, "lap"))
    f = FIELDS["evt_value"]
    for stage in (RESID, QUANT):
        run = lambda s, d, g=stage: derived(FIELDS["evt_value"], "chain1d", g, s, d)
        add(f"grad1d_chain1d_{short(stage)}_evt_value", lambda s, d, r=run: dif.gradient(r(s, d), 1), oracle.derivative_sql("evt_value", stage, REL, "grad"))
        add(f"lap1d_chain1d_{short(stage)}_evt_value", lambda s, d, r=run: dif.laplacian(r(s, d)), oracle.derivative_sql("evt_value", stage, REL, "lap"))


def vector_queries() -> None:
    plane, cube = ["emb_u", "emb_v"], ["emb3_x", "emb3_y", "emb3_z"]
    for codec in CODECS:
        for fields, tag, where in ((plane, "2", "emb_uv"), (cube, "3", "emb3")):
            for stage in stages_of(codec, "gradient"):
                sql = oracle.vector_value_sql if stage == VALUE else oracle.vector_sql
                parts = lambda s, d, fs=fields, c=codec, g=stage: [ready(FIELDS[n], c, g, s, d) for n in fs]
                add(f"div{tag}_{codec}_{short(stage)}_{where}", lambda s, d, p=parts: dif.divergence(p(s, d)), sql(fields, REL, "div"))
                add(f"curl{tag}_{codec}_{short(stage)}_{where}", lambda s, d, p=parts: dif.curl(p(s, d)), sql(fields, REL, "curl"))
    # components may have different codecs where both have integers
    mixed = lambda s, d: [ready(FIELDS[n], c, QUANT, s, d) for n, c in zip(plane, ("lorenzo", "meannd"))]
    add("div2_mixed_quant_emb_uv", lambda s, d: dif.divergence(mixed(s, d)), oracle.vector_sql(plane, REL, "div"))
    add("curl2_mixed_quant_emb_uv", lambda s, d: dif.curl(mixed(s, d)), oracle.vector_sql(plane, REL, "curl"))
    add("curl2_standard_sign", lambda s, d: dif.curl([ready(FIELDS[n], "meannd", QUANT, s, d) for n in plane], "standard"), oracle.vector_sql(plane, REL, "curl", "standard"))
    div = lambda s, d: dif.divergence([ready(FIELDS[n], "meannd", QUANT, s, d) for n in plane])
    add("divfree_check_emb_uv", lambda s, d: div(s, d).agg(F.count("*").alias("points"), F.max(F.abs("result")).alias("largest"), (F.max(F.abs("result")) <= 1e-6).alias("free")), f"SELECT count(*) AS points, max(abs(result)) AS largest, max(abs(result)) <= 1e-6 AS free FROM ({oracle.vector_sql(plane, REL, 'div')})")
    for codec, stage in (("meannd", QUANT), ("lorenzo", RESID), ("lorenzo", QUANT), ("chain1d", QUANT), ("mean1d", QUANT)):
        add(f"multi_grad_curl_{codec}_{short(stage)}", lambda s, d, c=codec, g=stage: measures.gradients_and_curl([ready(FIELDS[n], c, g, s, d) for n in cube]), measures.multi_sql(cube, REL))


def pipeline_queries() -> None:
    for name in ("emb", "ord_price", "evt_grid"):
        f = FIELDS[name]
        add(f"quantise_{name}", lambda s, d, f=f: quantised(f.points(s, d), ErrorBound(REL)).select("field", "i", "j", "k", "q"), oracle.quantise_sql(name, REL))
        sql = f"WITH {oracle.base(name, REL)} SELECT '{name}' AS field, count(*) AS n, bool_and(abs(CAST(q AS DOUBLE) * (2 * eps) - value) <= eps * (1 + 1e-9)) AS within FROM q"
        add(f"dequantise_bound_{name}", lambda s, d, f=f: quantised(f.points(s, d), ErrorBound(REL)).groupBy("field").agg(F.count("*").alias("n"), F.bool_and(F.abs(dequantise("q", F.col("eps")) - F.col("value")) <= F.col("eps") * (1 + 1e-9)).alias("within")), sql)
    names = ("emb", "ord_price", "cust_bal", "part_price", "evt_value", "evt_grid", "poly2d")
    one = "SELECT '{n}' AS field, eps, CAST(d0 AS BIGINT) AS d0, CAST(d1 AS BIGINT) AS d1, CAST(d2 AS BIGINT) AS d2, (SELECT count(*) FROM p{t}) AS n_points FROM e{t}"
    add("eps_all_fields", lambda s, d: _union([grid_facts(FIELDS[n].points(s, d), ErrorBound(REL)) for n in names]), "WITH " + ", ".join(oracle.base(n, REL, str(t)) for t, n in enumerate(names)) + " " + " UNION ALL ".join(one.format(n=n, t=t) for t, n in enumerate(names)))
    for codec, name in (("chain1d", "ord_price"), ("mean1d", "ord_price"), ("lorenzo", "emb"), ("meannd", "emb"), ("lorenzo", "part_price"), ("meannd", "part_price"), ("lorenzo", "part_price3"), ("meannd", "evt_cube")):
        f = FIELDS[name]
        for stage in (RESID, QUANT, VALUE):
            sql = oracle.residual_sql(name, codec, REL) if stage == RESID else oracle.stage_sql(name, stage, REL)
            add(f"stage_{short(stage)}_{codec}_{name}", lambda s, d, f=f, c=codec, g=stage: to_points(partial_decompress(packed(f, c, s, d), c, f.layout(CODECS[c].flat), g), f.layout(CODECS[c].flat)), sql)
    for codec in ("blockdiff", "midrange"):
        f = FIELDS["ord_price"]
        add(f"stage_value_{codec}_ord_price", lambda s, d, f=f, c=codec: to_points(partial_decompress(packed(f, c, s, d), c, f.layout(True), VALUE), f.layout(True)), oracle.stage_sql("ord_price", VALUE, REL))
    metas = {"mean1d": "CAST(ceil(CAST(sum(q) AS DOUBLE) / count(*) - 0.5) AS BIGINT)", "midrange": "CAST(floor((max(q) + min(q)) / 2.0) AS BIGINT)", "blockdiff": "arg_min(q, g)"}
    for codec, m in metas.items():
        f = FIELDS["ord_price"]
        sql = f"WITH {oracle.base('ord_price', REL)} SELECT CAST(g // 64 AS BIGINT) AS block, {m} AS meta, count(*) AS n FROM q GROUP BY 1"
        per = f.flat_chunk[0] // 64
        add({"mean1d": "block_means_mean1d_ord_price", "midrange": "midranges_ord_price", "blockdiff": "firsts_blockdiff_ord_price"}[codec], lambda s, d, f=f, c=codec: packed(f, c, s, d).select("ci", F.posexplode(F.arrays_zip("meta", "n")).alias("b", "x")).select((F.col("ci") * per + F.col("b")).cast("bigint").alias("block"), "x.meta", "x.n"), sql)
    for codec in CODECS:
        for name in ("part_price", "emb"):
            f = FIELDS[name]
            add(f"widths_{codec}_{name}", lambda s, d, f=f, c=codec: measures.width_histogram(packed(f, c, s, d)), oracle.widths_sql(name, codec, REL))
    for tag, rel in (("1e1", 1e-1), ("1e2", 1e-2), ("1e3", 1e-3), ("1e4", 1e-4), ("1e5", 1e-5)):
        for name in ("part_price", "emb") if tag in ("1e1", "1e3") else ("part_price",):
            f = FIELDS[name]
            for codec in CODECS:
                add(f"ratio_{codec}_{name}_{tag}", lambda s, d, f=f, c=codec, r=rel: measures.ratio(packed(f, c, s, d, r), c), oracle.ratio_sql(name, codec, rel))
    fields = ("ord_price2", "evt_grid", "poly2d")
    each = " UNION ALL ".join(f"SELECT * FROM ({oracle.ratio_sql(n, c, REL)})" for n in fields for c in ("lorenzo", "meannd"))
    add("ratio_all_rollup", lambda s, d: measures.ratio_rollup(_union([measures.ratio(packed(FIELDS[n], c, s, d), c) for n in fields for c in ("lorenzo", "meannd")])), f"SELECT codec, field, CAST(sum(raw_bytes) AS BIGINT) AS raw_bytes, CAST(sum(bytes) AS BIGINT) AS bytes, CAST(sum(raw_bytes) AS DOUBLE) / CAST(sum(bytes) AS DOUBLE) AS ratio FROM ({each}) GROUP BY ROLLUP (codec, field)")
    add("worked_example", measures.worked_example, measures.WORKED_SQL)


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def register() -> None:
    pipeline_queries()
    statistic_queries()
    differential_queries()
    vector_queries()


register()
