"""The SQL surface of the methods: functions, views of a container's stages, a table function, and what SQL asks of them."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fieldloom.functions.bitpack import decode_fixed
from fieldloom.model import CODECS, META, Layout
from fieldloom.operators import statistics as sta
from fieldloom.operators.codecs import partial_decompress, to_points
from fieldloom.plans import oracle
from fieldloom.plans.workloads import REL, packed
from fieldloom.sources.fields import FIELDS

SQL_FUNCTIONS = {
    "fl_quantise": "(v DOUBLE, eps DOUBLE) RETURNS BIGINT RETURN CAST(floor(v / (2 * eps) + 0.5) AS BIGINT)",
    "fl_dequantise": "(q BIGINT, eps DOUBLE) RETURNS DOUBLE RETURN CAST(q AS DOUBLE) * (2 * eps)",
    "fl_block_bytes": "(n BIGINT, width INT, meta INT) RETURNS BIGINT RETURN 1 + meta + CASE WHEN width = 0 THEN 0 ELSE (n + 7) DIV 8 + (n * width + 7) DIV 8 END",
}


def register_functions(spark: SparkSession) -> None:
    """fl_quantise, fl_dequantise and fl_block_bytes as SQL functions, which the optimiser inlines."""
    for name, body in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")


def register_stages(container: DataFrame, name: str, codec: str, layout: Layout) -> None:
    """Views ``name``_meta, _resid, _quant and _value of the stages that the codec has, and ``name``_mean_``stage`` and ``name``_sd_``stage``."""
    for stage in CODECS[codec].stages:
        short = stage.lower()
        rows = partial_decompress(container, codec, layout, stage)
        (rows if stage == META else to_points(rows, layout)).createOrReplaceTempView(f"{name}_{short}")
        sta.field_mean(container, codec, layout, stage).createOrReplaceTempView(f"{name}_mean_{short}")
        if stage != META:
            sta.field_stddev(container, codec, layout, stage).createOrReplaceTempView(f"{name}_sd_{short}")


class DecodeBlocks:
    """Residuals of an encoded chunk: (place in block order, residual)."""

    def eval(self, payload, width, n):
        p = decode_fixed(np.array(width, np.int64), np.array(n, np.int64), bytes(payload))
        for at, value in enumerate(p.tolist()):
            yield at, value


def register_table_function(spark: SparkSession) -> None:
    spark.udtf.register("fl_decode_blocks", F.udtf(DecodeBlocks, returnType="pos int, p bigint"))


def stage_views(spark: SparkSession, sf: str) -> DataFrame:
    f = FIELDS["part_price"]
    register_stages(packed(f, "meannd", spark, sf), "fl_part", "meannd", f.layout())
    return spark.sql("""
        SELECT 'quant' AS stage, count(*) AS n, sum(v) AS total FROM fl_part_quant UNION ALL
        SELECT 'resid', count(*), sum(v) FROM fl_part_resid UNION ALL
        SELECT 'meta', sum(aggregate(n, 0L, (a, x) -> a + x)), sum(aggregate(zip_with(n, meta, (n, m) -> n * m), 0L, (a, x) -> a + x)) FROM fl_part_meta UNION ALL
        SELECT 'mean', n, int_num FROM fl_part_mean_quant""")


def sql_quantise(spark: SparkSession, sf: str) -> DataFrame:
    register_functions(spark)
    FIELDS["ord_price"].points(spark, sf).createOrReplaceTempView("fl_points")
    return spark.sql(f"""
        WITH e AS (SELECT {REL!r}D * (max(value) - min(value)) AS eps FROM fl_points)
        SELECT i, fl_quantise(value, eps) AS q, fl_dequantise(fl_quantise(value, eps), eps) AS v FROM fl_points CROSS JOIN e""")


def block_bytes(spark: SparkSession, sf: str) -> DataFrame:
    register_functions(spark)
    packed(FIELDS["part_price"], "meannd", spark, sf).createOrReplaceTempView("fl_box")
    return spark.sql("SELECT sum(fl_block_bytes(b.n, b.width, 4)) AS bytes, sum(b.n) AS n FROM (SELECT explode(arrays_zip(n, width)) AS b FROM fl_box)")


def decoded_by_table_function(spark: SparkSession, sf: str) -> DataFrame:
    register_table_function(spark)
    packed(FIELDS["part_price"], "lorenzo", spark, sf).createOrReplaceTempView("fl_box")
    return spark.sql("SELECT t.p, count(*) AS c FROM fl_box, LATERAL fl_decode_blocks(payload, width, n) t GROUP BY t.p")


def pivoted(spark: SparkSession, sf: str) -> DataFrame:
    kinds = ["click", "error", "purchase", "signup", "view"]
    events = spark.read.parquet(f"{sf}/events.parquet").select(F.hour("ts").alias("h"), "event_type")
    return events.groupBy("h").pivot("event_type", kinds).count().na.fill(0, kinds)


def quantiles(spark: SparkSession, sf: str) -> DataFrame:
    """Exact quantiles, and whether the sketches' answers are within their promise of the exact ones."""
    q = sql_quantise(spark, sf)
    t = q.agg(F.percentile("q", F.lit(0.25)).alias("q1"), F.percentile("q", F.lit(0.5)).alias("q2"), F.percentile("q", F.lit(0.9)).alias("q9"), F.approx_percentile("q", F.lit(0.5), F.lit(1000)).alias("a2"), F.count_distinct("q").alias("levels"), F.approx_count_distinct("q", 0.02).alias("about"))
    return t.select("q1", "q2", "q9", "levels", (F.abs(F.col("a2") - F.col("q2")) <= 5).alias("median_close"), (F.abs(F.col("about") - F.col("levels")) <= 0.1 * F.col("levels")).alias("levels_close"))


def maps(spark: SparkSession, sf: str) -> DataFrame:
    events = spark.read.parquet(f"{sf}/events.parquet")
    m = F.from_json("props", "map<string,bigint>")
    return events.select("event_id", F.element_at(m, "k").alias("k"), F.size(F.map_keys(m)).alias("keys"), F.element_at(F.map_from_arrays(F.array(F.lit("a"), F.lit("b")), F.array("event_id", "user_id")), "b").alias("user"))


P = oracle.base("part_price", REL)
QUERIES = {
    "rel_r60_stage_views": stage_views, "sql_quantise_ord_price": sql_quantise, "sql_block_bytes_part_price": block_bytes,
    "udtf_decode_part_price": decoded_by_table_function, "rel_r31_pivot_stages": pivoted, "rel_r30_quantiles": quantiles, "rel_r52_maps": maps,
}
ORACLES = {
    "rel_r60_stage_views": f"WITH {P}, m AS (SELECT i // 8 AS a, j // 8 AS b, CAST(ceil(CAST(sum(q) AS DOUBLE) / count(*) - 0.5) AS BIGINT) * count(*) AS x FROM q GROUP BY 1, 2), t AS (SELECT count(*) AS n, CAST(sum(q) AS BIGINT) AS s FROM q), u AS (SELECT CAST(sum(x) AS BIGINT) AS x FROM m) SELECT 'quant' AS stage, n, s AS total FROM t UNION ALL SELECT 'resid', n, s - x FROM t, u UNION ALL SELECT 'meta', n, x FROM t, u UNION ALL SELECT 'mean', n, s FROM t",
    "sql_quantise_ord_price": f"WITH {oracle.base('ord_price', REL)} SELECT i, q, CAST(q AS DOUBLE) * (2 * eps) AS v FROM q",
    "sql_block_bytes_part_price": f"WITH {P}, {oracle.residual('meannd', 2)}, {oracle.widths('meannd', 2)} SELECT {oracle.bytes_sql('meannd')} AS bytes, CAST(sum(s) AS BIGINT) AS n FROM w",
    "udtf_decode_part_price": f"WITH {P}, {oracle.residual('lorenzo', 2)} SELECT p, count(*) AS c FROM r GROUP BY p",
    "rel_r31_pivot_stages": "SELECT CAST(hour(ts) AS INTEGER) AS h, " + ", ".join(f"count(*) FILTER (event_type = '{k}') AS {k}" for k in ("click", "error", "purchase", "signup", "view")) + " FROM events GROUP BY 1",
    "rel_r30_quantiles": f"WITH {oracle.base('ord_price', REL)} SELECT quantile_cont(CAST(q AS DOUBLE), 0.25) AS q1, quantile_cont(CAST(q AS DOUBLE), 0.5) AS q2, quantile_cont(CAST(q AS DOUBLE), 0.9) AS q9, count(DISTINCT q) AS levels, true AS median_close, true AS levels_close FROM q",
    "rel_r52_maps": "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, CAST(len(json_keys(props)) AS INTEGER) AS keys, user_id AS user FROM events",
}
__all__ = ["ORACLES", "QUERIES", "register_functions", "register_stages", "register_table_function"]
