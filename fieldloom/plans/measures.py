"""Ratios, widths, the worked example, and several operations from one decompression."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from fieldloom.model import CODECS, ErrorBound, Layout
from fieldloom.operators import differential as dif
from fieldloom.plans import oracle
from fieldloom.sources.fields import FIELDS


def width_histogram(container: DataFrame) -> DataFrame:
    return container.select(F.explode("width").alias("width")).groupBy("width").agg(F.count("*").alias("blocks"))


def ratio(container: DataFrame, codec: str) -> DataFrame:
    """(field, codec, raw_bytes, bytes, ratio) against single-precision input; a width byte a block, and its number."""
    points = F.aggregate("n", F.lit(0).cast("bigint"), lambda a, x: a + x)
    part = container.select("field", (points * 4).alias("raw"), (F.size("n") * (1 + CODECS[codec].meta_bytes) + F.octet_length("payload")).cast("bigint").alias("c"))
    t = part.groupBy("field").agg(F.sum("raw").alias("raw_bytes"), F.sum("c").alias("bytes"))
    return t.select("field", F.lit(codec).alias("codec"), "raw_bytes", "bytes", (F.col("raw_bytes").cast("double") / F.col("bytes")).alias("ratio"))


def ratio_rollup(ratios: DataFrame) -> DataFrame:
    """Aggregated ratios: total input over total output, by codec and field and over all."""
    t = ratios.rollup("codec", "field").agg(F.sum("raw_bytes").alias("raw_bytes"), F.sum("bytes").alias("bytes"))
    return t.withColumn("ratio", F.col("raw_bytes").cast("double") / F.col("bytes").cast("double"))


def gradients_and_curl(parts: list[dif.Ready]) -> DataFrame:
    """Three gradients and the curl of a velocity field, from one decompression of each component."""
    names = [f"{c}_d{x}" for c in "uvw" for x in "xyz"]
    return dif.vector_kernel(parts, [*names, "curl_x", "curl_y", "curl_z"], lambda d: [x for own in d for x in own] + dif.curl_3d(d))


def multi_sql(fields: list[str], rel: float) -> str:
    curl = oracle.vector_sql(fields, rel, "curl")
    cols = ", ".join(f"x{n}{a} AS {c}_d{x}" for n, c in enumerate("uvw") for a, x in enumerate("xyz"))
    return curl.replace("SELECT i, j, k, x21 - x12", f"SELECT i, j, k, {cols}, x21 - x12")


#: The worked example's field (2 x 4), bound and tile.
WORKED = ((1.2, 1.5, -2.3, -2.5), (2.5, -1.0, 2.0, 1.7))
WORKED_EPS = 0.1

WORKED_SQL = f"""WITH q AS (SELECT i, j, CAST(floor(value / (2 * CAST({WORKED_EPS} AS DOUBLE)) + 0.5) AS BIGINT) AS q FROM ({FIELDS["ord_price2"].sql()})),
m AS (SELECT *, CAST(ceil(CAST(sum(q) OVER w AS DOUBLE) / count(*) OVER w - 0.5) AS BIGINT) AS m FROM q WINDOW w AS (PARTITION BY i // 2, j // 2))
SELECT i, j, q, m, q - m AS p FROM m"""


def tile_example(points: DataFrame, layout: Layout) -> DataFrame:
    """(i, j, q, m, p) of points through the tile-mean codec with the worked example's bound."""
    from fieldloom.functions.quantise import quantised
    from fieldloom.operators.chunks import to_chunks
    from fieldloom.operators.codecs import compress_chunks, partial_decompress, to_points

    c = compress_chunks(to_chunks(quantised(points, ErrorBound(WORKED_EPS, relative=False)), layout), "meannd", layout)
    resid = partial_decompress(c, "meannd", layout, "RESID")
    t = to_points(resid.withColumn("data", F.arrays_zip("data", "means")), layout)
    return t.select("i", "j", (F.col("v.data") + F.col("v.means")).alias("q"), F.col("v.means").alias("m"), F.col("v.data").alias("p"))


def worked_example(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The worked example's tiles and bound over the plane of orders."""
    return tile_example(FIELDS["ord_price2"].points(spark, sf_dir), Layout((2, 2), FIELDS["ord_price2"].chunk))


def costs(spark: SparkSession, run: Callable[[], object]) -> dict[str, int]:
    """What the stages of ``run()`` cost, by Spark's own counts: bytes shuffled, spilled and read, and the largest peak of memory."""
    context = spark.sparkContext
    jvm = context._jvm

    def stages():
        found = context._jsc.sc().statusStore().stageList(jvm.java.util.ArrayList(), False, False, context._gateway.new_array(jvm.double, 0), jvm.java.util.ArrayList())
        return [found.apply(n) for n in range(found.size())]

    def settled():  # the counts arrive on a bus of their own
        context._jsc.sc().listenerBus().waitUntilEmpty()
        return stages()

    before = {x.stageId() for x in settled()}
    run()
    own = [x for x in settled() if x.stageId() not in before]
    return {
        "stages": len(own),
        "shuffled": sum(x.shuffleWriteBytes() for x in own),
        "spilled": sum(x.diskBytesSpilled() for x in own),
        "read": sum(x.inputBytes() for x in own),
        "peak_memory": max((x.peakExecutionMemory() for x in own), default=0),
    }


def codec_table(ratios: DataFrame) -> DataFrame:
    """(field, codec, stages, bytes, rank): each codec's stages, and its place by size for each field."""
    stages = F.create_map(*[F.lit(x) for c in CODECS.values() for x in (c.name, " ".join(c.stages))])
    place = F.rank().over(Window.partitionBy("field").orderBy("bytes"))
    return ratios.select("field", "codec", stages[F.col("codec")].alias("stages"), "bytes", place.alias("rank"))


def codec_table_sql(fields: tuple[str, ...], rel: float) -> str:
    ratios = " UNION ALL ".join(f"SELECT * FROM ({oracle.ratio_sql(f, c, rel)})" for f in fields for c in CODECS)
    stages = "CASE WHEN codec IN ('blockdiff', 'midrange') THEN 'VALUE' WHEN codec IN ('mean1d', 'meannd') THEN 'META RESID QUANT VALUE' ELSE 'RESID QUANT VALUE' END"
    return f"SELECT field, codec, {stages} AS stages, bytes, CAST(rank() OVER (PARTITION BY field ORDER BY bytes) AS INTEGER) AS rank FROM ({ratios})"
