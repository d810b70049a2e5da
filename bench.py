"""Headline queries on local[$BENCH_CPUS]: one JSON line of seconds, with throughput, speed-ups and a breakdown beside it.

Statistics run over fields of the tables in $BENCH_SF_DIR and over polynomial fields of $BENCH_SIDE squared points
(and as many in a cube), read from stored containers; throughput counts 4 bytes a point, as for single precision.
"""

from __future__ import annotations

import json
import os
import shutil
import sys
import tempfile
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
RUNS = int(os.environ.get("BENCH_RUNS", "2"))
SIDE = int(os.environ.get("BENCH_SIDE", "3072"))
BUDGET_S = float(os.environ.get("BENCH_BUDGET", "480"))


def main() -> None:
    from pyspark.sql import SparkSession

    from fieldloom.model import CODECS, META, QUANT, RESID, VALUE, ErrorBound, layout_for
    from fieldloom.operators import differential as dif
    from fieldloom.operators import statistics as sta
    from fieldloom.operators.codecs import compress_chunks, compress_points, partial_decompress
    from fieldloom.sources.container import read_container, write_container
    from fieldloom.sources.fields import FIELDS, polynomial_chunks

    builder = SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", CPUS)
    spark = builder.config("spark.driver.memory", "12g").config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    work = tempfile.mkdtemp(prefix="fieldloom-bench-")
    began, seconds, rate = time.time(), {}, {}

    def timed(name: str, run, points: int) -> None:
        if time.time() - began > BUDGET_S:
            return
        took = []
        for _ in range(RUNS):
            t = time.time()
            run().write.format("noop").mode("overwrite").save()
            took.append(time.time() - t)
        seconds[name] = round(min(took), 3)
        rate[name] = round(4 * points / 1e6 / min(took), 2)

    def kept(name: str, container) -> object:
        t = time.time()
        write_container(container, f"{work}/{name}")
        seconds[f"compress_{name}"] = round(time.time() - t, 3)
        return read_container(spark, f"{work}/{name}")

    def statistics(name: str, c, codec: str, layout, points: int) -> None:
        for stage in CODECS[codec].stages:
            timed(f"mean_{name}_{stage.lower()}", lambda: sta.field_mean(c, codec, layout, stage), points)
            if stage != META:
                timed(f"sd_{name}_{stage.lower()}", lambda: sta.field_stddev(c, codec, layout, stage), points)

    def decompression(name: str, c, codec: str, layout, points: int) -> None:
        for stage in CODECS[codec].stages:
            if stage != META:
                timed(f"decompress_{name}_{stage.lower()}", lambda: partial_decompress(c, codec, layout, stage), points)

    def moves(name: str, c, codec: str, layout, points: int, shape: tuple, operations=("gradient", "laplacian")) -> None:
        flat = CODECS[codec].flat
        box = layout_for("meannd", len(shape))
        for stage in (g for g in CODECS[codec].stages if g != META and not (flat and g == RESID)):
            for op in operations:
                timed(f"{op}_{name}_{stage.lower()}", lambda: dif.result_chunks(dif.prepared(c, codec, layout, stage, dims=shape if flat else None, work=box), op), points)

    cube = round((SIDE * SIDE) ** (1 / 3))
    plane_shape, cube_shape = (SIDE, SIDE), (cube, cube, cube)
    many = {2: SIDE * SIDE, 3: cube**3}
    try:
        f = FIELDS["line_price"]
        n = spark.read.parquet(f"{SF_DIR}/lineitem.parquet").count()
        c = kept("mean1d_line_price", compress_points(f.points(spark, SF_DIR), "mean1d", ErrorBound(1e-3), 1, f.flat_chunk))
        statistics("mean1d_line_price", c, "mean1d", f.layout(True), n)  # also warms up
        for codec in ("meannd", "lorenzo"):
            layout = layout_for(codec, 2)
            c = kept(f"{codec}_plane", compress_chunks(polynomial_chunks(spark, "plane", plane_shape, layout, 1e-3), codec, layout))
            statistics(f"{codec}_plane", c, codec, layout, many[2])
            decompression(f"{codec}_plane", c, codec, layout, many[2])
            moves(f"{codec}_plane", c, codec, layout, many[2], plane_shape, ("gradient", "laplacian") if codec == "lorenzo" else ("gradient",))
        for codec in ("lorenzo", "meannd"):
            layout = layout_for(codec, 3)
            c = kept(f"{codec}_cube", compress_chunks(polynomial_chunks(spark, "cube", cube_shape, layout, 1e-3), codec, layout))
            if codec == "lorenzo":
                decompression(f"{codec}_cube", c, codec, layout, many[3])
            moves(f"{codec}_cube", c, codec, layout, many[3], cube_shape, ("gradient",))
        for codec in ("chain1d", "mean1d", "blockdiff", "midrange"):
            layout = layout_for(codec, 2)
            c = kept(f"{codec}_plane", compress_chunks(polynomial_chunks(spark, "plane", plane_shape, layout, 1e-1), codec, layout))
            timed(f"mean_{codec}_plane_best", lambda: sta.field_mean(c, codec, layout), many[2])
            timed(f"sd_{codec}_plane_best", lambda: sta.field_stddev(c, codec, layout), many[2])
            moves(f"{codec}_plane", c, codec, layout, many[2], plane_shape, ("gradient",))
        raw = polynomial_chunks(spark, "plane", plane_shape, layout_for("meannd", 2), 1e-3).select("field", "data")
        raw.write.parquet(f"{work}/raw")
        timed("uncompressed_mean_plane", lambda: spark.read.parquet(f"{work}/raw").selectExpr("explode(data) AS v").selectExpr("avg(v)"), many[2])
    finally:
        shutil.rmtree(work, ignore_errors=True)

    def over(slow: str, fast: str) -> float | None:
        return round(seconds[slow] / seconds[fast], 2) if slow in seconds and fast in seconds else None

    g = "gradient_{}_{}_{}".format
    pairs = {f"{codec}_{field}_{fast}_over_{slow}": over(g(codec, field, slow), g(codec, field, fast)) for codec in ("lorenzo", "meannd") for field in ("plane", "cube") for fast, slow in (("resid", "value"), ("quant", "value"), ("resid", "quant"))}
    pairs |= {"chain1d_quant_over_blockdiff": over(g("blockdiff", "plane", "value"), g("chain1d", "plane", "quant")), "mean1d_quant_over_midrange": over(g("midrange", "plane", "value"), g("mean1d", "plane", "quant"))}
    pairs |= {f"mean_{a}_over_{b}": over(f"mean_{b}", f"mean_{a}") for a, b in (("meannd_plane_meta", "meannd_plane_value"), ("meannd_plane_meta", "blockdiff_plane_best"))}
    pairs |= {"sd_mean1d_over_best_baseline": over("sd_blockdiff_plane_best", "sd_mean1d_plane_best")}
    breakdown = {}
    for stage in ("value", "quant", "resid"):
        whole, part = seconds.get(g("lorenzo", "cube", stage)), seconds.get(f"decompress_lorenzo_cube_{stage}")
        if whole and part:
            breakdown[stage] = {"decompress": part, "compute_and_messages": round(whole - part, 3), "overall": whole}
    total = round(sum(seconds.values()), 3)
    print(json.dumps({"metric": "total of best query seconds", "value": total, "unit": "sec", "queries": seconds, "mb_per_s": rate, "speedup": pairs, "breakdown_gradient_cube_lorenzo": breakdown, "points": many, "sf": os.path.basename(SF_DIR)}))


if __name__ == "__main__":
    main()
