"""Queries over variants of the codecs: other encoders, the transform codec, codecs side by side, and formats of points."""

from __future__ import annotations

import uuid
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fieldloom.functions.bitpack import LONGEST
from fieldloom.functions.quantise import quantised
from fieldloom.model import CODECS, ErrorBound
from fieldloom.operators import encoders, transform
from fieldloom.operators.codecs import to_points
from fieldloom.operators.generic import symbol_counts
from fieldloom.plans import measures, oracle
from fieldloom.plans.workloads import REL, packed
from fieldloom.sources.fields import FIELDS
from fieldloom.streaming.events import shared_folder

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def add(name: str, query, sql: str) -> None:
    QUERIES[name] = query
    ORACLES[name] = sql


# other encoders


def round_trip(encoder: str, codec: str, name: str):
    """The residuals' histogram after a way through an encoder and back."""

    def query(spark: SparkSession, sf: str) -> DataFrame:
        f = FIELDS[name]
        layout = f.layout(CODECS[codec].flat)
        box = packed(f, codec, spark, sf)
        codes = encoders.code_table(box, layout, 200) if encoder == "huffman" else None
        return symbol_counts(encoders.unpacked(encoders.packed_by(box, encoder, codes), encoder, codes), layout)

    return query


def near_entropy(codec: str, name: str):
    """(symbols, residuals, kraft_is_one, near_entropy): the codes fill the tree, and their bits are within one a residual of the entropy."""

    def query(spark: SparkSession, sf: str) -> DataFrame:
        f = FIELDS[name]
        layout = f.layout(CODECS[codec].flat)
        box = packed(f, codec, spark, sf)
        codes = encoders.code_table(box, layout)
        kraft = int(sum(1 << (LONGEST - n) for n in codes.lengths.tolist())) == 1 << LONGEST
        bits = encoders.packed_by(box, "huffman", codes).agg(F.sum(F.aggregate("bits", F.lit(0).cast("bigint"), lambda a, x: a + x)).alias("bits"))
        counts = symbol_counts(box, layout)
        n = counts.agg(F.sum("c").alias("n"), F.count("*").alias("symbols"), F.sum(F.col("c") * F.log2("c")).alias("x"))
        entropy = F.col("n") * F.log2("n") - F.col("x")
        facts = n.unionByName(bits, allowMissingColumns=True).agg(*[F.max(c).alias(c) for c in ("n", "symbols", "x", "bits")])
        return facts.select("symbols", F.col("n").cast("bigint").alias("residuals"), F.lit(kraft).alias("kraft_is_one"), F.col("bits").between(entropy - 1, entropy + F.col("n")).alias("near_entropy"))

    return query


def encoder_queries() -> None:
    for codec, name in (("chain1d", "ord_price"), ("meannd", "part_price"), ("lorenzo", "evt_cube")):
        residuals = f"WITH {oracle.base(name, REL)}, {oracle.residual(codec, FIELDS[name].ndim)}"
        for encoder in encoders.ENCODERS:
            add(f"encoder_{encoder}_{codec}_{name}", round_trip(encoder, codec, name), f"{residuals} SELECT p, count(*) AS c FROM r GROUP BY p")
        add(f"huffman_bits_{codec}_{name}", near_entropy(codec, name), f"{residuals} SELECT count(DISTINCT p) AS symbols, count(*) AS residuals, true AS kraft_is_one, true AS near_entropy FROM r")


# the transform codec


def cosine(name: str, spark: SparkSession, sf: str) -> DataFrame:
    f = FIELDS[name]
    return transform.compress_cosine(f.points(spark, sf), ErrorBound(REL), f.layout())


def bound_kept(name: str):
    """(n, within): the points of the inverse, and whether all lie within the bound of the given ones."""

    def query(spark: SparkSession, sf: str) -> DataFrame:
        f = FIELDS[name]
        box = cosine(name, spark, sf)
        got = to_points(transform.cosine_values(box, f.layout()), f.layout())
        eps = box.groupBy("field").agg(F.first("eps").alias("eps"))
        t = f.points(spark, sf).join(got, ["field", "i", "j", "k"]).join(F.broadcast(eps), "field")
        return t.agg(F.count("*").alias("n"), F.bool_and(F.abs(F.col("v") - F.col("value")) <= F.col("eps") * (1 + 1e-9)).alias("within"))

    return query


def transform_queries() -> None:
    for name in ("emb", "part_price", "evt_cube"):
        key = oracle.block_key("meannd", FIELDS[name].ndim)
        sums = f"WITH {oracle.base(name, REL)}, m AS (SELECT CAST(floor(sum(value) / (2 * any_value(eps)) + 0.5) AS BIGINT) AS s, count(*) AS c FROM q GROUP BY {key})"
        add(
            f"mean_cosine_meta_{name}",
            lambda s, d, n=name: transform.cosine_mean(cosine(n, s, d)),
            f"{sums} SELECT '{name}' AS field, CAST(sum(c) AS BIGINT) AS n, CAST(sum(s) AS BIGINT) AS int_num, CAST(sum(s) AS DOUBLE) / CAST(sum(c) AS BIGINT) * (2 * any_value(eps)) AS result FROM m, e",
        )
        add(f"bound_cosine_{name}", bound_kept(name), f"WITH {oracle.base(name, REL)} SELECT count(*) AS n, true AS within FROM q")
        add(f"blocks_cosine_{name}", lambda s, d, n=name: cosine(n, s, d).agg(F.sum(F.size("n")).alias("blocks")), f"{sums} SELECT count(*) AS blocks FROM m")


# formats of points


def by_way_of(form: str):
    """Quantised points after a way through files of a format, read by their schema."""

    def query(spark: SparkSession, sf: str) -> DataFrame:
        q = quantised(FIELDS["ord_price"].points(spark, sf), ErrorBound(REL)).select("i", "value", "q")
        path = f"{shared_folder(spark)}/points_{form}_{uuid.uuid4().hex}"
        q.write.format(form).save(path)
        return spark.read.schema(q.schema).format(form).load(path)

    return query


def format_queries() -> None:
    for form in ("csv", "json", "orc"):
        add(f"rel_r03_{form}_points", by_way_of(form), f"WITH {oracle.base('ord_price', REL)} SELECT i, value, q FROM q")


# codecs side by side

COMPARED = ("emb", "part_price", "evt_cube")


def codec_table(spark: SparkSession, sf: str) -> DataFrame:
    return measures.codec_table(reduce(DataFrame.unionByName, [measures.ratio(packed(FIELDS[n], c, spark, sf), c) for n in COMPARED for c in CODECS]))


add("codec_table", codec_table, measures.codec_table_sql(COMPARED, REL))
format_queries()
encoder_queries()
transform_queries()
