"""Fields over the given tables: as points (field, i, j, k, value) in Spark, and the same points as DuckDB text.

Sums of floats depend on their order, so cells that aggregate rows add decimals and are cast once.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fieldloom.model import Layout

EMB = "CAST(vec_id AS BIGINT) AS i, CAST({p} AS BIGINT) AS j, CAST(0 AS BIGINT) AS k, CAST({v} AS DOUBLE) AS value"


@dataclass(frozen=True)
class Field:
    """``spark`` and ``duck`` are queries giving i, j, k, value over the tables."""

    name: str
    ndim: int
    tables: tuple[str, ...]
    spark: str
    duck: str
    chunk: tuple[int, ...]
    flat_chunk: tuple[int, ...] = (1024,)

    def layout(self, flat: bool = False) -> Layout:
        from fieldloom.model import BLOCKS

        return Layout(BLOCKS[1 if flat else self.ndim], self.flat_chunk if flat else self.chunk)

    def points(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        for t in self.tables:
            spark.read.parquet(f"{sf_dir}/{t}.parquet").createOrReplaceTempView(f"fl_{t}")
        text = self.spark
        for t in self.tables:
            text = text.replace(f"{{{t}}}", f"fl_{t}")
        return spark.sql(f"SELECT '{self.name}' AS field, i, j, k, value FROM ({text})").select("field", "i", "j", "k", F.col("value").cast("double").alias("value"))

    def sql(self) -> str:
        text = self.duck
        for t in self.tables:
            text = text.replace(f"{{{t}}}", t)
        return text


def alike(name: str, ndim: int, tables: tuple[str, ...], text: str, chunk: tuple[int, ...]) -> Field:
    return Field(name, ndim, tables, text, text, chunk)


def vector_slice(name: str, first: int, count: int, cube: bool = False, chunk: tuple[int, ...] = (64, 32)) -> Field:
    """A slice of each embedding as a row of a plane, or folded to rows of four as a slab of a cube."""
    at = "{p} // 4" if cube else "{p}"
    rest = ", CAST({p} % 4 AS BIGINT) AS k" if cube else ", CAST(0 AS BIGINT) AS k"
    spark_at = "p DIV 4" if cube else "p"
    spark_rest = ", CAST(p % 4 AS BIGINT) AS k" if cube else ", CAST(0 AS BIGINT) AS k"
    spark = f"SELECT vec_id AS i, CAST({spark_at} AS BIGINT) AS j{spark_rest}, CAST(v AS DOUBLE) AS value FROM {{embeddings}} LATERAL VIEW posexplode(slice(embedding, {first}, {count})) t AS p, v"
    duck = f"SELECT vec_id AS i, CAST({at.format(p='p')} AS BIGINT) AS j{rest.format(p='p')}, CAST(e[p + {first}] AS DOUBLE) AS value FROM (SELECT vec_id, embedding AS e, unnest(range(0, {count})) AS p FROM {{embeddings}})"
    return Field(name, 3 if cube else 2, ("embeddings",), spark, duck, chunk)


GRID_1D = "SELECT CAST({key} AS BIGINT) AS i, CAST(0 AS BIGINT) AS j, CAST(0 AS BIGINT) AS k, {value} AS value FROM {{{table}}}"


def line(name: str, table: str, key: str, value: str) -> Field:
    return alike(name, 1, (table,), GRID_1D.format(key=key, value=value, table=table), (1024,))


def folded(name: str, table: str, key: str, value: str, cols: tuple[int, ...], chunk: tuple[int, ...]) -> Field:
    """A one-dimensional key folded to rows of ``cols`` places."""
    inner = 1
    for c in cols:
        inner *= c
    at = [f"CAST(floor({key} / {inner}.0) AS BIGINT) AS i", f"CAST(floor(({key} % {inner}) / {inner // cols[0]}.0) AS BIGINT) AS j", f"CAST({key} % {cols[1]} AS BIGINT) AS k" if len(cols) > 1 else "CAST(0 AS BIGINT) AS k"]
    return alike(name, 1 + len(cols), (table,), f"SELECT {', '.join(at)}, {value} AS value FROM {{{table}}}", chunk)


EVENTS = """SELECT {cells}, CAST(coalesce(s, 0) AS DOUBLE) AS value FROM
 (SELECT d, h, t, c FROM (SELECT explode(sequence(0, 29)) AS d), (SELECT explode(sequence(0, 23)) AS h), (SELECT stack(5, 0, 'click', 1, 'error', 2, 'purchase', 3, 'signup', 4, 'view') AS (t, c)) WHERE {only})
 LEFT JOIN (SELECT datediff(CAST(ts AS DATE), DATE '2024-01-01') AS d, hour(ts) AS h, {type} AS c, sum(CAST(value AS DECIMAL(18,2))) AS s FROM {{events}} GROUP BY ALL) USING (d, h, c)"""
EVENTS_DUCK = """SELECT {cells}, CAST(coalesce(s, 0) AS DOUBLE) AS value FROM
 (SELECT d, h, t, c FROM range(0, 30) a(d), range(0, 24) b(h), (VALUES (0, 'click'), (1, 'error'), (2, 'purchase'), (3, 'signup'), (4, 'view')) v(t, c) WHERE {only})
 LEFT JOIN (SELECT datediff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS d, hour(ts) AS h, {type} AS c, sum(CAST(value AS DECIMAL(18,2))) AS s FROM {{events}} GROUP BY ALL) USING (d, h, c)"""
FLAT = {"cells": "CAST(d AS BIGINT) AS i, CAST(h AS BIGINT) AS j, CAST(0 AS BIGINT) AS k", "only": "t = 0", "type": "'click'"}
DEEP = {"cells": "CAST(d AS BIGINT) AS i, CAST(h AS BIGINT) AS j, CAST(t AS BIGINT) AS k", "only": "t >= 0", "type": "event_type"}

RANGE = 4096  # leading keys of a range that rows are numbered in
LINE_ORDER = "l_orderkey, l_linenumber, l_partkey, l_suppkey, l_extendedprice, l_quantity, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate"


def line_column(name: str, column: str) -> Field:
    """Rows of lineitem in a total order; its keys repeat, so the order takes all columns.

    Rows are numbered within ranges of the leading key, and the ranges' counts are added up, so no window
    holds more rows than there are ranges.
    """
    cells = f"CAST({{n}} AS BIGINT) AS i, CAST(0 AS BIGINT) AS j, CAST(0 AS BIGINT) AS k, {column} AS value"
    ranges = f"SELECT b, coalesce(sum(c) OVER (ORDER BY b ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM (SELECT l_orderkey DIV {RANGE} AS b, count(*) AS c FROM {{lineitem}} GROUP BY 1)"
    spark = f"SELECT {cells.format(n=f'before + row_number() OVER (PARTITION BY b ORDER BY {LINE_ORDER}) - 1')} FROM (SELECT *, l_orderkey DIV {RANGE} AS b FROM {{lineitem}}) JOIN ({ranges}) USING (b)"
    duck = f"SELECT {cells.format(n=f'row_number() OVER (ORDER BY {LINE_ORDER}) - 1')} FROM {{lineitem}}"
    return Field(name, 1, ("lineitem",), spark, duck, (8192,))


#: Ship month from January 1992 on, nation of the supplier, and line number; sums of decimals, 0 where no row is.
LINE_CUBE = """SELECT CAST(m AS BIGINT) AS i, CAST(n AS BIGINT) AS j, CAST(l AS BIGINT) AS k, CAST(coalesce(s, 0) AS DOUBLE) AS value FROM
 (SELECT m, n, l FROM {months} CROSS JOIN {nations} CROSS JOIN {lines})
 LEFT JOIN (SELECT (year(l_shipdate) - 1992) * 12 + month(l_shipdate) - 1 AS m, s_nationkey AS n, l_linenumber - 1 AS l, sum(CAST({column} AS DECIMAL(18,2))) AS s
  FROM {{lineitem}} JOIN {{supplier}} ON l_suppkey = s_suppkey GROUP BY ALL) USING (m, n, l)"""


def line_cube(name: str, column: str) -> Field:
    """A column of lineitem added up over the cells of a cube, whose extents come from the tables."""
    last = "(SELECT max((year(l_shipdate) - 1992) * 12 + month(l_shipdate) - 1) FROM {{lineitem}})", "(SELECT max(n_nationkey) FROM {{nation}})", "(SELECT max(l_linenumber) - 1 FROM {{lineitem}})"
    names = "mnl"
    spark = {k: f"(SELECT explode(sequence(0, {x})) AS {c})" for k, c, x in zip(("months", "nations", "lines"), names, last)}
    duck = {k: f"(SELECT unnest(range(0, {x} + 1)) AS {c})" for k, c, x in zip(("months", "nations", "lines"), names, last)}
    made = [LINE_CUBE.format(column=column, **part).replace("{{", "{").replace("}}", "}") for part in (spark, duck)]
    return Field(name, 3, ("lineitem", "supplier", "nation"), *made, (24, 12, 8))


def polynomial(name: str, shape: tuple[int, ...], chunk: tuple[int, ...]) -> Field:
    """A smooth field of any size: a quadratic in centred coordinates, in whole numbers."""
    c = [s // 2 for s in shape]
    u = [f"({x} - {m})" for x, m in zip("ijk", c)]
    v = f"{u[0]}*{u[0]} - 3*{u[0]}*{u[1]} + 2*{u[1]}*{u[1]}" if len(shape) == 2 else f"{u[0]}*{u[0]} + 2*{u[1]}*{u[2]} - {u[2]}*{u[2]}"
    d = [*shape, 1][:3]
    spark = f"SELECT id DIV {d[1] * d[2]} AS i, (id DIV {d[2]}) % {d[1]} AS j, id % {d[2]} AS k FROM range(0, {d[0] * d[1] * d[2]})"
    duck = f"SELECT id // {d[1] * d[2]} AS i, (id // {d[2]}) % {d[1]} AS j, id % {d[2]} AS k FROM range(0, {d[0] * d[1] * d[2]}) r(id)"
    return Field(name, len(shape), (), *(f"SELECT i, j, k, CAST({v} AS DOUBLE) AS value FROM ({s})" for s in (spark, duck)), chunk)


def smooth(name: str, table: str, key: str, cols: tuple[int, ...], chunk: tuple[int, ...]) -> Field:
    """The polynomial at each row of a table, whose key is folded to the places of a grid and centred there."""
    grid = folded(name, table, key, key, cols, chunk)
    last = "(SELECT " + ", ".join(f"CAST(floor((max({x}) + 1) / 2.0) AS BIGINT) AS m{x}" for x in "ijk") + " FROM ({grid}))"
    u = [f"({x} - m{x})" for x in "ijk"]
    v = f"{u[0]}*{u[0]} - 3*{u[0]}*{u[1]} + 2*{u[1]}*{u[1]}" if grid.ndim == 2 else f"{u[0]}*{u[0]} + 2*{u[1]}*{u[2]} - {u[2]}*{u[2]}"
    points = grid.spark.replace(f"{key} AS value", "0 AS value")
    text = f"SELECT i, j, k, CAST({v} AS DOUBLE) AS value FROM ({points}) CROSS JOIN {last.replace('{grid}', points)}"
    return alike(name, grid.ndim, (table,), text, chunk)


FIELDS = {
    f.name: f
    for f in (
        vector_slice("emb", 1, 64),
        vector_slice("emb_u", 1, 32),
        vector_slice("emb_v", 33, 32),
        *(vector_slice(f"emb3_{c}", 1 + 16 * n, 16, True, (64, 4, 4)) for n, c in enumerate("xyz")),
        line("ord_price", "orders", "o_orderkey", "o_totalprice"),
        line("cust_bal", "customer", "c_custkey", "c_acctbal"),
        line("supp_bal", "supplier", "s_suppkey", "s_acctbal"),
        line("part_price1", "part", "p_partkey", "p_retailprice"),
        line("evt_value", "events", "event_id", "value"),
        folded("ord_price2", "orders", "o_orderkey", "o_totalprice", (125,), (64, 64)),
        folded("part_price", "part", "p_partkey", "p_retailprice", (50,), (16, 16)),
        folded("part_size", "part", "p_partkey", "CAST(p_size AS DOUBLE)", (50,), (16, 16)),
        folded("part_price3", "part", "p_partkey", "p_retailprice", (10, 20), (8, 8, 8)),
        Field("evt_grid", 2, ("events",), EVENTS.format(**FLAT).replace("WHERE t = 0)", "WHERE t = 0)"), EVENTS_DUCK.format(**FLAT), (16, 16)),
        Field("evt_cube", 3, ("events",), EVENTS.format(**DEEP), EVENTS_DUCK.format(**DEEP), (16, 12, 4)),
        line_column("line_price", "l_extendedprice"),
        line_column("line_qty", "l_quantity"),
        line_column("line_disc", "l_discount"),
        line_column("line_tax", "l_tax"),
        line_cube("line_cube_price", "l_extendedprice"),
        line_cube("line_cube_qty", "l_quantity"),
        folded("ord_price3", "orders", "o_orderkey", "o_totalprice", (10, 15), (64, 12, 16)),
        smooth("ord_poly2d", "orders", "o_orderkey", (125,), (64, 64)),
        smooth("ord_poly3d", "orders", "o_orderkey", (10, 15), (64, 12, 16)),
        polynomial("poly2d", (96, 80), (32, 32)),
        polynomial("poly3d", (24, 20, 28), (8, 8, 8)),
    )
}


def polynomial_chunks(spark: SparkSession, name: str, shape: tuple[int, ...], layout: Layout, rel: float) -> DataFrame:
    """Quantised chunk rows of polynomial() at any size, made chunk by chunk: nothing is shuffled.

    A layout of one dimension gives the flattened field.  The range, which the bound is relative to, is
    that of a coarse mesh over the grid with its corners and middles.
    """
    import numpy as np

    from fieldloom.operators.chunks import HEAD, kernel, place

    c = [s // 2 for s in shape]

    def values(at):
        u = [x - m for x, m in zip(at, c)]
        return u[0] * u[0] - 3 * u[0] * u[1] + 2 * u[1] * u[1] if len(shape) == 2 else u[0] * u[0] + 2 * u[1] * u[2] - u[2] * u[2]

    some = values(np.meshgrid(*[np.array([0, s // 4, s // 2, 3 * s // 4, s - 1], np.int64) for s in shape], indexing="ij"))
    eps = rel * float(some.max() - some.min())
    flat = layout.ndim < len(shape)
    grid = [int(np.prod(shape))] if flat else list(shape)
    many = [-(-s // k) for s, k in zip(grid, layout.chunk)] + [1, 1]
    cell = {"ci": F.floor(F.col("id") / (many[1] * many[2])), "cj": F.pmod(F.floor(F.col("id") / many[2]), F.lit(many[1])), "ck": F.pmod(F.col("id"), F.lit(many[2]))}
    dims = [F.lit(d).cast("bigint").alias(f"d{a}") for a, d in enumerate([*grid, 1, 1][:3])]
    rows = spark.range(many[0] * many[1] * many[2]).select(F.lit(name).alias("field"), *[e.cast("int").alias(n) for n, e in cell.items()], F.lit(eps).alias("eps"), *dims)

    def run(row):
        lo, extent, _ = place(row, layout)
        at = [x + o for x, o in zip(np.indices(extent, sparse=True), lo)]
        v = values(np.unravel_index(at[0], shape) if flat else at).astype(np.float64)
        yield row | {"data": np.floor(v / (2 * row["eps"]) + 0.5).astype(np.int64).ravel()}

    return kernel(rows, run, f"{HEAD}, data array<bigint>")
