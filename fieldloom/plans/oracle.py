"""DuckDB text for every method, by brute force on the raw tables: no residual is ever used to answer."""

from __future__ import annotations

from fieldloom.model import BLOCKS, CODECS
from fieldloom.sources.fields import FIELDS

AXES = "ijk"


def base(field: str, rel: float, tag: str = "") -> str:
    """CTEs p, e, q (suffixed): points, the bound and extents, quantised integers with row-major place g."""
    t = tag
    return f"""p{t} AS (SELECT i, j, k, value FROM ({FIELDS[field].sql()})),
e{t} AS (SELECT CASE WHEN max(value) - min(value) > 0 THEN CAST({rel!r} AS DOUBLE) * (max(value) - min(value)) ELSE CAST({rel!r} AS DOUBLE) * greatest(max(abs(value)), 1.0) END AS eps, max(i) + 1 AS d0, max(j) + 1 AS d1, max(k) + 1 AS d2 FROM p{t}),
q{t} AS (SELECT i, j, k, value, CAST(floor(value / (2 * eps) + 0.5) AS BIGINT) AS q, eps, d0, d1, d2, (i * d1 + j) * d2 + k AS g FROM p{t}, e{t})"""


def block_key(codec: str, ndim: int) -> str:
    if CODECS[codec].flat:
        return "g // 64"
    return ", ".join(f"{a} // {b}" for a, b in zip(AXES, BLOCKS[ndim]))


def lagged(expr: str, axis: str, ndim: int) -> str:
    rest = ", ".join(a for a in AXES if a != axis)
    return f"lag({expr}, 1, 0) OVER (PARTITION BY {rest} ORDER BY {axis})"


def residual(codec: str, ndim: int) -> str:
    """CTEs ending in r (all of q, and p): the residual of each point."""
    kind, key = CODECS[codec], block_key(codec, ndim)
    if codec == "chain1d":
        return "r AS (SELECT *, q - lag(q, 1, 0) OVER (ORDER BY g) AS p FROM q)"
    if codec == "lorenzo":
        out, last = [], "q"
        for n, a in enumerate(AXES[:ndim]):
            src = "q" if n == 0 else f"r{n}"
            out.append(f"{'r' if n == ndim - 1 else f'r{n + 1}'} AS (SELECT * {'EXCLUDE (p)' if n else ''}, {last} - {lagged(last, a, ndim)} AS p FROM {src})")
            last = "p"
        return ",\n".join(out)
    middle = {"mean": "CAST(ceil(CAST(sum(q) OVER w AS DOUBLE) / count(*) OVER w - 0.5) AS BIGINT)", "midrange": "CAST(floor((max(q) OVER w + min(q) OVER w) / 2.0) AS BIGINT)"}
    if kind.predictor == "first":
        return f"r AS (SELECT *, CASE WHEN g % 64 = 0 THEN 0 ELSE q - lag(q) OVER (ORDER BY g) END AS p FROM q)"
    return f"r AS (SELECT *, q - {middle[kind.predictor]} AS p FROM q WINDOW w AS (PARTITION BY {key}))"


def widths(codec: str, ndim: int) -> str:
    return f"w AS (SELECT CASE WHEN max(abs(p)) = 0 THEN 0 ELSE length(bin(max(abs(p)))) END AS width, count(*) AS s FROM r GROUP BY {block_key(codec, ndim)})"


def quantise_sql(field: str, rel: float) -> str:
    return f"WITH {base(field, rel)} SELECT '{field}' AS field, i, j, k, q FROM q"


def residual_sql(field: str, codec: str, rel: float) -> str:
    return f"WITH {base(field, rel)}, {residual(codec, FIELDS[field].ndim)} SELECT '{field}' AS field, i, j, k, p AS v FROM r"


def stage_sql(field: str, stage: str, rel: float) -> str:
    v = "q" if stage == "QUANT" else "CAST(q AS DOUBLE) * (2 * eps)"
    return f"WITH {base(field, rel)} SELECT '{field}' AS field, i, j, k, {v} AS v FROM q"


def widths_sql(field: str, codec: str, rel: float) -> str:
    n = FIELDS[field].ndim
    return f"WITH {base(field, rel)}, {residual(codec, n)}, {widths(codec, n)} SELECT width, count(*) AS blocks FROM w GROUP BY width"


def bytes_sql(codec: str) -> str:
    return f"CAST(sum(1 + {CODECS[codec].meta_bytes} + CASE WHEN width = 0 THEN 0 ELSE (s + 7) // 8 + (s * width + 7) // 8 END) AS BIGINT)"


def ratio_sql(field: str, codec: str, rel: float) -> str:
    n = FIELDS[field].ndim
    return f"WITH {base(field, rel)}, {residual(codec, n)}, {widths(codec, n)}, c AS (SELECT CAST(sum(s) * 4 AS BIGINT) AS raw_bytes, {bytes_sql(codec)} AS bytes FROM w) SELECT '{field}' AS field, '{codec}' AS codec, raw_bytes, bytes, CAST(raw_bytes AS DOUBLE) / bytes AS ratio FROM c"


def mean_sql(field: str, codec: str, stage: str, rel: float) -> str:
    b = f"WITH {base(field, rel)}"
    if stage == "VALUE":
        return f"{b} SELECT '{field}' AS field, count(*) AS n, CAST(round(avg(CAST(q AS DOUBLE) * (2 * eps)) * 1e6) AS BIGINT) AS result_micro FROM q"
    if stage == "META":
        return f"{b}, m AS (SELECT CAST(ceil(CAST(sum(q) AS DOUBLE) / count(*) - 0.5) AS BIGINT) * count(*) AS x, count(*) AS c FROM q GROUP BY {block_key(codec, FIELDS[field].ndim)}) SELECT '{field}' AS field, CAST(sum(c) AS BIGINT) AS n, CAST(sum(x) AS BIGINT) AS int_num, CAST(sum(x) AS DOUBLE) / CAST(sum(c) AS BIGINT) * (2 * any_value(eps)) AS result FROM m, e"
    return f"{b} SELECT '{field}' AS field, count(*) AS n, CAST(sum(q) AS BIGINT) AS int_num, CAST(sum(q) AS DOUBLE) / count(*) * (2 * any_value(eps)) AS result FROM q"


def sd_sql(field: str, codec: str, stage: str, rel: float, rounded: bool = False) -> str:
    b = f"WITH {base(field, rel)}"
    if stage == "VALUE":
        return f"{b} SELECT '{field}' AS field, count(*) AS n, CAST(round(stddev_samp(CAST(q AS DOUBLE) * (2 * eps)) * 1e6) AS BIGINT) AS result_micro FROM q"
    if rounded:
        return f"{b}, m AS (SELECT CAST(ceil(CAST(sum(q) AS DOUBLE) / count(*) - 0.5) AS BIGINT) * count(*) AS x, count(*) AS c FROM q GROUP BY {block_key(codec, FIELDS[field].ndim)}), u AS (SELECT CAST(ceil(CAST(sum(x) AS DOUBLE) / CAST(sum(c) AS BIGINT) - 0.5) AS BIGINT) AS mid FROM m) SELECT '{field}' AS field, count(*) AS n, sqrt(CAST(sum((q - mid) * (q - mid)) AS DOUBLE) / (count(*) - 1)) * (2 * any_value(eps)) AS result FROM q, u"
    return f"{b} SELECT '{field}' AS field, count(*) AS n, sqrt(CAST(count(*) * sum(q * q) - sum(q) * sum(q) AS DOUBLE) / (CAST(count(*) AS DOUBLE) * CAST(count(*) - 1 AS DOUBLE))) * (2 * any_value(eps)) AS result FROM q"


def neighbours(ndim: int, v: str = "q", src: str = "q", keep: str = "eps") -> str:
    cols = ", ".join(f"lag({v}) OVER (PARTITION BY {', '.join(b for b in AXES if b != a)} ORDER BY {a}) AS l{n}, lead({v}) OVER (PARTITION BY {', '.join(b for b in AXES if b != a)} ORDER BY {a}) AS h{n}" for n, a in enumerate(AXES[:ndim]))
    return f"SELECT i, j, k, {v} AS c, {keep}, {cols} FROM {src}"


def inner(ndim: int) -> str:
    return " AND ".join(f"l{n} IS NOT NULL AND h{n} IS NOT NULL" for n in range(ndim))


def derivative_sql(field: str, stage: str, rel: float, kind: str) -> str:
    n = FIELDS[field].ndim
    b = f"WITH {base(field, rel)}"
    if stage == "VALUE":
        total = " + ".join(f"(h{a} + l{a})" for a in range(n))
        cols = ", ".join(f"(h{a} - l{a}) / 2 AS d{'xyz'[a]}" for a in range(n)) if kind == "grad" else f"{total} - {2.0 * n} * c AS lap"
        return f"{b}, v AS (SELECT i, j, k, eps, CAST(q AS DOUBLE) * (2 * eps) AS v FROM q), s AS ({neighbours(n, 'v', 'v')}) SELECT '{field}' AS field, i, j, k, {cols} FROM s WHERE {inner(n)}"
    if kind == "grad":
        cols = ", ".join(f"h{a} - l{a} AS d{'xyz'[a]}, (h{a} - l{a}) * (1 * eps) AS d{'xyz'[a]}_value" for a in range(n))
    else:
        lap = " + ".join(f"h{a} + l{a}" for a in range(n)) + f" - {2 * n} * c"
        cols = f"{lap} AS lap, ({lap}) * (2 * eps) AS lap_value"
    return f"{b}, s AS ({neighbours(n)}) SELECT '{field}' AS field, i, j, k, {cols} FROM s WHERE {inner(n)}"


def vector_sql(fields: list[str], rel: float, kind: str, sign: str = "paper") -> str:
    n = FIELDS[fields[0]].ndim
    ctes = ", ".join(f"{base(f, rel, str(c))}, s{c} AS ({neighbours(n, 'q', f'q{c}')}), t{c} AS (SELECT i, j, k, {', '.join(f'(h{a} - l{a}) * eps AS x{c}{a}' for a in range(n))} FROM s{c} WHERE {inner(n)})" for c, f in enumerate(fields))
    join = " ".join([f"t0", *(f"JOIN t{c} USING (i, j, k)" for c in range(1, len(fields)))])
    if kind == "div":
        cols = " + ".join(f"x{a}{a}" for a in range(len(fields))) + " AS result"
    elif len(fields) == 2:
        cols = ("x01 - x10" if sign == "paper" else "-(x01 - x10)") + " AS result"
    else:
        cols = "x21 - x12 AS curl_x, x02 - x20 AS curl_y, x10 - x01 AS curl_z"
    return f"WITH {ctes} SELECT i, j, k, {cols} FROM {join}"


def vector_value_sql(fields: list[str], rel: float, kind: str) -> str:
    """Divergence and curl of the decompressed doubles."""
    n = FIELDS[fields[0]].ndim
    ctes = ", ".join(
        f"{base(f, rel, str(c))}, v{c} AS (SELECT i, j, k, eps, CAST(q AS DOUBLE) * (2 * eps) AS v FROM q{c}), s{c} AS ({neighbours(n, 'v', f'v{c}')}), t{c} AS (SELECT i, j, k, {', '.join(f'(h{a} - l{a}) / 2 AS x{c}{a}' for a in range(n))} FROM s{c} WHERE {inner(n)})"
        for c, f in enumerate(fields)
    )
    join = " ".join(["t0", *(f"JOIN t{c} USING (i, j, k)" for c in range(1, len(fields)))])
    if kind == "div":
        cols = " + ".join(f"x{a}{a}" for a in range(n)) + " AS result"
    else:
        cols = "x01 - x10 AS result" if n == 2 else "x21 - x12 AS curl_x, x02 - x20 AS curl_y, x10 - x01 AS curl_z"
    return f"WITH {ctes} SELECT i, j, k, {cols} FROM {join}"
