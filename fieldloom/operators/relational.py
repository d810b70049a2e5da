"""The relational operators around the methods, as queries over fields and tables.

Each text runs in Spark and, with tables named plainly, in DuckDB.  Where the dialects differ a pair is given.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "embeddings", "labels", "documents")

# orders as a quantised field with the bound 1e-3 of the range
ORD = """WITH e AS (SELECT CAST('0.001' AS DOUBLE) * (max(o_totalprice) - min(o_totalprice)) AS eps FROM {orders}),
q AS (SELECT o_orderkey AS g, o_totalprice AS v, CAST(floor(o_totalprice / (2 * eps) + 0.5) AS BIGINT) AS q, eps, CAST(floor(o_orderkey / 64) AS BIGINT) AS b FROM {orders} CROSS JOIN e),
b AS (SELECT b, count(*) AS n, CAST(sum(q) AS BIGINT) AS s, min(q) AS lo, max(q) AS hi FROM q GROUP BY b) """

SQL: dict[str, str | tuple[str, str]] = {
    "rel_r01_pruned_scan": "SELECT o_orderkey, o_totalprice FROM {orders} WHERE o_totalprice > 400000",
    "rel_r07_matrix_to_points": ("SELECT vec_id AS i, CAST(p AS BIGINT) AS j, CAST(v AS DOUBLE) AS value FROM {embeddings} LATERAL VIEW posexplode(embedding) t AS p, v", "SELECT vec_id AS i, p AS j, CAST(embedding[p + 1] AS DOUBLE) AS value FROM (SELECT vec_id, embedding, unnest(range(0, len(embedding))) AS p FROM {embeddings})"),
    "rel_r08_points_to_rows": ("SELECT i, count(*) AS n, element_at(transform(array_sort(collect_list(struct(j, v))), x -> x.v), 3) AS third FROM (SELECT vec_id AS i, p AS j, CAST(v AS DOUBLE) AS v FROM {embeddings} LATERAL VIEW posexplode(embedding) t AS p, v) GROUP BY i", "SELECT vec_id AS i, len(embedding) AS n, CAST(embedding[3] AS DOUBLE) AS third FROM {embeddings}"),
    "rel_r10_quantise": ORD + "SELECT g, q, CAST(q AS DOUBLE) * (2 * eps) AS restored FROM q",
    "rel_r11_integer_threshold": ORD + "SELECT g FROM q WHERE q >= ceil(250000 / (2 * eps))",
    "rel_r12_box": "SELECT p_partkey, p_retailprice FROM {part} WHERE p_partkey BETWEEN 100 AND 900 AND p_size BETWEEN 5 AND 9",
    "rel_r13_metadata_filters": "SELECT event_id, CASE WHEN value > 50 THEN 'high' ELSE 'low' END AS side FROM {events} WHERE event_type IN ('click', 'view') AND event_type LIKE '%i%'",
    "rel_r14_block_sample": ORD + "SELECT b, n, s FROM b WHERE b % 10 = 3",
    "rel_r15_broadcast_bound": ORD + "SELECT count(*) AS n, max(abs(v - CAST(q AS DOUBLE) * (2 * eps))) <= max(eps) * (1 + 1e-9) AS within FROM q",
    "rel_r16_components": "SELECT a.vec_id, a.label AS la, b.label AS lb FROM {embeddings} a JOIN {embeddings} b ON a.vec_id = b.vec_id",
    "rel_r17_neighbour_blocks": ORD + "SELECT x.b, x.s AS here, y.s AS next FROM b x JOIN b y ON y.b = x.b + 1",
    "rel_r18_dense_grid": ("SELECT h.h, coalesce(c, 0) AS c FROM (SELECT explode(sequence(0, 23)) AS h) h LEFT JOIN (SELECT hour(ts) AS h, count(*) AS c FROM {events} WHERE event_type = 'error' GROUP BY hour(ts)) e ON e.h = h.h", "SELECT CAST(h.h AS INTEGER) AS h, coalesce(c, 0) AS c FROM range(0, 24) h(h) LEFT JOIN (SELECT hour(ts) AS h, count(*) AS c FROM {events} WHERE event_type = 'error' GROUP BY 1) e ON e.h = h.h"),
    # the containers of the bounds 1e-3 and 1e-2; d in steps of the finer one
    "rel_r19_container_diff": ORD + ", c AS (SELECT b, CAST(sum(CAST(floor(v / (20 * eps) + 0.5) AS BIGINT)) AS BIGINT) AS s FROM q GROUP BY b) SELECT coalesce(x.b, y.b) AS b, x.s AS sx, y.s AS sy, 10 * y.s - x.s AS d FROM b x FULL OUTER JOIN c y ON x.b = y.b",
    "rel_r20_touched": ORD + "SELECT b, s FROM b WHERE EXISTS (SELECT 1 FROM {customer} c WHERE c.c_custkey = b.b)",
    "rel_r20_untouched": ORD + "SELECT b, s FROM b WHERE NOT EXISTS (SELECT 1 FROM {supplier} c WHERE c.s_suppkey = b.b)",
    "rel_r21_boxes_by_chunks": "WITH x AS (SELECT r_regionkey AS id, r_regionkey * 130 AS lo, r_regionkey * 170 + 60 AS hi FROM {region}), c AS (SELECT DISTINCT CAST(floor(p_partkey / 64) AS BIGINT) AS c FROM {part}) SELECT x.id, c.c FROM x JOIN c ON c.c * 64 <= x.hi AND c.c * 64 + 63 >= x.lo",
    # each event goes to the first mark at or after it; a mark without one takes what the mark before it has
    "rel_r22_as_of": ("WITH m AS (SELECT n_nationkey * 100 + 50 AS k FROM {nation}), a AS (SELECT array_sort(collect_set(k)) AS ks FROM m), e AS (SELECT array_min(filter(ks, x -> x >= event_id)) AS k, max_by(struct(value), event_id) AS v FROM {events} CROSS JOIN a WHERE event_id <= element_at(ks, -1) GROUP BY 1) SELECT m.k, last_value(e.v) IGNORE NULLS OVER (ORDER BY m.k).value AS v FROM m LEFT JOIN e ON m.k = e.k", "SELECT n_nationkey * 100 + 50 AS k, e.value AS v FROM {nation} n ASOF LEFT JOIN {events} e ON n_nationkey * 100 + 50 >= e.event_id"),
    "rel_r23_interval_join": ("SELECT a.event_id AS a, b.event_id AS b FROM (SELECT event_id, explode(array(CAST(floor(event_id / 10) AS BIGINT), CAST(floor(event_id / 10) AS BIGINT) + 1)) AS bin FROM {events} WHERE event_type = 'purchase') a JOIN {events} b ON a.bin = CAST(floor(b.event_id / 10) AS BIGINT) AND b.event_id - a.event_id BETWEEN 1 AND 3", "SELECT a.event_id AS a, b.event_id AS b FROM {events} a JOIN {events} b ON b.event_id BETWEEN a.event_id + 1 AND a.event_id + 3 WHERE a.event_type = 'purchase'"),
    "rel_r24_star": "SELECT r_name, CAST(sum(CAST(l_extendedprice AS DECIMAL(18,2))) AS DOUBLE) AS total FROM {lineitem} JOIN {supplier} ON l_suppkey = s_suppkey JOIN {nation} ON s_nationkey = n_nationkey JOIN {region} ON n_regionkey = r_regionkey GROUP BY r_name",
    "rel_r25_hash_agg": ORD + "SELECT count(*) AS n, CAST(sum(q) AS BIGINT) AS s1, CAST(sum(q * q) AS BIGINT) AS s2 FROM q",
    "rel_r26_array_agg": (ORD + "SELECT b, array_join(transform(array_sort(collect_list(q)), x -> CAST(x AS STRING)), ',') AS qs FROM q GROUP BY b", ORD + "SELECT b, string_agg(CAST(q AS VARCHAR), ',' ORDER BY q) AS qs FROM q GROUP BY b"),
    "rel_r27_moments": "SELECT CAST(round(avg(o_totalprice) * 1e3) AS BIGINT) AS mean3, CAST(round(stddev_samp(o_totalprice) * 1e3) AS BIGINT) AS sd3, CAST(round(stddev_pop(o_totalprice) * 1e3) AS BIGINT) AS sdp3, min(o_totalprice) AS lo, max(o_totalprice) AS hi FROM {orders}",
    "rel_r28_distinct_levels": ORD + "SELECT count(DISTINCT q) AS levels FROM q",
    "rel_r29_rollup": "SELECT n_regionkey, n_nationkey, count(*) AS c FROM {customer} JOIN {nation} ON c_nationkey = n_nationkey GROUP BY ROLLUP (n_regionkey, n_nationkey)",
    "rel_r29_cube": "SELECT o_orderstatus, o_orderpriority, count(*) AS c FROM {orders} GROUP BY CUBE (o_orderstatus, o_orderpriority)",
    "rel_r29_grouping_sets": "SELECT l_returnflag, l_linestatus, count(*) AS c FROM {lineitem} GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())",
    "rel_r30_histogram": ORD + "SELECT CAST(floor(q / 50) AS BIGINT) AS bin, count(*) AS c FROM q GROUP BY CAST(floor(q / 50) AS BIGINT)",
    "rel_r31_pivot": "SELECT hour(ts) AS h, sum(CASE WHEN event_type = 'click' THEN 1 ELSE 0 END) AS clicks, sum(CASE WHEN event_type = 'error' THEN 1 ELSE 0 END) AS errors FROM {events} GROUP BY hour(ts)",
    "rel_r32_extreme_place": ("SELECT min_by(o_orderkey, struct(o_totalprice, o_orderkey)) AS lo, max_by(o_orderkey, struct(o_totalprice, o_orderkey)) AS hi, bool_and(o_totalprice > 0) AS positive FROM {orders}", "SELECT arg_min(o_orderkey, (o_totalprice, o_orderkey)) AS lo, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS hi, bool_and(o_totalprice > 0) AS positive FROM {orders}"),
    "rel_r33_entropy": ORD + ", r AS (SELECT q - coalesce(lag(q) OVER (ORDER BY g), 0) AS p, q FROM q), h AS (SELECT 'q' AS what, q AS x, count(*) AS c FROM r GROUP BY q UNION ALL SELECT 'p', p, count(*) FROM r GROUP BY p), t AS (SELECT what, x, c, sum(c) OVER (PARTITION BY what) AS n FROM h) SELECT what, CAST(round(-sum(CAST(c AS DOUBLE) / n * ln(CAST(c AS DOUBLE) / n) / ln(2)) * 1e6) AS BIGINT) AS micro_bits FROM t GROUP BY what",
    "rel_r34_mergeable": ORD + "SELECT CAST(floor(b / 8) AS BIGINT) AS chunk, CAST(sum(n) AS BIGINT) AS n, CAST(sum(s) AS BIGINT) AS s FROM b GROUP BY CAST(floor(b / 8) AS BIGINT)",
    "rel_r35_dense_index": "SELECT event_type, event_id, CAST(row_number() OVER (PARTITION BY event_type ORDER BY event_id) - 1 AS BIGINT) AS g FROM {events}",
    "rel_r36_stencil": ORD + "SELECT g, lead(q) OVER w - lag(q) OVER w AS d FROM q WINDOW w AS (PARTITION BY b ORDER BY g)",
    "rel_r37_running_sum": ORD + "SELECT g, CAST(sum(q) OVER (PARTITION BY b ORDER BY g ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS BIGINT) AS s FROM q",
    "rel_r38_three_blocks": ORD + "SELECT b, CAST(sum(s) OVER (ORDER BY b ROWS BETWEEN 1 PRECEDING AND 1 FOLLOWING) AS BIGINT) AS s3 FROM b",
    "rel_r39_day_range": "WITH d AS (SELECT day(ts) AS d, count(*) AS c FROM {events} GROUP BY day(ts)) SELECT d, CAST(sum(c) OVER (ORDER BY d RANGE BETWEEN 3 PRECEDING AND CURRENT ROW) AS BIGINT) AS c4 FROM d",
    "rel_r40_ranks": ORD + "SELECT b, rank() OVER (ORDER BY hi - lo) AS r, dense_rank() OVER (ORDER BY hi - lo) AS dr, ntile(4) OVER (ORDER BY hi - lo, b) AS t FROM b",
    "rel_r41_edge_values": ORD + "SELECT b, first_value(q) OVER w AS f, last_value(q) OVER w AS l, nth_value(q, 2) OVER w AS s FROM q WINDOW w AS (PARTITION BY b ORDER BY g ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)",
    "rel_r42_global_sort": "SELECT o_orderkey, o_totalprice FROM {orders} ORDER BY o_orderkey",
    "rel_r43_top_blocks": ORD + "SELECT b, hi - lo AS spread FROM b ORDER BY hi - lo DESC, b LIMIT 10",
    "rel_r44_top_per_group": "SELECT event_type, event_id, value FROM (SELECT *, row_number() OVER (PARTITION BY event_type ORDER BY value DESC, event_id) AS r FROM {events}) t WHERE r <= 3",
    "rel_r46_union_fields": "SELECT 'cust' AS field, c_custkey AS g, c_acctbal AS value FROM {customer} UNION ALL SELECT 'supp', s_suppkey, s_acctbal FROM {supplier}",
    "rel_r47_intersect": "SELECT o_custkey AS k FROM {orders} WHERE o_totalprice > 300000 INTERSECT SELECT o_custkey FROM {orders} WHERE o_totalprice < 100000",
    "rel_r48_except": "SELECT c_custkey AS k FROM {customer} EXCEPT SELECT o_custkey FROM {orders}",
    "rel_r49_distinct": "SELECT DISTINCT l_returnflag, l_linestatus FROM {lineitem}",
    "rel_r50_math": ORD + "SELECT g, abs(q - 250) AS a, CAST(sign(q - 250) AS INTEGER) AS sg, greatest(q, 100) AS hi, least(q, 100) AS lo, bit_count(q) AS ones, sqrt(CAST(q AS DOUBLE)) AS root FROM q",
    "rel_r51_arrays": ("SELECT vec_id, size(filter(embedding, x -> x > 0)) AS pos, exists(embedding, x -> x > 0.3) AS big, size(slice(embedding, 2, 5)) AS five FROM {embeddings}", "SELECT vec_id, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INTEGER) AS pos, len(list_filter(embedding, lambda x: x > 0.3)) > 0 AS big, CAST(len(embedding[2:6]) AS INTEGER) AS five FROM {embeddings}"),
    "rel_r53_json": ("SELECT event_id, CAST(get_json_object(props, '$.k') AS BIGINT) AS k FROM {events}", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM {events}"),
    "rel_r54_dates": ("SELECT o_orderkey, datediff(CAST(o_orderdate AS DATE), DATE '1992-01-01') AS days, month(o_orderdate) AS m, year(o_orderdate) AS y FROM {orders}", "SELECT o_orderkey, datediff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS days, month(o_orderdate) AS m, year(o_orderdate) AS y FROM {orders}"),
    "rel_r55_strings": "SELECT p_partkey, length(p_name) AS n, lpad(CAST(p_size AS VARCHAR(10)), 4, '0') AS s, concat_ws('-', p_brand, p_type) AS t, upper(p_name) AS u FROM {part}",
    "rel_r56_binary": ("SELECT n_nationkey, octet_length(encode(n_name, 'UTF-8')) AS n, hex(encode(n_name, 'UTF-8')) AS h FROM {nation}", "SELECT n_nationkey, octet_length(encode(n_name)) AS n, hex(encode(n_name)) AS h FROM {nation}"),
    "rel_r57_nulls": "SELECT d.doc_id, coalesce(toxic, -1) AS toxic, nullif(coalesce(quality, 9), 9) AS quality FROM {documents} d LEFT JOIN {labels} l ON d.doc_id = l.doc_id",
    "rel_r58_scalar_subquery": "SELECT count(*) AS n FROM {orders} WHERE o_totalprice > (SELECT avg(CAST(o_totalprice AS DECIMAL(18,2))) FROM {orders})",
    "rel_r59_correlated": "SELECT c_custkey FROM {customer} c WHERE EXISTS (SELECT 1 FROM {orders} o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 450000)",
    # generic operations of the methods
    "isosurface_cells_ord": ORD + ", n AS (SELECT g, q, lead(q) OVER (ORDER BY g) AS r, eps FROM q) SELECT g FROM n WHERE least(q, r) < ceil(250000 / (2 * eps)) AND greatest(q, r) >= ceil(250000 / (2 * eps))",
    "halo_points_ord": ORD + "SELECT g FROM q WHERE q > (SELECT 1.9 * sum(s) / sum(n) FROM b)",
    "block_agg_ord": ORD + "SELECT b, n, s, lo, hi FROM b",
    # what a derivative gives at the rim of the grid
    "grad_boundary_null": ORD + "SELECT g, lead(q) OVER (ORDER BY g) - lag(q) OVER (ORDER BY g) AS d FROM q",
    "grad_boundary_clamp": ORD + "SELECT g, coalesce(lead(q) OVER (ORDER BY g), q) - coalesce(lag(q) OVER (ORDER BY g), q) AS d FROM q",
    "grad_boundary_periodic": ORD + ", t AS (SELECT max(CASE WHEN g = 0 THEN q END) AS f, max_by(q, g) AS l FROM q) SELECT g, coalesce(lead(q) OVER (ORDER BY g), f) - coalesce(lag(q) OVER (ORDER BY g), l) AS d FROM q CROSS JOIN t",
    "grad_boundary_one_sided": ORD + ", n AS (SELECT g, q, lag(q) OVER (ORDER BY g) AS a, lead(q) OVER (ORDER BY g) AS b FROM q) SELECT g, CASE WHEN a IS NULL THEN 2 * (b - q) WHEN b IS NULL THEN 2 * (q - a) ELSE b - a END AS d FROM n",
    "rle_runs_ord": ORD + ", r AS (SELECT g, q - coalesce(lag(q) OVER (PARTITION BY b ORDER BY g), q) AS p, b FROM q), c AS (SELECT *, CASE WHEN p = lag(p) OVER (PARTITION BY b ORDER BY g) THEN 0 ELSE 1 END AS fresh FROM r) SELECT b, CAST(sum(fresh) AS BIGINT) AS runs FROM c GROUP BY b",
    "symbol_hist_ord": ORD + ", r AS (SELECT q - coalesce(lag(q) OVER (ORDER BY g), 0) AS p FROM q) SELECT p, count(*) AS c FROM r GROUP BY p",
    "stencil_3pt_ord": ORD + "SELECT g, 2 * lag(q) OVER (ORDER BY g) - 5 * q + 3 * lead(q) OVER (ORDER BY g) AS v FROM q",
    "lincomb_cust": "SELECT c_custkey, CAST(floor(c_acctbal / 20 + 0.5) AS BIGINT) * 3 - CAST(floor(c_custkey / 20.0 + 0.5) AS BIGINT) AS v FROM {customer}",
    "regional_mean_boxes": ORD + ", x AS (SELECT r_regionkey AS id, r_regionkey * 130 AS lo, r_regionkey * 170 + 60 AS hi FROM {region}), inside AS (SELECT x.id, b.n, b.s FROM x JOIN b ON b.b * 64 >= x.lo AND b.b * 64 + 63 <= x.hi), rim AS (SELECT x.id, count(*) AS n, CAST(sum(q.q) AS BIGINT) AS s FROM x JOIN b ON b.b * 64 <= x.hi AND b.b * 64 + 63 >= x.lo AND NOT (b.b * 64 >= x.lo AND b.b * 64 + 63 <= x.hi) JOIN q ON q.b = b.b AND q.g BETWEEN x.lo AND x.hi GROUP BY x.id), t AS (SELECT * FROM inside UNION ALL SELECT * FROM rim) SELECT id, CAST(sum(n) AS BIGINT) AS n, CAST(sum(s) AS BIGINT) AS int_num FROM t GROUP BY id",
}


def text(name: str, spark: bool) -> str:
    found = SQL[name]
    found = found if isinstance(found, str) else found[0 if spark else 1]
    for t in TABLES:
        found = found.replace(f"{{{t}}}", f"fl_{t}" if spark else t)
    return found


def run(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    found = text(name, True)
    for t in TABLES:
        if f"fl_{t}" in found:
            spark.read.parquet(f"{sf_dir}/{t}.parquet").createOrReplaceTempView(f"fl_{t}")
    return spark.sql(found)


QUERIES = {n: (lambda s, d, n=n: run(s, d, n)) for n in SQL}
ORACLES = {n: text(n, False) for n in SQL}
