"""A spread of registered queries against their SQL twins, and plans that should hold at any size."""

import math
from collections import Counter

import duckdb
import pytest

import __spark_entry__ as entry
from fieldloom.model import UnsupportedStage
from fieldloom.operators import differential as dif
from fieldloom.operators import relational
from fieldloom.plans import planner, workloads
from fieldloom.streaming import events

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SPREAD = [
    "eps_all_fields", "quantise_evt_grid", "stage_resid_lorenzo_part_price3", "stage_quant_chain1d_ord_price", "stage_value_midrange_ord_price",
    "mean_meannd_meta_emb", "mean_lorenzo_resid_evt_cube", "mean_quantop_ord_price", "sd_chain1d_resid_cust_bal", "sd_rounded_meannd_part_price",
    "grad_meannd_resid_part_price3", "grad_lorenzo_value_part_price", "lap_lorenzo_resid_part_price", "div2_meannd_resid_emb_uv", "curl3_lorenzo_quant_emb3",
    "widths_blockdiff_part_price", "ratio_meannd_part_price_1e3", "minmax_lorenzo_part_price", "stage_support",
    "rel_r22_as_of", "rel_r29_cube", "rel_r33_entropy", "regional_mean_boxes", "grad_boundary_periodic", "stream_session",
]


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"create view {t} as select * from read_parquet('{SF}/{t}.parquet')")
    return c


@pytest.mark.parametrize("name", SPREAD)
def test_query_equals_its_sql(spark, duck, name):
    df = entry.queries()[name](spark, SF)
    cols = sorted(df.columns)
    want = duck.sql(entry.oracle_sql()[name])
    assert sorted(want.columns) == cols
    rows = duck.sql(f"select {', '.join(cols)} from want").fetchall()
    assert Counter(repr(tuple(r)) for r in df.select(*cols).collect()) == Counter(map(repr, rows))


def test_entry_and_registry(spark):
    assert entry.entry(spark).count() == 3
    for module in (workloads, relational, planner, events):
        assert set(module.ORACLES) <= set(module.QUERIES)


def test_event_joins_keep_all_rows(spark, duck):
    events_ = {i: (kind, v) for i, kind, v in duck.sql("select event_id, event_type, value from events").fetchall()}
    marks = [n * 100 + 50 for (n,) in duck.sql("select n_nationkey from nation").fetchall()]
    want = {k: events_[max(i for i in events_ if i <= k)][1] for k in marks}
    assert {r.k: r.v for r in relational.run(spark, SF, "rel_r22_as_of").collect()} == want
    pairs = Counter((a, a + d) for a, (kind, _) in events_.items() if kind == "purchase" for d in (1, 2, 3) if a + d in events_)
    assert Counter((r.a, r.b) for r in relational.run(spark, SF, "rel_r23_interval_join").collect()) == pairs
    assert Counter(duck.sql(entry.oracle_sql()["rel_r23_interval_join"]).fetchall()) == pairs
    assert dict(duck.sql(entry.oracle_sql()["rel_r22_as_of"]).fetchall()) == want


def test_container_queries_take_all_blocks(spark, duck):
    rows = duck.sql("select o_orderkey, o_totalprice from orders order by 1").fetchall()
    eps = 0.001 * (max(v for _, v in rows) - min(v for _, v in rows))
    fine, coarse = {}, {}
    for g, v in rows:
        fine.setdefault(g // 64, []).append(math.floor(v / (2 * eps) + 0.5))
        coarse.setdefault(g // 64, []).append(math.floor(v / (20 * eps) + 0.5))
    got = {r.b: r.qs for r in relational.run(spark, SF, "rel_r26_array_agg").collect()}
    assert got == {b: ",".join(map(str, sorted(q))) for b, q in fine.items()}
    want = Counter((b, sum(q), sum(coarse[b]), 10 * sum(coarse[b]) - sum(q)) for b, q in fine.items())
    assert Counter((r.b, r.sx, r.sy, r.d) for r in relational.run(spark, SF, "rel_r19_container_diff").collect()) == want
    assert any(d for *_, d in want)


VALUE_VECTORS = ["div2_lorenzo_value_emb_uv", "curl2_midrange_value_emb_uv", "div3_mean1d_value_emb3", "curl3_blockdiff_value_emb3", "curl3_meannd_value_emb3", "div2_chain1d_value_emb_uv"]


@pytest.mark.parametrize("name", VALUE_VECTORS)
def test_vector_operations_of_values(spark, duck, name):
    df, want = entry.queries()[name](spark, SF), duck.sql(entry.oracle_sql()[name])
    rows = duck.sql(f"select {', '.join(df.columns)} from want").fetchall()
    assert rows and Counter(repr(tuple(r)) for r in df.collect()) == Counter(map(repr, rows))


def test_each_supported_vector_stage_is_registered(spark):
    for codec, operation, stage, _, points in (tuple(r) for r in planner.stage_support(spark, SF).collect()):
        assert points > 0
        if operation in ("divergence", "curl"):
            for n, where in ((2, "emb_uv"), (3, "emb3")):
                assert f"{operation[:3] if operation == 'divergence' else 'curl'}{n}_{codec}_{stage.lower()}_{where}" in entry.queries()


def test_integer_derivatives_refuse_values(spark):
    f = workloads.FIELDS["emb_u"]
    for codec in ("meannd", "mean1d"):
        c = workloads.packed(f, codec, spark, SF)
        with pytest.raises(UnsupportedStage):
            dif.grid_derivatives(c, codec, f.layout(workloads.CODECS[codec].flat), "VALUE", (500, 32), f.layout())


MOVED = ["ratio_grid_poly2d", "ratio_grid_poly3d", "worked_example", "stage_support", "advise_codec"]


@pytest.mark.parametrize("name", MOVED)
def test_moved_queries_read_a_table(spark, duck, name):
    df, want = entry.queries()[name](spark, SF), duck.sql(entry.oracle_sql()[name])
    assert any("orders" in f for f in df.inputFiles())
    rows = duck.sql("select " + ", ".join(f'"{c}"' for c in df.columns) + " from want").fetchall()
    assert rows and Counter(repr(tuple(r)) for r in df.collect()) == Counter(map(repr, rows))
