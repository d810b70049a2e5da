"""The staged engine: goldens, identities between stages, bounds and plans."""

from fractions import Fraction

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from fieldloom.functions import bitpack
from fieldloom.functions.quantise import checked
from fieldloom.model import META, QUANT, RESID, VALUE, ErrorBound, Layout, UnsupportedStage, require
from fieldloom.operators import differential as dif
from fieldloom.operators import statistics as sta
from fieldloom.operators.codecs import block_order, compress_points, half_down, partial_decompress, region, to_points
from fieldloom.plans import measures, planner
from fieldloom.sources import container as box

SCHEMA = "field string, i bigint, j bigint, k bigint, value double"


def points(spark, a, name="f"):
    grid = [(name, *map(int, (*at, 0, 0)[:3]), float(v)) for at, v in np.ndenumerate(a)]
    return spark.createDataFrame(grid, SCHEMA)


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(-(2**40), 2**40), min_size=1, max_size=90), st.integers(1, 9))
def test_fixed_width_round_trip(values, size):
    p = np.array(values, np.int64)
    sizes = np.array([size] * (len(p) // size) + ([len(p) % size] if len(p) % size else []))
    width, payload = bitpack.encode_fixed(p, sizes)
    assert np.array_equal(bitpack.decode_fixed(width, sizes, payload), p)
    assert len(payload) == bitpack.packed_bytes(sizes, width).sum()
    assert np.array_equal(bitpack.decode_runs(*bitpack.encode_runs(p)), p)


def test_huffman_lengths_satisfy_kraft():
    lengths = bitpack.huffman_lengths({0: 50, 1: 20, -1: 20, 5: 5, 7: 5})
    assert sum(2.0**-x for x in lengths.values()) == 1.0 and lengths[0] == min(lengths.values())
    assert bitpack.huffman_lengths({3: 9}) == {3: 1}


def test_rounding_rules():
    assert half_down(np.array([11, 22, -11, 7]), np.array([2, 4, 2, 2])).tolist() == [5, 5, -6, 3]
    order, sizes = block_order((3, 5), (2, 2))
    assert sizes.tolist() == [4, 4, 2, 2, 2, 1] and order[:4].tolist() == [0, 1, 5, 6]


def test_worked_example(spark):
    field = points(spark, np.array(measures.WORKED))
    got = {(r.i, r.j): (r.q, r.m, r.p) for r in measures.tile_example(field, Layout((2, 2), (2, 4))).collect()}
    q = [[6, 8, -11, -12], [13, -5, 10, 9]]
    p = [[1, 3, -10, -11], [8, -10, 11, 10]]
    assert got == {(i, j): (q[i][j], 5 if j < 2 else -1, p[i][j]) for i in range(2) for j in range(4)}


def compress(spark, a, codec, chunk, eps=0.5, anchor="grid"):
    flat = codec in ("chain1d", "mean1d", "blockdiff", "midrange")
    layout = Layout({1: (4,), 2: (2, 3), 3: (2, 2, 2)}[1 if flat else a.ndim], chunk)
    from fieldloom.functions.quantise import quantised
    from fieldloom.operators.chunks import flatten_grid, to_chunks
    from fieldloom.operators.codecs import compress_chunks

    q = quantised(points(spark, a), ErrorBound(eps, relative=False))
    return compress_chunks(to_chunks(flatten_grid(q) if flat else q, layout), codec, layout, anchor), layout


@pytest.mark.parametrize("shape,chunk", [((17,), (8,)), ((7, 11), (4, 6)), ((5, 6, 7), (4, 2, 4)), ((1, 9), (2, 3))])
def test_stages_agree_with_brute_force(spark, shape, chunk):
    a = np.random.default_rng(4).integers(-50, 50, shape).astype(float)
    q = np.floor(a + 0.5).astype(np.int64)
    for codec in ("lorenzo", "meannd"):
        c, layout = compress(spark, a, codec, chunk)
        back = {(r.i, r.j, r.k): r.v for r in to_points(partial_decompress(c, codec, layout, QUANT), layout).collect()}
        assert back == {(*at, 0, 0)[:3]: v for at, v in np.ndenumerate(q)}
        for stage in (RESID, QUANT):
            m = sta.field_mean(c, codec, layout, stage).first()
            assert (m.n, m.int_num) == (q.size, int(q.sum()))
            assert sta.field_stddev(c, codec, layout, stage).first().result == pytest.approx(np.std(q, ddof=1))
            inner = all(s > 2 for s in shape)
            got = {(r.i, r.j, r.k): (r.d0, r.d1, r.d2, r.lap) for r in dif.derivatives(c, codec, layout, stage).collect()}
            assert bool(got) == inner
            for at, d in got.items():
                at = at[: len(shape)]
                step = [tuple(np.add(at, np.eye(len(shape), dtype=int)[x] * s)) for x in range(len(shape)) for s in (1, -1)]
                v = [int(q[s]) for s in step]
                assert d[: len(shape)] == tuple(v[2 * x] - v[2 * x + 1] for x in range(len(shape)))
                assert d[3] == sum(v) - 2 * len(shape) * int(q[tuple(at)])


def test_chain_carries_over_blocks_and_chunks(spark):
    a = np.cumsum(np.random.default_rng(1).integers(-3, 4, 100)).astype(float)
    for anchor in ("grid", "chunk"):
        c, layout = compress(spark, a, "chain1d", (16,), anchor=anchor)
        v = to_points(partial_decompress(c, "chain1d", layout, VALUE, anchor), layout).orderBy("i").collect()
        assert [r.v for r in v] == a.tolist()
    c, layout = compress(spark, a, "chain1d", (16,))
    assert sta.field_mean(c, "chain1d", layout, RESID).first().int_num == int(a.sum())


def test_rounded_centre_and_its_bias(spark):
    c, layout = compress(spark, np.array([1.0, 0, 2, 1]), "mean1d", (4,))
    layout2 = Layout((2,), (4,))
    from fieldloom.functions.quantise import quantised
    from fieldloom.operators.chunks import to_chunks
    from fieldloom.operators.codecs import compress_chunks

    q = quantised(points(spark, np.array([1.0, 0, 2, 1])), ErrorBound(0.5, relative=False))
    c = compress_chunks(to_chunks(q, layout2), "mean1d", layout2)
    exact = sta.field_stddev(c, "mean1d", layout2, RESID).first().result
    rounded = sta.field_stddev(c, "mean1d", layout2, RESID, "rounded").first().result
    # the two roundings leave an offset r of the centre: squares differ by n / (n - 1) r r
    assert rounded**2 - exact**2 == pytest.approx(4 / 3 * 1.0)


def test_mean_from_metadata_is_within_the_bound(spark):
    a = np.random.default_rng(8).normal(size=(20, 30)) * 40
    c, layout = compress(spark, a, "meannd", (8, 12), eps=0.3)
    assert abs(sta.field_mean(c, "meannd", layout, META).first().result - sta.field_mean(c, "meannd", layout, QUANT).first().result) <= 0.3


def test_metadata_stage_reads_no_payload(spark, tmp_path):
    c, layout = compress(spark, np.arange(60.0).reshape(6, 10), "meannd", (4, 6))
    path = str(tmp_path / "c")
    box.write_container(c, path)
    stored = box.read_container(spark, path)
    plan = sta.field_mean(stored, "meannd", layout, META)._jdf.queryExecution().executedPlan().toString()
    scan = next(x for x in plan.splitlines() if "FileScan" in x)
    assert "payload" not in scan.split("ReadSchema")[1]
    assert sta.field_mean(stored, "meannd", layout, QUANT).first().int_num == sum(range(60))
    part = region(stored, layout, (0, 0), (3, 5))
    assert part.count() == 1 and "PushedFilters: [IsNotNull(ci)" in part._jdf.queryExecution().executedPlan().toString()


def test_unsupported_stages_raise(spark):
    for codec, stage, op in (("chain1d", META, "mean"), ("mean1d", META, "sd"), ("chain1d", RESID, "gradient"), ("midrange", RESID, "mean"), ("blockdiff", QUANT, "gradient")):
        with pytest.raises(UnsupportedStage):
            require(codec, stage, op)


def test_invalid_values(spark):
    p = points(spark, np.array([1.0, float("nan"), 3.0]))
    with pytest.raises(Exception, match="null, NaN or infinite"):
        checked(p).collect()
    assert checked(p, "mask").count() == 2
    assert {r.value for r in checked(p, "fill", -1.0).collect()} == {1.0, -1.0, 3.0}


def test_constant_field_and_one_point(spark):
    c = compress_points(points(spark, np.full((3, 3), 7.0)), "meannd", ErrorBound(1e-3), 2)
    layout = Layout((8, 8), (256, 256))
    assert sta.field_stddev(c, "meannd", layout, RESID).first().result == 0.0
    assert c.first().payload == b""
    one = compress_points(points(spark, np.array([5.0])), "chain1d", ErrorBound(1e-3), 1)
    assert sta.field_stddev(one, "chain1d", Layout((64,), (65536,)), QUANT).first().result is None


def test_curl_of_a_gradient_vanishes(spark):
    psi = np.random.default_rng(3).integers(-9, 9, (12, 12)).astype(float)
    c, layout = compress(spark, psi, "meannd", (4, 6))
    d = dif.derivatives(c, "meannd", layout, QUANT).collect()
    gx, gy = np.zeros((12, 12)), np.zeros((12, 12))
    for r in d:
        gx[r.i, r.j], gy[r.i, r.j] = r.d0, r.d1
    parts = []
    for g in (gx, gy):
        cc, ll = compress(spark, g, "lorenzo", (4, 6))
        parts.append(dif.derivatives(cc, "lorenzo", ll, RESID))
    out = dif.curl(parts).where("i between 2 and 9 and j between 2 and 9").collect()
    assert out and all(r.result == 0 for r in out)


def test_planner():
    assert planner.choose_stage("meannd", "mean", 2) == META and planner.choose_stage("meannd", "sd", 2) == RESID
    assert planner.choose_stage("lorenzo", "gradient", 2) == RESID and planner.choose_stage("lorenzo", "gradient", 3) == QUANT
    assert planner.choose_stage("meannd", "laplacian", 3) == QUANT
    assert planner.recommend_codec("vector", 2) == "lorenzo" and planner.recommend_codec("statistics", 3) == "meannd"


def test_raw_files(spark, tmp_path):
    a = np.arange(24, dtype="<f4").reshape(4, 6)
    (tmp_path / "u.f32").write_bytes(a.tobytes())
    got = {(r.i, r.j): r.value for r in box.raw_field(spark, str(tmp_path / "u.f32"), "u", (4, 6)).collect()}
    assert got == {at: float(v) for at, v in np.ndenumerate(a)}


def test_result_chunks_and_boundaries(spark):
    a = np.random.default_rng(7).integers(-30, 30, (9, 10)).astype(float)
    c, layout = compress(spark, a, "lorenzo", (4, 6))
    for stage in (RESID, QUANT, VALUE):
        got = {}
        for r in dif.result_chunks(dif.prepared(c, "lorenzo", layout, stage)).collect():
            at = [tuple(np.add(r.lo, x)) for x in np.ndindex(*r["shape"])]
            got |= dict(zip(at, r.d0))
        scale = 0.5 if stage == VALUE else 1
        assert got == {(i, j): (a[i + 1, j] - a[i - 1, j]) * scale for i in range(1, 8) for j in range(1, 9)}
    wide = np.pad(a, 1, mode="edge")
    clamp = {(r.i, r.j): (r.d0, r.d1) for r in dif.derivatives(c, "lorenzo", layout, RESID, boundary="clamp").collect()}
    assert clamp == {(i, j): (wide[i + 2, j + 1] - wide[i, j + 1], wide[i + 1, j + 2] - wide[i + 1, j]) for i in range(9) for j in range(10)}
    with pytest.raises(UnsupportedStage):
        dif.prepared(c, "lorenzo", layout, RESID, boundary="periodic")


def test_a_grid_with_holes_is_an_error(spark):
    from fieldloom.operators.codecs import compress_points

    p = points(spark, np.arange(20.0).reshape(4, 5))
    both = p.where("not (i = 1 and j = 2)").union(p.where("i = 0 and j = 0"))  # one missing, one twice
    with pytest.raises(Exception, match="1 points missing and 1 repeated"):
        compress_points(both, "meannd", ErrorBound(1e-3), 2).collect()


def test_sums_beyond_64_bits():
    big = np.full(1000, 1 << 40)
    assert sta.exact(big, big) == 1000 << 80 and sta.exact(big) == 1000 << 40


def test_carries_of_a_long_line(spark, monkeypatch):
    from fieldloom.operators import chunks

    monkeypatch.setattr(chunks, "LINE", 3)  # many pieces of a line
    a = np.random.default_rng(9).integers(-9, 9, 150).astype(float)
    c, layout = compress(spark, a, "chain1d", (8,))
    back = to_points(partial_decompress(c, "chain1d", layout, QUANT), layout).orderBy("i").collect()
    assert [r.v for r in back] == a.astype(int).tolist()


def test_generic_operators(spark):
    from fieldloom.operators import generic

    a = np.random.default_rng(2).integers(-20, 20, (7, 11)).astype(float)
    for codec in ("lorenzo", "meannd"):
        c, layout = compress(spark, a, codec, (4, 6))
        boxes = spark.createDataFrame([(1, [0, 0], [6, 10]), (2, [3, 4], [5, 7]), (3, [90, 0], [99, 2])], "id bigint, lo array<bigint>, hi array<bigint>")
        got = {r.id: (r.n, r.s1, r.lowest, r.highest) for r in generic.regional(c, codec, layout, boxes).collect()}
        part = a[3:6, 4:8]
        assert got == {1: (77, a.sum(), a.min(), a.max()), 2: (12, part.sum(), part.min(), part.max())}
        cells = {(r.i, r.j) for r in generic.isosurface_cells(c, codec, layout, 0.5).collect()}
        four = [a[i : i + 6, j : j + 10] for i in (0, 1) for j in (0, 1)]
        assert cells == {tuple(map(int, x)) for x in np.argwhere((np.minimum.reduce(four) < 0.5) & (np.maximum.reduce(four) >= 0.5))}


def test_micro_batches_become_containers(spark, tmp_path):
    from fieldloom.streaming import events

    rows = [(i, "click" if i % 3 else "view", float(i % 7)) for i in range(40)]
    spark.createDataFrame(rows, "event_id bigint, event_type string, value double").write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema("event_id bigint, event_type string, value double").parquet(str(tmp_path / "in"))
    events.compress_batches(stream, str(tmp_path / "out"), str(tmp_path / "state")).start().awaitTermination()
    layout = Layout((64,), (65536,))
    c = spark.read.parquet(str(tmp_path / "out")).drop("batch")
    got = {r.field: r.int_num for r in sta.field_mean(c, "mean1d", layout, QUANT).collect()}
    assert got == {k: sum(round(v / (2 * events.EPS)) for _, t, v in rows if t == k) for k in ("click", "view")}


def test_mean_of_values_is_exact_in_any_order(spark):
    a = np.random.default_rng(6).uniform(4e8, 3e9, (60, 70))
    box, layout = compress(spark, a, "lorenzo", (8, 9), 0.05)
    v = np.floor(a / 0.1 + 0.5) * 0.1
    want = sum(map(Fraction, v.ravel().tolist()))
    got = {sta.field_mean(box.repartition(n, "ci", "cj"), "lorenzo", layout, VALUE).first().result_micro for n in (1, 7)}
    assert got == {round(float(want) / a.size * 1e6)}
    assert sta.expansion([1e16, 1.0, -1e16, 2.0**-60]) == [1.0, 2.0**-60] and sta.expansion([]) == []
