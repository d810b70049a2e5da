"""Other encoders and the transform codec: round trips, bounds, and statistics without the inverse."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from fieldloom.functions.bitpack import LONGEST, Codes, huffman_lengths
from fieldloom.model import ErrorBound, Layout
from fieldloom.operators import encoders, transform
from fieldloom.operators.codecs import compress_points, partial_decompress
from fieldloom.plans import measures

SCHEMA = "field string, i bigint, j bigint, k bigint, value double"


def points(spark, a, name="f"):
    return spark.createDataFrame([(name, *map(int, (*at, 0, 0)[:3]), float(v)) for at, v in np.ndenumerate(a)], SCHEMA)


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(-(2**40), 2**40) | st.integers(-3, 3), min_size=1, max_size=90), st.integers(1, 9), st.integers(0, 6))
def test_huffman_round_trip(values, size, known):
    p = np.array(values, np.int64)
    sizes = np.array([size] * (len(p) // size) + ([len(p) % size] if len(p) % size else []))
    symbols, counts = np.unique(p, return_counts=True)
    table = dict(list(zip(symbols.tolist(), counts.tolist()))[:known])
    codes = Codes.of(table, len(p) - sum(table.values()))
    bits, escaped, payload = codes.encode(p, sizes)
    assert len(escaped) == len(p) - sum(table.values()) and -(-int(bits.sum()) // 8) == len(payload)
    assert np.array_equal(codes.decode(bits, sizes, escaped, payload), p)


def test_huffman_codes_are_best_and_bounded():
    counts = {0: 50, 1: 20, -1: 20, 5: 5, 7: 5}
    lengths = huffman_lengths(counts)
    assert sum(counts[s] * n for s, n in lengths.items()) == 50 + 2 * 20 + 3 * 20 + 4 * 10
    steep = [1, 1]
    while len(steep) < 80:
        steep.append(steep[-1] + steep[-2])
    assert max(huffman_lengths(dict(enumerate(steep))).values()) > LONGEST
    codes = Codes.of(dict(enumerate(steep)))
    assert codes.lengths.max() <= LONGEST and (1 << LONGEST - codes.lengths).sum() == 1 << LONGEST
    p, none = np.array([4, -9]), Codes.of({})
    bits, escaped, payload = none.encode(p, np.array([2]))
    assert none.decode(bits, np.array([2]), escaped, payload).tolist() == escaped.tolist() == [4, -9]


@pytest.mark.parametrize("encoder", encoders.ENCODERS)
def test_encoders_give_the_container_back(spark, tmp_path, encoder):
    a = np.cumsum(np.random.default_rng(3).normal(size=(19, 23)), axis=1)
    a[:, 5:14] = 2.0
    layout = Layout((8, 8), (8, 16))
    box = compress_points(points(spark, a), "lorenzo", ErrorBound(1e-2), 2, layout.chunk)
    codes = encoders.code_table(box, layout, 5) if encoder == "huffman" else None
    rows = encoders.packed_by(box, encoder, codes)
    if encoder == "columns":
        encoders.write_columns(rows, str(tmp_path / "columns"))
        rows = spark.read.schema(encoders.SCHEMAS[encoder]).parquet(str(tmp_path / "columns"))
    else:
        size = encoders.encoded_bytes(rows, encoder).first()
        assert size.blocks == 9 and 0 < size.bytes < a.size * 8
    back = encoders.unpacked(rows, encoder, codes)
    key = lambda r: (r.ci, r.cj)
    assert sorted(back.collect(), key=key) == sorted(box.collect(), key=key)
    assert encoders.unpacked(rows.limit(0), encoder, codes).count() == 0
    with pytest.raises(ValueError):
        encoders.packed_by(box, "none")
    with pytest.raises(ValueError):
        encoders.packed_by(box, "huffman")


@pytest.mark.parametrize(("shape", "block", "chunk"), [((37,), (8,), (16,)), ((11, 13), (8, 8), (8, 16)), ((5, 6, 9), (4, 4, 4), (4, 8, 4))])
def test_cosine_codec(spark, shape, block, chunk):
    a = np.random.default_rng(5).normal(size=shape) * 10 + 100
    layout = Layout(block, chunk)
    box = transform.compress_cosine(points(spark, a), ErrorBound(0.05, relative=False), layout).cache()
    n = [*chunk, 1, 1][:3]
    got = np.full(shape, np.nan)
    for r in transform.cosine_values(box, layout).collect():
        lo = [c * e for c, e in zip((r.ci, r.cj, r.ck), n)][: a.ndim]
        part = tuple(slice(x, x + c) for x, c in zip(lo, chunk))
        got[part] = np.array(r.data).reshape(got[part].shape)
    assert np.abs(got - a).max() <= 0.05
    mean, sd = transform.cosine_mean(box).first(), transform.cosine_stddev(box).first()
    assert mean.n == a.size and mean.result == pytest.approx(got.mean(), abs=1e-9) and mean.result == pytest.approx(a.mean(), abs=0.05)
    assert sd.result_micro == pytest.approx(got.std(ddof=1) * 1e6, abs=2)
    one = transform.cosine_stddev(transform.compress_cosine(points(spark, np.array([3.0])), ErrorBound(0.5, relative=False), Layout((8,), (8,)))).first()
    assert one.n == 1 and one.result_micro is None


def test_costs_grow_with_the_points(spark):
    layout = Layout((8, 8), (64, 64))
    cost = {}
    for n in (128, 256):
        a = spark.range(n * n).selectExpr("'f' AS field", f"id DIV {n} AS i", f"id % {n} AS j", "0L AS k", "CAST((id * 7919) % 1000 AS DOUBLE) AS value")
        box = compress_points(a, "lorenzo", ErrorBound(1e-3), 2, layout.chunk)
        cost["points", n] = measures.costs(spark, lambda: box.count())  # before a cache answers for it
        box = box.cache()
        box.count()
        cost["quant", n] = measures.costs(spark, lambda: partial_decompress(box, "lorenzo", layout, "QUANT").count())
        box.unpersist()
    for path in ("quant", "points"):
        small, large = cost[path, 128], cost[path, 256]
        assert small["shuffled"] > 0 and large["shuffled"] < 8 * small["shuffled"] and large["spilled"] == 0
    assert cost["quant", 256]["shuffled"] < cost["points", 256]["shuffled"] / 4  # carries, not points
