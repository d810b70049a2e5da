"""The registered queries of the subpackage against their SQL, and against brute force where SQL can't say it."""

import base64
import hashlib
import re
import zlib
from collections import Counter

import numpy as np
import pytest

from fieldloom.llm import queries

duckdb = pytest.importorskip("duckdb")
SF = "/root/testdata/sf0.001"
TABLES = ("documents", "embeddings", "benchmark", "labels")
pytestmark = pytest.mark.skipif(not __import__("os").path.isdir(SF), reason="no test tables")


@pytest.fixture(scope="module")
def db():
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{SF}/{t}.parquet')")
    return con


@pytest.fixture(scope="module")
def texts(db):
    return dict(db.execute("SELECT doc_id, text FROM documents").fetchall())


def rows_of(df):
    names = sorted(df.columns)
    return Counter(tuple(r[n] for n in names) for r in df.collect())


@pytest.mark.parametrize("name", sorted(queries.ORACLES | queries.SLOW_ORACLES))
def test_query_equals_its_sql(spark, db, name):
    got = queries.QUERIES[name](spark, SF)
    cur = db.execute((queries.ORACLES | queries.SLOW_ORACLES)[name])
    names = [c[0] for c in cur.description]
    order = sorted(range(len(names)), key=lambda i: names[i])
    assert sorted(names) == sorted(got.columns)
    assert rows_of(got) == Counter(tuple(r[i] for i in order) for r in cur.fetchall())


def held(doc_id, n, k):
    return zlib.crc32(str(doc_id).encode()) % n == k


def test_toxicity_query(spark, db, texts):
    toxic = dict(db.execute("SELECT doc_id, max(toxic) FROM labels GROUP BY doc_id").fetchall())
    out = queries.op1_toxicity(spark, SF).collect()
    assert sorted(r.doc_id for r in out) == sorted(texts)
    assert all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.3) and r.held_out == held(r.doc_id, 4, 2) for r in out)
    judged = [r for r in out if r.held_out and r.doc_id in toxic]
    assert sum(r.predicted == toxic[r.doc_id] for r in judged) >= 0.85 * len(judged)


def test_language_query(spark, db, texts):
    lang = dict(db.execute("SELECT doc_id, lang FROM documents").fetchall())
    out = queries.op7_language_id(spark, SF).collect()
    assert sorted(r.doc_id for r in out) == sorted(texts)
    assert all(r.held_out == held(r.doc_id, 5, 0) and 0 <= r.score <= 1 for r in out)
    for r in out:
        assert (r.lang_pred == "und") == (not any(c.isalpha() for c in texts[r.doc_id] or ""))
    judged = [r for r in out if r.held_out and lang[r.doc_id] and r.lang_pred != "und" and len(texts[r.doc_id].split()) > 5]
    assert sum(r.lang_pred == lang[r.doc_id] for r in judged) >= 0.95 * len(judged)


def test_bpe_query(spark, texts):
    import public_tokenizers as P
    import tiktoken

    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(P.path("byte_bpe_multi_50k.tiktoken"), "rb"))}
    enc = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    sha = lambda b: hashlib.sha256(b).hexdigest()
    want = set()
    for i, t in texts.items():
        ids = enc.encode_ordinary(t or "")
        want.add((i, len(ids), sha(",".join(map(str, ids)).encode()), sha((t or "").encode())))
    assert {tuple(r) for r in queries.op4_byte_bpe(spark, SF).select("doc_id", "n_tokens", "ids_sha256", "decoded_sha256").collect()} == want


ASSIGN = re.compile(r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.A)


def test_secret_query(spark, texts):
    out = {r.doc_id: r for r in queries.op8_secret_scan(spark, SF).collect()}
    assert sorted(out) == sorted(texts)
    for i, t in texts.items():
        t = t or ""
        spans = [(m.start(), 0, "assign", m.end()) for m in ASSIGN.finditer(t) if len(m[2]) >= 6]
        spans += [(m.start(), 1, "access", m.end()) for m in re.finditer("AKIA[A-Z0-9]+", t) if len(m[0]) >= 20]
        spans += [(m.start(), 2, "hex", m.end()) for m in re.finditer("[0-9a-f]+", t) if len(m[0]) >= 24]
        shown = [f"{k}:{a}:{b}" for a, _, k, b in sorted(spans)]
        many = Counter(k for _, _, k, _ in spans)
        r = out[i]
        assert (r.n_assign, r.n_access, r.n_hex) == tuple(many[k] for k in ("assign", "access", "hex"))
        assert r.base_sha256 == hashlib.sha256(",".join(shown).encode()).hexdigest()
        assert set(shown) <= set(r.spans.split(",")) | {""}


def test_neighbour_query(spark, db):
    rows = db.execute("SELECT vec_id, embedding FROM embeddings ORDER BY vec_id").fetchall()
    ids, x = np.array([r[0] for r in rows]), np.array([r[1] for r in rows], np.float64)
    got = {}
    for r in queries.op10_learned_partitions(spark, SF).collect():
        got.setdefault(r.query_id, []).append((r["rank"], r.vec_id, r.score))
    assert set(got) == {i for i in ids.tolist() if i % 100 == 0}
    hit = 0
    for q, found in got.items():
        d = np.sqrt(((x - x[ids == q]) ** 2).sum(1))
        d[ids == q] = np.inf
        best = ids[np.lexsort((ids, d))[:10]].tolist()
        found.sort()
        assert [f[0] for f in found] == list(range(1, 11)) and [f[1:] for f in found] == sorted((f[1:] for f in found), key=lambda f: (f[1], f[0]))
        assert all(abs(s - d[ids == v][0]) < 1e-12 for _, v, s in found)
        hit += len({v for _, v, _ in found} & set(best))
    assert hit >= 0.9 * 10 * len(got)
