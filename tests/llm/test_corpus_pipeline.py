"""The corpus pipeline: its result against a chain of brute-force steps, and odd rows through each stage."""

import base64
import hashlib
import os

import pytest

import corpus_pipeline
from fieldloom.llm import decontaminate, line_dedup, ngram_join

duckdb = pytest.importorskip("duckdb")
SF = "/root/testdata/sf0.001"
pytestmark = pytest.mark.skipif(not os.path.isdir(SF), reason="no test tables")
COLUMNS = "doc_id BIGINT, text VARCHAR, lang VARCHAR, source VARCHAR, n_chars BIGINT"


def test_run_equals_brute_force(spark):
    import public_tokenizers as P
    import tiktoken

    con = duckdb.connect()
    con.execute(f"CREATE TABLE documents AS SELECT * FROM read_parquet('{SF}/documents.parquet')")
    con.execute(f"CREATE VIEW benchmark AS SELECT * FROM read_parquet('{SF}/benchmark.parquet')")
    # texts without a letter go; which language a text gets does not matter
    texts = con.execute("SELECT doc_id, text FROM documents").fetchall()
    con.executemany("DELETE FROM documents WHERE doc_id = ?", [(i,) for i, t in texts if not any(c.isalpha() for c in t or "")] or [(-1,)])
    kept = line_dedup.ORACLE.replace("sha256(coalesce(kept, ''))", "coalesce(kept, '')")
    lines = con.execute(f"SELECT doc_id, n_removed_lines, kept_sha256 FROM ({kept})").fetchall()
    con.executemany("UPDATE documents SET text = ? WHERE doc_id = ?", [(t, i) for i, n, t in lines if n])
    con.executemany("DELETE FROM documents WHERE doc_id = ?", [(i,) for i, n, t in lines if n and not t] or [(-1,)])
    links = con.execute(f"SELECT doc_id, component_id FROM ({ngram_join.ORACLE})").fetchall()
    con.executemany("DELETE FROM documents WHERE doc_id = ?", [(i,) for i, c in links if i != c] or [(-1,)])
    leaks = con.execute(f"SELECT doc_id FROM ({decontaminate.ORACLE}) WHERE n_hit > 0").fetchall()
    con.executemany("DELETE FROM documents WHERE doc_id = ?", leaks or [(-1,)])
    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(P.path("byte_bpe_multi_50k.tiktoken"), "rb"))}
    enc = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    want = {i: (t, enc.encode_ordinary(t)) for i, t in con.execute("SELECT doc_id, text FROM documents").fetchall()}
    got = {r.doc_id: r for r in corpus_pipeline.run(spark, SF).collect()}
    assert got.keys() == want.keys()
    for i, (t, ids) in want.items():
        assert got[i].text == t and got[i].token_ids == ids
        assert got[i].decoded_sha256 == hashlib.sha256(t.encode()).hexdigest()


ROWS = [
    (1, "a line of ordinary words, one\nand another line of words, two\nthird", "en", "s", 70, 1, 0.5),
    (2, "a line of ordinary words, one\nand another line of words, two\nfourth", "en", "s", 70, 1, 0.5),
    (2, "a line of ordinary words, one\nand another line of words, two\nfourth", "en", "s", 70, 1, 0.5),
    (None, "a text whose id is missing, of words", "en", "s", 30, 1, 0.5),
    (4, None, None, None, None, None, None),
    (5, "", "en", "s", 0, 1, 0.5),
    (6, "12 34 !!", "en", "s", 8, 1, 0.5),
    (7, "word " * 30_000, "en", "hot", 150_000, 1, 0.5),
    (8, "x" * 50_000, "fr", "hot", 50_000, 1, 0.5),
]
SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint, n_hit int, score double"


@pytest.mark.parametrize("name,stage", corpus_pipeline.STAGES)
def test_stages_take_odd_rows(spark, name, stage):
    docs = spark.createDataFrame(ROWS, SCHEMA).repartition(2)
    out = stage(spark, docs, SF)
    ids = [r.doc_id for r in out.collect()]
    last = name == corpus_pipeline.STAGES[-1][0]
    assert out.columns[: len(docs.columns)] == docs.columns if last else out.columns == docs.columns
    assert {7, 8} <= set(ids) and ids.count(1) == 1
    if name == "language ID":
        assert sorted(i for i in ids if i) == [1, 2, 2, 7, 8] and None in ids
    else:
        # 1 and 2 share 8 of 10 shingles, so the smaller id of the two stays
        assert None in ids and 4 in ids and ids.count(2) == (0 if "Jaccard" in name else 2)
    empty = stage(spark, docs.where("doc_id < 0"), SF)
    assert empty.columns == out.columns and empty.count() == 0
