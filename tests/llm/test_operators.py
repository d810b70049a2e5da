"""The dealt operators against brute force, on a fixture with nulls, ties, copies, long and empty texts."""

import base64
import hashlib
import random
import re
from collections import Counter

import numpy as np
import pytest

from fieldloom.llm import byte_bpe, decontaminate, language_id, learned_partitions, line_dedup, ngram_join, secret_scan, substring_dedup, suffix_dedup, toxicity

SCHEMA = "doc_id bigint, text string, n_words string, kept int, extra string"


def made_texts(seed=1):
    rnd = random.Random(seed)
    vocab = ["".join(rnd.choice("abcdeéß日") for _ in range(rnd.randrange(2, 7))) for _ in range(400)]
    text = lambda n: " ".join(rnd.choice(vocab) + rnd.choice(["", "", "", ".\n", ","]) for _ in range(n))
    passage, base = text(70), text(120)
    out = [text(rnd.randrange(1, 150)) for _ in range(40)]
    out += [text(20) + " " + passage + " " + text(30) for _ in range(12)]  # one passage in many
    out += [base] * 15  # exact copies
    words = base.split(" ")
    for _ in range(25):  # near copies
        w = list(words)
        for _ in range(rnd.randrange(1, 6)):
            w[rnd.randrange(len(w))] = rnd.choice(vocab)
        out.append(" ".join(w))
    out += ["", "   \t\n", "x", "a b c d", "A b C d", "the " * 300, text(4000), None, None]
    rnd.shuffle(out)
    return out


@pytest.fixture(scope="module")
def rows():
    texts = made_texts()
    rows = [(i * 3, t) for i, t in enumerate(texts)]
    rows.append(rows[5])  # a repeated row
    rows.append((None, texts[5]))
    return rows


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame([(i, t, "clash", 1, "kept along") for i, t in rows], SCHEMA).repartition(3)


def split(text):
    return [w for w in re.split(r"[\x20\x09-\x0D]+", text or "") if w]


def smallest(rows, size, units):
    first = {}
    for i, t in rows:
        if i is not None:
            u = units(t)
            for j in range(len(u) - size + 1):
                k = tuple(u[j : j + size])
                first[k] = min(first.get(k, i), i)
    return first


def gone(i, u, first, size):
    out = [False] * len(u)
    for j in range(len(u) - size + 1):
        if i is not None and first[tuple(u[j : j + size])] < i:
            out[j : j + size] = [True] * size
    return out


def test_substring_dedup(docs, rows):
    first = smallest(rows, 50, split)
    want = Counter()
    for i, t in rows:
        w = split(t)
        g = gone(i, w, first, 50)
        want[(i, len(w), sum(g), " ".join(x for x, y in zip(w, g) if not y))] += 1
    out = substring_dedup.deduplicate(docs)
    assert Counter((r.doc_id, r.n_words, r.n_removed, bytes(r.kept).decode()) for r in out.collect()) == want
    assert "extra" in out.columns


def test_suffix_dedup(docs, rows):
    units = lambda t: list((t or "").encode())
    first = smallest(rows, 50, units)
    want = Counter()
    for i, t in rows:
        b = units(t)
        g = gone(i, b, first, 50)
        runs = sum(1 for j, x in enumerate(g) if x and (j == 0 or not g[j - 1]))
        want[(i, len(b), sum(g), runs, bytes(x for x, y in zip(b, g) if not y))] += 1
    assert Counter((r.doc_id, r.n_bytes, r.n_removed, r.n_spans, bytes(r.kept)) for r in suffix_dedup.deduplicate(docs).collect()) == want


def test_bucket_refinement_orders_suffixes():
    text = np.frombuffer(b"abracadabra" * 9 + b"xabracadabra" * 4, np.uint8)
    got = suffix_dedup.refine(text, 20)
    keys = [text[i : i + 20].tobytes() for i in range(len(text) - 19)]
    order = {k: n for n, k in enumerate(sorted(set(keys)))}
    assert got.tolist() == [order[k] for k in keys]


def test_ngram_join(docs, rows):
    lower = str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)})
    sets = []
    for i, t in rows:
        w = split((t or "").translate(lower))
        sets.append((i, {tuple(w[j : j + 5]) for j in range(max(1, len(w) - 4))} if w else set()))
    parent = {i: i for i, _ in sets if i is not None}

    def top(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, (i, x) in enumerate(sets):
        for j, y in sets[:a]:
            if i is not None and j is not None and x and y and 100 * len(x & y) >= 75 * len(x | y):
                p, q = sorted((top(i), top(j)))
                parent[q] = p
    want = Counter((i, len(s), None if i is None else top(i)) for i, s in sets)
    got = Counter(tuple(r) for r in ngram_join.link_components(docs).collect())
    assert got == want
    assert max(Counter(r[2] for r in got if r[0] is not None).values()) > 10


def test_components_of_a_chain(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(0, 40)] + [(100, 101)], "a bigint, b bigint")
    assert {r.v: r.comp for r in ngram_join.components(edges).collect()} == {**{i: 0 for i in range(41)}, 100: 100, 101: 100}


def test_line_dedup(spark):
    chunk = "one line of some length here\nanother line follows it\nand a third one to end"
    texts = [f"head {i}\n{chunk}\n{chunk}\ntail {i}" for i in range(6)] + [None, "", "\n\n", chunk, "no break at all"]
    docs = spark.createDataFrame([(i, t, "c") for i, t in enumerate(texts)] + [(None, texts[0], "c")], "doc_id bigint, text string, kept string")
    out = {r.doc_id: r for r in line_dedup.deduplicate(docs).collect()}
    assert out[0].n_lines == 8 and out[6].kept is None and out[6].n_lines == 0
    assert out[10].kept == "no break at all" and out[None].kept == texts[0]
    for i in range(1, 6):
        assert out[i].n_removed_lines > 0 and out[i].kept.startswith(f"head {i}") and out[i].kept.endswith(f"tail {i}")
    assert sum(len(re.findall("another line", r.kept or "")) for r in out.values()) < sum(len(re.findall("another line", t or "")) for t in texts) + 2


def test_decontaminate(spark, rows):
    items = [(1, " ".join(made_texts()[3].split()[:40]) if made_texts()[3] else "q"), (2, "x"), (3, ""), (4, None), (5, "A b, c!")]
    source = next(t for _, t in rows if t and len(t.split()) > 60)
    items.append((6, " ".join(source.split()[10:40])))
    docs = spark.createDataFrame([(i, t, 0) for i, t in rows] + [(9999, source + " x", 0)], "doc_id bigint, text string, n_hit int")
    word = lambda t: re.findall("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
    windows = {}
    for i, t in items:
        w = word(t)
        for j in range(max(1, len(w) - 9)) if w else ():
            windows.setdefault(tuple(w[j : j + 10]), set()).add(str(i))
    want = Counter()
    for i, t in [*rows, (9999, source + " x")]:
        w, hit, found = word(t), set(), set()
        for k, own in windows.items():
            for j in range(len(w) - len(k) + 1):
                if tuple(w[j : j + len(k)]) == k:
                    hit |= set(range(j, j + len(k)))
                    found |= own
        want[(i, len(w), len(hit), tuple(sorted(found)))] += 1
    bench = spark.createDataFrame(items, "item_id bigint, text string")
    assert Counter((r.doc_id, r.n_words, r.n_hit, tuple(r.item_ids)) for r in decontaminate.find(docs, bench).collect()) == want
    near = decontaminate.proximity_matches(docs, bench, 12).collect()
    assert (9999, "6") in {tuple(r) for r in near}


def test_byte_bpe(docs, rows):
    import public_tokenizers as P
    import tiktoken

    path = P.path("byte_bpe_multi_50k.tiktoken")
    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(path, "rb"))}
    enc = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    odd = ["it's we'll 'tis ''s", " \n  x\t\ty  ", " a 1²³ ٣", "a'b'ss'RE're", "'r", "x 'l", "<|endoftext|>", "😀́é"]
    both = docs.select("doc_id", "text").union(docs.sparkSession.createDataFrame([(-n, t) for n, t in enumerate(odd, 1)], "doc_id bigint, text string"))
    out = byte_bpe.encode_documents(both, path, digests=True)
    for r in out.collect():
        want = enc.encode_ordinary(r.text or "")
        assert r.token_ids == want and r.n_tokens == len(want)
        assert r.ids_sha256 == hashlib.sha256(",".join(map(str, want)).encode()).hexdigest()
        assert r.decoded_sha256 == hashlib.sha256((r.text or "").encode()).hexdigest()
        assert (r.token_ends[-1] if want else 0) == len((r.text or "").encode())
    back = byte_bpe.decode_documents(out.select("text", "token_ids"), path)
    assert all(bytes(r.decoded) == (r.text or "").encode() for r in back.collect())


def test_secret_scan(spark):
    key = "AKIA" + "ABCDEFGH12345678"
    texts = [None, "", f"x {key}. password = 'hunter2hunter'; token: abc, {'0a' * 13}", 'base = "Zx81kQpw0"\napi_key = base + "9f"\nname = "Zebra"', "secret=secret=aaaaaa token=ab:cd", "é Password: Pa55w0rd!x", "K" * 5000]
    docs = spark.createDataFrame([(i, t, "clash") for i, t in enumerate(texts)], "doc_id int, text string, secrets string")
    got = {r.doc_id: r.secrets for r in secret_scan.scan(docs).collect()}
    pattern = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)
    for i, t in enumerate(texts):
        t = t or ""
        want = {("assign", *m.span()) for m in pattern.finditer(t) if len(m[2]) >= 6}
        want |= {("access", *m.span()) for m in re.finditer(r"AKIA[A-Z0-9]+", t) if len(m[0]) >= 20}
        want |= {("hex", *m.span()) for m in re.finditer(r"[0-9a-f]+", t) if len(m[0]) >= 24}
        assert {(s.kind, s.start, s.end) for s in got[i] if s.kind != "named"} == want
    # the constant reaches the sensitive name by reference
    assert {texts[3][s.start : s.end] for s in got[3] if s.kind == "named"} == {"Zx81kQpw0", "9f"}


def test_maximal_segments_are_ruzzo_tompas():
    def slow(v):
        if not any(x > 0 for x in v):
            return []
        best, at = 0, None
        for i in range(len(v)):
            for j in range(i, len(v)):
                s = sum(v[i : j + 1])
                if s > best or s == best and at and (j - i) < at[1] - at[0]:
                    best, at = s, (i, j)
        i, j = at
        return slow(v[:i]) + [(best, i, j)] + [(s, a + j + 1, b + j + 1) for s, a, b in slow(v[j + 1 :])]

    rnd = random.Random(3)
    for _ in range(300):
        v = [rnd.choice([-7, -5, -3, -1.5, 2, 3.25, 4.125, 1.0625]) + rnd.random() / 64 for _ in range(rnd.randrange(0, 14))]
        got = [(round(s, 6), a, b) for s, a, b in toxicity.maximal_segments(v)]
        assert got == [(round(s, 6), a, b) for s, a, b in slow(v)]


def test_toxicity_and_language(spark):
    rnd = random.Random(5)
    en, fr = "the of and to in that is was for with on as by at from".split(), "le la les de des et en que pour dans sur une avec pas".split()
    bad = ["scumbagly", "idiotish", "moronical"]
    rows, labels = [], []
    for i in range(400):
        words = [rnd.choice(en if i % 2 else fr) + rnd.choice(["", "", "ing" if i % 2 else "eau"]) for _ in range(60)]
        if i % 4 == 1:
            for _ in range(3):
                words.insert(rnd.randrange(len(words)), rnd.choice(bad))
        rows.append((i, " ".join(words), "en" if i % 2 else "fr", 7))
        labels.append((i, int(i % 4 == 1)))
    rows += [(900, None, "en", 7), (901, "", None, 7), (902, "12 34!", "fr", 7)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, lang string, score int")
    labs = spark.createDataFrame([*labels, (None, 1), (5, None)], "doc_id bigint, toxic int")
    model = toxicity.fit(docs.select("doc_id", "text"), labs.where("doc_id % 3 <> 0"))
    got = {r.doc_id: r for r in toxicity.judge(docs, model).collect()}
    assert all((got[i].toxicity >= 0.3) == (i % 4 == 1) for i in range(400) if i % 3 == 0)
    assert all(0 <= r.toxicity <= 1 for r in got.values()) and got[901].toxicity < 0.3
    hit = next(r for r in got.values() if r.segments)
    assert any(b in hit.text[hit.segments[0].start : hit.segments[0].end] for b in bad)
    assert {r.toxicity for r in toxicity.judge(docs, None).collect()} == {0.0}
    out = {r.doc_id: r for r in language_id.identify(docs, docs.where("doc_id % 5 <> 0").select("text", "lang")).collect()}
    assert all(out[i].lang_pred == ("en" if i % 2 else "fr") for i in range(400))
    assert [out[i].lang_pred for i in (900, 901, 902)] == ["und"] * 3
    none = language_id.identify(docs, docs.where("doc_id < 0").select("text", "lang"))
    assert {r.lang_pred for r in none.collect()} == {"und"}


def test_learned_partitions(spark):
    rng = np.random.default_rng(2)
    x = rng.normal(size=(900, 16))
    x[100:140] = x[100]  # equal vectors
    rows = [(i, v.tolist()) for i, v in enumerate(x)] + [(2000, None), (2001, [0.0] * 16), (2002, [float("nan")] * 16), (2003, [1.0] * 3), (2004, [None] * 16)]
    df = spark.createDataFrame(rows, "vec_id bigint, embedding array<double>")
    got = {}
    for r in learned_partitions.search(df, df.where("vec_id % 100 = 0")).collect():
        got.setdefault(r.query_id, []).append((r["rank"], r.vec_id, r.score))
    assert set(got) == set(range(0, 900, 100))
    hit = 0
    for q, found in got.items():
        d = np.sqrt(((x - x[q]) ** 2).sum(1))
        d[q] = np.inf
        best = np.lexsort((np.arange(900), d))[:10]
        found.sort()
        assert [f[0] for f in found] == list(range(1, 11)) and all(abs(s - d[v]) < 1e-12 for _, v, s in found)
        hit += len({v for _, v, _ in found} & set(best.tolist()))
    assert hit >= 0.9 * 10 * len(got)
    assert [v for _, v, _ in got[100]] == list(range(101, 111))
    assert learned_partitions.search(df.where("vec_id < 0"), df).count() == 0


def test_empty_tables(spark):
    docs = spark.createDataFrame([], "doc_id bigint, text string, lang string")
    bench = spark.createDataFrame([], "item_id bigint, text string")
    labels = spark.createDataFrame([], "doc_id bigint, toxic int")
    assert substring_dedup.deduplicate(docs).count() == 0
    assert suffix_dedup.deduplicate(docs).count() == 0
    assert ngram_join.link_components(docs).count() == 0
    assert line_dedup.deduplicate(docs).count() == 0
    assert decontaminate.find(docs, bench).count() == 0
    assert secret_scan.scan(docs).count() == 0
    assert byte_bpe.encode_documents(docs, byte_bpe.default_ranks(spark)).count() == 0
    assert language_id.identify(docs, docs).count() == 0
    assert toxicity.fit(docs, labels) is None


def test_line_dedup_takes_each_repeated_run(spark):
    rnd = random.Random(3)
    pool = [f"line {i} " + "abcdefgh"[: rnd.randrange(8)] * rnd.randrange(4) for i in range(60)] + ["", "x", "yes", "é", "日"]
    texts = []
    for _ in range(60):
        lines = [rnd.choice(pool) for _ in range(rnd.randrange(1, 12))]
        if texts and rnd.random() < 0.7:  # a passage of 2 to 6 lines of an earlier text
            old = rnd.choice(texts).split("\n")
            at = rnd.randrange(len(old))
            lines[rnd.randrange(len(lines)) : 0] = old[at : at + rnd.randrange(2, 7)]
        texts.append("\n".join(lines))
    texts += ["x\n" * 90, "a line that is long enough by itself\n" * 5, texts[7], texts[9]]
    seen, want = {}, {}
    for d, t in enumerate(texts):  # each run of lines of the least size, against all earlier ones
        lines, gone = t.split("\n"), set()
        for a in range(len(lines)):
            for b in range(a + 2, len(lines) + 1):
                run = tuple(lines[a:b])
                if len("\n".join(run)) >= 32:
                    e, at = seen.setdefault(run, (d, a))
                    if e < d or at + len(run) <= a:
                        gone |= set(range(a, b))
        want[d] = (len(lines), len(gone), "\n".join(x for i, x in enumerate(lines) if i not in gone))
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string").repartition(3)
    assert {r.doc_id: (r.n_lines, r.n_removed_lines, r.kept) for r in line_dedup.deduplicate(docs).collect()} == want


def test_secret_scan_keeps_each_literal_of_a_statement():
    literals = [f"Zx{i}kQ9p" for i in range(90)]
    text = "part = " + " + ".join(f'"{x}"' for x in literals) + "\npassword = part + '7Tz'\n"
    want = {text.index(x) for x in literals} | {text.index("7Tz")}
    assert want <= {a for a, *_ in secret_scan.named_literals(text)}
    chain = 'token = "Q9xZ81kP"\n' + "".join(f"token = token + token + 'u{i}Xz'\n" for i in range(3000))
    assert len(secret_scan.named_literals(chain)) == 3001


def thue_morse(n, one, other):
    return "".join(other if bin(i).count("1") % 2 else one for i in range(n))


def test_words_that_weak_hashes_confuse(spark):
    """Long words of two letters, equal under any polynomial modulo 2**64, are different words."""
    a, b = thue_morse(1024, "a", "b"), thue_morse(1024, "b", "a")
    head, tail = [f"w{i}" for i in range(30)], [f"x{i}" for i in range(30)]
    docs = spark.createDataFrame([(1, " ".join([*head, a, *tail])), (2, " ".join([*head, b, *tail])), (3, " ".join([*head, a, *tail[:-1]]))], "doc_id bigint, text string")
    assert {r.doc_id: r.n_removed for r in substring_dedup.deduplicate(docs).collect()} == {1: 0, 2: 0, 3: 60}
    texts = [" ".join([x] * 3 + [y] + ["end"] * 2) for x in (a, b) for y in ("p", "q")]
    linked = ngram_join.link_components(spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string"))
    assert {r.doc_id: r.component_id for r in linked.collect()} == {0: 0, 1: 1, 2: 2, 3: 3}


def test_segment_scan_is_linear():
    import time

    for v in ([1.0, -1.5] * 40_000, [-1.0, 1.5] * 40_000):
        began = time.time()
        toxicity.maximal_segments(v)
        assert time.time() - began < 2


def test_byte_bpe_of_long_slices(spark):
    import time

    import public_tokenizers as P
    import tiktoken

    path = P.path("byte_bpe_multi_50k.tiktoken")
    ranks = byte_bpe.load_ranks(path)
    enc = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    codec = byte_bpe.Codec(ranks, byte_bpe.class_table(), byte_bpe.pair_slots(ranks))
    rnd = random.Random(4)
    for letters in ("abcdefghijklmnopqrstuvwxyz", "ab", "a", "aetion", "日本語中文"):
        for n in (250, 257, 700, 4000):
            text = "".join(rnd.choice(letters) for _ in range(n))
            ids, cuts = codec.encode(["x " + text, text, ""])
            assert [ids[a:b].tolist() for a, b in zip(cuts[:-1], cuts[1:])] == [enc.encode_ordinary(t) for t in ("x " + text, text, "")]
    long = "".join(rnd.choice("etaoinshrdlu") for _ in range(300_000))
    began = time.time()
    ids, _ = codec.encode([long])
    assert time.time() - began < 20 and codec.decode(ids.tolist()).decode() == long


def test_language_draw_keeps_each_language(spark):
    rnd = random.Random(8)
    rows = [("le petit chat est dans la maison de la mère", "fr")] * 3000
    rows += [(" ".join(rnd.choice("the of and to in that house cat mother is".split()) for _ in range(12)), "en") for _ in range(600)]
    rows += [("un autre texte pour la langue", "fr"), (None, "fr"), ("123", "fr"), ("no label", None)]
    got = Counter(lang for lang, _ in language_id.training_rows(spark.createDataFrame(rows, "text string, lang string"), 200))
    assert got == {"fr": 2, "en": 100}


def test_language_rows_stay_off_the_driver(spark, monkeypatch):
    rows = [(f"{w} {n} house of the cat", "en") for n, w in enumerate("one two three four".split())] + [(f"{w} {n} maison de la mère", "fr") for n, w in enumerate("un deux trois quatre".split())]
    docs = spark.createDataFrame(rows, "text string, lang string")
    want = language_id.fit(language_id.training_rows(docs, 8))

    def collected(*_):
        raise AssertionError("rows to learn from came to the driver")

    monkeypatch.setattr(language_id, "training_rows", collected)
    assert {(r.lang, r.lang_pred) for r in language_id.identify(docs, docs).collect()} == {("en", "en"), ("fr", "fr")}
    got = language_id.fitted(docs, 8)
    assert got["families"] == want["families"] and np.allclose(got["top"][0][2], want["top"][0][2], atol=1e-5)


#: Text, and what of it is secret.
LABELLED = [
    ('password = "hT7#kq92Lm"', ["hT7#kq92Lm"]),
    ("db:\n  password: |\n    hT7kq92Lm\n    Zp0xW81\n  user: bob\n", ["hT7kq92Lm", "Zp0xW81"]),
    ('API_SECRET = """hT7kq92LmZp0"""', ["hT7kq92LmZp0"]),
    ("<conf><password>hT7kq92Lm</password><user>alice</user></conf>", ["hT7kq92Lm"]),
    ('client.setPassword("hT7kq92Lm");', ["hT7kq92Lm"]),
    ('new Login().withToken("Zp0xW81QqLm2", 3)', ["Zp0xW81QqLm2"]),
    ("mysql --user bob --password hT7kq92Lm --host db", ["hT7kq92Lm"]),
    ("PW=hT7kq92Lm\nrun --password $PW\n", ["hT7kq92Lm"]),
    ('API_TOKEN := os.Getenv("API_TOKEN")', []),
    ("token = config.auth.token", []),
    ('secret = load_secret("path/to/it")', []),
    ("# old: password = 'hT7kq92Lm'\npassword = ask()", ["hT7kq92Lm"]),
    ('/* token: "Zp0xW81QqLm2" */ int token;', ["Zp0xW81QqLm2"]),
    ('url = "postgres://bob:hT7kq92Lm@db/x"', ["hT7kq92Lm"]),
    ('a = "hT7k"\nb = a + "q92Lm"\nsecret_key = b', ["hT7k", "q92Lm"]),
    ("const apiKey = `Zp0xW81QqLm2`;", ["Zp0xW81QqLm2"]),
    ('{"user": "bob", "accessKey": "Zp0xW81QqLm2"}', ["Zp0xW81QqLm2"]),
    ('name = "hT7kq92Lm"', []),
    ('password = "changeme"', []),
    ("The key point: tokens are words, and the password is a word too.", []),
    ('print("password: ", x)  # it\'s fine', []),
    ('keyboard = "hT7kq92Lm"', []),
    ('passphrase => "correct-Horse7battery"', ["correct-Horse7battery"]),
    ('salt = "Zp0xW81QqLm2"', ["Zp0xW81QqLm2"]),
]


def test_secret_lexer_on_labelled_texts():
    hit = missed = wrong = 0
    for text, want in LABELLED:
        got = [text[a:b] for a, b, *_ in secret_scan.named_literals(text)]
        hit += len(set(got) & set(want))
        missed += len(set(want) - set(got))
        wrong += len(set(got) - set(want))
    assert hit / (hit + missed) >= 0.95 and hit / (hit + wrong) >= 0.95, (hit, missed, wrong)


def test_secret_lexer_on_long_texts():
    import time

    for text in ("/* " * 100_000 + "key", '"""' * 100_000 + "key", "'" * 200_000 + "key", "key" + "A1b2" * 250_000, "key: " * 100_000, "<a>" * 100_000 + "key", "key(" * 100_000, "--key " * 50_000, "a://b:" * 50_000, "password: |\n" + " x1Y2z3\n" * 50_000):
        began = time.time()
        secret_scan.named_literals(text)
        assert time.time() - began < 10, text[:20]


def test_learned_partitions_prune_data_with_structure():
    rng = np.random.default_rng(6)
    x = rng.normal(size=(60, 24))[rng.integers(60, size=4000)] * 4 + rng.normal(size=(4000, 24)) * 0.4
    model = learned_partitions.fit(x[:3200])
    assert model["visits"] <= learned_partitions.LEAST_PARTS // 2
    order = learned_partitions.route(x, model)
    near = learned_partitions.nearest_in(x, 10)[3200:]
    found = (order[:, 0][near][:, :, None] == order[3200:, : model["visits"]][:, None, :]).any(2)
    assert found.mean() >= 0.9
    assert learned_partitions.parts_for(10**9) > learned_partitions.parts_for(10**5) >= learned_partitions.LEAST_PARTS
