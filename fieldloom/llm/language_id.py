"""Language identification by hierarchical discrimination.

A text is first assigned to a language family, then to a language of that family.  Both
steps use one-versus-one linear support vector machines over hashed character n-grams.
"""

from __future__ import annotations

import pickle

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import pieces, text_buffers, wider

#: Families of ISO 639-1 codes.  A code that is absent is a family of its own.
FAMILIES = {
    "germanic": ("en", "de", "nl", "sv", "da", "no", "nb", "nn", "is", "af", "fy", "lb", "yi"),
    "romance": ("fr", "es", "it", "pt", "ro", "ca", "gl", "oc", "la"),
    "slavic": ("ru", "uk", "be", "pl", "cs", "sk", "sl", "hr", "sr", "bs", "bg", "mk"),
    "uralic": ("fi", "et", "hu"),
    "turkic": ("tr", "az", "kk", "uz", "ky", "tk"),
    "indic": ("hi", "bn", "mr", "ne", "pa", "gu", "ur"),
    "semitic": ("ar", "he", "mt", "am"),
}

WIDTH = 4096  # hashed n-gram dimensions
MOST_TRAINING_ROWS = 4000  # bound on the distinct labelled texts that the classifiers are fitted on
BATCH_ROWS = 1024  # texts whose n-gram rows are in memory at once
UNKNOWN = "und"


def family_of(lang: str) -> str:
    base = lang.lower().replace("_", "-").split("-")[0]
    return next((f for f, codes in FAMILIES.items() if base in codes), f"own:{lang}")


def ngram_rows(column: pa.Array, width: int = WIDTH) -> np.ndarray:
    """Unit-length rows of square-rooted counts of hashed byte 2- and 3-grams of lower-cased texts."""
    raw, off, _ = text_buffers(pc.utf8_lower(column))
    n = len(off) - 1
    out = np.zeros((n, width), dtype=np.float32)
    if len(raw) < 2:
        return out
    b = raw.astype(np.uint32)
    two = b[:-1] * np.uint32(0x9E3779B1) + b[1:] * np.uint32(0x85EBCA77)
    three = (two[:-1] * np.uint32(0x2C1B3C6D) + b[2:] * np.uint32(0x297A2D39)) >> np.uint32(7)
    two >>= np.uint32(11)
    two &= np.uint32(width - 1)
    three &= np.uint32(width - 1)
    for i in range(n):
        s, e = off[i], off[i + 1]
        if e - s >= 2:
            out[i] = np.bincount(two[s : e - 1], minlength=width)
            if e - s >= 3:
                out[i] += np.bincount(three[s : e - 2], minlength=width)
    np.sqrt(out, out=out)
    norm = np.sqrt(np.einsum("ij,ij->i", out, out))
    out /= np.maximum(norm, 1e-9)[:, None]
    return out


def fit_svm(plus: list[np.ndarray], minus: list[np.ndarray], c: float = 10.0, steps: int = 120) -> np.ndarray:
    """Squared-hinge linear SVM of rows ``plus`` against ``minus``, by accelerated gradient descent. The bias is last.

    Rows come as views on one table, so no pair of classes needs a copy of its own.
    """
    d = (plus + minus)[0].shape[1] + 1
    sides = [(x, np.float32(y), np.float32(0.5 / max(1, sum(map(len, own))))) for own, y in ((plus, 1.0), (minus, -1.0)) for x in own]
    w = z = np.zeros(d, np.float32)
    rate, t = 1.0 / (1.0 / c + 4.0), 1.0
    for _ in range(steps):
        grad = z / np.float32(c) / 10
        for x, y, share in sides:
            push = share * y * np.maximum(np.float32(0), 1 - y * (x @ z[:-1] + z[-1]))
            grad[:-1] -= 2 * (push @ x)
            grad[-1] -= 2 * push.sum()
        new = z - np.float32(rate) * grad
        t2 = (1 + np.sqrt(1 + 4 * t * t)) / 2
        z = new + np.float32((t - 1) / t2) * (new - w)
        w, t = new, t2
    return w


def fit_pairs(classes: list[list[np.ndarray]]) -> list[tuple[int, int, np.ndarray]]:
    """A machine for each two of ``classes``, each a list of tables of rows."""
    return [(i, j, fit_svm(classes[i], classes[j])) for i in range(len(classes)) for j in range(i + 1, len(classes))]


def vote(x: np.ndarray, pairs: list, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Winner of the one-versus-one votes (ties: larger summed margin) and its smallest won margin."""
    if k == 1:
        return np.zeros(len(x), np.int64), np.full(len(x), np.inf)
    wins = np.zeros((len(x), k))
    least = np.full((len(x), k), np.inf)
    for i, j, w in pairs:
        m = x @ w[:-1] + w[-1]
        wins[:, i] += (m >= 0) + 1e-6 * np.tanh(m)
        wins[:, j] += (m < 0) - 1e-6 * np.tanh(m)
        least[:, i] = np.minimum(least[:, i], m)
        least[:, j] = np.minimum(least[:, j], -m)
    best = wins.argmax(1)
    return best, least[np.arange(len(x)), best]


def fit(rows: list[tuple[str, bytes]]) -> dict | None:
    """Model from (language, packed n-gram row) pairs; None without rows."""
    langs = sorted({lang for lang, _ in rows})
    if not langs:
        return None
    rows = sorted(rows)
    x = np.zeros((len(rows), WIDTH), np.float32)
    for row, (_, v) in zip(x, rows):
        k = len(v) // 6
        row[np.frombuffer(v, np.uint16, k)] = np.frombuffer(v, np.float32, k, 2 * k)
    ends = np.cumsum([sum(lang == k for lang, _ in rows) for k in langs]).tolist()
    own = dict(zip(langs, (x[a:b] for a, b in zip([0, *ends], ends))))
    fams = sorted({family_of(k) for k in langs})
    members = [[k for k in langs if family_of(k) == f] for f in fams]
    within = [(m, fit_pairs([[own[k]] for k in m])) for m in members]
    return {"families": fams, "top": fit_pairs([[own[k] for k in m] for m in members]), "within": within}


def predict(model: dict | None, column: pa.Array) -> tuple[list[str], np.ndarray]:
    n = len(column)
    lettered = np.asarray(pc.fill_null(pc.match_substring_regex(column, r"\p{L}"), False))
    names, score = [UNKNOWN] * n, np.zeros(n)
    if model is None or not lettered.any():
        return names, score
    x = ngram_rows(column)
    fam, margin = vote(x, model["top"], len(model["families"]))
    score = 1 / (1 + np.exp(-4 * np.minimum(margin, 50)))
    for f, (langs, pairs) in enumerate(model["within"]):
        at = np.flatnonzero((fam == f) & lettered)
        if len(at):
            got, m = vote(x[at], pairs, len(langs))
            score[at] *= 1 / (1 + np.exp(-4 * np.minimum(m, 50)))
            for i, g in zip(at.tolist(), got.tolist()):
                names[i] = langs[g]
    return names, np.where(lettered, score, 0.0)


def drawn_rows(docs: DataFrame, most: int) -> DataFrame | None:
    """(fl_lang, v) of at most ``most`` distinct labelled texts as packed n-gram rows, shared evenly among languages; None without any.

    They are drawn by a hash of the text, and a text counts once however often it stands in ``docs``,
    so copies can't push a language's other texts out, nor leave it without any.  Numbers of distinct
    texts are estimated over all labelled rows.
    """
    docs = docs.select(F.col("lang").alias("fl_lang"), F.col("text").alias("fl_text")).where("fl_lang is not null and fl_text is not null").where(F.col("fl_text").rlike(r"\p{L}"))
    counts = {r[0]: r[1] for r in docs.groupBy("fl_lang").agg(F.approx_count_distinct(F.xxhash64("fl_text")).alias("c")).orderBy(F.desc("c"), "fl_lang").limit(most).collect()}
    if not counts:
        return None
    each = max(1, most // len(counts))
    # about twice the share passes the hash filter, all of a language with few texts; the window then sees a bounded set
    share = F.create_map(*[F.lit(v) for k, c in counts.items() for v in (k, 1.0 if c < 8 * each else 2.0 * each / c)])
    draw = F.pmod(F.xxhash64("fl_text", F.lit(11)), F.lit(1 << 30)) / float(1 << 30)
    some = docs.withColumn("fl_draw", draw).where(F.col("fl_draw") < share[F.col("fl_lang")])
    some = some.groupBy("fl_lang", "fl_draw").agg(F.min("fl_text").alias("fl_text"))
    w = Window.partitionBy("fl_lang").orderBy("fl_draw", "fl_text")

    def grams(batches):
        for b in row_batches(batches, "fl_text"):
            made = []
            for row in ngram_rows(b.column("fl_text")):
                at = np.flatnonzero(row)
                made.append(at.astype(np.uint16).tobytes() + row[at].tobytes())
            yield pa.RecordBatch.from_arrays([b.column("fl_lang"), pa.array(made, pa.binary())], names=["fl_lang", "v"])

    drawn = some.withColumn("fl_n", F.row_number().over(w)).where(F.col("fl_n") <= each).select("fl_lang", "fl_text")
    return drawn.mapInArrow(grams, "fl_lang string, v binary")


def training_rows(docs: DataFrame, most: int) -> list[tuple[str, bytes]]:
    """The drawn rows as pairs."""
    rows = drawn_rows(docs, most)
    return [] if rows is None else [tuple(r) for r in rows.collect()]


def fitted(docs: DataFrame, most: int) -> dict | None:
    """The model of the drawn rows, fitted in one task: their number is bounded, and the model alone reaches the driver."""
    rows = drawn_rows(docs, most)
    if rows is None:
        return None

    def run(batches):
        held = [pair for b in batches for pair in zip(b.column("fl_lang").to_pylist(), b.column("v").to_pylist())]
        yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps(fit(held))], pa.binary())], names=["model"])

    made = rows.repartition(1).mapInArrow(run, "model binary").first()
    return pickle.loads(made[0]) if made else None


def row_batches(batches, column: str):
    """Slices of record batches by bytes of ``column`` and by rows."""
    for whole in batches:
        for b in pieces(whole, column):
            for at in range(0, b.num_rows, BATCH_ROWS):
                yield b.slice(at, BATCH_ROWS)


def identify(docs: DataFrame, train: DataFrame, most_rows: int = MOST_TRAINING_ROWS) -> DataFrame:
    """``docs`` with ``lang_pred`` and ``score`` added, fitted on ``train`` (text, lang).

    Every whole text is read.  A null or letterless text gives ``und`` and score 0; so does every
    text if ``train`` has no labelled row.  Repeated rows are judged alike; other columns pass
    through untouched, and input columns named like the results are replaced.  Ties between
    languages go to the larger summed margin, then to the alphabetically first.
    """
    model = fitted(train, most_rows)
    keep = docs.drop("lang_pred", "score")
    schema = wider(keep, ("lang_pred", "string"), ("score", "double"))

    def run(batches):
        for b in row_batches(batches, "text"):
            names, score = predict(model, b.column("text"))
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(names, pa.string()), pa.array(score, pa.float64())], names=[*b.schema.names, "lang_pred", "score"])

    return keep.mapInArrow(run, schema)
