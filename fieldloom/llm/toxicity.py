"""Toxicity by maximum-scoring segments.

Token scores are log-odds of toxic against other documents under an informative Dirichlet prior.
A linear-time scan finds every maximal-scoring segment of a text; segments are judged by the
extreme-value law of such scores (E-value K n exp(-lambda S)), and a logistic curve over these
turns a document into a probability.
"""

from __future__ import annotations

import math
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import pieces, wider, written

TOKEN = re.compile(r"[^\W\d_]+")
MOST_TOXIC, MOST_CLEAN = 8000, 12000  # bounds on the labelled rows that the model is fitted on
FOLDS = 5  # parts of the sample, each scored by a lexicon of the others when the curve is fitted
PRIOR_SHARE = 0.1  # the prior weighs this share of all observed tokens
LEAST_Z = 3.0  # tokens whose log-odds are fewer standard deviations from 0 score 0
DRIFT = 0.25  # subtracted from each token's score, so that scores fall on average
LEAST_SEGMENT = 1.0


def maximal_segments(values: list[float]) -> list[tuple[float, int, int]]:
    """All maximal-scoring segments (score, first, last), found in one left-to-right scan.

    Each open segment keeps the place of the nearest one below it that starts from a lower total, so
    the search for that one jumps over all segments in between: linear time, whatever the scores.
    """
    stack: list[tuple[float, float, int, int, int]] = []  # (total before, total after, first, last, lower segment)
    total = 0.0
    for i, v in enumerate(values):
        before, total = total, total + v
        if v <= 0:
            continue
        start, first, below = before, i, len(stack) - 1
        while True:
            while below >= 0 and stack[below][0] >= start:
                below = stack[below][4]
            if below < 0 or stack[below][1] >= total:
                stack.append((start, total, first, i, below))
                break
            start, _, first, _, lower = stack[below]
            del stack[below:]
            below = lower
    return [(b - a, i, k) for a, b, i, k, _ in stack]


def segments(text: str, lexicon: dict[str, float]) -> tuple[int, list[tuple[float, int, int, int, int]]]:
    """(number of tokens, segments as (score, first token, last token, start, end in code points)).

    Tokens outside the lexicon lose DRIFT each; a run of them counts as one step, which changes no segment.
    """
    low = text.lower()
    if len(low) != len(text):  # a few letters grow when lowered; then offsets come from them as they are
        low = "".join(c.lower() if len(c.lower()) == 1 else c for c in text)
    get = lexicon.get
    hits, n = [], 0
    for n, s in enumerate(map(get, TOKEN.findall(low)), 1):
        if s is not None:
            hits.append((n - 1, s))
    if not hits:
        return n, []
    values, place, last = [], [], -1
    for i, s in hits:
        if i - last > 1:
            values.append(-DRIFT * (i - last - 1))
            place.append(-1)
        values.append(s - DRIFT)
        place.append(i)
        last = i
    found = [(s, place[a], place[b]) for s, a, b in maximal_segments(values) if s >= LEAST_SEGMENT]
    if not found:
        return n, []
    ends = {i for _, a, b in found for i in (a, b)}
    spans = {i: m.span() for i, m in enumerate(TOKEN.finditer(low)) if i in ends}
    return n, [(s, a, b, spans[a][0], spans[b][1]) for s, a, b in found]


def features(n: int, scores: list[float], lam: float, log_k: float) -> list[float]:
    """What the logistic curve sees: best and summed log significance of the segments, and length."""
    base = log_k + math.log(n + 1)
    nats = [min(60.0, lam * s - base) for s in scores]
    over = [x for x in nats if x > 0]
    return [max([-base, *nats]) / 10, min(12.0, sum(over) / 10), math.log1p(len(over)), math.log(n + 1) / 5, 1.0]


def logistic(x: np.ndarray, w: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x @ w, -40, 40)))


def fit_logistic(x: np.ndarray, y: np.ndarray, weight: np.ndarray) -> np.ndarray:
    """Newton steps with a small ridge."""
    w = np.zeros(x.shape[1])
    ridge = 1e-3 * np.eye(len(w))
    for _ in range(30):
        p = logistic(x, w)
        g = x.T @ (weight * (p - y)) + ridge @ w
        h = (x * (weight * np.maximum(p * (1 - p), 1e-6))[:, None]).T @ x + ridge
        step = np.linalg.solve(h, g)
        w -= step * min(1.0, 5.0 / max(1e-9, np.abs(step).max()))
    return w


def solve_lambda(p: np.ndarray, s: np.ndarray) -> float:
    """The positive root of the sum of p exp(lambda s) = 1: the decay rate of segment scores by chance."""
    if not (s > 0).any() or (p * s).sum() >= 0:
        return 1.0
    lo, hi = 1e-6, 1.0
    total = lambda v: float((p * np.exp(np.minimum(v * s, 600))).sum())
    while total(hi) < 1 and hi < 64:
        hi *= 2
    for _ in range(60):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if total(mid) < 1 else (lo, mid)
    return lo


def fit(docs: DataFrame, labels: DataFrame, most_toxic: int = MOST_TOXIC, most_clean: int = MOST_CLEAN) -> dict | None:
    """Model from ``docs`` (doc_id, text) and ``labels`` (doc_id, toxic); None if either class is missing.

    At most ``most_toxic`` and ``most_clean`` labelled documents, drawn by hash, are read for fitting;
    several labels of a document count as toxic if one does.  The class shares come from all labels.
    The curve over segment scores is fitted on scores by lexicons that have not seen the text.
    """
    flat = labels.where("doc_id is not null and toxic is not null").groupBy("doc_id").agg(F.max("toxic").alias("fl_toxic"))
    flat = flat.withColumn("fl_toxic", (F.col("fl_toxic") > 0).cast("int"))
    share = {r[0]: r[1] for r in flat.groupBy("fl_toxic").count().collect()}
    if len(share) < 2:
        return None
    draw = F.xxhash64("doc_id", F.lit(5))
    some = flat.where("fl_toxic = 1").orderBy(draw, "doc_id").limit(most_toxic).union(flat.where("fl_toxic = 0").orderBy(draw, "doc_id").limit(most_clean))
    # at most most_toxic + most_clean rows of two numbers: of a fixed size, so it is broadcast
    fold = F.pmod(F.xxhash64("text", F.lit(9)), F.lit(FOLDS)).cast("int").alias("fl_fold")  # copies fall in one
    sample = written(docs.select("doc_id", "text").where("text is not null").join(F.broadcast(some), "doc_id").select("text", "fl_toxic", fold), "toxicity-sample")

    def tokens(batches):
        for whole in batches:
            for b in pieces(whole, "text"):
                words, toxic, folds = [], [], []
                for t, y, h in zip(*(b.column(c).to_pylist() for c in ("text", "fl_toxic", "fl_fold"))):
                    own = set(TOKEN.findall(t.lower()))
                    words.extend(own)
                    toxic.extend([y] * len(own))
                    folds.extend([h] * len(own))
                yield pa.RecordBatch.from_arrays([pa.array(words, pa.string()), pa.array(toxic, pa.int32()), pa.array(folds, pa.int32())], names=["w", "y", "fold"])

    counts = sample.mapInArrow(tokens, "w string, y int, fold int").groupBy("w")
    counts = written(counts.agg(*[F.sum(((F.col("y") == y) & (F.col("fold") == h)).cast("int")).alias(f"{c}{h}") for h in range(FOLDS) for y, c in ((1, "t"), (0, "c"))]), "toxicity-counts")
    # a lexicon of all of the sample, and one without each fold, which scores that fold
    parts = {f"{h}": [" + ".join(f"{c}{k}" for k in range(FOLDS) if k != h) for c in "tc"] for h in (*range(FOLDS), "")}
    sums = counts.agg(*[F.sum(F.expr(e)).alias(f"{c}{h}") for h, own in parts.items() for c, e in zip("tc", own)]).first()
    if not sums["t"] or not sums["c"]:
        return None
    shown = []
    for h, own in parts.items():
        t, c, nt, nc = *map(F.expr, own), float(sums[f"t{h}"] or 0), float(sums[f"c{h}"] or 0)
        a0 = PRIOR_SHARE * (nt + nc) + 1e-9
        a = (F.expr(" + ".join(parts[""])) / (sums["t"] + sums["c"])) * a0
        odds = F.log((t + a) / (nt + a0 - t - a)) - F.log((c + a) / (nc + a0 - c - a))
        z = odds / F.sqrt(1 / (t + a) + 1 / (c + a))
        shown += [F.when(F.abs(z) >= LEAST_Z, odds).alias(f"s{h}"), ((c + a) / F.lit(nc + a0)).alias(f"p{h}")]
    # bounded, as the sample is
    rows = counts.select("w", *shown).where(" or ".join(f"s{h} is not null" for h in parts)).orderBy("w").collect()
    without = [{r["w"]: float(r[f"s{h}"]) for r in rows if r[f"s{h}"] is not None} for h in range(FOLDS)]
    rows = [r for r in rows if r["s"] is not None]
    if not rows:
        return None
    lexicon = {r["w"]: float(r["s"]) for r in rows}
    p, s = np.array([r["p"] for r in rows]), np.array([r["s"] for r in rows])
    lam = solve_lambda(np.append(p, max(0.0, 1 - p.sum())), np.append(s - DRIFT, -DRIFT))

    def scored(batches):
        for whole in batches:
            for b in pieces(whole, "text"):
                ys, ns, ss = b.column("fl_toxic"), [], []
                for t, h in zip(b.column("text").to_pylist(), b.column("fl_fold").to_pylist()):
                    n, found = segments(t, without[h])
                    ns.append(n)
                    ss.append([f[0] for f in found])
                yield pa.RecordBatch.from_arrays([ys.cast(pa.int32()), pa.array(ns, pa.int64()), pa.array(ss, pa.list_(pa.float64()))], names=["y", "n", "s"])

    seen = sorted((tuple([r["y"], r["n"], tuple(r["s"])]) for r in sample.mapInArrow(scored, "y int, n bigint, s array<double>").collect()))
    # K: segments over a middling score in other documents, against the positions they had to arise
    clean = [(n, sc) for y, n, sc in seen if y == 0]
    cut = float(np.median([x for _, sc in clean for x in sc] or [LEAST_SEGMENT]))
    many = sum(x >= cut for _, sc in clean for x in sc)
    log_k = math.log(max(many, 0.5) / max(1, sum(n for n, _ in clean))) + lam * cut
    x = np.array([features(n, list(sc), lam, log_k) for _, n, sc in seen])
    y = np.array([r[0] for r in seen], float)
    share_t = share[1] / (share[0] + share[1])
    weight = np.where(y > 0, share_t / max(1, (y > 0).sum()), (1 - share_t) / max(1, (y < 1).sum())) * len(y)
    return {"lexicon": lexicon, "lambda": lam, "log_k": log_k, "curve": fit_logistic(x, y, weight)}


SEGMENT = "array<struct<start:bigint,end:bigint,score:double,e_value:double>>"


def judge(docs: DataFrame, model: dict | None) -> DataFrame:
    """``docs`` with ``toxicity`` (0 to 1) and ``segments``: the passages found in each whole ``text``.

    A null or empty text has no segment and the score of an empty text; without a model every score
    is 0.  Repeated rows are judged alike; other columns pass through, and input columns named like
    the results are replaced.
    """
    keep = docs.drop("toxicity", "segments")
    item = pa.struct([("start", pa.int64()), ("end", pa.int64()), ("score", pa.float64()), ("e_value", pa.float64())])

    def run(batches):
        for whole in batches:
            for b in pieces(whole, "text"):
                feats, spans = [], []
                for t in b.column("text").to_pylist():
                    if model is None:
                        spans.append([])
                        continue
                    n, found = segments(t or "", model["lexicon"])
                    feats.append(features(n, [f[0] for f in found], model["lambda"], model["log_k"]))
                    spans.append([{"start": f[3], "end": f[4], "score": f[0], "e_value": math.exp(min(50.0, model["log_k"] + math.log(n + 1) - model["lambda"] * f[0]))} for f in found])
                score = logistic(np.array(feats), model["curve"]) if feats else np.zeros(b.num_rows)
                yield pa.RecordBatch.from_arrays([*b.columns, pa.array(score, pa.float64()), pa.array(spans, pa.list_(item))], names=[*b.schema.names, "toxicity", "segments"])

    return keep.mapInArrow(run, wider(keep, ("toxicity", "double"), ("segments", SEGMENT)))
