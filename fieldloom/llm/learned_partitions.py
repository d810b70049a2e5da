"""Approximate nearest neighbours by learned partitions.

A bounded sample's neighbour graph is cut into parts of equal size, more of them for more rows, and a
small network learns to tell the part of a vector.  Every row is filed under its likeliest part; a query is routed to as many
of its likeliest parts as the sample shows are needed, and the rows there are ranked exactly.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

LEAST_SAMPLE, MOST_SAMPLE = 4000, 20_000  # bounds on the rows that the index is fitted on
LEAST_PARTS, MOST_PARTS = 16, 256
PART_ROWS = 5000  # rows a part while there are fewer than the most parts
SLICE_ROWS = 65_536  # rows of a part that one task holds against a block of queries
HIDDEN = 96
NEIGHBOURS = 10
WANTED_RECALL = 0.95  # on rows that the net has not seen; sets how many parts a query visits
BLOCK_ROWS, BLOCK_QUERIES = 1024, 256


def squared_distances(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.maximum(0.0, (a * a).sum(1)[:, None] + (b * b).sum(1)[None] - 2 * a @ b.T)


def nearest_in(x: np.ndarray, k: int) -> np.ndarray:
    """Row numbers of each row's k nearest other rows."""
    out = np.empty((len(x), k), np.int64)
    for at in range(0, len(x), 512):
        d = squared_distances(x[at : at + 512], x)
        d[np.arange(len(d)), at + np.arange(len(d))] = np.inf
        out[at : at + 512] = np.argpartition(d, k - 1, axis=1)[:, :k]
    return out


def balanced_parts(x: np.ndarray, graph: np.ndarray, parts: int, rounds: int = 10) -> np.ndarray:
    """Parts of the neighbour graph: seeded around spread centres, then moved to where neighbours are, under a size cap."""
    n = len(x)
    cap = -(-n * 21 // (20 * parts))
    rng = np.random.default_rng(7)
    centres = x[rng.choice(n, parts, replace=False)]
    # votes of both directions of each edge
    src = np.repeat(np.arange(n), graph.shape[1])
    ends = np.concatenate([src, graph.ravel()]), np.concatenate([graph.ravel(), src])
    part = None
    for r in range(rounds):
        if r < 4:
            if part is not None:
                centres = np.vstack([x[part == p].mean(0) if (part == p).any() else centres[p] for p in range(parts)])
            want = -squared_distances(x, centres)
        else:
            want = np.zeros((n, parts))
            np.add.at(want, (ends[0], part[ends[1]]), 1.0)
            want[np.arange(n), part] += 0.5
        order = np.argsort(-want, axis=1, kind="stable")
        gain = np.take_along_axis(want, order[:, :1], 1)[:, 0] - np.take_along_axis(want, order[:, 1:2], 1)[:, 0]
        room, new = np.full(parts, cap), np.full(n, -1)
        for i in np.argsort(-gain, kind="stable").tolist():  # the most decided rows choose first
            for p in order[i].tolist():
                if room[p]:
                    new[i] = p
                    room[p] -= 1
                    break
        part = new
    return part


def fit_router(x: np.ndarray, target: np.ndarray, steps: int = 200) -> tuple:
    """One hidden layer, softmax over parts, full-batch Adam."""
    rng = np.random.default_rng(3)
    d, k = x.shape[1], target.shape[1]
    w = [rng.normal(0, 1 / np.sqrt(d), (d, HIDDEN)), np.zeros(HIDDEN), rng.normal(0, 1 / np.sqrt(HIDDEN), (HIDDEN, k)), np.zeros(k)]
    m, v = [np.zeros_like(a) for a in w], [np.zeros_like(a) for a in w]
    for t in range(1, steps + 1):
        h = np.maximum(0, x @ w[0] + w[1])
        z = h @ w[2] + w[3]
        p = np.exp(z - z.max(1, keepdims=True))
        p /= p.sum(1, keepdims=True)
        e = (p - target) / len(x)
        back = (e @ w[2].T) * (h > 0)
        for i, g in enumerate((x.T @ back, back.sum(0), h.T @ e, e.sum(0))):
            m[i] = 0.9 * m[i] + 0.1 * g
            v[i] = 0.999 * v[i] + 0.001 * g * g
            w[i] = w[i] - 0.01 * (m[i] / (1 - 0.9**t)) / (np.sqrt(v[i] / (1 - 0.999**t)) + 1e-8)
    return tuple(w)


def route(x: np.ndarray, model: dict) -> np.ndarray:
    """Parts of each row, likeliest first."""
    if model["net"] is None:
        return np.zeros((len(x), 1), np.int64)
    x = (x - model["mean"]) / model["scale"]
    h = np.maximum(0, x @ model["net"][0] + model["net"][1])
    return np.argsort(-(h @ model["net"][2] + model["net"][3]), axis=1, kind="stable")


def parts_for(rows: int) -> int:
    """Parts of an index over so many rows."""
    return max(LEAST_PARTS, min(MOST_PARTS, rows // PART_ROWS))


def fit(x: np.ndarray, parts: int = LEAST_PARTS, k: int = NEIGHBOURS, recall: float = WANTED_RECALL) -> dict:
    """Router from sample vectors (n, d); with few rows there is a single part."""
    n = len(x)
    if n < 20 * parts:
        return {"net": None, "visits": 1}
    graph = nearest_in(x, k)
    part = balanced_parts(x, graph, parts)
    target = np.zeros((n, parts))
    target[np.arange(n), part] = 1.0
    for j in range(k):
        target[np.arange(n), part[graph[:, j]]] += 1.0
    model = {"mean": x.mean(0), "scale": float(x.std()) or 1.0}
    # routing is measured on rows that the net has not seen
    fresh = np.arange(n) % 8 == 0
    model["net"] = fit_router((x[~fresh] - model["mean"]) / model["scale"], (target / (k + 1))[~fresh])
    order = route(x, model)
    home = order[:, 0]
    rank = np.empty_like(order)
    np.put_along_axis(rank, order, np.arange(parts)[None], 1)
    need = np.sort(rank[np.flatnonzero(fresh)[:, None], home[graph[fresh]]].ravel())
    model["visits"] = int(need[min(len(need) - 1, int(np.ceil(recall * len(need))))]) + 1
    return model


def matrix(column: pa.Array) -> np.ndarray:
    arr = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    n = len(arr)
    return np.asarray(arr.flatten(), dtype=np.float64).reshape(n, -1) if n else np.zeros((0, 0))


def usable(vectors: DataFrame) -> DataFrame:
    """(vec_id, fl_v) of the rows that take part: no null, non-finite or all-zero vector, and the most common length only."""
    v = vectors.select(F.col("vec_id").cast("bigint").alias("vec_id"), F.col("embedding").cast("array<double>").alias("fl_v"))
    good = F.forall("fl_v", lambda x: x.isNotNull() & (F.abs(x) < F.lit(float("inf"))) & ~F.isnan(x)) & F.exists("fl_v", lambda x: x != 0)
    v = v.where(F.col("vec_id").isNotNull() & F.col("fl_v").isNotNull() & good)
    top = v.groupBy(F.size("fl_v").alias("n")).count().orderBy(F.desc("count"), "n").first()
    return v.where(F.size("fl_v") == (top["n"] if top else 0))


def search(vectors: DataFrame, queries: DataFrame, k: int = NEIGHBOURS, model: dict | None = None) -> DataFrame:
    """(query_id, rank, vec_id, score): the ``k`` nearest rows of ``vectors`` for each row of ``queries``.

    Both have (vec_id, embedding).  A query's own id is no candidate; nearness is the Euclidean distance
    in double precision, ties go to the smaller vec_id.  Rows with null, zero, non-finite or odd-length
    vectors take no part; of rows with one vec_id and vector one takes part; other columns are ignored.
    """
    base, asked = usable(vectors), usable(queries)
    many = base.count()
    parts = parts_for(many)
    if model is None:
        some = max(LEAST_SAMPLE, min(MOST_SAMPLE, 80 * parts))
        rows = base.orderBy(F.xxhash64("fl_v", F.lit(1)), "vec_id").limit(some).select("fl_v").collect()
        model = fit(np.array([r[0] for r in rows], dtype=np.float64).reshape(len(rows), -1) if rows else np.zeros((0, 1)), parts)
    visits = model["visits"]
    slices = -(-many // (parts * SLICE_ROWS)) or 1  # of each part; a query's block goes to all of them
    # of equal vectors only the k + 1 smallest ids can be among a query's k nearest
    copies = Window.partitionBy("fl_v").orderBy("vec_id")
    rows = base.dropDuplicates(["vec_id", "fl_v"]).withColumn("fl_c", F.row_number().over(copies)).where(F.col("fl_c") <= k + 1).drop("fl_c")

    def packed(visits: int, most: int):
        def run(batches):
            held: dict[int, list] = {}

            def flush(p):
                own = held.pop(p)
                ids, xs = np.concatenate([a for a, _ in own]), np.vstack([b for _, b in own])
                for at in range(0, len(ids), most):
                    yield pa.RecordBatch.from_arrays([pa.array([p], pa.int32()), pa.array([ids[at : at + most].tobytes()], pa.binary()), pa.array([xs[at : at + most].tobytes()], pa.binary())], names=["part", "ids", "xs"])

            for b in batches:
                if not b.num_rows:
                    continue
                ids, x = np.asarray(b.column("vec_id"), np.int64), matrix(b.column("fl_v"))
                order = route(x, model)[:, :visits]
                for p in np.unique(order).tolist():
                    at = (order == p).any(1)
                    held.setdefault(p, []).append((ids[at], x[at]))
                    if sum(len(a) for a, _ in held[p]) >= most:
                        yield from flush(p)
            for p in list(held):
                yield from flush(p)

        return run

    layout = "part int, ids binary, xs binary"
    filed = rows.mapInArrow(packed(1, BLOCK_ROWS), layout).withColumn("slice", F.pmod(F.xxhash64("ids"), F.lit(slices)))
    routed = asked.dropDuplicates(["vec_id", "fl_v"]).mapInArrow(packed(visits, BLOCK_QUERIES), layout).select("part", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(slices - 1).cast("bigint"))).alias("slice"), F.col("ids").alias("q_ids"), F.col("xs").alias("q_xs"))

    def ranked(batches):
        for b in batches:
            for i in range(b.num_rows):
                ids, q_ids = (np.frombuffer(b.column(c)[i].as_py(), np.int64) for c in ("ids", "q_ids"))
                x, q = (np.frombuffer(b.column(c)[i].as_py(), np.float64).reshape(len(m), -1) for c, m in (("xs", ids), ("q_xs", q_ids)))
                if x.shape[1] != q.shape[1]:
                    continue
                near = squared_distances(q, x)
                near[q_ids[:, None] == ids[None]] = np.inf
                slack = 1e-9 * (1 + (q * q).sum(1) + (x * x).sum(1).max())
                bound = np.partition(near, min(k, len(ids)) - 1, axis=1)[:, min(k, len(ids)) - 1] + slack
                out = []
                for j in range(len(q)):
                    at = np.flatnonzero((near[j] <= bound[j]) & (q_ids[j] != ids))
                    d = np.sqrt(((x[at] - q[j]) ** 2).sum(1))
                    best = np.lexsort((ids[at], d))[:k]
                    out.append((np.full(len(best), q_ids[j]), ids[at][best], d[best]))
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*out)], names=["query_id", "vec_id", "score"])

    pairs = filed.join(routed, ["part", "slice"]).select("ids", "xs", "q_ids", "q_xs").mapInArrow(ranked, "query_id bigint, vec_id bigint, score double")
    w = Window.partitionBy("query_id").orderBy("score", "vec_id")
    return pairs.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
