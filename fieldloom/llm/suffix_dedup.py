"""Suffix-array deduplication of bytes by bucket-pointer refinement.

A shard holds the suffixes of the stretches that may recur.  Each has a pointer to the bucket of its
first 8 bytes.  Buckets of more than one suffix are refined, each within its bounds, by sorting on the
pointers at later offsets; the new pointers serve the next refinement at twice the reach, until they
tell 50 bytes apart.  A suffix that is alone in its bucket is not touched again.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .repeats import WINDOW, binary_array, gathered, ragged, rejoined, removed_units, windows_of

FIRST = 8  # bytes that initial buckets look at


def first_bytes(text: np.ndarray, at: np.ndarray) -> np.ndarray:
    """The FIRST bytes from each place, as numbers in byte order."""
    codes = np.zeros(len(at), np.uint64)
    for i in range(FIRST):
        codes = (codes << np.uint64(8)) | text[at + i].astype(np.uint64)
    return codes


def runs_of(ranked: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(where the run of equal values of each place starts, whether the place is alone in it) of sorted values."""
    fresh = np.concatenate([[True], ranked[1:] != ranked[:-1]])
    start = np.maximum.accumulate(np.where(fresh, np.arange(len(ranked)), 0))
    return start, fresh & np.append(fresh[1:], True)


def refine(text: np.ndarray, length: int, starts: np.ndarray | None = None, codes=first_bytes, first: int = FIRST) -> np.ndarray:
    """For each of ``starts`` (all with room), the bucket of the ``length`` units from there; buckets are in order.

    ``codes(text, places)`` numbers the ``first`` units from each place.
    """
    n = len(text) - first + 1
    if starts is None:
        starts = np.arange(len(text) - length + 1)
    if not len(starts):
        return np.zeros(0, np.int64)
    steps, reach = [], first
    while reach < length:
        steps.append(min(reach, length - reach))
        reach += steps[-1]
    # from the last round back: the suffixes whose pointers the rounds after it read
    read = [np.zeros(n, bool)]
    read[0][starts] = True
    for step in reversed(steps):
        more = read[0].copy()
        more[step:] |= read[0][:-step]
        read.insert(0, more)
    at = np.flatnonzero(read[0])
    code = codes(text, at)
    order = np.argsort(code)
    at = at[order]
    pointer, alone = np.zeros(n, np.uint64), np.zeros(n, bool)
    pointer[at], alone[at] = runs_of(code[order])
    for step, later in zip(steps, read[1:]):
        at = np.flatnonzero(later & ~alone)
        if not len(at):
            break
        key = (pointer[at] << np.uint64(32)) | pointer[at + step]
        order = np.argsort(key)
        at, key = at[order], key[order]
        whole, _ = runs_of(key >> np.uint64(32))
        part, single = runs_of(key)
        pointer[at] += (part - whole).astype(np.uint64)
        alone[at] = single
    used = np.zeros(n + 1, np.int64)
    found = pointer[starts].astype(np.int64)
    used[found] = 1
    return (np.cumsum(used) - 1)[found]


def byte_groups(blobs: list[bytes]) -> tuple:
    """Runs of a shard and, for each of their windows, its bucket; a content that recurs is sorted once."""
    runs, contents = gathered(blobs)
    many = np.array([len(c) - WINDOW + 1 for c in contents], np.int64)
    start = np.cumsum(many + WINDOW - 1) - (many + WINDOW - 1)
    return windows_of(runs, refine(np.frombuffer(b"".join(contents), np.uint8), WINDOW, ragged(start, many)), many)


def deduplicate(docs: DataFrame) -> DataFrame:
    """``docs`` with ``n_bytes``, ``n_removed``, ``n_spans`` (maximal removed runs) and ``kept`` (remaining bytes).

    A byte of a text's UTF-8 form goes if a string of 50 bytes covers it that also starts in a row
    with a smaller doc_id, as the input has them; strings never cross rows.  A null text has no bytes.
    Rows with a null doc_id keep their bytes and count for no other row; rows of one doc_id do not
    remove from each other.  Other columns pass through; those named like the results are replaced.
    """

    def finish(raw, offsets, cover):
        gone = removed_units(offsets, cover)
        opens = gone.copy()
        opens[1:] &= ~gone[:-1]
        inner = offsets[(offsets > 0) & (offsets < len(raw))]
        opens[inner] = gone[inner]
        many = lambda mask: np.diff(np.concatenate([[0], np.cumsum(mask)])[offsets])
        removed, n = many(gone), np.diff(offsets)
        return pa.array(n, pa.int64()), pa.array(removed, pa.int64()), pa.array(many(opens), pa.int64()), binary_array(raw[~gone], np.concatenate([[0], np.cumsum(n - removed)]))

    return rejoined(docs, False, byte_groups, [("n_bytes", "bigint"), ("n_removed", "bigint"), ("n_spans", "bigint"), ("kept", "binary")], finish)


ORACLE = """
WITH d AS (SELECT doc_id, regexp_extract_all(hex(encode(coalesce(text, ''))), '..') AS b FROM documents),
s AS (SELECT doc_id, i, array_to_string(b[i : i + 49], '') AS win FROM (SELECT doc_id, b, unnest(range(1, len(b) - 48)) AS i FROM d)),
f AS (SELECT win, min(doc_id) AS first FROM s GROUP BY win),
g AS (SELECT DISTINCT doc_id, unnest(range(i, i + 50)) AS pos FROM s JOIN f USING (win) WHERE first < doc_id),
r AS (SELECT doc_id, count(*) AS n_spans FROM g WHERE NOT EXISTS (SELECT 1 FROM g x WHERE x.doc_id = g.doc_id AND x.pos = g.pos - 1) GROUP BY doc_id),
u AS (SELECT doc_id, unnest(b) AS byte, unnest(range(1, len(b) + 1)) AS pos FROM d),
k AS (SELECT u.doc_id, count(*) AS n, count(g.pos) AS gone, string_agg(CASE WHEN g.pos IS NULL THEN byte END, '' ORDER BY u.pos) AS kept
  FROM u LEFT JOIN g ON g.doc_id = u.doc_id AND g.pos = u.pos GROUP BY u.doc_id)
SELECT doc_id, coalesce(n, 0) AS n_bytes, coalesce(gone, 0) AS n_removed, coalesce(n_spans, 0) AS n_spans, sha256(unhex(coalesce(kept, ''))) AS kept_sha256
FROM d LEFT JOIN k USING (doc_id) LEFT JOIN r USING (doc_id)
"""
