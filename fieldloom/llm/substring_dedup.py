"""Substring deduplication over words, with a count-min prefilter.

Merged partition sketches overestimate how many documents hold a window of 50 words; a second pass
groups exactly the windows that may be in two, and loses none.  It numbers the words that a shard
holds, bytes and all, so that no two different windows can share a group.
"""

from __future__ import annotations

from collections import defaultdict
from itertools import count

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .repeats import WINDOW, binary_array, gathered, ragged, rejoined, removed_units, windows_of
from .rolling import words
from .suffix_dedup import refine


def two_words(units: np.ndarray, at: np.ndarray) -> np.ndarray:
    return (units[at].astype(np.uint64) << np.uint64(32)) | units[at + 1].astype(np.uint64)


def word_groups(blobs: list[bytes]) -> tuple:
    """Runs of a shard and, for each of their windows, a number that windows of the same words share."""
    runs, contents = gathered(blobs)
    number = defaultdict(count().__next__)
    units, many = [], []
    for c in contents:
        own = c.split()  # at blanks and ASCII control spaces
        units.extend(map(number.__getitem__, own))
        many.append(len(own) - WINDOW + 1)
    many = np.array(many, np.int64)
    start = np.cumsum(many + WINDOW - 1) - (many + WINDOW - 1)
    return windows_of(runs, refine(np.array(units, np.int64), WINDOW, ragged(start, many), two_words, 2), many)


def deduplicate(docs: DataFrame) -> DataFrame:
    """``docs`` with ``n_words``, ``n_removed`` and ``kept`` (the kept words joined by one blank, UTF-8 bytes).

    Words lie between blanks and ASCII control spaces.  A word goes if a window of 50 words covers it
    that also starts in a row with a smaller doc_id, as the input has them.  A null text has no words.
    Rows with a null doc_id keep their words and count for no other row; rows of one doc_id do not
    remove from each other.  Other columns pass through; those named like the results are replaced.
    """

    def finish(raw, offsets, cover):
        starts, ends, bounds = words(raw, offsets)
        gone = removed_units(bounds, cover)
        keep = np.flatnonzero(~gone)
        doc = np.searchsorted(bounds, keep, side="right") - 1
        # each kept word takes its bytes and, unless it is its document's last, one more for a blank
        sizes = ends[keep] - starts[keep]
        last = np.concatenate([doc[1:] != doc[:-1], [True]]) if len(keep) else np.zeros(0, bool)
        out_at = np.cumsum(sizes + ~last)
        out = np.full(int(out_at[-1]) if len(keep) else 0, 0x20, np.uint8)
        begin = out_at - (sizes + ~last)
        if len(keep):
            total = np.cumsum(sizes)
            step = np.arange(int(total[-1]))
            out[np.repeat(begin - (total - sizes), sizes) + step] = raw[np.repeat(starts[keep] - (total - sizes), sizes) + step]
        per = np.bincount(doc, weights=sizes + ~last, minlength=len(offsets) - 1).astype(np.int64)
        n = np.diff(bounds)
        removed = np.diff(np.concatenate([[0], np.cumsum(gone)])[bounds])
        return pa.array(n, pa.int64()), pa.array(removed, pa.int64()), binary_array(out, np.concatenate([[0], np.cumsum(per)]))

    return rejoined(docs, True, word_groups, [("n_words", "bigint"), ("n_removed", "bigint"), ("kept", "binary")], finish)


ORACLE = r"""
WITH d AS (SELECT doc_id, list_filter(string_split_regex(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents),
s AS (SELECT doc_id, i, array_to_string(w[i : i + 49], ' ') AS win FROM (SELECT doc_id, w, unnest(range(1, len(w) - 48)) AS i FROM d)),
f AS (SELECT win, min(doc_id) AS first FROM s GROUP BY win),
g AS (SELECT DISTINCT doc_id, unnest(range(i, i + 50)) AS pos FROM s JOIN f USING (win) WHERE first < doc_id),
u AS (SELECT doc_id, unnest(w) AS word, unnest(range(1, len(w) + 1)) AS pos FROM d),
k AS (SELECT u.doc_id, count(*) AS n, count(g.pos) AS gone, string_agg(CASE WHEN g.pos IS NULL THEN word END, ' ' ORDER BY u.pos) AS kept
  FROM u LEFT JOIN g ON g.doc_id = u.doc_id AND g.pos = u.pos GROUP BY u.doc_id)
SELECT doc_id, coalesce(n, 0) AS n_words, coalesce(gone, 0) AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256 FROM d LEFT JOIN k USING (doc_id)
"""
