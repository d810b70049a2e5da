"""Line deduplication by content-defined chunks of lines; DataFrame functions only.

A chunk opens at each line and ends where it has LEAST_LINES lines and LEAST_CHARS characters, and
one closes at each line by the same rule read backwards.  So a chunk depends on its own lines alone,
and any run of lines that is large enough is covered by the chunks inside it: a line goes if and only
if it lies in a run of that size which occurs earlier without overlap.  Bytes are compared before.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

LEAST_LINES, LEAST_CHARS = 2, 32  # smaller chunks stay
MOST_LINES = LEAST_LINES + LEAST_CHARS  # line feeds count, so that no chunk needs more


def split_lines(text: Column) -> Column:
    return F.split(text, "\n", -1)


def lines_needed(sizes: Column) -> Column:
    """How many of the first lines make up a chunk; 0 if all of them do not."""
    small = lambda a: (a["n"] < LEAST_LINES) | (a["c"] - 1 < LEAST_CHARS)
    more = lambda a, x: F.when(small(a), F.struct((a["n"] + 1).alias("n"), (a["c"] + x + 1).alias("c"))).otherwise(a)
    return F.aggregate(sizes, F.struct(F.lit(0).alias("n"), F.lit(0).alias("c")), more, lambda a: F.when(small(a), 0).otherwise(a["n"]))


def chunk_array(text: Column) -> Column:
    """The chunks of a text: (i, n, h) with the first line, counted from 1, the number of lines and their hash."""
    # transform over a one-element array names a value, so that it is computed once and not at each use
    once = lambda value, use: F.element_at(F.transform(F.array(value), use), 1)

    def opened(c: Column) -> Column:
        return F.transform(c, lambda x, i: F.when((i + 1 < F.size(c)) & (x + F.get(c, i + 1) + 1 >= LEAST_CHARS), 2).otherwise(lines_needed(F.slice(c, i + 1, MOST_LINES))))

    def closed(c: Column) -> Column:
        back = lambda i: F.slice(c, F.greatest(i + 2 - MOST_LINES, F.lit(1)), F.least(i + 1, F.lit(MOST_LINES)))
        return F.transform(c, lambda x, i: F.when((i > 0) & (x + F.get(c, i - 1) + 1 >= LEAST_CHARS), 2).otherwise(lines_needed(F.reverse(back(i)))))

    def spans(c: Column) -> Column:
        first = once(opened(c), lambda a: F.array_union(numbered(a, lambda i, n: i + 1), numbered(closed(c), lambda i, n: i - n + 2)))
        return F.filter(first, lambda s: s["n"] > 0)

    def numbered(ns: Column, start) -> Column:
        return F.transform(ns, lambda n, i: F.struct(F.when(n > 0, start(i, n)).otherwise(0).alias("i"), n.alias("n")))

    def hashed(h: Column, s: Column) -> Column:
        return F.transform(s, lambda x: F.struct(x["i"].alias("i"), x["n"].alias("n"), F.xxhash64(F.slice(h, x["i"], x["n"])).alias("h")))

    return once(split_lines(text), lambda lines: once(F.transform(lines, lambda x: F.xxhash64(x)), lambda h: hashed(h, spans(F.transform(lines, lambda x: F.char_length(x))))))


def deduplicate(docs: DataFrame) -> DataFrame:
    """``docs`` with ``n_lines``, ``n_removed_lines`` and ``kept`` (the text without repeated runs of lines).

    Lines end at line feeds.  Of equal chunks the one of the smallest doc_id, then the first in its
    text, stays.  Null texts stay null with 0 lines; a text all of whose lines go becomes empty.
    Rows with a null doc_id keep their lines and count for no other row; rows alike in doc_id and text
    are one document.  Other columns pass through; those named like the results are replaced.
    """
    keep = docs.drop("n_lines", "n_removed_lines", "kept", "fl_id", "fl_k", "fl_gone")
    keep = keep.withColumn("fl_id", F.col("doc_id").cast("bigint")).withColumn("fl_k", F.xxhash64("doc_id", "text"))
    base = keep.where("fl_id is not null and text is not null").select("fl_id", "fl_k", "text")

    light = base.select("fl_id", "fl_k", F.explode(chunk_array(F.col("text"))).alias("c")).select("fl_id", "fl_k", "c.i", "c.n", "c.h")
    groups = light.groupBy("h").agg(F.min(F.struct("fl_id", "fl_k", "i")).alias("first"), F.count("*").alias("many")).where("many > 1").select("h", "first")
    same_text = (F.col("fl_id") == F.col("first.fl_id")) & (F.col("fl_k") == F.col("first.fl_k"))
    repeated = light.join(groups, "h").withColumn("stays", same_text & (F.col("i") == F.col("first.i")))
    repeated = repeated.where(F.col("stays") | ~same_text | (F.col("i") >= F.col("first.i") + F.col("n")))  # no overlap with the first
    wanted = repeated.groupBy("fl_id", "fl_k").agg(F.collect_list(F.struct("i", "n", "h", "stays")).alias("w"))

    # bytes: the bodies of chunks with equal hashes, against the body of the one that stays
    chosen = base.join(wanted, ["fl_id", "fl_k"]).select("fl_id", "fl_k", split_lines(F.col("text")).alias("lines"), needed(F.col("w")).alias("w"))
    body = lambda w: w.withField("body", F.array_join(F.slice(F.col("lines"), w["i"], w["n"]), "\n"))
    bodies = chosen.select("fl_id", "fl_k", F.inline(F.transform("w", body)))
    stays = bodies.where("stays").select("h", F.col("body").alias("first_body")).dropDuplicates(["h"])
    gone = bodies.where("not stays").join(stays, "h").where(F.col("body") == F.col("first_body")).groupBy("fl_id", "fl_k").agg(F.collect_list(F.struct("i", "n")).alias("fl_gone"))

    out = keep.join(gone, ["fl_id", "fl_k"], "left").drop("fl_id", "fl_k")
    lines = split_lines(F.col("text"))
    lost = F.array_distinct(F.flatten(F.transform("fl_gone", lambda s: F.sequence(s["i"], s["i"] + s["n"] - 1))))
    out = out.withColumn("fl_gone", lost)
    rest = F.transform(F.array(lines), lambda x: F.array_join(F.transform(F.array_except(F.sequence(F.lit(1), F.size(x)), "fl_gone"), lambda i: F.get(x, i - 1)), "\n"))[0]
    left = F.when(F.col("fl_gone").isNull(), F.col("text")).otherwise(rest)
    n = F.when(F.col("text").isNull(), F.lit(0)).otherwise(F.size(lines))
    removed = F.when(F.col("fl_gone").isNull(), F.lit(0)).otherwise(F.size("fl_gone"))
    return out.withColumns({"n_lines": n.cast("bigint"), "n_removed_lines": removed.cast("bigint"), "kept": left}).drop("fl_gone")


def needed(w: Column) -> Column:
    """Chunks whose bytes are read: those that stay, and of those that go, not each second one whose lines its neighbours have."""
    end = lambda s: s["i"] + s["n"]
    go = F.transform(F.array(F.array_sort(F.filter(w, lambda s: ~s["stays"]))), lambda g: F.filter(g, lambda s, k: (k % 2 == 0) | (k + 1 == F.size(g)) | (end(F.get(g, k - 1)) < F.get(g, k + 1)["i"]) | (end(F.get(g, k + 1)) < end(s))))[0]
    return F.concat(F.filter(w, lambda s: s["stays"]), go)


ORACLE = f"""
WITH d AS (SELECT doc_id, string_split(text, chr(10)) AS lines FROM documents WHERE text IS NOT NULL),
o AS (SELECT doc_id, lines, unnest(range(1, len(lines))) AS i FROM d),
p AS (SELECT doc_id, lines, i, unnest(range({LEAST_LINES}, least({MOST_LINES}, len(lines) - i + 1) + 1)) AS n FROM o),
r AS (SELECT doc_id, i, n, array_to_string(lines[i : i + n - 1], chr(10)) AS body FROM p),
w AS (SELECT * FROM r WHERE length(body) >= {LEAST_CHARS}),
c AS (SELECT * FROM w QUALIFY n = min(n) OVER (PARTITION BY doc_id, i) OR n = min(n) OVER (PARTITION BY doc_id, i + n)),
f AS (SELECT body, min({{'d': doc_id, 'i': i}}) AS first FROM c GROUP BY body),
g AS (SELECT DISTINCT doc_id, unnest(range(i, i + n)) AS pos FROM c JOIN f USING (body) WHERE doc_id > first.d OR i >= first.i + n),
l AS (SELECT doc_id, unnest(lines) AS line, unnest(range(1, len(lines) + 1)) AS pos FROM d),
k AS (SELECT l.doc_id, count(*) AS n_lines, count(g.pos) AS gone, string_agg(CASE WHEN g.pos IS NULL THEN line END, chr(10) ORDER BY l.pos) AS kept
  FROM l LEFT JOIN g ON g.doc_id = l.doc_id AND g.pos = l.pos GROUP BY l.doc_id)
SELECT d.doc_id, coalesce(n_lines, 0) AS n_lines, coalesce(gone, 0) AS n_removed_lines,
  CASE WHEN d.text IS NULL THEN NULL ELSE sha256(coalesce(kept, '')) END AS kept_sha256
FROM documents d LEFT JOIN k USING (doc_id)
"""
