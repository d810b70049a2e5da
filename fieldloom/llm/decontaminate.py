"""Benchmark decontamination by a distributed positional inverted index; DataFrame functions only.

The index holds the postings (term, document, position) of training tokens.  A phrase is looked up from
its rarest terms: their lists, shifted by each term's offset in the phrase, are intersected, and what is
left is compared word by word.  Only terms that phrases start from are posted.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import hinted, written

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
GAPS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
WINDOW = 10
RAREST = 3  # terms of a phrase whose lists are intersected


def word_array(text: Column) -> Column:
    """Words of a text: ASCII letters lower-cased; letters, digits and non-ASCII code points hold together."""
    return F.array_remove(F.split(F.translate(F.coalesce(text, F.lit("")), UPPER, LOWER), GAPS), "")


def item_windows(items: DataFrame, size: int = WINDOW) -> DataFrame:
    """(win, words, n, items): the distinct windows of all items, with the ids of the items that hold each."""
    w = items.select(F.col("item_id").cast("string").alias("item"), word_array(F.col("text")).alias("w")).where(F.size("w") > 0)
    starts = F.sequence(F.lit(1), F.greatest(F.lit(1), F.size("w") - size + 1))
    w = w.select("item", F.explode(F.transform(starts, lambda i: F.slice("w", i, size))).alias("words"))
    w = w.groupBy("words").agg(F.sort_array(F.collect_set("item")).alias("items"))
    return w.select(F.xxhash64("words").alias("win"), "words", F.size("words").alias("n"), "items")


def tokens(docs: DataFrame) -> DataFrame:
    """(fl_k, pos, term) of each word of ``docs`` (fl_k, text); positions start at 0."""
    return docs.select("fl_k", F.posexplode(word_array(F.col("text"))).alias("pos", "term"))


def rarest_terms(docs: DataFrame, windows: DataFrame) -> DataFrame:
    """``windows`` with ``probe``: up to RAREST (term, offset), rarest in ``docs`` first, then by offset."""
    spots = windows.select("win", F.posexplode("words").alias("off", "term"))
    terms = spots.select("term").distinct()
    df = tokens(docs).join(hinted(terms, terms.count()), "term").groupBy("term").agg(F.count("*").alias("df"))
    probe = spots.join(df, "term", "left").groupBy("win").agg(F.slice(F.sort_array(F.collect_list(F.struct(F.coalesce("df", F.lit(0)).alias("df"), "off", "term"))), 1, RAREST).alias("probe"))
    # a window with a term that no document has occurs nowhere
    return windows.join(probe.where(F.element_at("probe", 1)["df"] > 0), "win")


def postings(docs: DataFrame, probes: DataFrame) -> DataFrame:
    """The positional index (term, fl_k, pos) over ``docs`` for the terms that ``probes`` ask for, stored."""
    terms = probes.select(F.explode("probe").alias("p")).select("p.term").distinct()
    return written(tokens(docs).join(hinted(terms, terms.count()), "term").select("term", "fl_k", "pos"), "postings")


def phrase_candidates(index: DataFrame, probes: DataFrame) -> DataFrame:
    """(fl_k, start, win): places where all probed terms of a window stand at their offsets."""
    asked = probes.select("win", "probe")
    at = lambda k: F.element_at("probe", k)
    first = asked.select("win", "probe", at(1)["term"].alias("term"), at(1)["off"].alias("off"))
    found = index.join(hinted(first, first.count()), "term").select("fl_k", "win", "probe", (F.col("pos") - F.col("off")).alias("start")).where("start >= 0")
    for k in range(2, RAREST + 1):
        has = F.size("probe") >= k
        more = found.where(has).withColumn("term", at(k)["term"]).withColumn("pos", F.col("start") + at(k)["off"])
        found = more.join(index, ["fl_k", "term", "pos"], "left_semi").select("fl_k", "win", "probe", "start").unionByName(found.where(~has))
    return found.select("fl_k", "start", "win")


def proximity_matches(docs: DataFrame, items: DataFrame, within: int) -> DataFrame:
    """(doc_id, item): rows of ``docs`` where all probed terms of a window of the item lie ``within`` words of the rarest.

    The same index as for phrases; order and offsets are free; ``within`` is at least 1.  Nulls have no words.
    """
    if within < 1:
        raise ValueError("within is a distance of at least one word")
    docs = docs.select("doc_id", "text").withColumn("fl_k", F.xxhash64("doc_id", "text"))
    probes = rarest_terms(docs, item_windows(items))
    index = postings(docs, probes)
    asked = probes.select("win", "probe")
    found = index.join(asked.withColumn("term", F.element_at("probe", 1)["term"]), "term").select("fl_k", "win", "probe", F.col("pos").alias("p1"))
    for k in range(2, RAREST + 1):
        has = F.size("probe") >= k
        cells = F.array(*[(F.col("p1") / within).cast("int") + d for d in (-1, 0, 1)])
        more = found.where(has).withColumn("term", F.element_at("probe", k)["term"]).withColumn("cell", F.explode(cells))
        near = more.join(index.withColumn("cell", (F.col("pos") / within).cast("int")), ["fl_k", "term", "cell"]).where(F.abs(F.col("pos") - F.col("p1")) <= within)
        found = near.select("fl_k", "win", "probe", "p1").distinct().unionByName(found.where(~has))
    hits = found.select("fl_k", "win").distinct().join(probes.select("win", F.explode("items").alias("item")), "win").select("fl_k", "item").distinct()
    return docs.select("doc_id", "fl_k").join(hits, "fl_k").select("doc_id", "item").distinct()


def find(docs: DataFrame, items: DataFrame) -> DataFrame:
    """``docs`` with ``n_words``, ``n_hit`` (words inside occurrences of windows), ``hit_words`` (their positions)
    and ``item_ids`` (items with occurring windows, as sorted strings).

    A window is 10 consecutive words of an item; an item of fewer words is one window, an item without
    words has none.  A null text has no words.  Rows with equal doc_id and text are judged alike, null
    ids included.  Other columns pass through; those named like the results are replaced.
    """
    keep = docs.drop("n_words", "n_hit", "hit_words", "item_ids", "fl_k", "fl_c").withColumn("fl_k", F.xxhash64("doc_id", "text"))
    base = keep.where("text is not null").select("fl_k", "text")
    probes = written(rarest_terms(base, item_windows(items)), "probes")
    places = phrase_candidates(postings(base, probes), probes).distinct()
    known = probes.select("win", "words", "items")
    listed = places.join(hinted(known, known.count()), "win").groupBy("fl_k").agg(F.collect_list(F.struct("start", "words", "items")).alias("fl_c"))
    out = keep.join(listed, "fl_k", "left").withColumn("fl_w", word_array(F.col("text")))
    # the last word on a place: every word of the window is compared
    hits = F.filter("fl_c", lambda c: F.slice("fl_w", c["start"] + 1, F.size(c["words"])) == c["words"])
    out = out.withColumn("fl_c", F.coalesce(hits, F.array().cast(dict(out.dtypes)["fl_c"])))
    covered = F.array_sort(F.array_distinct(F.flatten(F.transform("fl_c", lambda c: F.sequence(c["start"], c["start"] + F.size(c["words"]) - 1)))))
    return out.withColumns({
        "n_words": F.size("fl_w").cast("bigint"), "hit_words": covered, "n_hit": F.size(covered).cast("bigint"),
        "item_ids": F.sort_array(F.array_distinct(F.flatten(F.transform("fl_c", lambda c: c["items"])))),
    }).drop("fl_c", "fl_w", "fl_k")


ORACLE = f"""
WITH d AS (SELECT doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), '{UPPER}', '{LOWER}'), '{GAPS}'), lambda x: x <> '') AS w FROM documents),
i AS (SELECT CAST(item_id AS VARCHAR) AS item, list_filter(string_split_regex(translate(coalesce(text, ''), '{UPPER}', '{LOWER}'), '{GAPS}'), lambda x: x <> '') AS w FROM benchmark),
iw AS (SELECT DISTINCT item, n, array_to_string(w[s : s + n - 1], ' ') AS win FROM (SELECT item, w, least({WINDOW}, len(w)) AS n, unnest(range(1, len(w) - least({WINDOW}, len(w)) + 2)) AS s FROM i WHERE len(w) > 0)),
dw AS (SELECT doc_id, s, n, array_to_string(w[s : s + n - 1], ' ') AS win FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS s FROM d, (SELECT DISTINCT n FROM iw) WHERE len(w) >= n)),
m AS (SELECT DISTINCT doc_id, s, dw.n, item FROM dw JOIN iw ON dw.win = iw.win AND dw.n = iw.n),
p AS (SELECT doc_id, count(DISTINCT pos) AS n_hit FROM (SELECT doc_id, unnest(range(s, s + n)) AS pos FROM m) GROUP BY doc_id),
t AS (SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS ids FROM (SELECT DISTINCT doc_id, item FROM m) GROUP BY doc_id)
SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(ids, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN p USING (doc_id) LEFT JOIN t USING (doc_id)
"""
