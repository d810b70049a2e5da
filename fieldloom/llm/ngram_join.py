"""N-gram Jaccard join with several global token orders, reduced to link components.

Two texts that link share a token of their prefixes under every global order of tokens.  Both orders
put tokens that no other text has first and very frequent ones last.  Equal sets are joined before all
else.  Links to the most central text of each bucket come next, then links to members drawn anew; these
pairs share one bucket only, of either order, and go to verification without the test under both.  After
them only pairs between different components are left, and these are compared only if they share a prefix
token under each of the two orders; so a group of near copies costs its size and not its square.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import BROADCAST_ROWS, hinted, mix64, pieces, text_buffers, written
from .rolling import Hasher, full_windows, word_hashes, words
from .sketch import Sketch, bits_for, merged

SHINGLE = 5
NUMERATOR, DENOMINATOR = 75, 100  # 100 * intersection >= 75 * union
HOT = 200  # texts from which a token counts as very frequent
STAR_TOKENS = 3  # tokens of each text and order whose buckets give a first set of links
ROUNDS = 1  # times that texts outside a bucket's main component meet a member of it drawn anew
RECENT = 4  # shared tokens that the row of a very frequent token remembers from before it
SPLIT_ROWS = 5000  # rows of a token that meet the texts outside its main component in one piece
SECOND = np.uint64(0x5851F42D4C957F2D)
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


class Shingler:
    """Sets of hashed shingles of a batch: ``doc`` and ``token``, sorted, and ``n`` tokens for each text."""

    def __init__(self) -> None:
        self.hasher = Hasher(0)

    def load(self, column: pa.Array) -> None:
        raw, offsets, _ = text_buffers(column)
        raw = LOWER[raw]
        starts, ends, bounds = words(raw, offsets)
        h = self.hasher
        prefix = h.prefix(word_hashes(raw, starts, ends))
        texts = len(offsets) - 1
        n = max(0, len(starts) - SHINGLE + 1)
        at = np.flatnonzero(full_windows(bounds, SHINGLE, n))
        doc = np.searchsorted(bounds, at, side="right") - 1
        token = h.stretches(prefix, at, at + SHINGLE)
        many = np.diff(bounds)
        short = np.flatnonzero((many > 0) & (many < SHINGLE))
        doc = np.concatenate([doc, short])
        # a whole short text must not equal a stretch of another length
        token = np.concatenate([token, mix64(h.stretches(prefix, bounds[short], bounds[short + 1]) + many[short].astype(np.uint64))])
        order = np.lexsort((token, doc))
        doc, token = doc[order], token[order]
        keep = np.ones(len(doc), bool)
        keep[1:] = (doc[1:] != doc[:-1]) | (token[1:] != token[:-1])
        self.doc, self.token = doc[keep], token[keep]
        self.n = np.bincount(self.doc, minlength=texts)
        self.cuts = np.concatenate([[0], np.cumsum(self.n)])

    def sums(self, values: np.ndarray) -> np.ndarray:
        return np.diff(np.concatenate([np.zeros(1, values.dtype), np.cumsum(values)])[self.cuts])


def blob_list(token: np.ndarray, cuts: np.ndarray, keep: np.ndarray) -> pa.Array:
    return pa.array([token[a:b].tobytes() if k else None for a, b, k in zip(cuts[:-1].tolist(), cuts[1:].tolist(), keep.tolist())], pa.binary())


def text_sets(docs: DataFrame) -> DataFrame:
    """(doc_id, n, s1, s2, tokens): set size and fingerprint of each row; tokens only where a partner is possible."""
    docs = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text")
    size = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0

    def keys_of(batches):
        s = Shingler()
        for whole in batches:
            for b in pieces(whole, "text", 1 << 20):
                s.load(b.column("text"))
                yield s.token

    sketch = merged(docs.where("doc_id is not null").select("text"), keys_of, bits_for(size // 16))

    def run(batches):
        s, seen = Shingler(), Sketch(*sketch.value).seen
        for whole in batches:
            for b in pieces(whole, "text", 1 << 20):
                s.load(b.column("text"))
                # a partner shares three quarters of the tokens, so as many must be in two texts
                held = s.sums(seen(s.token).astype(np.int64))
                maybe = (s.n > 0) & (held * DENOMINATOR >= s.n * NUMERATOR)
                yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(s.n, pa.int64()), pa.array(s.sums(mix64(s.token)).view(np.int64)), pa.array(s.sums(mix64(s.token ^ SECOND)).view(np.int64)), blob_list(s.token, s.cuts, maybe)], names=["doc_id", "n", "s1", "s2", "tokens"])

    out = written(docs.mapInArrow(run, "doc_id bigint, n bigint, s1 bigint, s2 bigint, tokens binary"), "sets")
    sketch.destroy()
    return out


def token_arrays(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
    """All tokens of a batch of sets, and the row of each."""
    raw, offsets, _ = binary_buffers(batch.column("tokens"))
    return raw.view(np.uint64) if len(raw) else np.zeros(0, np.uint64), np.repeat(np.arange(batch.num_rows), np.diff(offsets) // 8)


def binary_buffers(column: pa.Array):
    raw, offsets, valid = text_buffers(column.cast(pa.large_binary()).cast(pa.binary()) if pa.types.is_large_binary(column.type) else column)
    return np.frombuffer(raw.tobytes(), np.uint8), offsets, valid


def prefixes(reps: DataFrame) -> DataFrame:
    """(ord, token, rep, n, pos, u, k, recent): the prefix tokens of each set under each order that another set may share.

    ``pos`` counts all tokens before it, ``u`` is the number of tokens that no other set has, and ``k``
    numbers the rows of a set and order.  ``recent`` holds, for a very frequent token, the listed tokens
    just before it: two sets with one of these in common have met there already.  Order 2 lists very
    frequent tokens, for first links only.
    """

    def keys_of(batches):
        for whole in batches:
            for b in pieces(whole, "tokens", 1 << 20):
                yield token_arrays(b)[0]

    size = reps.agg(F.sum("n")).first()[0] or 0
    shared = merged(reps.select("tokens"), keys_of, bits_for(size))
    hot = merged(reps.select("tokens"), keys_of, min(24, bits_for(size)), HOT)

    names = ["ord", "token", "rep", "n", "pos", "u", "k", "recent"]

    def run(batches):
        twice, often = Sketch(*shared.value).seen, Sketch(*hot.value).seen
        for whole in batches:
            for b in pieces(whole, "tokens", 1 << 20):
                token, row = token_arrays(b)
                n = np.asarray(b.column("n"), np.int64)
                kind = twice(token).astype(np.int8)
                kind[kind > 0] += often(token[kind > 0])
                own = n - np.bincount(row, weights=kind > 0, minlength=len(n)).astype(np.int64)
                begin = np.cumsum(n) - n
                # any partner shares at least the share's part of the set
                length = n - -(-n * NUMERATOR // DENOMINATOR) + 1

                def listed(o, at, place, star):
                    r = row[at]
                    many = np.where(kind[at] > 1, np.minimum(star, RECENT), 0) if o < 2 else np.zeros(len(at), np.int64)
                    ends = np.cumsum(many)
                    before = np.repeat(np.arange(len(at)) - many - (ends - many), many) + np.arange(int(many.sum()))
                    recent = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], ends]).astype(np.int32)), pa.array(token[at][before].view(np.int64)))
                    columns = [np.full(len(at), o, np.int32), token[at].view(np.int64), b.column("rep").take(pa.array(r)), n[r], place, own[r], star, recent]
                    return pa.RecordBatch.from_arrays([c if isinstance(c, pa.Array) else pa.array(c) for c in columns], names=names)

                for o, key in enumerate((token, mix64(token ^ SECOND))):
                    order = np.lexsort((key, kind, row))
                    pos = np.arange(len(order)) - begin[row[order]]
                    keep = (pos < length[row[order]]) & (kind[order] > 0)
                    at, place = order[keep], pos[keep]
                    yield listed(o, at, place, place - own[row[at]])
                # the very frequent tokens tell large groups: a few of them, by a third order, for first links only
                at = np.flatnonzero(kind > 1)
                at = at[np.lexsort((mix64(token[at] + SECOND), row[at]))]
                place = np.arange(len(at)) - np.searchsorted(row[at], row[at])
                keep = place < STAR_TOKENS
                yield listed(2, at[keep], place[keep], place[keep])

    out = written(reps.mapInArrow(run, "ord int, token bigint, rep bigint, n bigint, pos bigint, u bigint, k bigint, recent array<bigint>"), "prefixes")
    shared.destroy()
    hot.destroy()
    return out


def verified(pairs: DataFrame, reps: DataFrame) -> DataFrame:
    """Those of the distinct, written ``pairs`` (a, b) whose sets reach the similarity."""
    sets = reps.select("rep", "tokens")
    if pairs.count() <= BROADCAST_ROWS:
        # few pairs go to the sets, and only the sets that they name are shuffled
        sides = [sets.join(F.broadcast(pairs), F.col("rep") == F.col(c)).select("a", "b", F.struct(F.lit(n).alias("side"), "tokens").alias("t")) for n, c in enumerate("ab")]
        both = sides[0].union(sides[1]).groupBy("a", "b").agg(F.collect_list("t").alias("t"))
        side = lambda n: F.transform(F.filter("t", lambda x: x["side"] == n), lambda x: x["tokens"])
        both = both.select("a", "b", side(0).alias("ta"), side(1).alias("tb"))
    else:
        both = pairs.join(sets.withColumnsRenamed({"rep": "a", "tokens": "ta"}), "a").join(sets.withColumnsRenamed({"rep": "b", "tokens": "tb"}), "b").select("a", "b", F.array("ta").alias("ta"), F.array("tb").alias("tb"))

    def alike(x: bytes, y: bytes) -> bool:
        both = np.concatenate([np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64)])
        both.sort()
        same = int((both[1:] == both[:-1]).sum())
        return DENOMINATOR * same >= NUMERATOR * (len(both) - same)

    def run(batches):
        for batch in batches:
            keep = [i for i, (xs, ys) in enumerate(zip(batch.column("ta"), batch.column("tb"))) if any(alike(x.as_py(), y.as_py()) for x in xs for y in ys)]
            at = pa.array(keep, pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column("a").take(at), batch.column("b").take(at)], names=["a", "b"])

    return both.mapInArrow(run, "a bigint, b bigint")


def components(edges: DataFrame) -> DataFrame:
    """(v, comp): the smallest vertex that each vertex of ``edges`` (a, b) reaches.

    Labels take the least of their neighbours' and then jump to their label's label, until none moves.
    """
    both = written(edges.select("a", "b").union(edges.select("b", "a")).distinct(), "edges")
    labels = written(both.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("comp")).select(F.col("a").alias("v"), "comp"), "labels")
    while True:
        near = both.join(labels.withColumnRenamed("v", "b"), "b").groupBy("a").agg(F.min("comp").alias("best")).withColumnRenamed("a", "v")
        step = labels.join(near, "v").select("v", F.col("comp").alias("was"), F.least("comp", "best").alias("comp"))
        jump = step.select(F.col("v").alias("comp"), F.col("comp").alias("over"))
        new = written(step.join(jump, "comp", "left").select("v", "was", F.least("comp", F.coalesce("over", "comp")).alias("comp")), "labels")
        labels = new.select("v", "comp")
        if new.where("comp <> was").isEmpty():
            return labels


def close_in_size(x: str, y: str):
    return (F.least(x, y) * DENOMINATOR >= F.greatest(x, y) * NUMERATOR)


def with_components(rows: DataFrame, labels: DataFrame) -> DataFrame:
    return rows.join(hinted(labels.withColumnRenamed("v", "rep"), labels.count()), "rep", "left").withColumn("comp", F.coalesce("comp", "rep"))


def fits():
    """Whether two sets (n1, n2) with a first common token at pos1 and pos2 can still reach the similarity."""
    room = F.least(F.col("n1") - F.col("pos1"), F.col("n2") - F.col("pos2"))
    return close_in_size("n1", "n2") & (room * (NUMERATOR + DENOMINATOR) >= (F.col("n1") + F.col("n2")) * NUMERATOR)


def between_components(rows: DataFrame, labels: DataFrame) -> DataFrame:
    """Distinct pairs (a, b) of different components that share a prefix token of one order, places permitting.

    A pair comes from the first very frequent token that it shares and not from the later ones, and the
    rows of a very frequent token are dealt over many tasks.
    """
    rows = with_components(rows, labels)
    # the component with most of a bucket needs no pairs within it: the others meet it and each other
    per = rows.groupBy("token", "comp").agg(F.count("*").alias("c")).groupBy("token").agg(F.max_by("comp", F.struct("c", "comp")).alias("main"), F.count("*").alias("comps"), F.sum("c").alias("m"))
    main = per.where("comps > 1").select("token", "main", F.ceil(F.col("m") / SPLIT_ROWS).cast("int").alias("pieces"))
    rows = rows.join(main, "token")
    side = ("rep", "comp", "n", "pos", "recent")
    few = rows.where("comp <> main").select("token", "main", F.explode(F.sequence(F.lit(0), F.col("pieces") - 1)).alias("piece"), *(F.col(c).alias(f"{c}1") for c in side))
    all_ = rows.select("token", F.pmod(F.hash("rep"), F.col("pieces")).alias("piece"), *(F.col(c).alias(f"{c}2") for c in side))
    test = (F.col("comp1") != F.col("comp2")) & ((F.col("comp2") == F.col("main")) | (F.col("rep1") < F.col("rep2"))) & fits() & ~F.arrays_overlap("recent1", "recent2")
    return few.join(all_, ["token", "piece"]).where(test).select(F.least("rep1", "rep2").alias("a"), F.greatest("rep1", "rep2").alias("b")).distinct()


def drawn_pairs(rows: DataFrame, labels: DataFrame, turn: int) -> DataFrame:
    """Distinct pairs (a, b) of each text outside its bucket's drawn component with the member drawn this turn."""
    rows = with_components(rows.where(F.col("k") < STAR_TOKENS), labels)
    one = F.struct("rep", "comp", "n", "pos")
    drawn = rows.groupBy("ord", "token").agg(F.min_by(one, F.xxhash64("rep", F.lit(turn))).alias("c"), (F.min("comp") != F.max("comp")).alias("mixed")).where("mixed")
    drawn = drawn.select("ord", "token", *(F.col(f"c.{c}").alias(f"{c}2") for c in ("rep", "comp", "n", "pos")))
    near = rows.withColumnsRenamed({c: f"{c}1" for c in ("rep", "comp", "n", "pos")}).join(drawn, ["ord", "token"]).where((F.col("comp1") != F.col("comp2")) & close_in_size("n1", "n2"))
    return near.select(F.least("rep1", "rep2").alias("a"), F.greatest("rep1", "rep2").alias("b")).distinct()


def relabelled(labels: DataFrame, links: DataFrame) -> DataFrame:
    """``labels`` after further ``links``, which join whole components."""
    label = lambda name: labels.select(F.col("v").alias(name), F.col("comp").alias(f"c{name}"))
    bridges = links.join(label("a"), "a", "left").join(label("b"), "b", "left").select(F.coalesce("ca", "a").alias("a"), F.coalesce("cb", "b").alias("b"))
    more = components(bridges).select(F.col("v").alias("comp"), F.col("comp").alias("top"))
    return written(labels.join(more, "comp", "full").select(F.coalesce("v", "comp").alias("v"), F.coalesce("top", "comp").alias("comp")).groupBy("v").agg(F.min("comp").alias("comp")), "labels")


def link_components(docs: DataFrame) -> DataFrame:
    """(doc_id, n_shingles, component_id) for each row of ``docs`` (doc_id, text).

    A text's set holds its distinct shingles of five words, ASCII letters lower-cased; a text of fewer
    words is one shingle, one without words or a null has none and links with nothing.  Two rows link
    if 100 * intersection >= 75 * union; ``component_id`` is the smallest doc_id that links reach, the
    row's own included.  Rows with a null doc_id link with nothing and have a null component; rows of
    one doc_id are separate texts under one id.  Other columns of ``docs`` are ignored.
    """
    sets = text_sets(docs)
    equal = ["n", "s1", "s2"]
    classes = sets.where("n > 0 and doc_id is not null").groupBy(*equal).agg(F.min("doc_id").alias("rep"))
    reps = sets.where("tokens is not null and doc_id is not null").join(classes, equal).where("doc_id = rep").select("rep", "n", "tokens")
    reps = written(reps, "representatives")
    rows = prefixes(reps)

    central = F.struct((F.col("u") * 1_000_000 / F.col("n")).cast("bigint").alias("f"), F.col("rep"), F.col("n"))
    few = rows.where(F.col("k") < STAR_TOKENS)
    stars = few.groupBy("ord", "token").agg(F.min(central).alias("c"), F.count("*").alias("m")).where("m > 1").select("ord", "token", F.col("c.rep").alias("centre"), F.col("c.n").alias("cn"))
    near = few.join(stars, ["ord", "token"]).where((F.col("rep") != F.col("centre")) & close_in_size("n", "cn"))
    tried = written(near.select(F.least("rep", "centre").alias("a"), F.greatest("rep", "centre").alias("b")).distinct(), "star-pairs")
    labels = components(verified(tried, reps))

    # most texts of a large group are joined now; members drawn at random join most of the others
    for turn in range(1, ROUNDS + 1):
        pairs = written(drawn_pairs(rows, labels, turn), "drawn-pairs")
        if pairs.isEmpty():
            break
        labels = relabelled(labels, verified(pairs, reps))

    # all pairs that may link and are not joined yet: under one order, then those of them under the other
    first = written(between_components(rows.where("ord = 0"), labels), "first-order")
    held = written(first.select(F.explode(F.array("a", "b")).alias("rep")).distinct(), "first-order-texts")
    second = between_components(rows.where("ord = 1").join(hinted(held, held.count()), "rep", "left_semi"), labels)
    rest = written(first.join(second, ["a", "b"], "left_semi").join(tried, ["a", "b"], "left_anti"), "pairs")
    final = relabelled(labels, verified(rest, reps)).withColumnRenamed("v", "rep")
    out = sets.select("doc_id", *equal).join(classes, equal, "left").join(final, "rep", "left")
    return out.select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("doc_id").isNull(), None).otherwise(F.coalesce("comp", "rep", "doc_id")).alias("component_id"))


ORACLE = r"""
WITH RECURSIVE w AS (SELECT doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents),
s AS (SELECT DISTINCT doc_id, md5(array_to_string(w[i : i + least(5, len(w)) - 1], ' ')) AS h FROM (SELECT doc_id, w, unnest(range(1, len(w) - least(5, len(w)) + 2)) AS i FROM w WHERE len(w) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
o AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM s a JOIN s b ON a.h = b.h AND a.doc_id < b.doc_id GROUP BY ALL),
e AS (SELECT a, b FROM o JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * c >= 75 * (x.n + y.n - c)),
u AS (SELECT a, b FROM e UNION ALL SELECT b, a FROM e),
r AS (SELECT doc_id AS v, doc_id AS m FROM documents UNION SELECT u.b, r.m FROM r JOIN u ON u.a = r.v AND r.m < u.b)
SELECT d.doc_id, coalesce(n.n, 0) AS n_shingles, min(r.m) AS component_id FROM documents d LEFT JOIN n USING (doc_id) JOIN r ON r.v = d.doc_id GROUP BY d.doc_id, n.n
"""
