"""Stretches of 50 units (words or bytes) that also start in a document with a smaller id.

Both substring operators take the same road:

1. every window has an anchor, a stretch of 25 units that depends on the window alone, so equal
   windows have equal anchors; partitions count anchors in a count-min sketch, and merged counts
   are never below the number of documents that hold a window;
2. only windows whose anchor is estimated to be in two documents go, as bytes of their text, to the
   shard of that anchor, where they are grouped by what they hold, not by hashes, and the smallest
   document of each group is found;
3. covered stretches return to their documents.

A group of any size costs a shard one entry for each occurrence, never pairs.
"""

from __future__ import annotations

import math
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import BinaryType, DataType, StructField, StructType

from .common import hinted, pieces, text_buffers, written
from .rolling import Hasher, anchor_runs, full_windows, word_hashes, words
from .sketch import Sketch, bits_for, merged

WINDOW, ANCHOR = 50, 25
WHOLE = (1 << 31) - 1  # the end of a stretch that takes all of a text
SHARD_BYTES = 16 << 20  # text for each shard of the second pass


class Scanner:
    """Units, window anchors and stretches of windows with one anchor, of a batch of texts."""

    def __init__(self, by_words: bool) -> None:
        self.by_words = by_words
        self.hasher = Hasher(0)

    def load(self, column: pa.Array) -> None:
        self.raw, self.offsets, _ = text_buffers(column)
        if self.by_words:
            self.starts, self.ends, self.bounds = words(self.raw, self.offsets)
            units = word_hashes(self.raw, self.starts, self.ends)
        else:
            units, self.bounds = self.raw, self.offsets
        self.prefix = self.hasher.prefix(units)
        n = max(0, len(units) - WINDOW + 1)
        hashes = self.hasher.windows(self.prefix, ANCHOR)
        anchor, self.first, self.last = anchor_runs(hashes, WINDOW, ANCHOR, full_windows(self.bounds, WINDOW, n))
        self.key = hashes[anchor]
        self.doc = np.searchsorted(self.bounds, anchor, side="right") - 1

    def places(self, run: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(start, size) in bytes of what the windows of each run cover."""
        if self.by_words:
            start = self.starts[self.first[run]]
            return start, self.ends[self.last[run] + WINDOW - 1] - start
        return self.first[run], self.last[run] - self.first[run] + WINDOW

    def alike(self, run: np.ndarray) -> np.ndarray:
        """For each of ``run`` the place in it of one that covers the same bytes: found by hash, then compared."""
        start, size = self.places(run)
        _, one, which = np.unique(self.hasher.stretches(self.prefix, self.first[run], self.last[run] + WINDOW), return_index=True, return_inverse=True)
        other = one[which]
        own = np.arange(len(run))
        other = np.where(size == size[other], other, own)
        moved = np.flatnonzero(other != own)
        if len(moved):
            differ = self.raw[ragged(start[moved], size[moved])] != self.raw[ragged(start[other[moved]], size[moved])]
            wrong = np.add.reduceat(differ.astype(np.int64), np.cumsum(size[moved]) - size[moved]) > 0
            other[moved[wrong]] = moved[wrong]
        return other

    def keys(self) -> np.ndarray:
        """Each document's anchors, once."""
        tagged = self.key + self.doc.astype(np.uint64) * np.uint64(0x9FB21C651E98DF25)
        return self.key[np.unique(tagged, return_index=True)[1]]


def ragged(first: np.ndarray, count: np.ndarray) -> np.ndarray:
    """The ranges ``first[i], first[i] + 1, ...`` of ``count[i]`` numbers, one after another."""
    done = np.cumsum(count)
    return np.repeat(first - (done - count), count) + np.arange(int(done[-1]) if len(done) else 0)


def pack(*arrays: np.ndarray) -> bytes:
    head = np.array([a.nbytes for a in arrays], np.int64).tobytes()
    return head + pa.compress(b"".join(a.tobytes() for a in arrays), codec="zstd", asbytes=True)


def unpack(blob: bytes, kinds: tuple) -> list[np.ndarray]:
    sizes = np.frombuffer(blob, np.int64, len(kinds))
    data = pa.decompress(blob[8 * len(kinds) :], decompressed_size=int(sizes.sum()), codec="zstd", asbytes=True)
    ends = np.cumsum(sizes)
    return [np.frombuffer(data[e - s : e], k) for s, e, k in zip(sizes.tolist(), ends.tolist(), kinds)]


RUN = (np.int64, np.int64, np.int32, np.uint8, np.int32)  # doc_id, row key, first window, windows, content number


def gathered(blobs: list[bytes]) -> tuple[list[np.ndarray], list[bytes]]:
    """The runs of a shard and its distinct contents; a run knows its content by its place among them."""
    runs, contents = [], {}
    for blob in blobs:
        *run, size, text = unpack(blob, (*RUN, np.int32, np.uint8))
        ends = np.cumsum(size.astype(np.int64)).tolist()
        data = text.tobytes()
        number = np.array([contents.setdefault(data[a:e], len(contents)) for a, e in zip([0, *ends], ends)], np.int64)
        run[4] = number[run[4]]
        runs.append(run)
    return [np.concatenate(c) for c in zip(*runs)], list(contents)


def windows_of(runs: list[np.ndarray], bucket: np.ndarray, many: np.ndarray) -> tuple:
    """Runs, and the bucket of each of their windows; ``bucket`` lists those of all contents, ``many`` in each."""
    ids, keys, first, count, content = runs
    count = count.astype(np.int64)
    return ids, keys, first, count, bucket[ragged((np.cumsum(many) - many)[content], count)]


def covered_runs(ids, keys, first, count, group) -> tuple:
    """(doc_id, row key, start, end) of what windows cover that start in a smaller document, run by run."""
    owner = np.repeat(np.arange(len(ids)), count)
    place = ragged(first.astype(np.int64), count)
    least = np.full(int(group.max()) + 1 if len(group) else 0, np.iinfo(np.int64).max)
    np.minimum.at(least, group, ids[owner])
    gone = least[group] < ids[owner]
    owner, place = owner[gone], place[gone]
    if not len(owner):
        return (np.zeros(0, np.int64),) * 4
    new = np.concatenate([[True], (owner[1:] != owner[:-1]) | (place[1:] != place[:-1] + 1)])
    at = np.flatnonzero(new)
    stop = place[np.append(at[1:], len(place)) - 1] + WINDOW
    return ids[owner[at]], keys[owner[at]], place[at], stop


def covers(docs: DataFrame, by_words: bool, groups: Callable) -> DataFrame:
    """(fl_id, fl_k, fl_cover) for each document with something to remove; ``docs`` has (fl_id, fl_k, text)."""
    spark = docs.sparkSession
    usable = docs.where("fl_id is not null and text is not null")
    # of rows with one text only those of the smallest id are scanned; the others go as a whole
    whole_text = [F.xxhash64("text").alias("t1"), F.hash("text").alias("t2"), F.octet_length("text").alias("t3")]
    same = usable.select("fl_id", "fl_k", *whole_text)
    first = same.groupBy("t1", "t2", "t3").agg(F.min("fl_id").alias("first"), F.count("*").alias("many")).where("many > 1").drop("many")
    copies = written(same.join(first, ["t1", "t2", "t3"]).where("fl_id > first").select("fl_id", "fl_k").distinct(), "copies")
    many = copies.count()
    usable = usable.join(hinted(copies, many), ["fl_id", "fl_k"], "left_anti")
    size = usable.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    keys = size // (13 * (7 if by_words else 1)) + 1
    shards = max(1, math.ceil(size / SHARD_BYTES)) * 8

    def keys_of(batches):
        s = Scanner(by_words)
        for whole in batches:
            for b in pieces(whole, "text", 1 << 20):
                s.load(b.column("text"))
                yield s.keys()

    sketch = merged(usable.select("text"), keys_of, bits_for(keys))

    def suspects(batches):
        s, seen = Scanner(by_words), Sketch(*sketch.value).seen
        for whole in batches:
            for b in pieces(whole, "text", 1 << 20):
                s.load(b.column("text"))
                keep = np.flatnonzero(seen(s.key))
                if not len(keep):
                    continue
                shard = (s.key[keep] % np.uint64(shards)).astype(np.int64)
                keep = keep[np.argsort(shard, kind="stable")]
                shard = np.sort(shard)
                cuts = np.append(np.flatnonzero(np.concatenate([[True], shard[1:] != shard[:-1]])), len(shard))
                ids, row_keys = np.asarray(b.column("fl_id"), np.int64), np.asarray(b.column("fl_k"), np.int64)
                count = s.last - s.first + 1
                start, size = s.places(keep)
                alike = s.alike(keep)
                blobs = []
                for a, e in zip(cuts[:-1].tolist(), cuts[1:].tolist()):
                    r = keep[a:e]
                    one, which = np.unique(alike[a:e], return_inverse=True)  # a content that recurs in this batch is sent once
                    run = [ids[s.doc[r]], row_keys[s.doc[r]], (s.first[r] - s.bounds[s.doc[r]]).astype(np.int32), count[r].astype(np.uint8), which.astype(np.int32)]
                    blobs.append(pack(*run, size[one].astype(np.int32), s.raw[ragged(start[one], size[one])]))
                yield pa.RecordBatch.from_arrays([pa.array(shard[cuts[:-1]], pa.int64()), pa.array(blobs, pa.binary())], names=["shard", "blob"])

    def judged(batches):
        def shard_of(blobs):
            out = covered_runs(*groups(blobs))
            for at in range(0, len(out[0]), 200_000):
                yield pa.RecordBatch.from_arrays([pa.array(np.asarray(c[at : at + 200_000], np.int64)) for c in out], names=["fl_id", "fl_k", "a", "e"])

        now, held = None, []
        for b in batches:  # sorted by shard; one shard at a time is in memory
            for shard, blob in zip(b.column("shard").to_pylist(), b.column("blob")):
                if shard != now and held:
                    yield from shard_of(held)
                    held = []
                now = shard
                held.append(blob.as_py())
        if held:
            yield from shard_of(held)

    width = max(shards // 8, int(spark.conf.get("spark.sql.shuffle.partitions")))
    found = usable.mapInArrow(suspects, "shard bigint, blob binary").repartition(width, "shard").sortWithinPartitions("shard").mapInArrow(judged, "fl_id bigint, fl_k bigint, a bigint, e bigint")
    # a copy of W units or more is covered whole: its end is open
    found = found.unionByName(copies.select("fl_id", "fl_k", F.lit(0).cast("bigint").alias("a"), F.lit(WHOLE).cast("bigint").alias("e")))
    return found.select("fl_id", "fl_k", F.struct(F.col("a").cast("int"), F.col("e").cast("int")).alias("x")).groupBy("fl_id", "fl_k").agg(F.collect_list("x").alias("fl_cover"))


def removed_units(bounds: np.ndarray, cover: pa.Array) -> np.ndarray:
    """Whether each unit lies in a covered stretch of its document."""
    arr = cover.combine_chunks() if isinstance(cover, pa.ChunkedArray) else cover
    depth = np.zeros(int(bounds[-1]) + 1, np.int32)
    flat = arr.flatten()
    if len(flat):
        many = np.asarray(pa.compute.fill_null(pa.compute.list_value_length(arr), 0), np.int64)
        base, units = np.repeat(bounds[:-1], many), np.repeat(np.diff(bounds), many)
        start, stop = (np.asarray(flat.field(c), np.int64) for c in (0, 1))
        keep = (stop < WHOLE) | (units >= WINDOW)
        np.add.at(depth, (base + start)[keep], 1)
        np.add.at(depth, (base + np.minimum(stop, units))[keep], -1)
    return np.cumsum(depth)[:-1] > 0


def keyed(docs: DataFrame) -> DataFrame:
    """``docs`` with ``fl_id`` (doc_id) and ``fl_k``, which tells rows of one id apart by their text."""
    return docs.withColumn("fl_id", F.col("doc_id").cast("bigint")).withColumn("fl_k", F.xxhash64("doc_id", "text"))


def packed_text(docs: DataFrame) -> DataFrame:
    """``docs`` with ``text`` as compressed bytes after its length, so that a shuffle moves less."""
    schema = StructType([f if f.name != "text" else StructField("text", BinaryType()) for f in docs.schema.fields])

    def run(batches):
        for b in batches:
            small = [None if x is None else len(x).to_bytes(8, "little") + pa.compress(x, codec="zstd", asbytes=True) for x in (None if t is None else t.encode() for t in b.column("text").to_pylist())]
            yield pa.RecordBatch.from_arrays([pa.array(small, pa.binary()) if n == "text" else b.column(n) for n in b.schema.names], names=b.schema.names)

    return docs.mapInArrow(run, schema)


def unpacked_text(batch: pa.RecordBatch) -> pa.RecordBatch:
    texts = [None if x is None else pa.decompress(x[8:], decompressed_size=int.from_bytes(x[:8], "little"), codec="zstd", asbytes=True) for x in batch.column("text").to_pylist()]
    return pa.RecordBatch.from_arrays([pa.array(texts, pa.binary()).cast(pa.string()) if n == "text" else batch.column(n) for n in batch.schema.names], names=batch.schema.names)


def rejoined(docs: DataFrame, by_words: bool, groups: Callable, names: list[tuple[str, str]], finish: Callable) -> DataFrame:
    """``docs`` with the columns ``names`` that ``finish(raw, offsets, cover)`` gives for each batch of texts."""
    keep = keyed(docs.drop(*[n for n, _ in names], "fl_id", "fl_k", "fl_cover"))
    cover = covers(keep.select("fl_id", "fl_k", "text"), by_words, groups)
    own = [c for c in keep.columns if c not in ("fl_id", "fl_k")]
    slim = packed_text(keep)
    joined = slim.join(cover, ["fl_id", "fl_k"], "left").drop("fl_id", "fl_k")
    result = StructType([keep.schema[c] for c in own])
    for n, kind in names:
        result = result.add(n, DataType.fromDDL(kind))

    def run(batches):
        for whole in batches:
            for b in pieces(unpacked_text(whole), "text", 2 << 20):
                raw, offsets, _ = text_buffers(b.column("text"))
                yield pa.RecordBatch.from_arrays([*(b.column(c) for c in own), *finish(raw, offsets, b.column("fl_cover"))], names=[*own, *(n for n, _ in names)])

    return joined.mapInArrow(run, result)


def binary_array(data: np.ndarray, offsets: np.ndarray) -> pa.Array:
    return pa.Array.from_buffers(pa.binary(), len(offsets) - 1, [None, pa.py_buffer(offsets.astype(np.int32).tobytes()), pa.py_buffer(data.tobytes())])
