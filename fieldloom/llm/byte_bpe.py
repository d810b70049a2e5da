"""Byte-level BPE encoding and decoding.

Pre-tokenisation runs no regex.  Code points become class numbers, each class is a
transition function on the states of a small automaton, and functions compose
associatively: blocks are composed side by side, block results are scanned, and a second
sweep yields each position's state and from it the slice starts.  Slices unknown to the
cache are merged together, all at once, with array operations, and long ones by a heap over
a linked list; offsets are kept, so a document's ids can be decoded, also in part.
"""

from __future__ import annotations

import base64
import hashlib
import unicodedata
from heapq import heappop, heappush

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .common import pieces, wider

# The code points with the Unicode property White_Space.
WHITE_SPACE = (*range(0x09, 0x0E), 0x20, 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000)

# Classes of code points. STMD, RV, E and EL are letters that contractions need.
LETTER, STMD, RV, E, EL, NUMBER, OTHER, QUOTE, BLANK, SPACE, END = range(11)
# States: what the slice in progress is.
FRESH, IN_LETTERS, IN_NUMBERS, IN_OTHERS, AT_QUOTE, QUOTE_RV, QUOTE_L, AT_BLANK, IN_SPACE = range(9)
STATES, HERE, BEFORE = 9, 1, 2
BLOCK = 256
LONG_SLICE = 256  # bytes beyond which a slice is merged on its own
CACHE_MOST = 300_000  # slices kept by a task; beyond it the cache starts anew


def class_table() -> np.ndarray:
    table = np.full(0x110000, OTHER, dtype=np.uint8)
    for cp in range(0x110000):
        c = unicodedata.category(chr(cp))[0]
        if c == "L":
            table[cp] = LETTER
        elif c == "N":
            table[cp] = NUMBER
    table[list(WHITE_SPACE)] = SPACE
    table[0x20] = BLANK
    table[ord("'")] = QUOTE
    for letters, k in (("stmd", STMD), ("rv", RV), ("e", E), ("l", EL)):
        table[[ord(x) for x in letters]] = k
    return table


def automaton() -> tuple[np.ndarray, np.ndarray]:
    """(next state, start flags) by [class, state]. HERE: a slice starts at this code point, BEFORE: at the one before."""
    letters = (LETTER, STMD, RV, E, EL)
    run = {**{k: IN_LETTERS for k in letters}, NUMBER: IN_NUMBERS, OTHER: IN_OTHERS, QUOTE: AT_QUOTE, BLANK: AT_BLANK, SPACE: IN_SPACE}
    go, out = np.zeros((11, STATES), np.uint8), np.zeros((11, STATES), np.uint8)
    for k in range(END):
        for s in range(STATES):
            to, flag = run[k], HERE
            if s in (QUOTE_RV, QUOTE_L):
                if (s, k) in ((QUOTE_RV, E), (QUOTE_L, EL)):
                    to, flag = FRESH, 0
                else:  # the quote stood alone, and letters began before this code point
                    flag = BEFORE | (0 if k in letters else HERE)
            elif s == AT_QUOTE:
                if k == STMD:
                    to, flag = FRESH, 0
                elif k in (RV, EL):
                    to, flag = (QUOTE_RV if k == RV else QUOTE_L), 0
                elif k in (OTHER, QUOTE):
                    to, flag = IN_OTHERS, 0
            elif s == IN_LETTERS and k in letters or s == IN_NUMBERS and k == NUMBER:
                flag = 0
            elif s == IN_OTHERS and k in (OTHER, QUOTE):
                to, flag = IN_OTHERS, 0
            elif s in (AT_BLANK, IN_SPACE):
                if k in (BLANK, SPACE):
                    flag = 0
                elif s == AT_BLANK:  # one blank joins what follows it
                    to, flag = (IN_OTHERS if k == QUOTE else to), BEFORE
                else:
                    flag = BEFORE | HERE
            go[k, s], out[k, s] = to, flag
    out[END, QUOTE_RV] = out[END, QUOTE_L] = BEFORE
    go[END] = FRESH
    return go, out


def monoid(go: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """All functions that the classes generate, as rows, with the table of their compositions by (number, class)."""
    rows = [tuple(range(STATES))]
    known, step, at = {rows[0]: 0}, [], 0
    while at < len(rows):
        line = []
        for k in range(len(go)):
            f = tuple(int(go[k, s]) for s in rows[at])
            if f not in known:
                known[f] = len(rows)
                rows.append(f)
            line.append(known[f])
        step.append(line)
        at += 1
    return np.array(rows, np.uint8), np.array(step, np.uint16)


class Splitter:
    def __init__(self, table: np.ndarray) -> None:
        self.table = table
        self.go, self.out = automaton()
        self.rows, self.step = monoid(self.go)

    def starts(self, points: np.ndarray) -> np.ndarray:
        """Positions where slices start; ``points`` are code points, with 0xFFFFFFFF after each document."""
        n = len(points)
        classes = np.full(-(-max(n, 1) // BLOCK) * BLOCK, END, np.uint8)
        end = points == 0xFFFFFFFF
        classes[:n] = np.where(end, END, self.table[np.where(end, 0, points)])
        by = np.ascontiguousarray(classes.reshape(-1, BLOCK).T)  # row: one step of all blocks
        f = np.zeros(by.shape[1], np.uint16)
        flat, width = self.step.ravel(), self.step.shape[1]
        for row in by:
            f = flat[f * width + row]
        # inclusive scan over the blocks' functions: each round composes twice the reach
        scan, reach = self.rows[f], 1
        while reach < len(scan):
            scan[reach:] = np.take_along_axis(scan[reach:], scan[:-reach].copy(), axis=1)
            reach *= 2
        state = np.concatenate([[FRESH], scan[:-1, FRESH]]).astype(np.uint16)
        go, out = self.go.ravel(), self.out.ravel()
        flags = np.empty_like(by)
        for i, row in enumerate(by):
            at = row.astype(np.uint16) * STATES + state
            flags[i], state = out[at], go[at].astype(np.uint16)
        flags = flags.T.ravel()[: n + 1] if n < flags.size else np.append(flags.T.ravel(), 0)
        start = (flags[:n] & HERE) > 0
        start |= (flags[1 : n + 1] & BEFORE) > 0
        return np.flatnonzero(start)


def slot_shift(slots: int) -> np.uint64:
    return np.uint64(65 - slots.bit_length())


def slot_of(keys: np.ndarray, shift: np.uint64) -> np.ndarray:
    return ((keys * np.uint64(0x9E3779B97F4A7C15)) >> shift).astype(np.int64)


def pair_slots(ranks: dict[bytes, int]) -> tuple[np.ndarray, np.ndarray, int]:
    """Hash table from two adjacent tokens to the rank of their join: keys, ranks, and the longest probe."""
    pairs = {}
    for b, r in ranks.items():
        for cut in range(1, len(b)):
            left, right = ranks.get(b[:cut]), ranks.get(b[cut:])
            if left is not None and right is not None:
                pairs[(left << 32) | right] = r
    keys = np.array(sorted(pairs), dtype=np.uint64)
    slots = 1 << max(10, int(len(keys) * 2).bit_length())
    slots_key, slots_rank = np.zeros(slots, np.uint64), np.full(slots, -1, np.int32)
    at, value = slot_of(keys, slot_shift(slots)), np.array([pairs[int(k)] for k in keys], np.int64)
    left, probes = np.arange(len(keys)), 0
    while len(left):  # open addressing: the first key of a free slot gets it
        probes += 1
        free = left[slots_rank[at[left]] < 0]
        _, first = np.unique(at[free], return_index=True)
        won = free[first]
        slots_key[at[won]], slots_rank[at[won]] = keys[won], value[won]
        left = np.setdiff1d(left, won)
        at[left] = (at[left] + 1) & (slots - 1)
    return slots_key, slots_rank, probes


class Merger:
    """Ranks of a vocabulary, and merging of many slices at once."""

    def __init__(self, ranks: dict[bytes, int], slots: tuple[np.ndarray, np.ndarray, int]) -> None:
        self.ranks = ranks
        size = max(ranks.values(), default=-1) + 1
        self.bytes_of = [b""] * size
        for b, r in ranks.items():
            self.bytes_of[r] = b
        self.single = np.array([ranks.get(bytes([i]), 0) for i in range(256)], np.int64)
        self.slots_key, self.slots_rank, self.probes = slots
        self.shift = slot_shift(len(self.slots_key))

    def rank(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        keys = (left.astype(np.uint64) << np.uint64(32)) | right.astype(np.uint64)
        at, top = slot_of(keys, self.shift), len(self.slots_key) - 1
        out = np.where(self.slots_key[at] == keys, self.slots_rank[at], -1)
        miss = np.flatnonzero((out < 0) & (self.slots_rank[at] >= 0))
        for _ in range(self.probes):
            if not len(miss):
                break
            at[miss] = (at[miss] + 1) & top
            hit = self.slots_key[at[miss]] == keys[miss]
            out[miss[hit]] = self.slots_rank[at[miss[hit]]]
            miss = miss[~hit & (self.slots_rank[at[miss]] >= 0)]
        return out

    def merge_long(self, piece: bytes) -> list[int]:
        """Ids of one long slice: pairs wait in a heap by (rank, place), and merged tokens form a linked list."""
        ids = self.single[np.frombuffer(piece, np.uint8)]
        rank = self.rank(ids[:-1], ids[1:]).astype(np.int64)
        at = np.flatnonzero(rank >= 0)
        heap = np.sort(rank[at] << 40 | at).tolist()  # sorted, so a heap
        n, now = len(piece), rank.tolist()
        now.append(-1)
        end, back = list(range(1, n + 1)), list(range(-1, n))  # of the token that starts at a place: where it ends, who is before
        get, mask = self.ranks.get, (1 << 40) - 1
        while heap:
            top = heappop(heap)
            r, i = top >> 40, top & mask
            if now[i] != r:  # one of the pair has been merged since
                continue
            j = end[i]
            e = end[i] = end[j]
            now[j] = -1
            if e < n:
                back[e] = i
                now[i] = m = get(piece[i : end[e]], -1)
                if m >= 0:
                    heappush(heap, m << 40 | i)
            else:
                now[i] = -1
            h = back[i]
            if h >= 0:
                now[h] = m = get(piece[h:e], -1)
                if m >= 0:
                    heappush(heap, m << 40 | h)
        out, i = [], 0
        while i < n:
            out.append(self.ranks[piece[i : end[i]]])
            i = end[i]
        return out

    def merge(self, slices: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all slices, ids in each). Every round merges each slice's leftmost pair of the lowest rank."""
        whole = np.array([self.ranks.get(s, -1) for s in slices], np.int64)
        sizes = np.array([len(s) for s in slices], np.int64)
        long_ = np.flatnonzero((whole < 0) & (sizes > LONG_SLICE))
        open_ = np.flatnonzero((whole < 0) & (sizes <= LONG_SLICE))
        known = np.flatnonzero(whole >= 0)
        done_ids, done_owner = [whole[known]], [known]
        for i in long_.tolist():
            done_ids.append(np.array(self.merge_long(slices[i]), np.int64))
            done_owner.append(np.full(len(done_ids[-1]), i))
        if not len(open_):
            ids, owner = np.concatenate(done_ids), np.concatenate(done_owner)
            return ids[np.argsort(owner, kind="stable")], np.bincount(owner, minlength=len(slices))
        sizes = sizes[open_]
        ids = self.single[np.frombuffer(b"".join(slices[i] for i in open_), np.uint8)]
        owner = np.repeat(open_, sizes)
        none = np.int64(1 << 40)
        while len(ids):
            r = np.full(len(ids), none)
            same = np.flatnonzero(owner[:-1] == owner[1:])
            got = self.rank(ids[same], ids[same + 1])
            r[same] = np.where(got < 0, none, got)
            first = np.flatnonzero(np.concatenate([[True], owner[1:] != owner[:-1]]))
            counts = np.diff(np.append(first, len(ids)))
            best = np.minimum.reduceat(r, first)
            stuck = np.repeat(best == none, counts)
            if stuck.any():
                done_ids.append(ids[stuck])
                done_owner.append(owner[stuck])
                ids, owner, r = ids[~stuck], owner[~stuck], r[~stuck]
                counts, best = counts[best < none], best[best < none]
                if not len(ids):
                    break
            hits = np.flatnonzero(r == np.repeat(best, counts))
            lead = hits[np.concatenate([[True], owner[hits[1:]] != owner[hits[:-1]]])]
            ids[lead] = r[lead]
            keep = np.ones(len(ids), bool)
            keep[lead + 1] = False
            ids, owner = ids[keep], owner[keep]
        ids, owner = np.concatenate(done_ids), np.concatenate(done_owner)
        return ids[np.argsort(owner, kind="stable")], np.bincount(owner, minlength=len(slices))


class Codec:
    def __init__(self, ranks: dict[bytes, int], table: np.ndarray, slots: tuple) -> None:
        self.splitter, self.merger = Splitter(table), Merger(ranks, slots)
        self.decimal = [str(i) for i in range(len(self.merger.bytes_of))]
        self.forget()

    def forget(self) -> None:
        self.place: dict[str, int] = {}  # slice: its number
        self.flat, self.begin, self.count = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64)

    def learn(self, slices: list[str]) -> None:
        ids, counts = self.merger.merge([s.encode() for s in slices])
        self.place.update(zip(slices, range(len(self.place), len(self.place) + len(slices))))
        self.begin = np.append(self.begin, len(self.flat) + np.cumsum(counts) - counts)
        self.count = np.append(self.count, counts)
        self.flat = np.append(self.flat, ids)

    def encode(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all texts, offset of each text's ids)."""
        if len(self.place) > CACHE_MOST:
            self.forget()
        joined = "\0".join([*texts, ""])
        points = np.frombuffer(joined.encode("utf-32-le"), np.uint32).copy()
        ends = np.cumsum(np.array([len(t) + 1 for t in texts], np.int64))
        points[ends - 1] = 0xFFFFFFFF  # ends a document; no code point is as large
        starts = self.splitter.starts(points)
        starts = starts[points[starts] != 0xFFFFFFFF]
        bounds = np.searchsorted(starts, np.concatenate([[0], ends]))
        stops = np.append(starts[1:], len(points))
        last = bounds[1:][np.diff(bounds) > 0] - 1
        stops[last] = ends[np.diff(bounds) > 0] - 1
        own = [joined[a:b] for a, b in zip(starts.tolist(), stops.tolist())]
        at = list(map(self.place.get, own))
        if None in at:
            self.learn(list(dict.fromkeys(s for s, i in zip(own, at) if i is None)))
            at = list(map(self.place.__getitem__, own))
        which = np.array(at, np.int64)
        count = self.count[which]
        done = np.cumsum(count)
        ids = self.flat[np.repeat(self.begin[which] - (done - count), count) + np.arange(int(done[-1]) if len(done) else 0)]
        return ids, np.concatenate([[0], done])[bounds]

    def shown(self, ids: list[int]) -> str:
        return ",".join(map(self.decimal.__getitem__, ids))

    def decode(self, ids: list[int]) -> bytes:
        return b"".join(map(self.merger.bytes_of.__getitem__, ids))


def load_ranks(path: str) -> dict[bytes, int]:
    """A rank file: a base64 token and its rank on each line."""
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}


def encode_documents(docs: DataFrame, ranks_path: str, ids: bool = True, digests: bool = False) -> DataFrame:
    """``docs`` with the ids of each whole ``text`` and the byte offset at which each id's token ends.

    Adds ``n_tokens``; with ``ids`` also ``token_ids`` and ``token_ends`` arrays; with ``digests``
    ``ids_sha256`` and ``decoded_sha256``, the latter of the bytes decoded from the ids.  Null and
    empty texts have no tokens.  Repeated rows are encoded alike; other columns pass through, and
    input columns named like the results are replaced.
    """
    names = ["n_tokens", *(["token_ids", "token_ends"] if ids else []), *(["ids_sha256", "decoded_sha256"] if digests else [])]
    kinds = {"n_tokens": "bigint", "token_ids": "array<int>", "token_ends": "array<bigint>", "ids_sha256": "string", "decoded_sha256": "string"}
    keep = docs.drop(*kinds)
    # the vocabulary is of a fixed size, whatever the data; executors may not have its file
    ranks = load_ranks(ranks_path)
    tables = docs.sparkSession.sparkContext.broadcast((ranks, class_table(), pair_slots(ranks)))

    def run(batches):
        codec = Codec(*tables.value)
        width = np.array([len(b) for b in codec.merger.bytes_of], np.int64)
        for whole in batches:
            for b in pieces(whole, "text", 1 << 20):
                made = {k: [] for k in names}
                flat, cuts = codec.encode([t or "" for t in b.column("text").to_pylist()])
                for x, y in zip(cuts[:-1], cuts[1:]):
                    own = flat[x:y]
                    made["n_tokens"].append(len(own))
                    if ids:
                        made["token_ids"].append(own)
                        made["token_ends"].append(np.cumsum(width[own]))
                    if digests:
                        listed = own.tolist()
                        made["ids_sha256"].append(hashlib.sha256(codec.shown(listed).encode()).hexdigest())
                        made["decoded_sha256"].append(hashlib.sha256(codec.decode(listed)).hexdigest())
                kinds_pa = {"n_tokens": pa.int64(), "token_ids": pa.list_(pa.int32()), "token_ends": pa.list_(pa.int64()), "ids_sha256": pa.string(), "decoded_sha256": pa.string()}
                yield pa.RecordBatch.from_arrays([*b.columns, *(pa.array(made[k], kinds_pa[k]) for k in names)], names=[*b.schema.names, *names])

    return keep.mapInArrow(run, wider(keep, *((k, kinds[k]) for k in names)))


def decode_documents(encoded: DataFrame, ranks_path: str) -> DataFrame:
    """``encoded`` with ``decoded``: the bytes of ``token_ids`` (null: null)."""
    keep = encoded.drop("decoded")
    ranks = encoded.sparkSession.sparkContext.broadcast(load_ranks(ranks_path))

    def run(batches):
        of = {r: b for b, r in ranks.value.items()}
        for b in batches:
            got = [None if x is None else b"".join([of[i] for i in x]) for x in b.column("token_ids").to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(got, pa.binary())], names=[*b.schema.names, "decoded"])

    return keep.mapInArrow(run, wider(keep, ("decoded", "binary")))


def default_ranks(spark: SparkSession) -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_multi_50k.tiktoken")
