"""Encoders of integer residuals: fixed width, run-length and Huffman. Array kernels."""

from __future__ import annotations

import heapq
from dataclasses import dataclass

import numpy as np


def widths(p: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Bits of the largest magnitude of each block; blocks lie one after another in ``p``."""
    if not len(sizes):
        return np.zeros(0, np.int8)
    starts = np.cumsum(sizes) - sizes
    top = np.maximum.reduceat(np.abs(p.astype(np.int64)).astype(np.uint64), starts)
    out = np.zeros(len(top), np.int8)
    for bit in range(64):
        out[top >> np.uint64(bit) > 0] = bit + 1
    return out


def packed_bytes(sizes: np.ndarray, width: np.ndarray) -> np.ndarray:
    """Bytes of each block: sign bits, then magnitude bits; none for a constant block."""
    s, w = sizes.astype(np.int64), width.astype(np.int64)
    return np.where(w > 0, -(-s // 8) + -(-s * w // 8), 0)


def grouped(sizes: np.ndarray, width: np.ndarray):
    """(size, width, block numbers) of blocks that are packed alike."""
    for key in np.unique(sizes.astype(np.int64) * 128 + width):
        if key % 128:
            yield int(key // 128), int(key % 128), np.flatnonzero((sizes == key // 128) & (width == key % 128))


def encode_fixed(p: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, bytes]:
    width = widths(p, sizes)
    many = packed_bytes(sizes, width)
    out = np.zeros(int(many.sum()), np.uint8)
    at, starts = np.cumsum(many) - many, np.cumsum(sizes) - sizes
    for s, w, blocks in grouped(sizes, width):
        v = p[starts[blocks][:, None] + np.arange(s)].astype(np.int64)
        mag = np.abs(v).astype("<u8").view(np.uint8).reshape(len(blocks), s, 8)[:, :, : -(-w // 8)]
        bits = np.unpackbits(mag, axis=2, bitorder="little")[:, :, :w].reshape(len(blocks), s * w)
        both = np.hstack([np.packbits(v < 0, axis=1), np.packbits(bits, axis=1)])
        out[at[blocks][:, None] + np.arange(both.shape[1])] = both
    return width, out.tobytes()


def decode_fixed(width: np.ndarray, sizes: np.ndarray, payload: bytes) -> np.ndarray:
    raw = np.frombuffer(payload, np.uint8)
    many = packed_bytes(sizes, width)
    out = np.zeros(int(sizes.sum()), np.int64)
    at, starts = np.cumsum(many) - many, np.cumsum(sizes) - sizes
    for s, w, blocks in grouped(sizes, width):
        head = -(-s // 8)
        both = raw[at[blocks][:, None] + np.arange(int(many[blocks[0]]))]
        sign = np.unpackbits(both[:, :head], axis=1)[:, :s]
        bits = np.unpackbits(both[:, head:], axis=1)[:, : s * w].reshape(len(blocks), s, w)
        part = np.packbits(bits, axis=2, bitorder="little")
        size = next(b for b in (1, 2, 4, 8) if b >= part.shape[2])
        if size != part.shape[2]:
            part = np.concatenate([part, np.zeros((len(blocks), s, size - part.shape[2]), np.uint8)], axis=2)
        mag = np.ascontiguousarray(part).view(f"<u{size}")[:, :, 0].astype(np.int64)
        out[starts[blocks][:, None] + np.arange(s)] = np.where(sign == 1, -mag, mag)
    return out


def encode_runs(p: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(value, length) of the runs of equal residuals."""
    cut = np.flatnonzero(np.concatenate([[True], p[1:] != p[:-1]])) if len(p) else np.zeros(0, np.int64)
    return p[cut], np.diff(np.append(cut, len(p)))


def decode_runs(values: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    return np.repeat(values, lengths)


def huffman_lengths(counts: dict[int, int]) -> dict[int, int]:
    """Code length of each symbol of a histogram; a single symbol takes one bit."""
    symbols = sorted(counts)
    if len(symbols) < 2:
        return dict.fromkeys(symbols, 1)
    above = [0] * (2 * len(symbols) - 1)  # the node over each node; leaves come first, the root last
    heap = [(counts[s], i) for i, s in enumerate(symbols)]
    heapq.heapify(heap)
    for node in range(len(symbols), len(above)):
        a, b = heapq.heappop(heap), heapq.heappop(heap)
        above[a[1]] = above[b[1]] = node
        heapq.heappush(heap, (a[0] + b[0], node))
    depth = [0] * len(above)
    for node in range(len(above) - 2, -1, -1):
        depth[node] = depth[above[node]] + 1
    return dict(zip(symbols, depth))


LONGEST = 48  # bits of a code: any code then lies in the eight bytes from where it starts


@dataclass(frozen=True)
class Codes:
    """Canonical Huffman codes. ``symbols`` are in code order; ``escape`` is the place there of the code for all others."""

    symbols: np.ndarray
    lengths: np.ndarray
    escape: int

    @classmethod
    def of(cls, counts: dict[int, int], others: int = 0) -> Codes:
        """Codes of a histogram; there is always a code for a symbol that it lacks."""
        place = {s: n for n, s in enumerate(sorted(counts))}
        weights = {n: counts[s] for s, n in place.items()} | {len(place): max(1, others)}
        lengths = huffman_lengths(weights)
        while max(lengths.values()) > LONGEST:  # flatter weights make a lower tree
            weights = {n: max(1, c >> 1) for n, c in weights.items()}
            lengths = huffman_lengths(weights)
        order = sorted(lengths, key=lambda n: (lengths[n], n))
        back = [*sorted(counts), 0]
        return cls(np.array([back[n] for n in order], np.int64), np.array([lengths[n] for n in order], np.int64), order.index(len(place)))

    def codes(self) -> np.ndarray:
        """Code words, left-aligned in LONGEST bits: sums of the sizes of the words before them."""
        size = np.int64(1) << (LONGEST - self.lengths)
        return np.cumsum(size) - size

    def encode(self, p: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray, bytes]:
        """(bits of each block, residuals written out, payload)."""
        if not len(p):
            return np.zeros(len(sizes), np.int64), np.zeros(0, np.int64), b""
        known = np.delete(np.arange(len(self.symbols)), self.escape)
        known = known[np.argsort(self.symbols[known])]
        if len(known):
            at = known[np.minimum(np.searchsorted(self.symbols[known], p), len(known) - 1)]
            at = np.where(self.symbols[at] == p, at, self.escape)
        else:
            at = np.full(len(p), self.escape)
        lengths = self.lengths[at]
        ends = np.cumsum(lengths)
        # bit n of the payload is a bit of the code in which it falls
        code = np.repeat(self.codes()[at], lengths)
        inner = np.arange(int(ends[-1])) - np.repeat(ends - lengths, lengths)
        payload = np.packbits(((code >> (LONGEST - 1 - inner)) & 1).astype(np.uint8))
        return np.add.reduceat(lengths, np.cumsum(sizes) - sizes), p[at == self.escape], payload.tobytes()

    def decode(self, bits: np.ndarray, sizes: np.ndarray, escaped: np.ndarray, payload: bytes) -> np.ndarray:
        """The residuals: all blocks are read side by side, one code of each at a step."""
        out = np.zeros(int(sizes.sum()), np.int64)
        if not len(out):
            return out
        raw = np.concatenate([np.frombuffer(payload, np.uint8), np.zeros(8, np.uint8)])
        codes, starts, at = self.codes(), np.cumsum(sizes) - sizes, np.cumsum(bits) - bits
        for step in range(int(sizes.max())):
            live = np.flatnonzero(sizes > step)
            word = raw[(at[live] >> 3)[:, None] + np.arange(8)].view(">u8")[:, 0].astype(np.uint64)
            word = (word << (at[live] & 7).astype(np.uint64)) >> np.uint64(64 - LONGEST)
            found = np.searchsorted(codes, word.astype(np.int64), side="right") - 1
            out[starts[live] + step] = found
            at[live] += self.lengths[found]
        missing = out == self.escape
        out = self.symbols[out]
        out[missing] = escaped
        return out
