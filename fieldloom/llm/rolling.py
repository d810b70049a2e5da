"""Array kernels shared by the deduplication operators: words, window hashes and window anchors.

All texts of a batch lie end to end in one buffer of units (bytes, or word hashes).  Window hashes
come from prefix sums of a polynomial modulo 2**64, so a window costs the same whatever its length.
Such a polynomial is weak over long stretches of two units (it loses bits with each doubling), so it
serves windows of at most 50 units only; words of any length are hashed by place-dependent scrambles.
"""

from __future__ import annotations

import numpy as np

from .common import mix64

# Odd bases of the polynomials and seeds of the unit scrambles.
BASES = (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F)
SEEDS = (0x632BE59BD9B4E019, 0xD6E8FEB86659FD93)
PLACE_BITS = 31


class Powers:
    """Powers of a base and of its inverse, grown as needed."""

    def __init__(self, base: int) -> None:
        self.base, self.inverse = base, pow(base, -1, 1 << 64)
        self.up = self.down = np.ones(1, np.uint64)

    def reach(self, n: int) -> None:
        while len(self.up) < n:
            k = len(self.up)
            self.up = np.concatenate([self.up, self.up * np.uint64(pow(self.base, k, 1 << 64))])
            self.down = np.concatenate([self.down, self.down * np.uint64(pow(self.inverse, k, 1 << 64))])


class Hasher:
    """Hashes of stretches of a unit buffer."""

    def __init__(self, which: int = 0) -> None:
        self.seed, self.powers = np.uint64(SEEDS[which]), Powers(BASES[which])

    def prefix(self, units: np.ndarray) -> np.ndarray:
        self.powers.reach(len(units) + 1)
        out = np.zeros(len(units) + 1, np.uint64)
        if units.dtype == np.uint8:
            scrambled = mix64(np.arange(1, 257, dtype=np.uint64) * self.seed)[units]
        else:
            scrambled = mix64(units ^ self.seed)
        scrambled *= self.powers.up[: len(units)]
        np.cumsum(scrambled, out=out[1:])
        return out

    def stretches(self, prefix: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        return mix64((prefix[ends] - prefix[starts]) * self.powers.down[starts])

    def windows(self, prefix: np.ndarray, size: int) -> np.ndarray:
        """Hash of the ``size`` units from each position that has so many in the buffer."""
        n = len(prefix) - size
        if n <= 0:
            return np.zeros(0, np.uint64)
        return mix64((prefix[size:] - prefix[:n]) * self.powers.down[:n])


def words(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(starts, ends, words before each text) of the words between blanks and ASCII control spaces."""
    n = len(raw)
    solid = ~((raw == 0x20) | ((raw >= 0x09) & (raw <= 0x0D)))
    first, last = solid.copy(), solid.copy()
    first[1:] &= ~solid[:-1]
    last[:-1] &= ~solid[1:]
    inner = offsets[(offsets > 0) & (offsets < n)]
    first[inner] = solid[inner]
    last[inner - 1] = solid[inner - 1]
    starts, ends = np.flatnonzero(first), np.flatnonzero(last) + 1
    return starts, ends, np.searchsorted(starts, offsets)


def word_hashes(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray, which: int = 0) -> np.ndarray:
    """A hash of each word's bytes: its blocks of eight bytes, each scrambled with its place, added up."""
    if not len(starts):
        return np.zeros(0, np.uint64)
    room = np.concatenate([raw, np.zeros(8, np.uint8)])
    eight = np.ndarray(len(raw) + 1, "<u8", room, 0, (1,))  # the eight bytes from each place on
    size = ends - starts
    blocks = -(-size // 8)
    first = np.cumsum(blocks) - blocks
    k = np.arange(int(blocks.sum())) - np.repeat(first, blocks)
    value = eight[np.repeat(starts, blocks) + 8 * k]
    left = np.repeat(size, blocks) - 8 * k
    short = np.flatnonzero(left < 8)
    value[short] &= (np.uint64(1) << (8 * left[short]).astype(np.uint64)) - np.uint64(1)
    value = mix64(mix64(value ^ np.uint64(SEEDS[which])) + k.astype(np.uint64) * np.uint64(BASES[which]))
    return mix64(np.add.reduceat(value, first) + size.astype(np.uint64))


def full_windows(bounds: np.ndarray, size: int, n: int) -> np.ndarray:
    """For each of ``n`` window starts, whether the window ends inside the text it starts in."""
    ends = np.repeat(bounds[1:], np.diff(bounds))
    return np.arange(n) + size <= ends[:n]


def anchor_runs(hashes: np.ndarray, size: int, inner: int, valid: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(anchor, first, last) for runs of windows that share an anchor.

    A window of ``size`` units has ``size - inner + 1`` stretches of ``inner`` units, whose hashes are
    given; its anchor is the leftmost with the least hash.  Equal windows have equal anchors.
    """
    span = size - inner + 1
    n = len(valid)
    if n <= 0 or not valid.any():
        return (np.zeros(0, np.int64),) * 3
    low = (hashes >> np.uint64(PLACE_BITS) << np.uint64(PLACE_BITS)) | np.arange(len(hashes), dtype=np.uint64)
    width = 1
    while width * 2 <= span:
        low = np.minimum(low[:-width], low[width:])
        width *= 2
    low = np.minimum(low[:n], low[span - width : span - width + n])
    owner = (low & np.uint64((1 << PLACE_BITS) - 1)).astype(np.int64)
    owner[~valid] = -1
    cut = np.flatnonzero(np.concatenate([[True], owner[1:] != owner[:-1]]))
    stop = np.append(cut[1:], n) - 1
    keep = owner[cut] >= 0
    return owner[cut][keep], cut[keep], stop[keep]
