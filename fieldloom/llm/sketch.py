"""A count-min sketch that partitions fill, shards merge and all tasks consult.

Each partition sends the counters that it touched, sorted and delta-coded, one message for each
shard of the counters.  A shard adds them up and keeps one bit a counter: whether it reached the
threshold.  Estimates are never below true counts, so a key above the threshold is always reported.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import mix64

ROWS = 2
SHARD_BITS = 5
LEAST_BITS, MOST_BITS = 14, 30  # counters of a row; the merged bits take 2 * 2**MOST_BITS / 8 bytes at most, 256 MB
HELD = 3_000_000  # keys that a task holds before it sends


def bits_for(keys: int) -> int:
    """Counters a row for about ``keys`` distinct keys: four each, within fixed bounds."""
    return max(LEAST_BITS, min(MOST_BITS, int(4 * max(1, keys) - 1).bit_length()))


def counter(keys: np.ndarray, row: int, bits: int) -> np.ndarray:
    return (mix64(keys ^ np.uint64(0xA24BAED4963EE407)) if row else keys) >> np.uint64(64 - bits)


def shrink(counters: np.ndarray) -> bytes:
    """Sorted counters as delta-coded bytes, one plane for each byte of a delta."""
    gaps = np.diff(counters, prepend=0).astype("<u4")
    return len(gaps).to_bytes(4, "little") + pa.compress(np.ascontiguousarray(gaps.view(np.uint8).reshape(-1, 4).T).tobytes(), codec="zstd", asbytes=True)


def grow(blob: bytes) -> np.ndarray:
    n = int.from_bytes(blob[:4], "little")
    planes = np.frombuffer(pa.decompress(blob[4:], decompressed_size=4 * n, codec="zstd", asbytes=True), np.uint8).reshape(4, n)
    return np.cumsum(np.ascontiguousarray(planes.T).view("<u4").ravel().astype(np.int64))


class Sketch:
    """Merged bits; ``seen(keys)`` is whether each key's estimate reaches the threshold."""

    def __init__(self, bits: int, planes: list[np.ndarray]) -> None:
        self.bits, self.planes = bits, planes

    def seen(self, keys: np.ndarray) -> np.ndarray:
        out = np.ones(len(keys), bool)
        at = np.arange(len(keys))
        for row, plane in enumerate(self.planes):
            c = counter(keys[at], row, self.bits)
            hit = (plane[(c >> np.uint64(3)).astype(np.int64)] >> (c & np.uint64(7)).astype(np.uint8)) & 1
            out[at[hit == 0]] = False
            at = at[hit == 1]
        return out


def merged(df: DataFrame, keys_of: Callable[[Iterable[pa.RecordBatch]], Iterator[np.ndarray]], bits: int, threshold: int = 2):
    """Broadcast (bits, planes) of the keys that ``keys_of`` yields from each partition of ``df``.

    What is broadcast has a fixed size given ``bits``, whatever the number of keys.
    """
    shards, inner = 1 << SHARD_BITS, bits - SHARD_BITS
    cap = min(threshold, 255)

    def touched(batches):
        held, many = [], 0

        def send():
            keys = np.concatenate(held)
            held.clear()
            for row in range(ROWS):
                c = np.sort(counter(keys, row, bits).astype(np.int64))
                # a counter is sent as often as it was hit, up to the threshold
                keep = np.ones(len(c), bool)
                keep[cap:] = c[cap:] != c[:-cap]
                c = c[keep]
                cuts = np.searchsorted(c, np.arange(shards + 1) << inner)
                blobs = [(row * shards + s, shrink(c[a:b] - (s << inner))) for s, (a, b) in enumerate(zip(cuts[:-1], cuts[1:])) if b > a]
                yield pa.RecordBatch.from_arrays([pa.array([s for s, _ in blobs], pa.int32()), pa.array([x for _, x in blobs], pa.binary())], names=["shard", "blob"])

        for keys in keys_of(batches):
            held.append(keys)
            many += len(keys)
            if many >= HELD:
                yield from send()
                many = 0
        if many:
            yield from send()

    def added(batches):
        now, counts = None, np.zeros(1 << inner, np.uint8)

        def done():
            return pa.RecordBatch.from_arrays([pa.array([now], pa.int32()), pa.array([pa.compress(np.packbits(counts >= cap, bitorder="little").tobytes(), codec="zstd", asbytes=True)], pa.binary())], names=["shard", "blob"])

        for b in batches:
            for s, blob in zip(b.column("shard").to_pylist(), b.column("blob")):
                if s != now:
                    if now is not None:
                        yield done()
                    now = s
                    counts[:] = 0
                one, n = np.unique(grow(blob.as_py()), return_counts=True)
                counts[one] = np.minimum(counts[one].astype(np.int64) + n, cap).astype(np.uint8)
        if now is not None:
            yield done()

    layout = "shard int, blob binary"
    rows = df.mapInArrow(touched, layout).repartition(ROWS * shards, "shard").sortWithinPartitions("shard").mapInArrow(added, layout).collect()
    planes = [np.zeros((1 << bits) // 8, np.uint8) for _ in range(ROWS)]
    size = (1 << inner) // 8
    for s, blob in rows:
        planes[s // shards][(s % shards) * size : (s % shards + 1) * size] = np.frombuffer(pa.decompress(blob, decompressed_size=size, codec="zstd", asbytes=True), np.uint8)
    return df.sparkSession.sparkContext.broadcast((bits, planes))
