"""Stages, codecs, error bounds and grid layouts."""

from __future__ import annotations

from dataclasses import dataclass

META, RESID, QUANT, VALUE = "META", "RESID", "QUANT", "VALUE"
STAGES = (META, RESID, QUANT, VALUE)

#: Points of a block and of a chunk, by number of dimensions. A chunk is a box of whole blocks.
BLOCKS = {1: (64,), 2: (8, 8), 3: (4, 4, 4)}
CHUNKS = {1: (65536,), 2: (256, 256), 3: (40, 40, 40)}


class UnsupportedStage(ValueError):
    """The codec, or the operation on it, has no such stage."""


@dataclass(frozen=True)
class Codec:
    name: str
    predictor: str  # difference, mean, first or midrange
    flat: bool  # blocks run along the flattened array
    stages: tuple[str, ...]

    @property
    def meta_bytes(self) -> int:
        return 0 if self.predictor == "difference" else 4


CODECS = {
    c.name: c
    for c in (
        Codec("chain1d", "difference", True, (RESID, QUANT, VALUE)),
        Codec("lorenzo", "difference", False, (RESID, QUANT, VALUE)),
        Codec("mean1d", "mean", True, STAGES),
        Codec("meannd", "mean", False, STAGES),
        Codec("blockdiff", "first", True, (VALUE,)),
        Codec("midrange", "midrange", True, (VALUE,)),
    )
}


@dataclass(frozen=True)
class ErrorBound:
    """An absolute bound, or one relative to the range of the values."""

    size: float
    relative: bool = True


@dataclass(frozen=True)
class Layout:
    """How a field is cut: ``block`` and ``chunk`` extents, of as many dimensions as the codec works in."""

    block: tuple[int, ...]
    chunk: tuple[int, ...]

    def __post_init__(self) -> None:
        if len(self.block) != len(self.chunk) or any(c % b for b, c in zip(self.block, self.chunk)):
            raise ValueError("a chunk is a box of whole blocks")

    @property
    def ndim(self) -> int:
        return len(self.block)


def layout_for(codec: str, ndim: int, chunk: tuple[int, ...] | None = None) -> Layout:
    n = 1 if CODECS[codec].flat else ndim
    return Layout(BLOCKS[n], tuple(chunk or CHUNKS[n]))


def require(codec: str, stage: str, operation: str = "") -> None:
    """Raise UnsupportedStage unless ``codec`` has ``stage`` and ``operation`` runs there."""
    c = CODECS[codec]
    moves = operation in ("gradient", "laplacian", "divergence", "curl")
    if stage not in c.stages or stage == META and operation not in ("", "mean") or moves and c.flat and stage == RESID:
        raise UnsupportedStage(f"{codec} has no {stage} for {operation or 'decompression'}")
