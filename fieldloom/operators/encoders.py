"""Other encoders of a container's residuals: run-length, Huffman, and the columns of Parquet.

Each takes the rows of a container and gives rows of its own; ``unpacked`` makes the container again.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fieldloom.functions.bitpack import Codes, decode_fixed, decode_runs, encode_fixed, encode_runs
from fieldloom.model import Layout
from fieldloom.operators.chunks import HEAD, head, kernel
from fieldloom.operators.codecs import CONTAINER
from fieldloom.operators.generic import symbol_counts

ENCODERS = ("runs", "huffman", "columns")
COMMON = f"{HEAD}, codec string, n array<bigint>, meta array<bigint>"
SCHEMAS = {
    "runs": f"{COMMON}, runs int, widths array<int>, payload binary",
    "huffman": f"{COMMON}, bits array<int>, escaped array<bigint>, payload binary",
    "columns": f"{COMMON}, p array<bigint>",
}
SYMBOLS = 65_535  # symbols with a code of their own; the others share one and are written out


def code_table(container: DataFrame, layout: Layout, symbols: int = SYMBOLS) -> Codes:
    """Codes of a container's residuals: the most frequent ``symbols``, and one for all others.

    At most ``symbols`` rows come to the driver, however many residuals differ.
    """
    counts = symbol_counts(container, layout)
    top = counts.orderBy(F.desc("c"), "p").limit(symbols).collect()
    total = counts.agg(F.sum("c")).first()[0] or 0
    known = {r.p: r.c for r in top}
    return Codes.of(known, total - sum(known.values()))


def common(row: dict) -> dict:
    return head(row) | {k: row[k] for k in ("codec", "n", "meta")}


def packed_by(container: DataFrame, encoder: str, codes: Codes | None = None) -> DataFrame:
    """The container's rows under another encoder; ``huffman`` needs the codes of ``code_table``."""
    if encoder not in ENCODERS:
        raise ValueError(f"no encoder {encoder}")
    if encoder == "huffman" and codes is None:
        raise ValueError("huffman needs a table of codes")

    def run(row):
        sizes = np.asarray(row["n"], np.int64)
        p = decode_fixed(np.asarray(row["width"], np.int64), sizes, row["payload"])
        if encoder == "columns":
            yield common(row) | {"p": p}
        elif encoder == "runs":
            values, lengths = encode_runs(p)
            width, payload = encode_fixed(np.concatenate([values, lengths]), np.array([len(values)] * 2 if len(values) else [], np.int64))
            yield common(row) | {"runs": len(values), "widths": width, "payload": payload}
        else:
            bits, escaped, payload = codes.encode(p, sizes)
            yield common(row) | {"bits": bits, "escaped": escaped, "payload": payload}

    return kernel(container, run, SCHEMAS[encoder])


def unpacked(rows: DataFrame, encoder: str, codes: Codes | None = None) -> DataFrame:
    """The container that ``packed_by`` took."""

    def run(row):
        sizes = np.asarray(row["n"], np.int64)
        if encoder == "columns":
            p = row["p"]
        elif encoder == "runs":
            many = row["runs"]
            both = decode_fixed(np.asarray(row["widths"], np.int64), np.array([many] * 2 if many else [], np.int64), row["payload"])
            p = decode_runs(both[:many], both[many:])
        else:
            p = codes.decode(np.asarray(row["bits"], np.int64), sizes, np.asarray(row["escaped"], np.int64), row["payload"])
        width, payload = encode_fixed(p, sizes)
        yield common(row) | {"width": width, "payload": payload}

    return kernel(rows, run, CONTAINER)


def encoded_bytes(rows: DataFrame, encoder: str) -> DataFrame:
    """(field, encoder, blocks, bytes) of payloads: with two bytes a block for its bits, eight for a written-out residual."""
    extra = {"runs": F.lit(6), "huffman": 2 * F.size("n") + 8 * F.size("escaped")}
    if encoder not in extra:
        raise ValueError("the bytes of plain columns are those of their Parquet files")
    size = (F.octet_length("payload") + extra[encoder]).cast("bigint")
    return rows.groupBy("field").agg(F.lit(encoder).alias("encoder"), F.sum(F.size("n")).alias("blocks"), F.sum(size).alias("bytes"))


def write_columns(rows: DataFrame, path: str, mode: str = "error") -> None:
    """Residuals as a Parquet column: version 2 pages pack differences of integers, and zstd takes the rest."""
    rows.write.mode(mode).option("parquet.writer.version", "v2").option("parquet.enable.dictionary", "false").option("compression", "zstd").parquet(path)


__all__ = ["ENCODERS", "code_table", "encoded_bytes", "packed_by", "unpacked", "write_columns"]
