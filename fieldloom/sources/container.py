"""Container tables, and raw binary field files."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from fieldloom.operators.codecs import CONTAINER


def write_container(container: DataFrame, path: str, mode: str = "error") -> None:
    """One row a chunk, a folder a field, ordered by chunk within files: boxes prune row groups."""
    container.repartition("field", "ci").sortWithinPartitions("ci", "cj", "ck").write.mode(mode).option("compression", "zstd").partitionBy("field").parquet(path)


def read_container(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(CONTAINER).parquet(path)


RECORD = 65_536  # values that a record of a raw file holds at most


def record_length(points: int) -> int:
    """The largest number of values up to RECORD that divides a field's points: records must fill a file."""
    return next(n for n in range(min(RECORD, points), 0, -1) if points % n == 0)


def raw_field(spark: SparkSession, path: str, name: str, shape: tuple[int, ...]) -> DataFrame:
    """Points of a file of little-endian 32-bit floats in row-major order.

    The file is read in records of a fixed length, so a file of any size is split among tasks; a record's
    key is its place in bytes.  A file of another size than the shape's is an error.
    """
    d = [*shape, 1, 1][:3]
    points = int(np.prod(d))
    many = record_length(points)
    hadoop = "org.apache.hadoop"
    records = spark.sparkContext.newAPIHadoopFile(path, f"{hadoop}.mapreduce.lib.input.FixedLengthInputFormat", f"{hadoop}.io.LongWritable", f"{hadoop}.io.BytesWritable", conf={"fixedlengthinputformat.record.length": str(4 * many)})
    rows = records.map(lambda kv: (int(kv[0]), bytes(kv[1]))).toDF("at bigint, content binary")

    def run(batches):
        for b in batches:
            for at, blob in zip(b.column("at"), b.column("content")):
                v = np.frombuffer(blob.as_py(), "<f4").astype(np.float64)
                g = np.arange(at.as_py() // 4, at.as_py() // 4 + len(v))
                if g[-1] >= points:
                    raise ValueError(f"{path} holds more than {points} values")
                i, j, k = np.unravel_index(g, d)
                yield pa.RecordBatch.from_arrays([pa.array([name] * len(g)), pa.array(i), pa.array(j), pa.array(k), pa.array(v)], names=["field", "i", "j", "k", "value"])

    return rows.mapInArrow(run, "field string, i bigint, j bigint, k bigint, value double")
