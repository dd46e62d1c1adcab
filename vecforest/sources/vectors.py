"""Length-prefixed vector files: each record is a little-endian int32 dimension, then so many float32 (or bytes, or int32)."""

from __future__ import annotations

import struct

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

KINDS = {"f": ("<f4", 4), "b": ("u1", 1), "i": ("<i4", 4)}


def parse(data: bytes, kind: str = "f") -> list[tuple[int, list[float]]]:
    """(place, vector) of each record."""
    dtype, width = KINDS[kind]
    out, at, i = [], 0, 0
    while at < len(data):
        (d,) = struct.unpack_from("<i", data, at)
        out.append((i, np.frombuffer(data, dtype=dtype, count=d, offset=at + 4).astype(float).tolist()))
        at += 4 + d * width
        i += 1
    return out


def record(vector, kind: str = "f") -> bytes:
    return struct.pack("<i", len(vector)) + np.asarray(vector, dtype=KINDS[kind][0]).tobytes()


def read_vectors(spark, path: str, kind: str = "f") -> DataFrame:
    """(file, place, embedding) through Spark's binary file reader: any store that Spark reads; one file is one task."""
    rows = F.udf(lambda data: parse(bytes(data), kind), "array<struct<place:long,embedding:array<double>>>")
    files = spark.read.format("binaryFile").load(path)
    return files.select(F.element_at(F.split("path", "/"), -1).alias("file"), F.explode(rows("content")).alias("r")).select("file", "r.place", "r.embedding")


def write_vectors(points: DataFrame, path: str, kind: str = "f") -> None:
    """Rows (vec_id, embedding) as a table of records, which VectorFiles reads again."""
    encode = F.udf(lambda v: record(v, kind), "binary")
    points.select("vec_id", encode("embedding").alias("record")).write.mode("overwrite").parquet(path)


class _Part(InputPartition):
    def __init__(self, path: str):
        self.path = path


class VectorFiles(DataSource):
    """Python data source `vector_files`: records that write_vectors() wrote to a local or mounted folder."""

    @classmethod
    def name(cls) -> str:
        return "vector_files"

    def schema(self) -> str:
        return "vec_id long, embedding array<double>"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options["path"])


class _Reader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path.removeprefix("file://").removeprefix("file:")

    def partitions(self):
        import glob

        return [_Part(p) for p in sorted(glob.glob(f"{self.path}/*.parquet"))]

    def read(self, partition):
        import pyarrow.parquet as pq

        for batch in pq.ParquetFile(partition.path).iter_batches():
            for i, data in zip(batch["vec_id"].to_pylist(), batch["record"].to_pylist(), strict=True):
                yield (i, parse(data)[0][1])
