"""Graph layout: lists sorted by rank in buckets of their source, so searches and cuts read what they need."""

from __future__ import annotations

import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..functions.exact import Share


def write_edges(edges: DataFrame, name: str, path: str, buckets: int) -> None:
    """(src, rank, dst, dist, gain, cum) as a table bucketed by src; a join or a frontier step on src needs no shuffle of it."""
    edges.write.mode("overwrite").bucketBy(buckets, "src").sortBy("src", "rank").format("parquet").option("path", path).saveAsTable(name)


def read_edges(spark: SparkSession, name: str, share, n: int) -> DataFrame:
    """The lists of a share: a pushed-down filter on the full ones."""
    return spark.table(name).where(f"cum - gain < {Share.of(share).need(n)}")


def write_cliques(members: DataFrame, path: str) -> None:
    """The compressed form of a peeled graph, a row per node and round; edges are multiplied out on reading."""
    members.write.mode("overwrite").partitionBy("round").parquet(path)


def through(df: DataFrame, form: str, path: str) -> DataFrame:
    """df written in a format and read back with its own schema: csv, json, orc or parquet."""
    at = f"{path}/{form}-{uuid.uuid4().hex}"
    options = {"header": "true"} if form == "csv" else {}
    df.write.format(form).options(**options).save(at)
    return df.sparkSession.read.format(form).schema(df.schema).options(**options).load(at)


def flat_vectors(spark: SparkSession, path: str) -> DataFrame:
    """(id, vec) of binary files of vectors, each its length as a 32-bit integer and then 32-bit floats.

    A file is a row and a task's work, below 2 GiB; ids count on over the files
    in the order of their names, by a number per file."""
    found = spark.read.format("binaryFile").load(path)

    def parse(batches):
        for batch in batches:
            for name, raw in zip(batch.column(0), batch.column(1), strict=True):
                data = np.frombuffer(raw.as_py(), "<i4")
                dim = int(data[0]) if len(data) else 0
                rows = data.reshape(-1, dim + 1)[:, 1:].copy().view("<f4") if len(data) else np.empty((0, 0), "<f4")
                for at in range(0, len(rows), 8192):
                    part = rows[at : at + 8192]
                    vecs = pa.ListArray.from_arrays(pa.array(np.arange(len(part) + 1, dtype=np.int32) * dim), pa.array(part.ravel()))
                    yield pa.RecordBatch.from_arrays([pa.array([name.as_py()] * len(part)), pa.array(np.arange(at, at + len(part))), vecs], ["path", "row", "vec"])

    def count(batches):
        for batch in batches:
            n = [len(x.as_py()) // (4 + 4 * int.from_bytes(x.as_py()[:4], "little")) if len(x.as_py()) else 0 for x in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64())], ["_path", "_n"])

    files = found.select("path", "content")
    first = files.mapInArrow(count, "_path string, _n long").select("_path", F.coalesce(F.sum("_n").over(W.orderBy("_path").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("_first"))
    rows = files.mapInArrow(parse, "path string, row long, vec array<float>")
    return rows.join(F.broadcast(first), F.col("path") == F.col("_path")).select((F.col("row") + F.col("_first")).alias("id"), "vec")


def write_flat(points: DataFrame, path: str) -> None:
    """points as files of flat_vectors() in a mounted folder, one per partition, named in order; single precision."""

    def save(batches):
        import os

        from pyspark import TaskContext

        os.makedirs(path, exist_ok=True)
        name = f"{path}/part-{TaskContext.get().partitionId():06d}.fvecs"
        with open(f"{name}.new", "wb") as f:
            for batch in batches:
                v = batch.column(0).flatten().to_numpy(zero_copy_only=False).astype("<f4").reshape(batch.num_rows, -1)
                f.write(np.concatenate([np.full((len(v), 1), v.shape[1], "<i4").view("<f4"), v], axis=1).tobytes())
        os.replace(f"{name}.new", name)  # a task that runs again leaves the same file
        yield pa.RecordBatch.from_pydict({"done": [1]})

    points.select("vec").mapInArrow(save, "done long").agg(F.sum("done")).collect()


class FlatVectorSource(DataSource):
    """spark.read.format("flat_vectors"): (file, row, vec) of binary vector files in a mounted folder, a partition for each file."""

    @classmethod
    def name(cls) -> str:
        return "flat_vectors"

    def schema(self) -> str:
        return "file string, row long, vec array<float>"

    def reader(self, schema):
        return FlatVectorReader(self.options["path"])


class FlatVectorReader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path

    def partitions(self):
        import os

        return [InputPartition(n) for n in sorted(os.listdir(self.path)) if n.endswith(".fvecs")]

    def read(self, partition):
        data = np.fromfile(f"{self.path}/{partition.value}", "<i4")
        if len(data):
            rows = data.reshape(-1, int(data[0]) + 1)[:, 1:]
            for at in range(0, len(rows), 8192):
                part = rows[at : at + 8192].copy().view("<f4")
                vecs = pa.ListArray.from_arrays(pa.array(np.arange(len(part) + 1, dtype=np.int32) * part.shape[1]), pa.array(part.ravel()))
                yield pa.RecordBatch.from_arrays([pa.array([partition.value] * len(part)), pa.array(np.arange(at, at + len(part))), vecs], ["file", "row", "vec"])
