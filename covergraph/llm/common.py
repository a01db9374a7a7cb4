"""Shared pieces: table access, staging in the shared folder, ranks within hot keys."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid
from contextlib import contextmanager

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

#: Fixed by the contracts: the ASCII white space that separates words.
SPACE = r"[\x20\x09-\x0D]+"
WORD = r"[^\x20\x09-\x0D]+"
#: Rows of an Arrow batch of texts.
BATCH_ROWS = 2000
#: Bytes of input to a bucket, about; most buckets that Spark allows.
BUCKET_BYTES, MOST_BUCKETS = 64 << 20, 100_000
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ascii_lower(c: Column) -> Column:
    """Lower-cases A-Z only; `lower` would also fold other scripts."""
    return F.translate(c, UPPER, LOWER)


def let(value: Column, body) -> Column:
    """Evaluates `value` once and hands it to `body`; a plain reference inside a lambda is evaluated for each element."""
    return F.transform(F.array(value), body)[0]


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors share: spark.checkpoint.dir, or a temporary one where it is unset (tests on one machine)."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not found:
        made = tempfile.mkdtemp(prefix="staged-")
        atexit.register(shutil.rmtree, made, ignore_errors=True)
        found = "file://" + made
        spark.conf.set("spark.checkpoint.dir", found)
    return found


@contextmanager
def small_batches(spark: SparkSession):
    """Arrow batches of at most BATCH_ROWS while a job runs: thousands of long texts at once would fill a worker."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(name)
    spark.conf.set(name, str(min(int(before), BATCH_ROWS) if int(before) > 0 else BATCH_ROWS))
    try:
        yield
    finally:
        spark.conf.set(name, before)


def stage(df: DataFrame) -> DataFrame:
    """Writes df to the shared folder and reads it back: cuts the lineage and survives lost executors."""
    path = f"{shared_dir(df.sparkSession)}/staged-{uuid.uuid4().hex}"
    with small_batches(df.sparkSession):
        df.write.option("compression", "zstd").parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._staged_path = path
    return out


def bucketed(df: DataFrame, key: str, prefix: str, source: DataFrame | None = None) -> DataFrame:
    """Writes df as a table in the shared folder, bucketed by key: what meets it by that key travels to it, and it stays where it is.

    The estimated size of `source`, which df is made from, sets the buckets, at least one for each partition of a shuffle.
    The catalog forgets the table at once; plans made from the result know its files and buckets."""
    spark, name = df.sparkSession, f"{prefix}_{uuid.uuid4().hex}"
    size = (source if source is not None else df)._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()
    # Spark gives what it can't estimate an enormous size
    buckets = max(shuffle_width(spark), min(MOST_BUCKETS, int(size) // BUCKET_BYTES if size < 1 << 50 else 0))
    with small_batches(spark):
        df.write.bucketBy(buckets, key).sortBy(key).format("parquet").option("compression", "zstd").option("path", f"{shared_dir(spark)}/{name}").saveAsTable(name)
    out = spark.table(name)
    spark.sql(f"DROP TABLE {name}")
    return out


def scratch_dir(spark: SparkSession) -> str | None:
    """Where a task may keep files that only it reads: the shared folder if that is mounted, else None, the executor's own spill folder."""
    found = shared_dir(spark)
    return found.removeprefix("file://").removeprefix("file:") if found.startswith(("file:", "/")) else None


def squeeze(x) -> bytes:
    """Bytes of equal weight side by side, then zstd: rising or small numbers leave their high bytes empty."""
    from zstandard import ZstdCompressor

    return ZstdCompressor(level=1).compress(np.ascontiguousarray(np.ascontiguousarray(x).view(np.uint8).reshape(len(x), -1).T).tobytes() if len(x) else b"")


def unsqueeze(b: bytes, kind):
    from zstandard import ZstdDecompressor

    raw = np.frombuffer(ZstdDecompressor().decompress(b), np.uint8).reshape(np.dtype(kind).itemsize, -1)
    return np.ascontiguousarray(raw.T).view(kind).ravel()


def pieces(text: bytes, most: int):
    """The text cut at white space, so that a long one is never split into words at once."""
    at = 0
    while len(text) - at > most:
        end = at + most
        cut = max(text.rfind(c, at, end) for c in (b" ", b"\n", b"\t", b"\r", b"\x0b", b"\x0c"))
        if cut < at:
            break
        yield text[at:cut]
        at = cut
    yield text[at:]


def discard(*frames: DataFrame) -> None:
    """Deletes what stage() wrote, once no later plan reads it."""
    for df in frames:
        spark, path = df.sparkSession, df._staged_path
        hadoop = spark._jvm.org.apache.hadoop.fs.Path(path)
        hadoop.getFileSystem(spark._jsc.hadoopConfiguration()).delete(hadoop, True)


def shuffle_width(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def rank_within(df: DataFrame, keys: list[str], order: list[str], name: str = "rank", attach: DataFrame | None = None) -> DataFrame:
    """Adds a 0-based rank within `keys`, whole for a key of any size.

    Each key is split over ranges of a hash of its order columns: a window ranks
    within (key, range), and small counts give each range its first rank. No
    task holds more than one range of a key. Ranks follow the hash, then
    `order`, which must be unique within the key, so they are the same on every
    run, however many ranges the shuffle's width makes. `attach` has one row
    per key; its other columns ride along with the counts."""
    buckets = max(64, shuffle_width(df.sparkSession))
    hashed = F.shiftrightunsigned(F.xxhash64(*order), 32)
    cut = df.withColumn("_bucket", F.shiftright(hashed * F.lit(buckets), 32).cast("int"))
    counts = cut.groupBy(*keys, "_bucket").agg(F.count(F.lit(1)).alias("_n"))
    before = W.partitionBy(*keys).orderBy("_bucket").rowsBetween(W.unboundedPreceding, -1)
    first = counts.select(*[F.col(k).alias(f"_k{i}") for i, k in enumerate(keys)], F.col("_bucket").alias("_b"), F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_first"))
    extra = [c for c in attach.columns if c not in keys] if attach is not None else []
    if attach is not None:
        to = attach.select(*[F.col(k).alias(f"_a{i}") for i, k in enumerate(keys)], *extra)
        match = F.lit(True)
        for i in range(len(keys)):
            match = match & F.col(f"_k{i}").eqNullSafe(F.col(f"_a{i}"))
        first = first.join(to, match).drop(*[f"_a{i}" for i in range(len(keys))])
    inner = F.row_number().over(W.partitionBy(*keys, "_bucket").orderBy(hashed, *order)) - 1
    same = F.col("_bucket") == F.col("_b")
    for i, k in enumerate(keys):
        same = same & F.col(k).eqNullSafe(F.col(f"_k{i}"))
    joined = cut.withColumn("_inner", inner).join(first, same)
    return joined.withColumn(name, F.col("_inner") + F.col("_first")).drop("_bucket", "_b", "_inner", "_first", *[f"_k{i}" for i in range(len(keys))])
