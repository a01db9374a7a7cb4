"""Point sets (id, vec) from the given tables, and checks on them."""

from __future__ import annotations

import atexit
import math
import shutil
import tempfile
import uuid

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.metric import lattice

#: Vectors that may be broadcast; larger sets take the distributed way or are refused.
BROADCAST_BYTES = 256 << 20


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All embeddings on the exact lattice."""
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), lattice(F.col("embedding")).alias("vec"))


def split(points: DataFrame, every: int = 100) -> tuple[DataFrame, DataFrame]:
    """Index and queries: every point is indexed, and those whose id `every` divides ask; a search leaves out the asking point itself."""
    return points, points.where(F.col("id") % every == 0).withColumnRenamed("id", "qid")


def tokens(text: Column) -> Column:
    return F.array_remove(F.split(F.lower(F.coalesce(text, F.lit(""))), r"[^\p{L}\p{N}_]+"), "")


def text_vectors(docs: DataFrame, buckets: int = 64, key: str = "doc_id") -> DataFrame:
    """Token counts by hash bucket, as whole numbers: the first 8 hex digits of md5, modulo `buckets`."""
    bucket = F.conv(F.substring(F.md5(F.col("t")), 1, 8), 16, 10).cast("long") % buckets
    counted = docs.select(F.col(key).alias("id"), F.explode(tokens(F.col("text"))).alias("t")).groupBy("id", bucket.alias("b")).count()
    vec = F.transform(F.sequence(F.lit(0), F.lit(buckets - 1)), lambda i: F.coalesce(F.element_at(F.col("m"), i), F.lit(0)).cast("double"))
    packed = counted.groupBy("id").agg(F.map_from_entries(F.collect_list(F.struct(F.col("b").cast("int"), F.col("count")))).alias("m"))
    return packed.select("id", vec.alias("vec"))


def token_sets(docs: DataFrame, buckets: int = 64) -> DataFrame:
    """Sets of token buckets as vectors of 0 and 1."""
    return text_vectors(docs, buckets).withColumn("vec", F.transform("vec", lambda x: F.least(x, F.lit(1.0))))


def line_item_vectors(items: DataFrame) -> DataFrame:
    """Distinct (quantity, price, discount, tax) in whole units; ids are dense, in the order of the vectors."""
    part = lambda c, by: F.round(F.col(c) * by).cast("double")
    names = ["a", "b", "c", "d"]
    cols = [part("l_quantity", 100), part("l_extendedprice", 1), part("l_discount", 10000), part("l_tax", 10000)]
    ranked = indexed(items.select(*[c.alias(n) for c, n in zip(cols, names, strict=True)]).distinct(), *names)
    return ranked.select(F.col("pos").alias("id"), F.array(*names).alias("vec"))


def dedupe(points: DataFrame) -> DataFrame:
    """One point of each vector, the smallest id, with the number of its copies."""
    return points.groupBy("vec").agg(F.min("id").alias("id"), F.count(F.lit(1)).alias("copies")).select("id", "vec", "copies")


def jitter(points: DataFrame, amount: float, seed: int = 1) -> DataFrame:
    """Moves each coordinate by at most `amount`, by a hash of id and place: ties break, reruns agree."""
    noise = lambda i: (F.pmod(F.xxhash64(F.col("id"), i, F.lit(seed)), F.lit(2000001)) - 1000000) / 1000000.0
    return points.withColumn("vec", F.transform("vec", lambda x, i: x + amount * noise(i)))


def medoids(points: DataFrame, group: str) -> DataFrame:
    """The point of each group nearest to the group's mean, ties by id: means are sums by (group, coordinate), so a group of any size is added up before it is shuffled."""
    mean = points.select(group, F.posexplode("vec").alias("i", "x")).groupBy(group, "i").agg(F.avg("x").alias("x")).groupBy(group).agg(F.array_sort(F.collect_list(F.struct("i", "x"))).alias("m"))
    centre = mean.select(F.col(group).alias("_g"), F.transform("m", lambda p: p["x"]).alias("_mean"))
    far = F.aggregate(F.zip_with("vec", "_mean", lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)
    return points.join(centre, F.col(group).eqNullSafe(F.col("_g"))).groupBy(group).agg(F.min(F.struct(far.alias("d"), F.col("id"))).alias("m")).select(group, F.col("m.id").alias("id"))


def profile(points: DataFrame) -> DataFrame:
    """Counts of rows, bad rows (null, NaN or of another length), equal vectors, and the dimension."""
    bad = F.col("vec").isNull() | F.exists("vec", lambda x: x.isNull() | F.isnan(x))
    return points.agg(F.count(F.lit(1)).alias("n"), F.min(F.size("vec")).alias("dim_min"), F.max(F.size("vec")).alias("dim_max"), F.sum(F.coalesce(bad, F.lit(True)).cast("long")).alias("bad"), F.count_distinct("vec").alias("distinct_vecs"))


def line_of_balls(n: int, k: int, eps: float = 1.0) -> tuple[list, list]:
    """The hard case: k clusters on a line, further apart than greedy walks can cross, of n/k colours each.

    Every node links the node of its colour in the clusters beside it."""
    per = n // k
    places = [(c * per + j, [c * 5 * eps + eps * math.cos(2 * math.pi * j / per), eps * math.sin(2 * math.pi * j / per)]) for c in range(k) for j in range(per)]
    links = [(c * per + j, o * per + j) for c in range(k) for j in range(per) for o in (c - 1, c + 1) if 0 <= o < k]
    return places, links


def balls_of_points(points: DataFrame, k: int) -> tuple[DataFrame, DataFrame]:
    """The hard case over given points (id, vec): (nodes, links (src, dst)). Points are dealt by rank of id into k clusters, in which the
    first two coordinates place them; clusters stand on a line, five times the largest radius apart.

    Every node links the node of its colour in the clusters beside it; where that cluster is a node short, the last colour there."""
    placed = stage(indexed(points.select("id", F.col("vec")[0].alias("x"), F.col("vec")[1].alias("y")), "id"))
    n, radius = placed.agg(F.count(F.lit(1)), F.max(F.hypot("x", "y"))).first()
    apart = 5.0 * math.ceil(radius or 1)
    cluster = F.col("pos") % k
    beside = placed.select(F.col("id").alias("src"), "pos", F.explode(F.array(cluster - 1, cluster + 1)).alias("to")).where(f"to >= 0 and to < {k}")
    at = F.col("to") + F.floor(F.col("pos") / k) * k
    links = beside.select("src", F.when(at < n, at).otherwise(at - k).alias("pos")).join(placed.select("pos", F.col("id").alias("dst")), "pos")
    return placed.select("id", F.array(F.col("x") + cluster * apart, "y").alias("vec")), links.select("src", "dst")


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors share: spark.checkpoint.dir; where it is unset, as in tests on one machine, a temporary one that goes at exit."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not found:
        made = tempfile.mkdtemp(prefix="staged-")
        atexit.register(shutil.rmtree, made, ignore_errors=True)
        found = "file://" + made
        spark.conf.set("spark.checkpoint.dir", found)
    return found


def stage(df: DataFrame) -> DataFrame:
    """Written to the shared folder and read back: cuts the lineage, survives lost executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/points-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def width(df: DataFrame) -> int:
    """Partitions of a shuffle, as configured."""
    return int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))


def bounded_blocks(vectors: DataFrame, key: str, most: int) -> list[DataFrame]:
    """The rows, cut by a hash of their key so that a block of vectors stays well below `most` bytes."""
    n, dim = vectors.agg(F.count(F.lit(1)), F.max(F.size("vec"))).first()
    size = n * ((dim or 0) + 1) * 8
    if size <= most:
        return [vectors]
    cuts = -(-2 * size // most)
    return [vectors.where(F.pmod(F.xxhash64(key), F.lit(cuts)) == i) for i in range(cuts)]


def measured(points: DataFrame) -> tuple[int, int, type]:
    """Number of vectors, bytes of them as block() holds them, and the type of their numbers."""
    whole = F.forall("vec", lambda x: F.coalesce(x.cast("float").cast("double") == x.cast("double"), F.lit(False)))
    n, dim, narrow = points.agg(F.count(F.lit(1)), F.max(F.size("vec")), F.every(whole)).first()
    kind = np.float32 if narrow else np.float64
    return n, n * ((dim or 0) * np.dtype(kind).itemsize + 8), kind


def fits(points: DataFrame) -> bool:
    """May the points be broadcast?"""
    return measured(points)[1] <= BROADCAST_BYTES


def block(points: DataFrame, key: str = "id", most: int = BROADCAST_BYTES) -> tuple[np.ndarray, np.ndarray]:
    """Ids and vectors of a set whose size is checked before it is collected; sorted by id. Vectors that single precision
    holds whole are kept so; kernels work in double precision."""
    n, size, kind = measured(points)
    if size > most:
        raise ValueError(f"{n} vectors are more than {most} bytes: use probes, a sample or shards")
    t = points.select(key, F.col("vec").cast("array<float>" if kind is np.float32 else "array<double>").alias("vec")).toArrow()
    ids = t.column(0).to_numpy()
    vecs = t.column(1).combine_chunks().flatten().to_numpy(zero_copy_only=False).astype(kind, copy=False).reshape(len(ids), -1) if n else np.empty((0, 1))
    order = np.argsort(ids)
    return ids[order], vecs[order]


def indexed(points: DataFrame, *order: str | Column) -> DataFrame:
    """points with `pos`, a dense 0-based rank by `order`, without one task that holds all rows."""
    spark = points.sparkSession
    cut = stage(points.repartitionByRange(width(points), *order).withColumn("_part", F.spark_partition_id()))
    sizes = cut.groupBy("_part").agg(F.count(F.lit(1)).alias("_n"))
    before = sizes.select("_part", F.coalesce(F.sum("_n").over(W.orderBy("_part").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("_first"))
    ranked = cut.withColumn("_in", F.row_number().over(W.partitionBy("_part").orderBy(*order)) - 1)
    return ranked.join(F.broadcast(before), "_part").withColumn("pos", F.col("_in") + F.col("_first")).drop("_part", "_in", "_first")
