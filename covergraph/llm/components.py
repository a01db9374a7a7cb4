"""Connected components by alternating stars, with DataFrame operations only."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, stage

#: Rows of a key from which its minimum is broadcast to them; most keys for which that is done.
HOT_ROWS, HOT_KEYS = 500, 10_000
#: Links that one task may join, 16 MB of them: rounds of small jobs cost the driver more than the links are worth.
FEW = 1 << 20


def _state(edges: DataFrame) -> tuple:
    """Count and an order-free checksum; unchanged means converged."""
    return tuple(edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("hi", "lo").cast("decimal(38,0)"))).first())


def _joined(rows: DataFrame, least: DataFrame, key: str, most: int) -> DataFrame:
    """rows with m, the minimum of their key, from least(key, m, n); n: the key's rows, `most` those of all keys or more.

    Keys with more than a fixed share of `most` are HOT_KEYS at the most, so
    their minima are broadcast and their rows stay where they are. The other
    keys meet by a shuffle."""
    cut = max(HOT_ROWS, most // HOT_KEYS)
    if most <= cut:
        return rows.join(least.drop("n"), key)
    hot = least.where(F.col("n") > cut).select(key, F.col("m").alias("_m"))
    met = rows.join(F.broadcast(hot), key, "left")
    cold = met.where("_m is null").drop("_m").join(least.where(F.col("n") <= cut).drop("n"), key)
    return cold.unionByName(met.where("_m is not null").withColumnRenamed("_m", "m"))


def _solved(batches):
    """(node, component) of all links at once: roots hook to their smallest neighbour, which leaves half of them at the most."""
    both = [np.empty((0, 2), np.int64), *(np.stack([c.to_numpy(zero_copy_only=False) for c in b.columns], 1) for b in batches)]
    names, at = np.unique(np.concatenate(both), return_inverse=True)
    u, v = at.reshape(-1, 2).T
    root = np.arange(len(names))
    while len(u):
        np.minimum.at(root, np.r_[root[u], root[v]], np.tile(np.minimum(root[u], root[v]), 2))
        while not np.array_equal(jump := root[root], root):
            root = jump
        apart = root[u] != root[v]
        u, v = u[apart], v[apart]
    yield pa.RecordBatch.from_arrays([pa.array(names), pa.array(names[root])], ["node", "component"])


def components(edges: DataFrame, a: str = "a", b: str = "b", few: int = 0) -> DataFrame:
    """(node, component): the smallest node reachable, for every node that an edge names.

    A large star links the larger neighbours of a node to its smallest one, a
    small star the smaller ones; both are a minimum by key, summed up before the
    shuffle, and a join that leaves a hub's rows where they are. Null ends and loops are left
    out. Rounds grow with the logarithm of the longest path. Each round is
    written to the shared folder. Up to `few` links between whole numbers are joined in one task, without rounds."""
    clean = edges.select(F.col(a).alias("x"), F.col(b).alias("y")).where("x is not null and y is not null and x <> y")
    now = stage(clean.select(F.greatest("x", "y").alias("hi"), F.least("x", "y").alias("lo")).distinct())
    state = _state(now)
    while state[0] > few:
        both = now.select(F.col("hi").alias("u"), F.col("lo").alias("v")).unionByName(now.select(F.col("lo").alias("u"), F.col("hi").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m"), F.count(F.lit(1)).alias("n")).select("u", F.least("u", "m").alias("m"), "n")
        large = _joined(both.where("v > u"), least, "u", 2 * state[0]).select(F.col("v").alias("hi"), F.col("m").alias("lo")).distinct()
        lower = large.groupBy("hi").agg(F.min("lo").alias("m"), F.count(F.lit(1)).alias("n"))
        small = _joined(large, lower, "hi", state[0]).where("lo <> m").select(F.col("lo").alias("hi"), F.col("m").alias("lo")).unionByName(lower.select("hi", F.col("m").alias("lo"))).distinct()
        after = stage(small)
        discard(now)
        now, before = after, state
        state = _state(now)
        if state == before:
            break
    else:
        if few:
            out = stage(now.coalesce(1).mapInArrow(_solved, "node long, component long"))
            discard(now)
            return out
    ends = now.select(F.col("hi").alias("node"), F.col("lo").alias("component"))
    return ends.unionByName(now.select(F.col("lo").alias("node"), F.col("lo").alias("component")).distinct())
