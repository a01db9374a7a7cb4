"""Clique peeling: exact and sampled ownership."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.exact import Share, draw, portable_hash
from ..functions.metric import KERNELS, Owners, Rows, owned_by
from ..sources import points as source
from ..sources.points import block, bounded_blocks, indexed, stage, width

#: Links of leftovers that edges() multiplies out.
MOST_PAIRS = 10**11
#: Most partitions that a round of partition-wise chunks leaves.
WIDEST = 100_000
#: Chunks of one kernel call.
TOGETHER = 32
#: Members compared with all points at once where points are sent whole; tasks of a round, at most.
MEMBERS, TASKS = 8192, 1000


@dataclass
class Peel:
    """members(round, chunk, member, owned, kept): the graph as cliques, two numbers per node and round; leftovers link to all points."""

    points: DataFrame
    members: DataFrame
    leftovers: DataFrame
    log: list[dict]

    def inside(self) -> DataFrame:
        """(src, dst) within cliques; leftovers, which link to all points, are left implicit."""
        m = self.members
        return m.where("kept").select("round", "chunk", F.col("member").alias("src")).join(m.select("round", "chunk", F.col("member").alias("dst")), ["round", "chunk"]).where("src <> dst").select("src", "dst")

    def edges(self) -> DataFrame:
        """(src, dst), explicit; leftovers are multiplied out here only, at most MOST_PAIRS of them."""
        if self.log and (self.log[-1]["carried"]) * self.log[0]["pool"] > MOST_PAIRS:
            raise ValueError("leftovers link to all points: use inside() and leftovers")
        tail = self.points.select(F.col("id").alias("dst")).join(self.leftovers.select(F.col("id").alias("src")), F.col("src") != F.col("dst"))
        return self.inside().unionByName(tail.select("src", "dst"))

    def rounds(self) -> DataFrame:
        return self.points.sparkSession.createDataFrame([tuple(r.values()) for r in self.log], "round int, pool long, chunks long, kept long, carried long, distances long, tie_limited boolean")


def projection(vec, turn: int, seed: int):
    """A vector's sum with signs drawn by place: near points get near numbers."""
    signed = F.transform(vec, lambda x, i: F.when(portable_hash(i.cast("long"), turn, seed) % 2 == 0, x).otherwise(-x))
    return F.aggregate(signed, F.lit(0.0), lambda s, x: s + x)


ORDERS = {"hash": lambda turn, seed: portable_hash(F.col("id"), turn, seed), "id": lambda turn, seed: F.col("id"), "locality": lambda turn, seed: projection(F.col("vec"), turn, seed)}


def chunks(pool: DataFrame, size: int, turn: int, seed: int, order: str = "hash") -> DataFrame:
    """pool with chunk numbers in an order: drawn by the portable hash, by id, or along a drawn direction (any will do); the short last chunk is -1."""
    n = pool.count()
    ranked = indexed(pool.withColumn("_key", ORDERS[order](turn, seed)), "_key", "id").drop("_key")
    return ranked.withColumn("chunk", F.when(F.col("pos") < n // size * size, F.floor(F.col("pos") / size)).otherwise(F.lit(-1)).cast("long"))


def draws(n: int, w: int, turn: int, seed: int) -> np.ndarray:
    """w positions in 0..n-1, with replacement, the same in every engine."""
    return draw(np.arange(w, dtype=np.int64), turn, seed, n)


def owned_counts(distances: np.ndarray, weight: np.ndarray) -> np.ndarray:
    """Weight of the targets to which a member is nearest, ties to all nearest."""
    return (distances == distances.min(axis=0)) @ weight


def ownership(chunked: DataFrame, targets: tuple[np.ndarray, np.ndarray], metric: str = "l2sq") -> DataFrame:
    """(chunk, member, owned): a chunk is whole in one call; targets (weights, vectors) are broadcast."""
    spark = chunked.sparkSession
    sent = spark.sparkContext.broadcast(targets)
    kernel = KERNELS[metric]

    def run(t: pa.Table) -> pa.Table:
        weight, vecs = sent.value
        chunk, ids = t.column("chunk").to_numpy(), t.column("id").to_numpy()
        own = t.column("vec").combine_chunks().flatten().to_numpy(zero_copy_only=False).astype(float).reshape(len(ids), -1)
        order = np.lexsort((ids, chunk))
        chunk, ids, own = chunk[order], ids[order], own[order]
        starts = np.flatnonzero(np.r_[True, chunk[1:] != chunk[:-1]])
        ends = np.r_[starts[1:], len(chunk)]
        owned = np.zeros(len(ids), np.int64)
        rows, at = 1024, 0
        while at < len(ids):  # whole chunks together: one matrix product, the least distance by chunk
            end = int(ends[max(np.searchsorted(ends, at + rows, "right") - 1, np.searchsorted(starts, at))])
            first = starts[(starts >= at) & (starts < end)] - at
            many = np.diff(np.r_[first, end - at])
            for k in range(0, len(vecs), 4096):
                d = kernel(own[at:end], vecs[k : k + 4096])
                owned[at:end] += (d == np.repeat(np.minimum.reduceat(d, first, axis=0), many, axis=0)) @ weight[k : k + 4096]
            at = end
        return pa.table({"chunk": chunk, "member": ids, "owned": owned})

    full = chunked.where("chunk >= 0").withColumn("_group", F.floor(F.col("chunk") / TOGETHER))
    return full.select("_group", "chunk", "id", "vec").groupBy("_group").applyInArrow(run, "chunk long, member long, owned long")


def local_ownership(pool: DataFrame, size: int, targets: tuple[np.ndarray, np.ndarray], metric: str = "l2sq") -> DataFrame:
    """(chunk, member, owned) of chunks formed of neighbours within partitions, without a shuffle; what is left over of a partition is in none."""
    sent = pool.sparkSession.sparkContext.broadcast(targets)
    kernel = KERNELS[metric]

    def run(batches):
        from pyspark import TaskContext

        weight, vecs = sent.value
        at, ids, held = TaskContext.get().partitionId() << 32, np.empty(0, np.int64), None
        for batch in batches:
            mine = batch.column(1).flatten().to_numpy(zero_copy_only=False).astype(float).reshape(batch.num_rows, -1)
            ids, held = np.r_[ids, batch.column(0).to_numpy()], mine if held is None else np.concatenate([held, mine])
            for s in range(0, len(ids) - size + 1, size):
                owned = sum(owned_counts(kernel(held[s : s + size], vecs[k : k + 4096]), weight[k : k + 4096]) for k in range(0, len(vecs), 4096))
                yield pa.RecordBatch.from_pydict({"chunk": np.full(size, at), "member": ids[s : s + size], "owned": owned.astype(np.int64)})
                at += 1
            done = len(ids) // size * size
            ids, held = ids[done:], held[done:]

    return pool.select("id", "vec").mapInArrow(run, "chunk long, member long, owned long")


def peel(points: DataFrame, share, delta: float | None = None, metric: str = "l2sq", seed: int = 1, order: str = "hash") -> Peel:
    """Rounds of cliques over the points not yet finished. delta None: ownership over all points; else over a fresh
    sample each round, right with probability 1 - delta.

    Vectors must be distinct (dedupe) for the size bound; equal distances only
    make the rounds stop early (tie_limited), never the coverage fail. One count
    per round comes to the driver. order: hash, id or locality cut the pool as a
    whole; partition cuts each partition as it lies, with no shuffle, and leaves
    a remainder in each (so a round that keeps nothing may come early)."""
    share = Share.of(share)
    points = stage(points.select("id", "vec"))
    n = points.count()
    size = share.clique(2 if delta is None else 4)
    pool, left, log, parts, turn = points, n, [], [], 0
    if delta is None and order == "hash" and source.fits(points):
        return peel_sent(points, share, metric, seed)
    every = bounded_blocks(points, "id", source.BROADCAST_BYTES) if delta is None and n else None
    placed = None
    while left >= size:
        turn += 1
        cut = pool if order == "partition" else stage(chunks(pool, size, turn, seed, order))
        if delta is None:
            targets, w = every, n
        else:
            w = share.sample(n, delta)
            pos, weight = np.unique(draws(n, w, turn, seed), return_counts=True)
            placed = stage(indexed(points, "id")) if placed is None else placed
            picked = points.sparkSession.createDataFrame([(int(p), int(m)) for p, m in zip(pos, weight, strict=True)], "pos long, mult long")
            rows = placed.join(F.broadcast(picked), "pos").select("mult", "vec").collect()
            targets = [(np.array([r[0] for r in rows], np.int64), np.array([r[1] for r in rows]))]
        met = n if delta is None else len(targets[0][0])
        owned = None
        for target in targets:
            if delta is None:  # a block of all points at a time, no matter how many there are
                vecs = block(target)[1]
                target = np.ones(len(vecs), np.int64), vecs
                if not len(vecs):
                    continue
            one = local_ownership(cut, size, target, metric) if order == "partition" else ownership(cut, target, metric)
            one = stage(one) if len(targets) > 1 else one
            owned = one if owned is None else owned.unionByName(one)
        owned = owned if len(targets) == 1 else owned.groupBy("chunk", "member").agg(F.sum("owned").alias("owned"))
        test = share.keeps(F.col("owned"), n) if delta is None else share.keeps_sampled(F.col("owned"), w)
        members = stage(owned.select(F.lit(turn).alias("round"), "chunk", "member", "owned", test.alias("kept")))
        parts.append(members)
        kept, full = members.agg(F.coalesce(F.sum(F.col("kept").cast("long")), F.lit(0)), F.count(F.lit(1))).first()
        pool = pool.join(members.where("kept").select(F.col("member").alias("id")), "id", "left_anti")
        pool = stage(pool.coalesce(max(1, min(WIDEST, (left - kept) // (4 * size)))) if order == "partition" else pool)
        stuck = kept == 0 or turn >= share.rounds(n)
        log.append({"round": turn, "pool": left, "chunks": full // size, "kept": kept, "carried": left - kept, "distances": full * met, "tie_limited": stuck and left - kept >= size})
        left -= kept
        if stuck:
            break
    none = points.sparkSession.createDataFrame([], "round int, chunk long, member long, owned long, kept boolean")
    members = none
    for p in parts:
        members = members.unionByName(p)
    return Peel(points, members, pool.select("id"), log)


def peel_sent(points: DataFrame, share, metric: str = "l2sq", seed: int = 1) -> Peel:
    """peel() with ownership over all points and order="hash", of points that are sent whole, once for all rounds: a round sends the order
    of its pool, its chunks are dealt over tasks, and the places kept come to the driver, which holds the points as it is."""
    share, spark, kind = Share.of(share), points.sparkSession, "round int, chunk long, member long, owned long, kept boolean"
    points = stage(points.select("id", "vec"))
    ids, vecs = block(points)
    n, size = len(ids), share.clique(2)
    sent = spark.sparkContext.broadcast((ids, Owners(vecs, metric)))
    pool, parts, log, turn = np.arange(n), [], [], 0
    step = max(1, MEMBERS // size)
    while len(pool) >= size:
        turn += 1
        pool = pool[np.lexsort((ids[pool], portable_hash(ids[pool], turn, seed)))]
        left, full = len(pool), len(pool) // size * size
        dealt = spark.sparkContext.broadcast(pool[:full].reshape(-1, size))

        def run(batches, turn=turn, dealt=dealt):
            (ids, every), chunked = sent.value, dealt.value
            for batch in batches:
                mine = batch.column(0).to_numpy()
                for s in range(0, len(mine), step):
                    some = chunked[mine[s : s + step]].ravel()
                    owned = every.counts(every.vecs[some], size)
                    yield pa.RecordBatch.from_pydict({"round": np.full(len(some), turn, np.int32), "chunk": np.repeat(mine[s : s + step], size), "member": ids[some], "owned": owned, "kept": share.keeps(owned, n)})

        tasks = max(1, min(TASKS, full // size // 8, max(width(points), 4 * spark.sparkContext.defaultParallelism)))
        members = stage(spark.range(0, full // size, 1, tasks).mapInArrow(run, kind))
        parts.append(members)
        kept = members.where("kept").select("member").toArrow().column(0).to_numpy()
        pool = pool[~np.isin(ids[pool], kept)]
        stuck = not len(kept) or turn >= share.rounds(n)
        log.append({"round": turn, "pool": left, "chunks": full // size, "kept": len(kept), "carried": len(pool), "distances": full * n, "tie_limited": stuck and len(pool) >= size})
        dealt.unpersist()
        if stuck:
            break
    members = spark.createDataFrame([], kind)
    for p in parts:
        members = members.unionByName(p)
    return Peel(points, members, spark.createDataFrame(pa.table({"id": pa.array(ids[pool], pa.int64())})), log)


def peel_here(ids: np.ndarray, vecs: np.ndarray, share, delta: float | None = None, metric: str = "l2sq", seed: int = 1) -> tuple[list, np.ndarray, list[dict]]:
    """peel() with order="hash" of points sorted by id, within one task: (rounds as (places by chunk, kept), places left over, log)."""
    share, n = Share.of(share), len(ids)
    size = share.clique(2 if delta is None else 4)
    w = n if delta is None else share.sample(n, delta)
    pool, rounds, log, turn = np.arange(n), [], [], 0
    while len(pool) >= size:
        turn += 1
        met = np.arange(n) if delta is None else draws(n, w, turn, seed)
        pool = pool[np.lexsort((ids[pool], portable_hash(ids[pool], turn, seed)))]
        left, full = len(pool), len(pool) // size * size
        owned = owned_by(vecs[pool[:full]], size, vecs[met], metric)
        kept = share.keeps(owned, n) if delta is None else share.keeps_sampled(owned, w)
        rounds.append((pool[:full].reshape(-1, size), kept.reshape(-1, size)))
        pool = np.r_[pool[:full][~kept], pool[full:]]
        stuck = len(pool) == left or turn >= share.rounds(n)
        log.append({"round": turn, "pool": left, "chunks": full // size, "kept": left - len(pool), "carried": len(pool), "distances": full * len(np.unique(met)), "tie_limited": stuck and len(pool) >= size})
        if stuck:
            break
    return rounds, pool, log


def covers_here(vecs: np.ndarray, rounds: list, left: np.ndarray, need: int, metric: str = "l2sq") -> bool:
    """Does every node of peel_here()'s graph cover `need` points?"""
    for places, kept in rounds:
        some = kept.any(axis=1)
        owned = owned_by(vecs[places[some].ravel()], places.shape[1], vecs, metric)
        if (len(vecs) - owned[kept[some].ravel()] < need).any():
            return False
    rows = Rows(vecs, metric)
    return all((rows.full(left[s : s + 8]) > 0).sum(axis=1).min() >= need for s in range(0, len(left), 8))


def peels_here(points: DataFrame, many: list[tuple], solve, kind: str):
    """Rows of `kind` from solve(ids, vecs, number of the case, *case), a task a case; points are broadcast behind the size check."""
    spark = points.sparkSession
    sent = spark.sparkContext.broadcast((block(points), many))

    def run(batches):
        (ids, vecs), cases = sent.value
        for batch in batches:
            for i in batch.column(0).to_pylist():
                row = solve(ids, vecs, i, *cases[i])
                yield pa.RecordBatch.from_pylist([dict(zip(names, row, strict=True))], schema)

    names = [c.split()[0] for c in kind.split(", ")]
    types = {"long": pa.int64(), "int": pa.int32(), "boolean": pa.bool_()}
    schema = pa.schema([(c.split()[0], types[c.split()[1]]) for c in kind.split(", ")])
    return spark.range(0, len(many), 1, max(1, len(many))).mapInArrow(run, kind)
