"""Exact neighbours, greedy walks and beam search."""

from __future__ import annotations

import bisect
import copy
import heapq
from functools import reduce
from types import SimpleNamespace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.exact import Share, draw
from ..functions.metric import KERNELS, Rows
from ..sources.points import block, bounded_blocks, stage, width
from .audit import cover, together

#: Bytes of queries that one scan of the points compares.
QUERY_BLOCK = 64 << 20


def query_blocks(queries: DataFrame, most: int | None = None) -> list[DataFrame]:
    """The queries, cut by a hash of qid so that a block stays well below `most` bytes (None: QUERY_BLOCK)."""
    return bounded_blocks(queries, "qid", most or QUERY_BLOCK)


def knn_exact(points: DataFrame, queries: DataFrame, k: int, metric: str = "l2sq", own: bool = False) -> DataFrame:
    """(qid, pos, id, dist): the k nearest by (distance, id). own: queries are points too, and none finds itself.

    Queries are broadcast behind a size check, larger sets block by block; each
    partition keeps its k best per query and those are merged."""
    kernel = KERNELS[metric]
    parts = query_blocks(queries)
    if len(parts) > 1:
        return reduce(DataFrame.unionByName, [knn_exact(points, q, k, metric, own) for q in parts])
    sent = points.sparkSession.sparkContext.broadcast(block(queries, "qid", QUERY_BLOCK))

    def run(batches):
        qid, qvec = sent.value
        for batch in batches:
            ids = batch.column(0).to_numpy()
            if not len(ids):
                continue
            vecs = batch.column(1).flatten().to_numpy(zero_copy_only=False).astype(float).reshape(len(ids), -1)
            for at in range(0, len(qid), 256):
                d = kernel(qvec[at : at + 256], vecs)
                if own:
                    d[qid[at : at + 256, None] == ids[None]] = np.inf
                best = np.stack([np.lexsort((ids, row))[:k] for row in d])
                row = np.repeat(np.arange(len(best)), best.shape[1])
                yield pa.RecordBatch.from_arrays([pa.array(qid[at + row]), pa.array(ids[best.ravel()]), pa.array(d[row, best.ravel()])], ["qid", "id", "dist"])

    near = points.select("id", "vec").mapInArrow(run, "qid long, id long, dist double")
    near = near.where("id <> qid") if own else near
    return near.withColumn("pos", F.row_number().over(W.partitionBy("qid").orderBy("dist", "id"))).where(F.col("pos") <= k).select("qid", "pos", "id", "dist")


def radius_search(points: DataFrame, queries: DataFrame, radius: float, metric: str = "l2sq") -> DataFrame:
    """(qid, id, dist) within `radius`; large query sets go block by block."""
    kernel = KERNELS[metric]
    parts = query_blocks(queries)
    if len(parts) > 1:
        return reduce(DataFrame.unionByName, [radius_search(points, q, radius, metric) for q in parts])
    sent = points.sparkSession.sparkContext.broadcast(block(queries, "qid", QUERY_BLOCK))

    def run(batches):
        qid, qvec = sent.value
        for batch in batches:
            ids = batch.column(0).to_numpy()
            vecs = batch.column(1).flatten().to_numpy(zero_copy_only=False).astype(float).reshape(len(ids), -1) if len(ids) else np.empty((0, qvec.shape[1]))
            d = kernel(qvec, vecs)
            q, i = np.nonzero(d <= radius)
            yield pa.RecordBatch.from_arrays([pa.array(qid[q]), pa.array(ids[i]), pa.array(d[q, i])], ["qid", "id", "dist"])

    return points.select("id", "vec").mapInArrow(run, "qid long, id long, dist double")


class Graph:
    """A graph and its vectors as arrays, sent to every task; both sizes are checked.

    Lists that carry rank, gain and cum stay in order of rank, so that the list
    of a smaller share is the front of each."""

    def __init__(self, points: DataFrame, edges: DataFrame, most_edges: int = 1 << 26):
        self.ids, self.vecs = block(points)
        n = edges.count()
        if n > most_edges:
            raise ValueError(f"{n} edges are too many to broadcast: search by frontier joins (greedy_joins) or in shards")
        ranked = {"rank", "cum", "gain"} <= set(edges.columns)
        t = (edges.select("src", "dst", "rank", (F.col("cum") - F.col("gain")).alias("before")) if ranked else edges.select("src", "dst", F.col("dst").alias("rank"), F.lit(0).cast("long").alias("before")).distinct()).toArrow()
        src, dst = (np.searchsorted(self.ids, t.column(c).to_numpy()) for c in ("src", "dst"))
        order = np.lexsort((t.column("rank").to_numpy(), src))
        self.source, self.links, self.before = src[order], dst[order], t.column("before").to_numpy()[order]
        self.start = np.searchsorted(self.source, np.arange(len(self.ids) + 1))
        self.end = self.start[1:]

    def cut(self, need: int) -> Graph:
        """The graph of the share that needs so many covered points, on the same arrays."""
        out = copy.copy(self)
        out.end = self.start[:-1] + np.bincount(self.source[self.before < need], minlength=len(self.ids))
        return out

    def out(self, x: int) -> np.ndarray:
        return self.links[self.start[x] : self.end[x]]

    def medoid(self) -> int:
        """Position of the point nearest to the mean."""
        v = self.vecs.astype(float, copy=False)
        return int(((v - v.mean(0)) ** 2).sum(1).argmin())

    def starts(self, rule: str | int, qids, seed: int = 1) -> list[int]:
        """Positions to start from: a fixed one, the medoid, or one drawn for each query."""
        if rule == "random":
            return [draw(int(q), 0, seed, len(self.ids)) for q in qids]
        return [self.medoid() if rule == "medoid" else int(rule)] * len(qids)


def beam(g: Graph, q: np.ndarray, start: int, widths: list[int], kernel, near: np.ndarray | None = None):
    """One walk for all widths: (width, evaluated, scanned, expanded, found) at each width's stop; found sorted by (distance, id).

    The order of expansion doesn't depend on the width, only the stop does: the
    nearest open point is expanded unless `width` expanded ones are as near.
    near: q's distances to all points, for several walks of one query; what a walk evaluates is counted all the same."""
    far = (lambda some: near[some]) if near is not None else lambda some: kernel(q[None], g.vecs[some])[0]
    dist = {start: float(far([start])[0])}
    frontier = [(dist[start], int(g.ids[start]), start)]
    expanded: list[float] = []
    scanned, left, out = 0, sorted(widths), []
    while left:
        stop = not frontier or bisect.bisect_right(expanded, frontier[0][0]) >= left[0]
        if stop:
            out.append((left.pop(0), len(dist), scanned, len(expanded), dict(dist)))
            continue
        d, _, x = heapq.heappop(frontier)
        bisect.insort(expanded, d)
        nbrs = g.out(x)
        scanned += len(nbrs)
        fresh = [y for y in nbrs.tolist() if y not in dist]
        if fresh:
            for y, e in zip(fresh, far(fresh).tolist(), strict=True):
                dist[y] = e
                heapq.heappush(frontier, (e, int(g.ids[y]), y))
    return out


SWEEP = "share string, qid long, b int, k int, pos int, id long, dist double, dist_evals long, edges_scanned long, expanded long"


def beam_sweep(g: Graph, queries: DataFrame, widths: list[int], ks: list[int], metric: str = "l2sq", start: int | str = 0, needs: dict[str, int] | None = None, own: bool = False) -> DataFrame:
    """(share, qid, b, k, pos, id, dist, dist_evals, edges_scanned, expanded) for every width and k, from one walk per query and share.

    needs: points that each share must cover; the graph's lists are cut for each
    in the task. own: queries are points too, and none finds itself. start: a
    position, 'medoid' or 'random'."""
    kernel = KERNELS[metric]
    start = g.medoid() if start == "medoid" else start
    sent = queries.sparkSession.sparkContext.broadcast(g)

    def run(batches):
        whole = sent.value
        graphs = {s: whole.cut(n) for s, n in needs.items()} if needs else {None: whole}
        kinds = [pa.string(), pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.int64(), pa.float64(), pa.int64(), pa.int64(), pa.int64()]
        for batch in batches:
            qids = batch.column(0).to_pylist()
            for qid, v, first in zip(qids, batch.column(1).to_pylist(), whole.starts(start, qids), strict=True):
                rows, q = [], np.array(v, float)
                near = np.concatenate([kernel(q[None], whole.vecs[s : s + 16384])[0] for s in range(0, len(whole.vecs), 16384)])
                for share, g in graphs.items():
                    for b, evals, scanned, expanded, dist in beam(g, q, first, widths, kernel, near):
                        met = np.fromiter(dist, np.int64, len(dist))
                        met = met[g.ids[met] != qid] if own else met
                        met = met[np.lexsort((g.ids[met], near[met]))[: max(ks)]]
                        best = list(zip(near[met].tolist(), g.ids[met].tolist(), strict=True))
                        rows += [(share, qid, b, k, pos, i, d, evals, scanned, expanded) for k in ks for pos, (d, i) in enumerate(best[:k], 1)]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True) if rows else [()] * 10, kinds, strict=True)], [c.split()[0] for c in SWEEP.split(", ")])

    return queries.select("qid", "vec").repartition(width(queries)).mapInArrow(run, SWEEP)


def greedy(g: Graph, queries: DataFrame, metric: str = "l2sq", start: int | str = 0) -> DataFrame:
    """(qid, result, dist, steps, dist_evals): moves to the nearest out-neighbour (by distance, id) while it is strictly nearer."""
    kernel = KERNELS[metric]
    start = g.medoid() if start == "medoid" else start
    sent = queries.sparkSession.sparkContext.broadcast(g)

    def run(batches):
        g = sent.value
        for batch in batches:
            rows, qids = [], batch.column(0).to_pylist()
            for qid, v, at in zip(qids, batch.column(1).to_pylist(), g.starts(start, qids), strict=True):
                q, steps = np.array(v, float), 0
                here, seen = float(kernel(q[None], g.vecs[at : at + 1])[0, 0]), {at}
                while len(g.out(at)):
                    nbrs = g.out(at)
                    seen.update(nbrs.tolist())
                    d = kernel(q[None], g.vecs[nbrs])[0]
                    best = np.lexsort((g.ids[nbrs], d))[0]
                    if d[best] >= here:
                        break
                    at, here, steps = int(nbrs[best]), float(d[best]), steps + 1
                rows.append((qid, int(g.ids[at]), here, steps, len(seen)))
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True) if rows else [()] * 5, (pa.int64(), pa.int64(), pa.float64(), pa.int32(), pa.int64()), strict=True)], ["qid", "result", "dist", "steps", "dist_evals"])

    return queries.select("qid", "vec").repartition(width(queries)).mapInArrow(run, "qid long, result long, dist double, steps int, dist_evals long")


def greedy_joins(points: DataFrame, edges: DataFrame, queries: DataFrame, start: int) -> DataFrame:
    """greedy() for graphs of any size: every walk takes a step per round, by a join on the node it stands at. (qid, result, dist, steps)"""
    d = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)
    first = points.where(F.col("id") == start).select(F.col("id").alias("at"), F.col("vec").alias("v"))
    state = stage(queries.crossJoin(F.broadcast(first)).select("qid", F.col("vec").alias("q"), "at", d(F.col("vec"), F.col("v")).alias("dist"), F.lit(0).alias("steps"), F.lit(True).alias("open")))
    while not state.where("open").isEmpty():
        moves = state.where("open").join(edges.select(F.col("src").alias("at"), "dst"), "at").join(points.select(F.col("id").alias("dst"), "vec"), "dst")
        best = moves.groupBy("qid").agg(F.min(F.struct(d(F.col("q"), F.col("vec")).alias("d"), F.col("dst"))).alias("m"))
        nearer = F.coalesce(F.col("m.d") < F.col("dist"), F.lit(False))
        state = stage(state.join(best, "qid", "left").select("qid", "q", F.when(nearer, F.col("m.dst")).otherwise(F.col("at")).alias("at"), F.when(nearer, F.col("m.d")).otherwise(F.col("dist")).alias("dist"), (F.col("steps") + nearer.cast("int")).alias("steps"), nearer.alias("open")))
    return state.select("qid", F.col("at").alias("result"), "dist", "steps")


def beam_joins(points: DataFrame, edges: DataFrame, queries: DataFrame, start: int, b: int, k: int) -> DataFrame:
    """beam_sweep() of one width for graphs of any size: every open walk expands a node per round, by joins on the node and on its links.

    (qid, pos, id, dist, dist_evals, expanded). A walk is a row that holds what
    it evaluated, degree times expansions of it, so no row grows with the graph.
    Walks that have stopped are left out of the joins."""
    d = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)
    seen = lambda dist, i: F.struct(dist.alias("d"), i.alias("id"), F.lit(False).alias("done"))
    kind = "array<struct<d:double,id:bigint,done:boolean>>"
    nearest = F.array_min(F.filter("pool", lambda x: ~x["done"]))
    as_near = F.size(F.filter("pool", lambda x: x["done"] & (x["d"] <= F.col("at.d"))))
    aim = lambda walks: walks.withColumn("at", nearest).withColumn("open", F.col("at").isNotNull() & (as_near < b))
    first = points.where(F.col("id") == start).select(F.col("id").alias("_at"), F.col("vec").alias("_v"))
    begun = queries.crossJoin(F.broadcast(first)).select("qid", F.col("vec").alias("q"), F.array(seen(d(F.col("vec"), F.col("_v")), F.col("_at"))).cast(kind).alias("pool"))
    state = stage(aim(begun))
    links = edges.select(F.col("src").alias("_src"), F.col("dst").alias("_dst")).distinct()
    while not state.where("open").isEmpty():
        going = state.where("open")
        fresh = going.join(links, F.col("at.id") == F.col("_src")).where(~F.exists("pool", lambda x: x["id"] == F.col("_dst")))
        met = fresh.join(points.select(F.col("id").alias("_id"), F.col("vec").alias("_v")), F.col("_dst") == F.col("_id"))
        more = met.select(F.col("qid").alias("_qid"), seen(d(F.col("q"), F.col("_v")), F.col("_id")).alias("x")).groupBy("_qid").agg(F.collect_list("x").alias("more"))
        marked = F.transform("pool", lambda x: F.struct(x["d"].alias("d"), x["id"].alias("id"), (x["done"] | (F.col("open") & (x["id"] == F.col("at.id")))).alias("done")))
        pool = F.concat(marked, F.coalesce("more", F.array().cast(kind)))
        state = stage(aim(state.join(more, F.col("qid") == F.col("_qid"), "left").select("qid", "q", pool.cast(kind).alias("pool"))))
    best = F.slice(F.array_sort("pool"), 1, k)
    out = state.select("qid", F.size("pool").cast("long").alias("dist_evals"), F.size(F.filter("pool", lambda x: x["done"])).cast("long").alias("expanded"), F.posexplode(best).alias("pos", "x"))
    return out.select("qid", (F.col("pos") + 1).alias("pos"), "x.id", F.col("x.d").alias("dist"), "dist_evals", "expanded")


def beam_sharded(points: DataFrame, queries: DataFrame, shards: int, share, b: int, k: int, metric: str = "l2sq", own: bool = False) -> DataFrame:
    """(qid, pos, id, dist) over sets too large for one graph: each shard of ids, which a task must hold, is pruned and
    searched where it lies, and the best k of all are kept. Coverage holds within shards only. Queries go block by block."""
    share, kernel = Share.of(share), KERNELS[metric]
    parts = query_blocks(queries)
    if len(parts) > 1:
        return reduce(DataFrame.unionByName, [beam_sharded(points, q, shards, share, b, k, metric, own) for q in parts])
    sent = points.sparkSession.sparkContext.broadcast(block(queries, "qid", QUERY_BLOCK))

    def run(group: pa.Table) -> pa.Table:
        qid, qvec = sent.value
        ids = group.column("id").to_numpy()
        order = np.argsort(ids)
        vecs = group.column("vec").combine_chunks().flatten().to_numpy(zero_copy_only=False).astype(float).reshape(len(ids), -1)[order]
        ids, lists, all_rows, size = ids[order], [], Rows(vecs, metric), together(len(ids))
        for first in range(0, len(ids), size):
            some = list(range(first, min(len(ids), first + size)))
            lists += [np.array([s for s, _, _ in got], np.int64) for got, _ in cover(all_rows, some, share.need(len(ids)))]
        g = SimpleNamespace(ids=ids, vecs=vecs, out=lists.__getitem__)
        rows = []
        for q, v in zip(qid.tolist(), qvec, strict=True):
            (_, _, _, _, dist), = beam(g, v.astype(float), 0, [b], kernel)
            rows += [(q, i, d) for d, i in heapq.nsmallest(k, ((d, int(ids[x])) for x, d in dist.items() if not own or int(ids[x]) != q))]
        return pa.table([pa.array(c, t) for c, t in zip(zip(*rows, strict=True) if rows else [()] * 3, (pa.int64(), pa.int64(), pa.float64()), strict=True)], names=["qid", "id", "dist"])

    found = points.select("id", "vec").groupBy(F.pmod(F.xxhash64("id"), F.lit(shards)).alias("shard")).applyInArrow(run, "qid long, id long, dist double")
    return found.withColumn("pos", F.row_number().over(W.partitionBy("qid").orderBy("dist", "id"))).where(F.col("pos") <= k).select("qid", "pos", "id", "dist")
