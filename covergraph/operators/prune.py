"""Nearest-first pruning, greedy set cover, and what their lists tell."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.exact import Share
from ..functions.metric import KERNELS, NARROW, Boxes, Rows, whole_numbers
from ..sources.points import block, bounded_blocks
from .audit import cover, cover_boxed, even, together

EDGES = "src long, rank int, dst long, dist double, gain long, cum long"


def target_ranks(rows: Rows) -> np.ndarray:
    """At [r, s]: how many different distances from r are below that of s. Ranks take two bytes where distances take eight."""
    n = len(rows.vecs)
    out = np.empty((n, n), np.uint16)
    for first in range(0, n, 32):
        for r, d in enumerate(rows.full(np.arange(first, min(n, first + 32))), first):
            order = np.argsort(d)
            sorted_ = d[order]
            out[r, order] = np.r_[0, np.cumsum(sorted_[1:] > sorted_[:-1])]
    return out


def column_ranks(rows: Rows) -> np.ndarray:
    """target_ranks() at [s, r]."""
    return target_ranks(rows).T


#: Targets that are compared with all points at once: their ranks stay in a core's cache for all sources of a call.
STRIP = 32


def most_first_many(ranks: np.ndarray, owns: np.ndarray, places: np.ndarray, need: int) -> list[list[tuple[int, int]]]:
    """most_first() of several sources, from target_ranks().

    While many targets are open, what the points cover of them is counted anew after each link, strip by strip for all sources;
    once a quarter is left, a source's hits are kept and those of each link's targets are taken off."""
    n, k = len(ranks), len(places)
    below = np.ascontiguousarray(ranks[:, places].T)  # by source: a target's rank of it
    open_, covered, out = np.ones((k, n), bool), np.zeros(k, np.int64), [[] for _ in range(k)]
    open_[np.arange(k), places] = False
    taken, some_hits, kept = np.empty((STRIP, n), np.uint16), np.empty((STRIP, n), bool), np.empty((n // 4, n), bool)  # filled anew by each source

    def link(i, counts, hits):
        """Takes the best point: the targets that it newly covers, of those that hits(s) tells of, or None at the end."""
        best = int(counts.max())
        if covered[i] >= need or best <= 0:
            return None
        ties = np.flatnonzero(counts == best)
        s = int(ties[np.lexsort((ties, owns[i, ties]))[0]])
        covered[i] += best
        out[i].append((s, best))
        return hits(s)

    def own_ones(i, counts, targets):
        """A point covers itself, also where it equals the source, which is no link."""
        same = targets[below[i, targets] == 0]
        counts[same] += 1
        counts[places[i]] = -1

    def strips(many):
        """Of the open targets of each of these sources: how many each point covers."""
        counts = np.zeros((k, n), np.int32)
        for r in range(0, n, STRIP):
            strip = ranks[r : r + STRIP]
            for i in many:
                at = np.flatnonzero(open_[i, r : r + STRIP])
                if len(at):
                    some = strip if len(at) == len(strip) else np.take(strip, at, axis=0, out=taken[: len(at)], mode="clip")
                    counts[i] += tally(np.less(some, below[i, r + at, None], out=some_hits[: len(at)]))
        return counts

    def tally(hit):
        return np.add.reduce(hit.view(np.uint8), axis=0, dtype=np.uint8)

    live = list(range(k))
    while many := [i for i in live if np.count_nonzero(open_[i]) > n // 4]:
        counts = strips(many)
        for i in many:
            own_ones(i, counts[i], np.flatnonzero(open_[i]))

            def hits(s, i=i):
                got = ranks[:, s] < below[i]
                got[s] = True
                return got

            new = link(i, counts[i], hits)
            if new is None:
                live.remove(i)
            else:
                open_[i] &= ~new
    for i in live:
        targets = np.flatnonzero(open_[i])
        hit, counts = kept[: len(targets)], np.zeros(n, np.int32)
        for t in range(0, len(targets), STRIP):
            at = targets[t : t + STRIP]
            counts += tally(np.less(np.take(ranks, at, axis=0, out=taken[: len(at)], mode="clip"), below[i, at, None], out=hit[t : t + STRIP]))
        own_ones(i, counts, targets)
        left = np.ones(len(targets), bool)
        while True:
            new = link(i, counts, lambda s: left & (hit[:, s] | (targets == s)))  # noqa: B023
            if new is None:
                break
            left &= ~new
            gone, at = targets[new], np.flatnonzero(new)
            for t in range(0, len(at), STRIP):
                counts -= tally(np.take(hit, at[t : t + STRIP], axis=0, out=some_hits[: len(at[t : t + STRIP])], mode="clip"))
            counts[gone[below[i, gone] == 0]] -= 1
    return out


def most_first(rows: Rows, own: np.ndarray, p: int, need: int, ranks: np.ndarray | None = None):
    """Greedy set cover: links the point that covers most of what is left, ties by distance and place: (position, gain) in order.

    What a point covers is a bit per target. Counts only fall, so that a point is counted anew only while its last count
    may still be the largest. Bits are kept where they fit MOST_BITS, else taken from distances again. ranks: column_ranks(), if they fit."""
    n = len(own)

    def bits(some):
        hits = ranks[some] < ranks[p] if ranks is not None else rows.full(some) < own
        hits[np.arange(len(some)), some] = True
        hits[:, p] = False
        hits[some == p] = False
        packed = np.zeros((len(some), -(-n // 64) * 8), np.uint8)
        packed[:, : -(-n // 8)] = np.packbits(hits, axis=1)
        return packed.view(np.uint64)

    held = np.concatenate([bits(np.arange(s, min(n, s + 512))) for s in range(0, n, 512)]) if n * n // 8 <= MOST_BITS else None
    covers = (lambda some: held[some]) if held is not None else bits
    open_ = np.zeros(-(-n // 64) * 64, bool)
    open_[:n] = True
    open_[p] = False
    most, covered, out = np.full(n, n, np.int64), 0, []
    while covered < need:
        left, order, best = np.packbits(open_).view(np.uint64), np.argsort(-most, kind="stable"), 0
        for s in range(0, n, 512):
            some = order[s : s + 512]
            if most[some[0]] < best:
                break
            most[some] = np.bitwise_count(covers(some) & left).sum(axis=1, dtype=np.int64)
            best = max(best, int(most[some].max()))
        if not best:
            break
        ties = np.flatnonzero(most == best)
        s = int(ties[np.lexsort((ties, own[ties]))[0]])
        open_ &= ~np.unpackbits(covers(np.array([s]))[0].view(np.uint8)).astype(bool)
        covered += best
        out.append((s, best))
    return out


#: Bytes of ranks of all pairs, and of bits of a source's set cover, that a task may hold; beyond them both are computed again where needed.
MOST_RANKS, MOST_BITS = 256 << 20, 256 << 20


def _lists(points: DataFrame, share, sources: DataFrame | None, metric: str, rule: str, candidates: DataFrame | None = None, slack: float = 1.0) -> DataFrame:
    share = Share.of(share)
    ids, vecs = block(points)
    need = share.need(len(ids))
    boxed = rule == "prune" and candidates is None and slack == 1 and metric == "l2sq" and len(ids) and vecs.shape[1] <= NARROW and whole_numbers(vecs)[1]
    sent = points.sparkSession.sparkContext.broadcast((ids, vecs, Boxes(vecs) if boxed else None))

    def run(batches):
        ids, vecs, boxes = sent.value
        rows, size = Rows(vecs, metric), together(len(ids))
        row_of = None if boxes is None else np.argsort(boxes.order)
        ranks = None
        for batch in batches:
            src = batch.column(0).to_numpy()
            place = np.searchsorted(ids, src)
            for first in range(0, len(src), size):
                lists, some = [], place[first : first + size]
                if rule == "cover":
                    every = rows.full(some)
                    every[np.arange(len(some)), some] = 0
                    if ranks is None and 2 * len(ids) ** 2 <= MOST_RANKS:
                        ranks = target_ranks(rows)
                    picked = most_first_many(ranks, every, some, need) if ranks is not None else [most_first(rows, own, p, need) for p, own in zip(some.tolist(), every, strict=True)]
                    found = [[(d, float(own[d]), gain) for d, gain in got] for got, own in zip(picked, every, strict=True)]
                elif boxes is not None:
                    found = [cover_boxed(boxes, p, need) for p in row_of[some].tolist()]
                else:
                    allowed = [np.searchsorted(ids, np.sort(np.array(x.as_py() or [], np.int64))) for x in batch.column(1).slice(first, size)] if batch.num_columns > 1 else None
                    found = [got for got, _ in cover(rows, some.tolist(), need, allowed=allowed, slack=slack)]
                for i, got in enumerate(found, first):
                    cum = 0
                    for rank, (d, dist, gain) in enumerate(got, 1):
                        cum += gain
                        lists.append((int(src[i]), rank, int(ids[d]), dist, gain, cum))
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*lists, strict=True) if lists else [()] * 6, (pa.int64(), pa.int32(), pa.int64(), pa.float64(), pa.int64(), pa.int64()), strict=True)], ["src", "rank", "dst", "dist", "gain", "cum"])

    nodes = (sources or points).select(F.col("id").alias("src"))
    if candidates is not None:
        nodes = nodes.join(candidates.groupBy("src").agg(F.collect_set("dst").alias("dsts")), "src", "left")
    if rule == "cover":  # a task ranks all pairs once
        return nodes.repartition(max(1, points.sparkSession.sparkContext.defaultParallelism)).mapInArrow(run, EDGES)
    return even(nodes).mapInArrow(run, EDGES)


def prune(points: DataFrame, share=1, sources: DataFrame | None = None, metric: str = "l2sq", candidates: DataFrame | None = None, slack: float = 1.0) -> DataFrame:
    """(src, rank, dst, dist, gain, cum) of each source: candidates nearest first (by distance and id), each linked unless covered, until the share is.

    Points are broadcast behind a size check; probe_prune() is for larger sets.
    candidates (src, dst): links come from them only, so the share may be missed."""
    return _lists(points, share, sources, metric, "prune", candidates, slack)


def set_cover(points: DataFrame, share=1, sources: DataFrame | None = None, metric: str = "l2sq") -> DataFrame:
    return _lists(points, share, sources, metric, "cover")


def probe_prune(points: DataFrame, probes: DataFrame, share, metric: str = "l2sq", shell: int = 64) -> DataFrame:
    """prune() of a bounded number of probes over points of any number; probes go block by block."""
    n = points.count()
    out = None
    for some in bounded_blocks(probes.select("id", "vec"), "id", PROBE_BLOCK):
        one = _probe_block(points, some, Share.of(share).need(n), metric, shell)
        out = one if out is None else out.unionByName(one)
    return out


PROBE_BLOCK = 1 << 20


def _probe_block(points: DataFrame, probes: DataFrame, need: int, metric: str, shell: int) -> DataFrame:
    """Each pass scans the points once: what the links so far cover is counted by its first coverer, and the nearest
    `shell` of the rest are kept, by partition and then by probe, where they are pruned to new links. The driver sees
    the links of a block's probes only: ids, distances and vectors as arrays."""
    spark, kernel = points.sparkSession, KERNELS[metric]
    pid, pvec = block(probes, most=64 << 20)
    dim = pvec.shape[1]
    links = {i: (np.empty(0, np.int64), np.empty(0), np.empty((0, dim))) for i in range(len(pid))}
    gains = {i: np.empty(0, np.int64) for i in range(len(pid))}
    todo = list(range(len(pid))) if need > 0 else []
    while todo:
        sent = spark.sparkContext.broadcast((pid, pvec, {i: links[i] for i in todo}))

        def scan(batches):
            pid, pvec, chosen = sent.value
            hits = {i: np.zeros(len(c[0]), np.int64) for i, c in chosen.items()}
            best = {i: (np.empty(0), np.empty(0, np.int64), np.empty((0, dim))) for i in chosen}
            for batch in batches:
                every = batch.column(0).to_numpy()
                all_vecs = batch.column(1).flatten().to_numpy(zero_copy_only=False).astype(float).reshape(len(every), -1)
                for at in range(0, len(every), 16384):
                    ids, vecs = every[at : at + 16384], all_vecs[at : at + 16384]
                    todo = list(chosen)
                    for s in range(0, len(todo), 64):
                        some = todo[s : s + 64]
                        owns = kernel(pvec[some], vecs)
                        sizes = np.cumsum([0, *(len(chosen[i][0]) for i in some)])
                        near = kernel(np.concatenate([chosen[i][2] for i in some]), vecs) if sizes[-1] else np.empty((0, len(ids)))
                        for own, i, u, v in zip(owns, some, sizes[:-1], sizes[1:], strict=True):
                            covers = near[u:v] < own
                            for k, j in enumerate(chosen[i][0].tolist()):
                                covers[k, ids == j] = True  # a link covers itself
                            covers[:, ids == pid[i]] = False
                            met = covers.any(axis=0)
                            if v > u:  # the first coverer counts
                                hits[i] += np.bincount(covers.argmax(axis=0)[met], minlength=v - u)
                            rest = np.flatnonzero(~met & (ids != pid[i]))
                            d0, i0, v0 = best[i]
                            if len(d0) == shell:
                                rest = rest[own[rest] <= d0[-1]]
                            if len(rest) > shell:
                                rest = rest[own[rest] <= np.partition(own[rest], shell - 1)[shell - 1]]
                            if len(rest):
                                d1, i1 = np.r_[d0, own[rest]], np.r_[i0, ids[rest]]
                                keep = np.lexsort((i1, d1))[:shell]
                                best[i] = d1[keep], i1[keep], np.concatenate([v0, vecs[rest]])[keep]
            for i in chosen:
                d, x, v = best[i]
                yield pa.RecordBatch.from_pydict({"probe": [i], "hits": [hits[i]], "ids": [x], "dists": [d], "vecs": [v.ravel()]}, schema=pa.schema([("probe", pa.int32()), ("hits", pa.list_(pa.int64())), ("ids", pa.list_(pa.int64())), ("dists", pa.list_(pa.float64())), ("vecs", pa.list_(pa.float64()))]))

        def merge(group: pa.Table) -> pa.Table:
            _, _, chosen = sent.value
            probe = group.column("probe")[0].as_py()
            flat = lambda c: group.column(c).combine_chunks().flatten().to_numpy(zero_copy_only=False)
            hits = flat("hits").reshape(group.num_rows, -1).sum(axis=0)
            ids, dists, vecs = flat("ids"), flat("dists"), flat("vecs").reshape(-1, dim)
            order = np.lexsort((ids, dists))[:shell]
            mine, new = chosen[probe][2], []
            if hits.sum() < need:
                for j in order.tolist():
                    if len(mine) and (kernel(vecs[j : j + 1], mine)[0] < dists[j]).any():
                        continue  # a link of this pass covers it
                    mine = np.concatenate([mine, vecs[j : j + 1]])
                    new.append(j)
            return pa.table({"probe": pa.array([probe], pa.int32()), "hits": pa.array([hits.astype(np.int64)], pa.list_(pa.int64())), "ids": pa.array([ids[new]], pa.list_(pa.int64())), "dists": pa.array([dists[new]], pa.list_(pa.float64())), "vecs": pa.array([vecs[new].ravel()], pa.list_(pa.float64()))})

        kind = "probe int, hits array<long>, ids array<long>, dists array<double>, vecs array<double>"
        t = points.select("id", "vec").mapInArrow(scan, kind).groupBy("probe").applyInArrow(merge, kind).toArrow()
        after = []
        for j, i in enumerate(t.column("probe").to_pylist()):
            get = lambda c, j=j: t.column(c)[j].values.to_numpy(zero_copy_only=False)  # noqa: B023, E731
            gains[i] = get("hits")
            if len(get("ids")):
                old = links[i]
                links[i] = np.r_[old[0], get("ids")], np.r_[old[1], get("dists")], np.concatenate([old[2], get("vecs").reshape(-1, dim)])
                after.append(i)
        todo = after
        sent.unpersist()
    out = []
    for i, p in enumerate(pid.tolist()):
        cum = np.cumsum(gains[i])
        used = int(np.searchsorted(cum, need)) + 1 if len(cum) and need > 0 else 0
        out += [(p, k + 1, int(links[i][0][k]), float(links[i][1][k]), int(gains[i][k]), int(cum[k])) for k in range(min(used, len(cum)))]
    return spark.createDataFrame(out, EDGES)


def cut(edges: DataFrame, share, n: int) -> DataFrame:
    """The list for a smaller share is the front of the list for the full one."""
    return edges.where(F.col("cum") - F.col("gain") < Share.of(share).need(n))


def coverage_trace(edges: DataFrame, n: int) -> DataFrame:
    """Share not covered after each edge, and its log10, not below that of half a point."""
    left = 1 - F.col("cum") / (n - 1)
    return edges.select("src", "rank", left.alias("uncovered"), F.log10(F.greatest(left, F.lit(0.5 / (n - 1)))).alias("log10_uncovered"))


def median_trace(edges: DataFrame, n: int) -> DataFrame:
    """Median of the trace over nodes at each rank; finished nodes keep their last value."""
    last = edges.groupBy("src").agg(F.max("rank").alias("last"))
    top = last.agg(F.coalesce(F.max("last"), F.lit(0)))
    grid = last.crossJoin(F.broadcast(top.select(F.explode(F.sequence(F.lit(1), F.greatest(F.col(top.columns[0]), F.lit(1)))).alias("at"))))
    trace = coverage_trace(edges, n)
    held = grid.select("src", "at", F.least("at", "last").alias("rank")).join(trace, ["src", "rank"])
    return held.groupBy(F.col("at").alias("rank")).agg(F.percentile("log10_uncovered", F.lit(0.5)).alias("median_log10"))


def edges_to_reach(edges: DataFrame, shares: list, n: int) -> DataFrame:
    """Median over nodes of the edges that each share takes."""
    out = None
    for s in shares:
        need = Share.of(s).need(n)
        one = edges.where(F.col("cum") >= need).groupBy("src").agg(F.min("rank").alias("r")).agg(F.lit(str(Share.of(s))).alias("share"), F.percentile("r", F.lit(0.5)).alias("median_edges"), F.avg("r").alias("mean_edges"))
        out = one if out is None else out.unionByName(one)
    return out
