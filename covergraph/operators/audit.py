"""Coverage, degree and reachability of any graph (src, dst) over points (id, vec)."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.exact import DRAWS, Share, portable_hash
from ..functions.metric import KERNELS, NARROW, Boxes, Rows, owned_by
from ..sources.points import block, stage, width


def adjacency(edges: DataFrame) -> DataFrame:
    return edges.groupBy("src").agg(F.array_sort(F.collect_set("dst")).alias("dsts"))


def together(n: int) -> int:
    """Sources compared with all of n points at once."""
    return max(1, min(32, (1 << 22) // max(1, n)))


#: Links of which distances to all points are taken, for many sources at once; after them only points still open are compared.
WHOLE = 4


def cover(rows: Rows, places: list[int], need: int, links: list[np.ndarray] | None = None, allowed: list[np.ndarray] | None = None, slack: float = 1.0):
    """For each of a few sources: its links (position, distance, gain) in order, and the positions left open.

    links: those of each source, nearest first; None: the nearest open point is linked (by distance and place, of the
    positions `allowed`) until `need` points are covered."""
    n, own = len(rows.vecs), rows.full(np.array(places, np.int64))
    own[np.arange(len(places)), places] = np.inf  # covered, or the source itself
    given = None if links is None else [iter(x[np.argsort(own[i][x], kind="stable")].tolist()) for i, x in enumerate(links)]
    out, left = [[] for _ in places], [n - 1] * len(places)

    def pick(i, o, may):
        if n - 1 - left[i] >= need or not left[i]:
            return None
        if given is not None:
            return next(given[i], None)
        s = int(o.argmin()) if may is None else int(may[o[may].argmin()]) if len(may) else None
        return None if s is None or o[s] == np.inf else s

    def take(i, s, o, d, at):
        dist = float(o[at]) if at is not None else None
        o[slack * d < o if slack != 1 else d < o] = np.inf
        if at is not None:
            o[at] = np.inf
        now = int(np.count_nonzero(o < np.inf))
        out[i].append((s, dist, left[i] - now))
        left[i] = now

    live = list(range(len(places)))
    for turn in range(WHOLE):
        if turn and rows.vecs.shape[1] <= NARROW and 2 * sum(left[i] for i in live) < n * len(live):
            break
        chosen = {i: s for i in live if (s := pick(i, own[i], allowed and allowed[i])) is not None}
        live = list(chosen)
        if not live:
            break
        for (i, s), d in zip(chosen.items(), rows.full(np.array(list(chosen.values()))), strict=True):
            take(i, s, own[i], d, s if given is None else None)
    rest = [np.empty(0, np.int64)] * len(places)
    for i in range(len(places)):
        at = np.flatnonzero(own[i] < np.inf)
        if i in live:
            o, part = own[i][at], rows.part(at)
            may = None if allowed is None else np.flatnonzero(np.isin(at, allowed[i]))
            while (s := pick(i, o, may)) is not None:
                x = s if given is not None else int(at[s])
                take(i, x, o, rows.row(x, part), s if given is None else None)
                if 2 * left[i] < len(o):
                    keep = o < np.inf
                    at, o, part = at[keep], o[keep], tuple(p if p is None else p[keep] for p in part)
                    may = None if may is None else np.flatnonzero(np.isin(at, allowed[i]))
            at = at[o < np.inf]
        rest[i] = at
    return list(zip(out, rest, strict=True))


def cover_boxed(boxes: Boxes, p: int, need: int) -> list[tuple[int, float, int]]:
    """cover() of one source at row p of boxes.vecs, of whole numbers under squared Euclidean distances, by the nearest open points: (place, distance, gain).

    A link covers what lies on its side of a plane. Boxes beyond it go as a whole, those that it cuts are opened and
    their points compared one by one; a box is opened too once it may hold the nearest open point."""
    x, n, out = boxes.vecs[p], len(boxes.vecs), []
    least = (np.maximum(np.abs(x - boxes.centre) - boxes.half, 0) ** 2).sum(1)
    shut = np.argsort(least, kind="stable")  # boxes of which no point is covered
    least, centre, half = least[shut], boxes.centre[shut], boxes.half[shut]
    held, far = np.empty(0, np.int64), np.empty(0)  # open points of opened boxes
    vecs, left = np.empty((0, len(x))), n - 1

    def opened(some):
        at = boxes.inside(some)
        at = at[at != p]
        return at, boxes.vecs[at]

    def hold(at, v):
        return np.r_[held, at], np.r_[far, ((v - x) ** 2).sum(1)], np.concatenate([vecs, v])

    while left and n - 1 - left < need:
        while len(shut) and (not len(far) or least[0] <= far.min()):
            k = int(np.searchsorted(least, far.min(), "right")) if len(far) else 1
            held, far, vecs = hold(*opened(shut[:k]))
            shut, least, centre, half = shut[k:], least[k:], centre[k:], half[k:]
        if not len(far):
            break
        near = np.flatnonzero(far == far.min())
        s = int(near[boxes.order[held[near]].argmin()])
        y, dist, link = vecs[s], float(far[s]), held[s]
        w, t = 2 * (y - x), y @ y - x @ x
        open_ = vecs @ w <= t
        open_[s] = False
        gain = len(open_) - int(np.count_nonzero(open_))
        held, far, vecs = held[open_], far[open_], vecs[open_]
        middle, reach = centre @ w - t, half @ np.abs(w)
        beyond, apart = middle > reach, middle + reach <= 0
        gain += int(boxes.sizes[shut[beyond]].sum())
        at, v = opened(shut[~beyond & ~apart])
        open_ = v @ w <= t
        gain += len(at) - int(np.count_nonzero(open_))
        held, far, vecs = hold(at[open_], v[open_])
        shut, least, centre, half = shut[apart], least[apart], centre[apart], half[apart]
        left -= gain
        out.append((int(boxes.order[link]), dist, gain))
    return out


def _uncovered(points: DataFrame, metric: str):
    """The points as broadcast, and a function from batches (src, dsts) to (batch, src, rows, positions that each src leaves uncovered)."""
    ids, vecs = block(points)
    sent = points.sparkSession.sparkContext.broadcast((ids, vecs))

    def run(batches):
        ids, vecs = sent.value
        rows, size = Rows(vecs, metric), together(len(ids))
        for batch in batches:
            for first in range(0, batch.num_rows, size):
                some = batch.slice(first, size)
                src = some.column(0).to_numpy()
                links = [np.searchsorted(ids, np.array(x.as_py() or [], np.int64)) for x in some.column(1)]
                yield some, src, rows, [open_ for _, open_ in cover(rows, np.searchsorted(ids, src).tolist(), len(ids), links)]

    return sent, run


def covered_counts(points: DataFrame, edges: DataFrame, metric: str = "l2sq", targets: int | None = None, seed: int = 1, all_linked: DataFrame | None = None) -> DataFrame:
    """(src, covered, checked, half_width): points strictly nearer to an out-neighbour than to src, src itself not counted.

    targets: check that many drawn points only (sampled_counts), for points of
    any number. all_linked(id): points that link to all others, with no edges
    spelled out: each other point is a link at no distance from itself, so those
    apart from src are covered. Whole counts send the points to every task behind a size check."""
    if targets is not None:
        return sampled_counts(points, edges, targets, metric, seed, all_linked)
    sent, uncovered = _uncovered(points, metric)

    def counts(src, covered, n):
        return pa.RecordBatch.from_arrays([pa.array(src), pa.array(covered, pa.int64()), pa.array(np.full(len(src), n - 1)), pa.array(np.zeros(len(src)))], COUNTED)

    def run(batches):
        for some, src, rows, left in uncovered(batches):
            yield counts(src, [len(rows.vecs) - 1 - len(x) for x in left], len(rows.vecs))

    def run_all(batches):
        ids, vecs = sent.value
        rows, size = Rows(vecs, metric), together(len(ids))
        for batch in batches:
            for first in range(0, batch.num_rows, size):
                src = batch.column(0).slice(first, size).to_numpy()
                place = np.searchsorted(ids, src)
                apart = rows.full(place) > 0
                apart[np.arange(len(src)), place] = False
                yield counts(src, apart.sum(axis=1), len(ids))

    every = points.select(F.col("id").alias("src"))
    if all_linked is None:
        return even(every.join(adjacency(edges), "src", "left")).mapInArrow(run, COUNTS)
    whole = all_linked.select(F.col("id").alias("src")).distinct()
    some = every.join(whole, "src", "left_anti").join(adjacency(edges), "src", "left")
    return even(some).mapInArrow(run, COUNTS).unionByName(even(every.join(whole, "src", "left_semi")).mapInArrow(run_all, COUNTS))


def clique_counts(points: DataFrame, members: DataFrame, leftovers: DataFrame, metric: str = "l2sq") -> DataFrame:
    """covered_counts() of a graph kept as cliques, members(round, chunk, member, kept) of one size, and leftovers(id), which link to all.

    A member covers all points but those to which it is nearest in its clique, so a clique is compared with all points at once."""
    sent = points.sparkSession.sparkContext.broadcast(block(points))

    def counted(src, covered, n):
        return pa.RecordBatch.from_arrays([pa.array(src), pa.array(covered, pa.int64()), pa.array(np.full(len(src), n - 1)), pa.array(np.zeros(len(src)))], COUNTED)

    def run(batches):
        ids, vecs = sent.value
        for batch in batches:
            if batch.num_rows:
                src, kept = (batch.column(i).flatten().to_numpy(zero_copy_only=False) for i in (0, 1))
                owned = owned_by(vecs[np.searchsorted(ids, src)], len(src) // batch.num_rows, vecs, metric)
                yield counted(src[kept], (len(ids) - owned)[kept], len(ids))

    def run_all(batches):
        ids, vecs = sent.value
        rows, size = Rows(vecs, metric), together(len(ids))
        for batch in batches:
            for first in range(0, batch.num_rows, size):
                src = batch.column(0).slice(first, size).to_numpy()
                place = np.searchsorted(ids, src)
                apart = rows.full(place) > 0
                apart[np.arange(len(src)), place] = False
                yield counted(src, apart.sum(axis=1), len(ids))

    cliques = members.groupBy("round", "chunk").agg(F.collect_list(F.struct("member", "kept")).alias("m")).where("exists(m, x -> x.kept)")
    return even(cliques.select("m.member", "m.kept")).mapInArrow(run, COUNTS).unionByName(even(leftovers.select("id")).mapInArrow(run_all, COUNTS))


def even(sources: DataFrame) -> DataFrame:
    """Dealt evenly: each source costs a comparison with all points."""
    return sources.repartition(max(width(sources), 8))


COUNTS = "src long, covered long, checked long, half_width double"
COUNTED = [c.split()[0] for c in COUNTS.split(", ")]


def _with_all_linked(counts: DataFrame, all_linked: DataFrame | None) -> DataFrame:
    if all_linked is None:
        return counts
    whole = all_linked.select(F.col("id").alias("_id")).distinct()
    return counts.join(whole, F.col("src") == F.col("_id"), "left").select("src", F.when(F.col("_id").isNotNull(), F.col("checked")).otherwise(F.col("covered")).alias("covered"), "checked", "half_width")


def drawn_targets(points: DataFrame, m: int, seed: int) -> DataFrame:
    """m points by the portable hash of their ids: the same ones in every engine."""
    return points.orderBy(portable_hash(F.col("id"), DRAWS, seed), "id").limit(m)


def sampled_counts(points: DataFrame, edges: DataFrame, m: int, metric: str = "l2sq", seed: int = 1, all_linked: DataFrame | None = None, error: float = 0.05) -> DataFrame:
    """covered_counts() over m drawn points, which alone are sent to the tasks; sources and their links meet by joins.

    covered / checked is off by more than half_width with probability `error` at most."""
    targets = stage(drawn_targets(points.select("id", "vec"), m, seed))
    sent = points.sparkSession.sparkContext.broadcast(block(targets))
    kernel = KERNELS[metric]

    def run(group: pa.Table) -> pa.Table:
        ids, vecs = sent.value
        src, own = group.column("src").to_numpy(), group.column("own").to_numpy(zero_copy_only=False)
        v = group.column("vec").combine_chunks().flatten().to_numpy(zero_copy_only=False).astype(float).reshape(len(src), -1)
        order = np.lexsort((~own, src))
        src, v = src[order], v[order]
        starts = np.flatnonzero(np.r_[True, src[1:] != src[:-1]])
        out = {"src": [], "covered": [], "checked": [], "half_width": []}
        for s, e in zip(starts, np.r_[starts[1:], len(src)], strict=True):
            here = ids != src[s]
            near = np.full(len(ids), np.inf)
            for at in range(s + 1, e, 256):
                near = np.minimum(near, kernel(v[at : min(e, at + 256)], vecs).min(axis=0))
            n = int(here.sum())
            for c, x in zip(out, (int(src[s]), int((near < kernel(v[s : s + 1], vecs)[0])[here].sum()), n, float(np.sqrt(np.log(2 / error) / (2 * max(n, 1))))), strict=True):
                out[c].append(x)
        return pa.table(out)

    links = edges.select("src", "dst").distinct().join(points.select(F.col("id").alias("dst"), "vec"), "dst").select("src", "vec", F.lit(False).alias("own"))
    both = links.unionByName(points.select(F.col("id").alias("src"), "vec", F.lit(True).alias("own")))
    return _with_all_linked(both.groupBy("src").applyInArrow(run, COUNTS), all_linked)


def coverage_check(counts: DataFrame, share) -> DataFrame:
    """One row: does every node cover its need?"""
    share = Share.of(share)
    need = F.ceil(F.lit(share.num) * F.col("checked") / share.den)
    return counts.agg(F.coalesce(F.every(F.col("covered") >= need), F.lit(True)).alias("ok"), F.sum((F.col("covered") < need).cast("long")).alias("n_bad"), F.min("covered").alias("min_covered"), F.max(need).cast("long").alias("need"))


def achieved_share(counts: DataFrame) -> DataFrame:
    part = F.col("covered") / F.col("checked")
    return counts.agg(F.min(part).alias("share_min"), F.avg(part).alias("share_mean"), F.max(part).alias("share_max"))


def uncovered_pairs(points: DataFrame, edges: DataFrame, metric: str = "l2sq") -> DataFrame:
    """(src, target) that src does not cover."""
    sent, uncovered = _uncovered(points, metric)

    def run(batches):
        ids, _ = sent.value
        for _, src, _, left in uncovered(batches):
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat(src, [len(x) for x in left])), pa.array(ids[np.concatenate(left)])], ["src", "target"])

    return even(points.select(F.col("id").alias("src")).join(adjacency(edges), "src", "left")).mapInArrow(run, "src long, target long")


def degree_stats(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """Mean, median, smallest and largest out-degree; nodes without an edge count."""
    per = nodes.select(F.col("id").alias("src")).distinct().join(edges.groupBy("src").agg(F.count_distinct("dst").alias("d")), "src", "left").select(F.coalesce("d", F.lit(0)).alias("d"))
    return per.agg(F.avg("d").alias("mean"), F.percentile("d", F.lit(0.5)).alias("median"), F.min("d").alias("min"), F.max("d").alias("max"))


def validate_graph(points: DataFrame, edges: DataFrame) -> DataFrame:
    """Counts of self-loops, parallel edges and edges to missing points."""
    ids = points.select(F.col("id").alias("dst"))
    ends = edges.join(ids.withColumn("_dst", F.lit(1)), "dst", "left").join(ids.select(F.col("dst").alias("src"), F.lit(1).alias("_src")), "src", "left")
    loose = ends.agg(F.count(F.lit(1)).alias("edges"), F.sum((F.col("src") == F.col("dst")).cast("long")).alias("self_loops"), F.sum((F.col("_dst").isNull() | F.col("_src").isNull()).cast("long")).alias("dangling"))
    parallel = edges.groupBy("src", "dst").count().agg(F.coalesce(F.sum(F.col("count") - 1), F.lit(0)).alias("parallel"))
    return loose.crossJoin(parallel)


def bounds(spark, n: int, share) -> DataFrame:
    """The theory's yardsticks for n points: average degree at most 4/(1-share); sqrt(n) for full navigability."""
    share = Share.of(share)
    peel = 4 * share.den / (share.den - share.num) if share.num < share.den else float(n - 1)
    full = math.sqrt(n)
    return spark.createDataFrame([(n, str(share), share.need(n), peel, full, n * full, "cliques" if peel < full else "navigable")], "n long, share string, need long, clique_degree double, navigable_degree double, worst_edges double, regime string")


#: Links of a node from which it is a hub; most hubs.
HUB, HUBS = 10_000, 1000


def reachable(edges: DataFrame, start: int) -> DataFrame:
    """(node, hops) along edges from start: one join per hop."""
    seen = stage(edges.sparkSession.createDataFrame([(start, 0)], "node long, hops int"))
    frontier, hop = seen, 0
    while not frontier.isEmpty():
        hop += 1
        nxt = edges.join(frontier.select(F.col("node").alias("src")), "src").select(F.col("dst").alias("node")).distinct()
        frontier = stage(nxt.join(seen, "node", "left_anti").select("node", F.lit(hop).alias("hops")))
        seen = stage(seen.unionByName(frontier))
    return seen


def components(points: DataFrame, edges: DataFrame) -> DataFrame:
    """(node, component): smallest id that edges reach in either direction; labels spread and jump until they rest."""
    both = stage(edges.select("src", "dst").unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct())
    now = stage(points.select(F.col("id").alias("node"), F.col("id").alias("component")))
    degree = both.groupBy("src").agg(F.count(F.lit(1)).alias("n"))
    cut = max(HUB, both.count() // HUBS)
    hubs = stage(degree.where(F.col("n") > cut).select(F.col("src").alias("hub")))
    # links of hubs, of which there are HUBS at the most, stay where they are and get the hub's label sent
    to_hub, others = (both.join(F.broadcast(hubs), F.col("dst") == F.col("hub"), how) for how in ("left_semi", "left_anti"))
    while True:
        label = now.select(F.col("node").alias("dst"), "component")
        at_hubs = label.join(F.broadcast(hubs), F.col("dst") == F.col("hub"), "left_semi")
        met = others.join(label, "dst").unionByName(to_hub.join(F.broadcast(at_hubs), "dst"))
        near = met.groupBy("src").agg(F.min("component").alias("near"))
        lower = now.join(near, now["node"] == near["src"], "left").select("node", "component", F.least("component", F.coalesce("near", "component")).alias("low"))
        jump = lower.select(F.col("node").alias("_n"), F.col("low").alias("_c"))
        after = stage(lower.join(jump, lower["low"] == jump["_n"]).select("node", F.col("_c").alias("component"), (F.col("_c") != F.col("component")).alias("moved")))
        if after.where("moved").isEmpty():
            return after.select("node", "component")
        now = after.select("node", "component")
