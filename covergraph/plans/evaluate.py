"""Recall against cost, and what a smaller coverage share saves."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.exact import Share
from ..operators import prune as pruning
from ..operators import search
from ..sources.points import stage

WIDTHS, KS = [1, 2, 4, 16, 32, 64, 100, 128, 256], [1, 10, 100]
SHARES = ["0.8", "0.9", "0.95", "0.98", "0.99", "0.995", "0.999", "0.9995", "1"]
TARGETS = [0.90, 0.95, 0.97, 0.99]


def recall(found: DataFrame, truth: DataFrame) -> DataFrame:
    """(share, qid, b, k, hits/k, dist_evals, edges_scanned, expanded) by a join on the true neighbours."""
    near = truth.select("qid", "id", F.col("pos").alias("true_pos"))
    hit = found.join(near, ["qid", "id"], "left").withColumn("hit", F.coalesce(F.col("true_pos") <= F.col("k"), F.lit(False)))
    return hit.groupBy("share", "qid", "b", "k").agg((F.sum(F.col("hit").cast("int")) / F.first("k")).alias("recall"), F.max("dist_evals").alias("dist_evals"), F.max("edges_scanned").alias("edges_scanned"), F.max("expanded").alias("expanded"))


def tradeoff(points: DataFrame, queries: DataFrame, shares=SHARES, widths=WIDTHS, ks=KS, edges: DataFrame | None = None, own: bool = False) -> DataFrame:
    """(share, degree, k, b, recall, dc), b >= k only: mean recall and distance computations for every share.

    One pruned list per node serves all shares and one graph is sent for all;
    each task cuts it. own: queries are points too, and none finds itself."""
    n = points.count()
    full = stage(pruning.prune(points, 1)) if edges is None else edges
    truth = search.knn_exact(points, queries, max(ks), own=own)
    needs = {str(float(Share.of(s))): Share.of(s).need(n) for s in shares}
    found = search.beam_sweep(search.Graph(points, full), queries, widths, ks, needs=needs, own=own)
    mean = recall(found, truth).where("b >= k").groupBy("share", "k", "b").agg(F.avg("recall").alias("recall"), F.avg("dist_evals").alias("dc"))
    sizes = full.agg(*[F.sum((F.col("cum") - F.col("gain") < need).cast("long")) for need in needs.values()]).first()
    degree = points.sparkSession.createDataFrame([(s, (m or 0) / max(1, n)) for s, m in zip(needs, sizes, strict=True)], "share string, degree double")
    return stage(mean.join(F.broadcast(degree), "share").select(F.col("share").cast("double").alias("share"), "degree", "k", "b", "recall", "dc"))


def cost_at(points: DataFrame, targets=TARGETS) -> DataFrame:
    """Distance computations at each target recall, linear between beam widths; censored: the first width is above the target already."""
    w = W.partitionBy("share", "k").orderBy("b")
    steps = points.withColumn("r0", F.lag("recall").over(w)).withColumn("c0", F.lag("dc").over(w))
    grid = steps.crossJoin(F.broadcast(points.sparkSession.createDataFrame([(t,) for t in targets], "target double")))
    crossed = grid.where((F.col("recall") >= F.col("target")) & (F.col("r0").isNull() | (F.col("r0") < F.col("target"))))
    at = F.when(F.col("r0").isNull(), F.col("dc")).otherwise(F.col("c0") + (F.col("target") - F.col("r0")) / (F.col("recall") - F.col("r0")) * (F.col("dc") - F.col("c0")))
    first = crossed.groupBy("share", "degree", "k", "target").agg(F.min_by(F.struct(at.alias("dc"), F.col("r0").isNull().alias("censored")), "b").alias("x"))
    return first.select("share", "degree", "k", "target", "x.dc", "x.censored")


def ratio_table(points: DataFrame, targets=TARGETS) -> DataFrame:
    """Per k and target: the cheapest share below 1 against the full graph, in distance computations and in degree; null where none reaches the target."""
    cost = cost_at(points, targets)
    full = cost.where("share = 1").select("k", "target", F.col("dc").alias("full_dc"), F.col("degree").alias("full_degree"), F.col("censored").alias("ref_censored"))
    best = cost.where("share < 1").groupBy("k", "target").agg(F.min(F.struct("dc", "share", "degree", "censored")).alias("m"))
    return full.join(best, ["k", "target"], "left").select("k", "target", F.col("m.share").alias("share"), (F.col("m.dc") / F.col("full_dc")).alias("dc_ratio"), (F.col("m.degree") / F.col("full_degree")).alias("degree_ratio"), "ref_censored", F.col("m.censored").alias("num_censored"))


def ratio_average(points: DataFrame) -> DataFrame:
    """Means per k, with and without targets that the first width passes."""
    t = ratio_table(points)
    honest = ~(F.col("ref_censored") | F.col("num_censored"))
    return t.groupBy("k").agg(F.avg("dc_ratio").alias("dc_ratio"), F.avg("degree_ratio").alias("degree_ratio"), F.avg(F.when(honest, F.col("dc_ratio"))).alias("dc_ratio_uncensored"), F.sum(honest.cast("long")).alias("n_uncensored"))


def pareto(points: DataFrame) -> DataFrame:
    """Points below share 1 that no point of the full graph, nor any between two of them, beats at the same cost."""
    w = W.partitionBy("k").orderBy("dc")
    full = points.where("share = 1").select(F.col("k").alias("fk"), F.col("dc").alias("hi"), F.col("recall").alias("r_hi"), F.lag("dc").over(w).alias("lo"), F.lag("recall").over(w).alias("r_lo"))
    low = points.where("share < 1")
    at = F.when(F.col("lo").isNull(), F.col("r_hi")).otherwise(F.col("r_lo") + (F.col("dc") - F.col("lo")) / (F.col("hi") - F.col("lo")) * (F.col("r_hi") - F.col("r_lo")))
    inside = (F.col("k") == F.col("fk")) & (F.col("dc") <= F.col("hi")) & (F.col("lo").isNull() & (F.col("dc") == F.col("hi")) | (F.col("dc") > F.col("lo")))
    joined = low.join(full, inside, "left")
    best = points.where("share = 1").groupBy(F.col("k").alias("bk")).agg(F.max("recall").alias("top"), F.max("dc").alias("top_dc"))
    met = joined.join(best, F.col("k") == F.col("bk")).withColumn("full_recall", F.coalesce(at, F.when(F.col("dc") > F.col("top_dc"), F.col("top")), F.lit(0.0)))
    return met.select("share", "k", "b", "recall", "dc", "full_recall", (F.col("recall") > F.col("full_recall")).alias("beats"))


def min_share(points: DataFrame, target: float = 0.97) -> DataFrame:
    """Smallest share that reaches the target at some width, per k."""
    return points.groupBy("k", "share").agg(F.max("recall").alias("top")).where(F.col("top") > target).groupBy("k").agg(F.min("share").alias("min_share"))
