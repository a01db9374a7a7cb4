"""Mixing sources to target weights by entropy balancing."""

from __future__ import annotations

import math

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import discard, rank_within, stage, table

WEIGHTS, SHARE, MOST = (3, 1, 2), 1.5, 2


def sizes(docs: DataFrame, keep: list[str] | None = None) -> DataFrame:
    """docs, or its columns `keep`, with `size`, the words of the whole text; null: 0."""
    names = [c for c in keep or docs.columns if c != "size"]

    def count(batches):
        for batch in batches:
            n = [len(x.as_py() or b"") and len(x.as_py().split()) for x in batch.column(len(names))]
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(n, pa.int64())], [*names, "size"])

    schema = ", ".join(f"`{k}` {docs.schema[k].dataType.simpleString()}" for k in names) + ", size long"
    return docs.select(*names, F.col("text").cast("binary").alias("_bytes")).mapInArrow(count, schema)


def targets(totals: dict, weights: dict, share: float = SHARE, most: float = MOST) -> dict:
    """Words for each source: `share` of all words by weight; a source stops at `most` times its size and the others take the excess."""
    left, fixed, free = share * sum(totals.values()), {}, set(totals)
    while free:
        part = {k: left * weights[k] / sum(weights[x] for x in free) for k in free}
        over = {k for k in free if part[k] > most * totals[k]}
        if not over:
            return fixed | part
        fixed |= {k: float(most * totals[k]) for k in over}
        left -= sum(fixed[k] for k in over)
        free -= over
    return fixed


def tilt(hist: DataFrame, target: list[float], total: list[int], rows: list[int], most: float = MOST, rounds: int = 60) -> list[float]:
    """One multiplier per source: Newton steps on the convex dual of "least relative entropy to one copy each, so
    that rates times sizes sum to the target and no rate is above `most`".

    The optimal rate is min(most, exp(l * size / mean size)). Each step sums
    gradient and curvature over (source, size, count) rows on the cluster; the
    driver holds a number per source. A step that leaves the bracket is halved
    into it."""
    spark, now = hist.sparkSession, [0.0] * len(target)
    low, high = [-50.0] * len(target), [50.0] * len(target)
    mean = [max(1.0, t / max(1, n)) for t, n in zip(total, rows, strict=True)]
    todo = {i for i, t in enumerate(target) if 0 < t < most * total[i]}
    for i in set(range(len(target))) - todo:
        now[i] = math.inf if target[i] > 0 else -math.inf
    for _ in range(rounds):
        if not todo:
            break
        state = spark.createDataFrame([(i, now[i], mean[i]) for i in sorted(todo)], "sid int, l double, mean double")
        x = F.col("size") / F.col("mean")
        rate = F.exp(F.least(F.col("l") * x, F.lit(50.0)))
        word = F.col("size") * F.col("n")
        sums = hist.join(F.broadcast(state), "sid").groupBy("sid").agg(F.sum(word * F.least(rate, F.lit(float(most)))).alias("g"), F.sum(F.when(rate < most, word * x * rate).otherwise(0.0)).alias("h"))
        for i, g, h in sums.collect():
            if abs(g - target[i]) <= 1e-9 * target[i]:
                todo.discard(i)
                continue
            if g > target[i]:
                high[i] = now[i]
            else:
                low[i] = now[i]
            step = now[i] - (g - target[i]) / h if h > 0 else math.nan
            if high[i] - low[i] < 1e-13:
                todo.discard(i)
            now[i] = step if low[i] < step < high[i] else (low[i] + high[i]) / 2
    return now


def _rounded(most: float):
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        """Copies of one source's sizes: largest first, each size carries what it missed to the next, so the smallest settle the rest."""
        pdf = pdf.sort_values("size", ascending=False, ignore_index=True)
        base, extra, carry = [], [], 0.0
        for size, n, rate in zip(pdf["size"].to_list(), pdf["n"].to_list(), pdf["rate"].to_list(), strict=True):
            want = n * size * rate + carry
            copies = min(most * n, max(0, round(want / size))) if size else n
            carry = want - copies * size
            base.append(copies // n)
            extra.append(copies % n)
        return pdf.assign(base=base, extra=extra)[["sid", "size", "base", "extra"]]

    return run


def mix(docs: DataFrame, weights: dict | None = None, share: float = SHARE, most: int = MOST) -> DataFrame:
    """mix_sized() of docs, with the text kept."""
    return mix_sized(sizes(docs), weights, share, most)


def mix_sized(sized: DataFrame, weights: dict | None = None, share: float = SHARE, most: int = MOST) -> DataFrame:
    """Rows with doc_id, source and size get source_size, target and copies (0 to `most`).

    `weights` names every source (None: 3, 1, 2 in code point order, null last);
    the driver holds a row per source, as it does the weights. Rates are tilted
    by size and rounded within each (source, size): which of its documents get
    the extra copy is drawn by a hash of doc_id, so reruns agree. One source's
    sizes meet in one task as counts: at most sqrt(2 * words) rows. A null
    source is a source; a null or empty text has size 0, keeps one copy and
    counts for nothing; repeated rows are drawn each on its own; an empty table
    gives no rows."""
    sized = stage(sized.drop("source_size", "target", "copies", "sid", "base", "extra"))
    found = {r[0]: (int(r[1]), int(r[2])) for r in sized.groupBy("source").agg(F.sum("size"), F.count(F.lit(1))).collect()}
    order = sorted(k for k in found if k is not None) + [None] * (None in found)
    weights = weights or {k: WEIGHTS[i % len(WEIGHTS)] for i, k in enumerate(order)}
    goal = targets({k: found[k][0] for k in order}, weights, share, most)
    spark = sized.sparkSession
    per = spark.createDataFrame([(i, k, found[k][0], float(goal[k])) for i, k in enumerate(order)], "sid int, _source string, source_size long, target double")
    known = sized.join(F.broadcast(per), F.col("source").eqNullSafe(F.col("_source"))).drop("_source")
    hist = stage(known.groupBy("sid", "size").agg(F.count(F.lit(1)).alias("n")))
    at = tilt(hist, [float(goal[k]) for k in order], [found[k][0] for k in order], [found[k][1] for k in order], most)
    state = spark.createDataFrame([(i, at[i], max(1.0, found[k][0] / max(1, found[k][1]))) for i, k in enumerate(order)], "sid int, l double, mean double")
    rate = F.when(F.col("size") == 0, 1.0).when(F.col("l") == math.inf, float(most)).when(F.col("l") == -math.inf, 0.0).otherwise(F.least(F.exp(F.least(F.col("l") * F.col("size") / F.col("mean"), F.lit(50.0))), F.lit(float(most))))
    rated = hist.join(F.broadcast(state), "sid").select("sid", "size", "n", rate.alias("rate"))
    copies = stage(rated.groupBy("sid").applyInPandas(_rounded(most), "sid int, size long, base int, extra long"))
    discard(hist)
    ranked = rank_within(known, ["sid", "size"], ["doc_id"], "_rank", attach=copies)
    return ranked.withColumn("copies", F.col("base") + (F.col("_rank") < F.col("extra")).cast("int")).drop("_rank", "base", "extra", "sid")


def op2_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    sized = sizes(table(spark, sf_dir, "documents"), ["doc_id", "source"])
    return mix_sized(sized).select("doc_id", "size", "source_size", "target", (F.col("copies") * F.col("size")).alias("taken"))
