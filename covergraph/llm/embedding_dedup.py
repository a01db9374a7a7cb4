"""Embedding near-duplicates by an epsilon grid order join."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import shuffle_width, stage, table
from .components import components

COSINE = 0.98
#: Leading principal dimensions of the grid, and of the boxes that bound intervals of the sequence.
DIMENSIONS, BOXED = 6, 16
#: Vectors of a sequence block; vectors of a recursion's leaf; vectors of a box; blocks of a run.
BLOCK, LEAF, BOX, RUN = 1024, 64, 16, 16
#: Vectors, their bytes and the vector lengths that the principal dimensions are fitted on; they steer the order, never the result.
SAMPLE, SAMPLE_BYTES, SAMPLE_DIMS = 10_000, 64 << 20, 8
#: Rows of an equal vector from which its class is broadcast to them; at most one class for each so many of all rows.
HOT_ROWS, HOT_SHARE = 500, 1000


def unit(v: np.ndarray) -> np.ndarray:
    v = v.astype(np.float64)
    v = v / np.abs(v).max(axis=1, keepdims=True)  # so that no square overflows
    return v / np.sqrt((v * v).sum(axis=1, keepdims=True))


def principal(reps: DataFrame, dim: int, n: int, dimensions: int, sample: int) -> np.ndarray:
    """Leading directions of the unit vectors of a length, orthonormal, from at most about `sample` of its n vectors."""
    most = max(dim, min(sample, SAMPLE_BYTES // (8 * dim)))
    t = reps.where(F.size("v") == dim).sample(min(1.0, most / max(1, n)), seed=11).select("v").limit(2 * most).toArrow()
    if not t.num_rows:
        return np.eye(dim)[:, :dimensions]
    x = unit(t.column("v").combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(-1, dim))
    return np.linalg.eigh(x.T @ x - len(x) * np.outer(x.mean(0), x.mean(0)))[1][:, ::-1][:, :dimensions]


def fit_axes(reps: DataFrame, sample: int) -> dict[int, np.ndarray]:
    """Directions for the commonest vector lengths; vectors of the others go by their first coordinates."""
    sizes = reps.groupBy(F.size("v").alias("d")).count().orderBy(F.desc("count"), "d").limit(SAMPLE_DIMS).collect()
    return {d: principal(reps, d, n, min(d, BOXED), sample) for d, n in sizes}


def _axes(axes: dict[int, np.ndarray], d: int) -> np.ndarray:
    return axes[d] if d in axes else np.eye(d)[:, :BOXED]


def _cells(axes: dict[int, np.ndarray], dimensions: int, epsilon: float):
    def run(batches):
        for batch in batches:
            v = batch.column(batch.schema.get_field_index("v"))
            size = v.value_lengths().to_numpy(zero_copy_only=False)
            cells = np.zeros((len(v), dimensions), np.int32)
            for d in np.unique(size):
                i = np.flatnonzero(size == d)
                x = unit(v.take(pa.array(i)).flatten().to_numpy(zero_copy_only=False).reshape(-1, d))
                at = np.floor(x @ _axes(axes, int(d))[:, :dimensions] / epsilon).astype(np.int32)
                cells[i, : at.shape[1]] = at
            yield pa.RecordBatch.from_arrays([*batch.columns, *[pa.array(cells[:, k]) for k in range(dimensions)]], [*batch.schema.names, *[f"c{k}" for k in range(dimensions)]])

    return run


def _narrow(v: np.ndarray) -> np.ndarray:
    """Single precision where it holds every number whole, as it does for float input."""
    with np.errstate(over="ignore"):
        small = v.astype(np.float32)
    return small if (small == v).all() else v.astype(np.float64)


def _wide(v: bytes, dim: int, n: int) -> np.ndarray:
    return np.frombuffer(v, np.float32 if len(v) == 4 * dim * n else np.float64).reshape(-1, dim)


BLOCKS = "block long, part long, run long, label long, dim int, los array<array<double>>, his array<array<double>>, reps binary, ns binary, vs binary"


def _sequence(axes: dict[int, np.ndarray], block: int, leaf: int):
    def run(batches):
        """Cuts a sorted partition into blocks of one label and one dimension, with a box around each leaf of them."""
        from pyspark import TaskContext

        part, at = TaskContext.get().partitionId(), 0
        for batch in batches:
            label, dim = (batch.column(batch.schema.get_field_index(c)).to_numpy(zero_copy_only=False) for c in ("label", "dim"))
            cuts = np.flatnonzero(np.r_[True, (label[1:] != label[:-1]) | (dim[1:] != dim[:-1])]).tolist() + [len(label)]
            rows = []
            for s, e in zip(cuts[:-1], cuts[1:], strict=True):
                for i in range(s, e, block):
                    b = batch.slice(i, min(block, e - i))
                    get = lambda c, b=b: b.column(b.schema.get_field_index(c))
                    d = dim[i].item()
                    v = get("v").flatten().to_numpy(zero_copy_only=False)
                    seen = unit(v.reshape(-1, d)) @ _axes(axes, d)
                    starts = np.arange(0, len(seen), leaf)
                    lo, hi = np.minimum.reduceat(seen, starts), np.maximum.reduceat(seen, starts)
                    rows.append((part << 32 | at, part, part << 32 | at // RUN, label[i].item(), d, lo.tolist(), hi.tolist(), get("rep").to_numpy(zero_copy_only=False).tobytes(), get("n").to_numpy(zero_copy_only=False).tobytes(), _narrow(v).tobytes()))
                    at += 1
            if rows:
                box = pa.list_(pa.list_(pa.float64()))
                kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), box, box, pa.binary(), pa.binary(), pa.binary())
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], [c.split()[0] for c in BLOCKS.split(", ")])

    return run


class Join:
    """Joins two sequence intervals by halving the longer: skips pairs of intervals that are provably apart, counts
    those provably within reach whole, and compares the vectors of the others in leaves."""

    def __init__(self, reps, ns, vs, cosine: float):
        self.rep, self.n, self.v, self.cosine = reps, ns, vs, cosine
        self.reach = np.sqrt(2 - 2 * cosine)
        self.links = np.zeros(len(reps), np.int64)
        self.group = np.arange(len(reps))
        self.edges: list[tuple[int, int]] = []
        self.balls: dict[tuple[int, int], tuple[np.ndarray, float]] = {}

    def ball(self, s: int, e: int):
        if (s, e) not in self.balls:
            c = self.v[s:e].mean(0)
            self.balls[s, e] = c, float(np.sqrt(((self.v[s:e] - c) ** 2).sum(1).max())) + 1e-9
        return self.balls[s, e]

    def unite(self, i: int, others: np.ndarray) -> None:
        groups, first = np.unique(self.group[others], return_index=True)
        for g, k in zip(groups, first, strict=True):
            if g != self.group[i]:
                self.edges.append((int(self.rep[i]), int(self.rep[others[k]])))
                self.group[self.group == g] = self.group[i]

    def run(self, a: tuple[int, int], b: tuple[int, int]) -> None:
        (ca, ra), (cb, rb) = self.ball(*a), self.ball(*b)
        gap = float(np.sqrt(((ca - cb) ** 2).sum()))
        if gap > ra + rb + self.reach:
            return
        na, nb = a[1] - a[0], b[1] - b[0]
        ia, ib = np.arange(*a), np.arange(*b)
        if (2 * ra if a == b else gap + ra + rb) < self.reach - 1e-6:  # all of them are linked
            own = self.n[a[0] : a[1]]
            self.links[a[0] : a[1]] += self.n[b[0] : b[1]].sum() - (own if a == b else 0)
            if a != b:
                self.links[b[0] : b[1]] += own.sum()
            self.unite(a[0], np.r_[ia[1:], ib] if a != b else ia[1:])
            return
        if max(na, nb) > LEAF:
            cut = lambda x: ((x[0], (x[0] + x[1]) // 2), ((x[0] + x[1]) // 2, x[1]))
            if a == b:
                left, right = cut(a)
                for pair in ((left, left), (left, right), (right, right)):
                    self.run(*pair)
            elif na >= nb:
                for x in cut(a):
                    self.run(x, b)
            else:
                for x in cut(b):
                    self.run(a, x)
            return
        near = self.v[a[0] : a[1]] @ self.v[b[0] : b[1]].T >= self.cosine
        if a == b:
            np.fill_diagonal(near, False)
        if near.any():
            self.links[a[0] : a[1]] += near @ self.n[b[0] : b[1]]
            if a != b:
                self.links[b[0] : b[1]] += self.n[a[0] : a[1]] @ near
            for i in np.flatnonzero(near.any(axis=1)):
                self.unite(a[0] + i, ib[near[i]])


def _join(cosine: float):
    def run(batches):
        """(a, b, links): link counts have no b, links between classes have no count."""
        for batch in batches:
            col = lambda c: batch.column(batch.schema.get_field_index(c)).to_pylist()
            for same, dim, r1, n1, v1, r2, n2, v2 in zip(*map(col, ("same", "dim", "r1", "n1", "v1", "r2", "n2", "v2")), strict=True):
                sides = [(np.frombuffer(r, np.int64), np.frombuffer(n, np.int64), unit(_wide(v, dim, len(r) // 8))) for r, n, v in ((r1, n1, v1), (r2, n2, v2))[: 1 if same else 2]]
                j = Join(*[np.concatenate(x) for x in zip(*sides, strict=True)], cosine)
                m = len(sides[0][0])
                j.run((0, m), (0, m) if same else (m, len(j.rep)))
                hit = np.flatnonzero(j.links)
                a = np.r_[j.rep[hit], np.array([e[0] for e in j.edges], np.int64)]
                b = pa.array([None] * len(hit) + [e[1] for e in j.edges], pa.int64())
                yield pa.RecordBatch.from_arrays([pa.array(a), b, pa.array(np.r_[j.links[hit], np.zeros(len(j.edges), np.int64)])], ["a", "b", "links"])

    return run


def _near(reach: float):
    """Whether two boxes of projections come within reach: projections never lie further apart than what they are of."""
    gaps = F.zip_with(F.zip_with("a_lo", "b_hi", lambda x, y: x - y), F.zip_with("b_lo", "a_hi", lambda x, y: x - y), lambda x, y: F.greatest(x, y, F.lit(0.0)))
    return F.aggregate(gaps, F.lit(0.0), lambda s, x: s + x * x) <= reach * reach * (1 + 1e-6) + 1e-12


def block_pairs(blocks: DataFrame, reach: float) -> DataFrame:
    """(a_block, b_block): pairs of blocks of a label and a vector length, each once, that may hold a link.

    Intervals of the sequence are joined from whole partitions down to runs of
    blocks, blocks and leaves; a pair goes down a level only if its boxes come
    within reach. Boxes travel, vectors don't."""
    leaves = blocks.select("label", "dim", "part", "run", "block", F.posexplode(F.arrays_zip(F.col("los").alias("lo"), F.col("his").alias("hi"))).alias("leaf", "x")).select("*", "x.lo", "x.hi").drop("x")
    leaves = stage(leaves.withColumn("leaf", F.struct("block", "leaf")))

    def interval(keys: list[str], name: str) -> DataFrame:
        if name == "leaf":
            return leaves.select(*keys, F.col("leaf").alias("id"), "lo", "hi")
        flat = leaves.select(*keys, F.col(name).alias("id"), F.posexplode(F.arrays_zip("lo", "hi")).alias("k", "x"))
        box = flat.groupBy(*keys, "id", "k").agg(F.min("x.lo").alias("lo"), F.max("x.hi").alias("hi")).groupBy(*keys, "id").agg(F.array_sort(F.collect_list(F.struct("k", "lo", "hi"))).alias("box"))
        return box.select(*keys, "id", F.transform("box", lambda x: x["lo"]).alias("lo"), F.transform("box", lambda x: x["hi"]).alias("hi"))

    side = lambda df, n: df.select(*[F.col(c).alias(f"{n}_{c}") for c in df.columns])
    top = interval(["label", "dim"], "part")
    same = (F.col("a_label") == F.col("b_label")) & (F.col("a_dim") == F.col("b_dim"))
    pairs = side(top, "a").join(side(top, "b"), same & (F.col("a_id") <= F.col("b_id"))).where(_near(reach))
    pairs = pairs.select("a_label", "a_dim", F.col("a_id").alias("a_up"), F.col("b_id").alias("b_up"))
    for up, name in (("part", "run"), ("run", "block"), ("block", "leaf")):
        below = interval(["label", "dim", up], name).withColumnRenamed(up, "up")
        a, b = (side(below, n) for n in "ab")
        met = pairs.join(a, ["a_label", "a_dim", "a_up"]).join(b, (F.col("a_label") == F.col("b_label")) & (F.col("a_dim") == F.col("b_dim")) & (pairs["b_up"] == b["b_up"]))
        found = met.where((F.col("a_id") <= F.col("b_id")) & _near(reach))
        if name == "leaf":
            return found.select(F.col("a_id.block").alias("a_block"), F.col("b_id.block").alias("b_block")).distinct()
        pairs = stage(found.select("a_label", "a_dim", F.col("a_id").alias("a_up"), F.col("b_id").alias("b_up")))


def sequence(reps: DataFrame, reach: float, dimensions: int, block: int, sample: int) -> DataFrame:
    """Blocks of the epsilon grid order: vectors sorted by their cells on leading principal dimensions."""
    axes = fit_axes(reps, sample)
    order = ["label", "dim", *[f"c{k}" for k in range(dimensions)], "rep"]
    schema = "label long, v array<double>, rep long, n long, dim int, " + ", ".join(f"c{k} int" for k in range(dimensions))
    celled = reps.select("label", "v", "rep", "n", F.size("v").alias("dim")).mapInArrow(_cells(axes, dimensions, reach * (1 + 1e-9) + 1e-12), schema)
    ordered = celled.repartitionByRange(shuffle_width(reps.sparkSession), *order).sortWithinPartitions(*order)
    return stage(ordered.mapInArrow(_sequence(axes, block, BOX), BLOCKS))


def classes_of(rows: DataFrame, cosine: float, dimensions: int = DIMENSIONS, block: int = BLOCK, sample: int = SAMPLE):
    """(reps, blocks, pairs): equal vectors of a label as one, their sequence, and the pairs of blocks to compare."""
    reach = float(np.sqrt(2 - 2 * cosine))
    reps = stage(rows.where("good").groupBy("label", "v").agg(F.min("vec_id").alias("rep"), F.count(F.lit(1)).alias("n")))
    blocks = sequence(reps, reach, dimensions, block, sample)
    return reps, blocks, stage(block_pairs(blocks, reach))


def pairs_report(blocks: DataFrame, pairs: DataFrame) -> DataFrame:
    """One row: pairs of blocks that were formed, and all pairs within labels."""
    every = blocks.groupBy("label", "dim").agg(F.count(F.lit(1)).alias("m")).agg(F.coalesce(F.sum(F.expr("m * (m + 1) div 2")), F.lit(0)).alias("every"))
    return pairs.agg(F.count(F.lit(1)).alias("formed")).crossJoin(every)


def checked(rows: DataFrame) -> DataFrame:
    """(vec_id, label, v, good)"""
    v = F.col("embedding").cast("array<double>")
    good = F.col("vec_id").isNotNull() & F.col("label").isNotNull() & v.isNotNull() & F.forall(v, lambda x: F.coalesce(~F.isnan(x) & (F.abs(x) < float("inf")), F.lit(False))) & F.exists(v, lambda x: x != 0)
    return rows.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("label").cast("long").alias("label"), v.alias("v"), F.coalesce(good, F.lit(False)).alias("good"))


def _attach(cast: DataFrame, classes: DataFrame) -> DataFrame:
    """cast with its classes (_label, _v, _n, ...) by vector: classes of many rows are broadcast, as there are HOT_SHARE of
    them at the most, and their rows stay where they are; the others meet by a shuffle."""
    total = classes.agg(F.coalesce(F.sum("_n"), F.lit(0))).first()[0]
    cut = max(HOT_ROWS, total // HOT_SHARE)
    on = F.col("good") & (F.col("label") == F.col("_label")) & (F.col("v") == F.col("_v"))
    if total <= cut:
        return cast.join(classes, on, "left")
    met = cast.join(F.broadcast(classes.where(F.col("_n") > cut)), on, "left")
    hot = met.where("_label is not null")
    return met.where("_label is null").select(*cast.columns).join(classes.where(F.col("_n") <= cut), on, "left").unionByName(hot)


def link_vectors(rows: DataFrame, cosine: float = COSINE, dimensions: int = DIMENSIONS, block: int = BLOCK, sample: int = SAMPLE) -> DataFrame:
    """rows(vec_id, embedding, label) with n_links and component_id.

    Vectors link when their labels and lengths are equal and their cosine is at
    least `cosine` (0 to 1). Equal vectors of a label collapse to a class with a
    count before the join. A row without id or label, or with a null, empty,
    zero or non-finite vector links nothing: 0 links, its own component.
    Repeated rows are vectors of their own; an empty table gives no rows; other
    columns are left out, whatever their names."""
    cast = checked(rows)
    reps, blocks, pairs = classes_of(cast, cosine, dimensions, block, sample)
    one = blocks.select(F.col("block").alias("a_block"), "dim", F.col("reps").alias("r1"), F.col("ns").alias("n1"), F.col("vs").alias("v1"))
    two = blocks.select(F.col("block").alias("b_block"), F.col("reps").alias("r2"), F.col("ns").alias("n2"), F.col("vs").alias("v2"))
    sides = pairs.join(one, "a_block").join(two, "b_block").withColumn("same", F.col("a_block") == F.col("b_block"))
    found = stage(sides.select("same", "dim", "r1", "n1", "v1", "r2", "n2", "v2").mapInArrow(_join(cosine), "a long, b long, links long"))
    links = found.where("b is null").groupBy("a").agg(F.sum("links").alias("links"))
    groups = components(found.where("b is not null").select("a", "b"))
    classes = reps.join(links, F.col("rep") == F.col("a"), "left").join(groups, F.col("rep") == F.col("node"), "left")
    classes = classes.select(F.col("label").alias("_label"), F.col("v").alias("_v"), F.col("n").alias("_n"), (F.coalesce("links", F.lit(0)) + F.col("n") - 1).alias("_links"), F.coalesce("component", "rep").alias("_component"))
    out = _attach(cast, stage(classes))
    return out.select("vec_id", F.coalesce("_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("_component", "vec_id").alias("component_id"))


def op10_embedding_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    linked = link_vectors(table(spark, sf_dir, "embeddings"))
    return linked.withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(False)))


ORACLE = """
WITH RECURSIVE e AS (SELECT vec_id, label, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS v FROM embeddings),
l AS (SELECT a.vec_id AS a, b.vec_id AS b FROM e a JOIN e b ON a.label = b.label AND a.vec_id <> b.vec_id AND list_cosine_similarity(a.v, b.v) >= 0.98),
c AS (SELECT vec_id AS n, vec_id AS c FROM e UNION SELECT l.b, c.c FROM c JOIN l ON l.a = c.n)
SELECT n AS vec_id, (SELECT count(*) FROM l WHERE l.a = n) AS n_links, min(c) AS component_id, n = min(c) AS kept FROM c GROUP BY n
"""
