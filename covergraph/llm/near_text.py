"""Near copies by 5-word shingles: SimHash and min-hash candidates, verified on the whole sets."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import simhash
from .common import pieces, rank_within, shuffle_width, stage
from .components import FEW, components

#: Words of a shingle; similarity from which two texts are near copies, as a fraction.
WORDS, NUM, DEN = 5, 4, 5
#: Two min-hashes make a key. At similarity 0.8 two texts share no key with probability 0.36**16 < 1e-7.
BANDS, EACH = 16, 2
#: Bytes of a text that are split into words at once.
PIECE = 1 << 18
#: Texts of a side of a block that a task compares.
TOGETHER = 256
#: Bytes of a sketch, each of one min-hash, and how many must agree. At 0.8 fewer do with probability < 1e-7.
SKETCH, AGREE = 64, 32


def _constants() -> tuple[np.ndarray, np.ndarray]:
    r = np.random.default_rng(20)
    return r.integers(0, 1 << 64, SKETCH, np.uint64), r.integers(0, 1 << 64, SKETCH + WORDS, np.uint64) | np.uint64(1)


XOR, ODD = _constants()


def mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(31))) * np.uint64(0x9E3779B97F4A7C15)
    x = (x ^ (x >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    return x ^ (x >> np.uint64(32))


def shingles(text: bytes | None) -> np.ndarray:
    """Sorted distinct hashes of the 5-word shingles in lower-cased A-Z; fewer words: one shingle; none: empty."""
    from xxhash import xxh64_intdigest

    h = np.concatenate([np.fromiter(map(xxh64_intdigest, p.split()), np.uint64) for p in pieces((text or b"").lower(), PIECE)])
    if not len(h):
        return np.empty(0, np.uint64)
    n = max(1, len(h) - WORDS + 1)
    h = np.r_[h, np.full(max(0, WORDS - len(h)), 0, np.uint64)]
    total = np.zeros(n, np.uint64)
    for k in range(WORDS):
        total += mix(h[k : k + n] ^ XOR[k]) * ODD[SKETCH + k]
    return np.unique(mix(total))


def sketch(s: np.ndarray) -> tuple[int, np.ndarray, bytes]:
    """(digest of the set, a key a band, SKETCH bytes)."""
    if not len(s):
        return 0, np.empty(0, np.int64), b""
    least = np.full(SKETCH, (1 << 64) - 1, np.uint64)
    for at in range(0, len(s), 1024):
        least = np.minimum(least, ((s[at : at + 1024, None] ^ XOR) * ODD[:SKETCH]).min(axis=0))
    least = mix(least)
    pairs = least[: BANDS * EACH].reshape(BANDS, EACH)
    keys = mix(pairs[:, 0] * ODD[0] + pairs[:, 1] * ODD[1] + np.arange(BANDS, dtype=np.uint64))
    return int(mix(s).sum(dtype=np.uint64).view(np.int64)), keys.view(np.int64), (least & np.uint64(255)).astype(np.uint8).tobytes()


def _sketches(batches):
    for batch in batches:
        rows = [sketch(shingles(x.as_py())) for x in batch.column(1)]
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.list_(pa.int64())), pa.array([r[2] for r in rows], pa.binary())], ["doc_id", "digest", "keys", "sketch"])


def _forest(sk: np.ndarray) -> list[tuple[int, int]]:
    """Links that connect what agrees within one run, at most one a member."""
    left, out = np.arange(1, len(sk)), []
    queue = [0]
    while len(left):
        if not queue:
            queue, left = [int(left[0])], left[1:]
            continue
        i = queue.pop()
        near = (sk[left] == sk[i]).sum(axis=1) >= AGREE
        out += [(i, int(j)) for j in left[near]]
        queue += left[near].tolist()
        left = left[~near]
    return out


def _scan(batches):
    """Candidate links within the runs of equal keys of a sorted partition; a run goes on over batches."""

    def solve(k, r, s):
        starts = np.flatnonzero(np.r_[True, k[1:] != k[:-1]]) if len(k) else np.empty(0, np.int64)
        lengths = np.diff(np.r_[starts, len(k)])
        links = [np.empty((0, 2), np.int64)]
        few = (lengths > 1) & (lengths <= 4)
        for step in range(1, 4):  # runs of up to four: all pairs at once
            i = np.concatenate([starts[few] + o for o in range(4)])
            i = i[i + step < np.concatenate([(starts + lengths)[few]] * 4)]
            i = i[(s[i] == s[i + step]).sum(axis=1) >= AGREE]
            links.append(np.stack([r[i], r[i + step]], 1))
        for at, n in zip(starts[lengths > 4], lengths[lengths > 4], strict=True):
            if found := _forest(s[at : at + n]):
                links.append(r[at + np.array(found)])
        links = np.concatenate(links)
        return pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(links[:, i])) for i in (0, 1)], ["a", "b"])

    held: list[tuple] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        k, r = (batch.column(i).to_numpy(zero_copy_only=False) for i in (0, 1))
        s = np.frombuffer(b"".join(batch.column(2).to_pylist()), np.uint8).reshape(-1, SKETCH)
        held.append((k, r, s))
        if held[0][0][0] == k[-1]:
            continue  # one run so far
        k, r, s = (np.concatenate(x) for x in zip(*held, strict=True))
        cut = int(np.searchsorted(k, k[-1]))
        yield solve(k[:cut], r[:cut], s[:cut])
        held = [(k[cut:], r[cut:], s[cut:])]
    if held:
        yield solve(*(np.concatenate(x) for x in zip(*held, strict=True)))


def verified(ids: np.ndarray, sets: list[np.ndarray]) -> np.ndarray:
    """The smallest id reachable from each member over pairs at the similarity; equal ids are one member.

    Members outside the largest group are compared with all others; what lies
    inside it has no link left to find."""
    size = np.array([len(s) for s in sets])
    owner, every = np.repeat(np.arange(len(sets)), size), np.concatenate(sets)
    group = np.unique(ids, return_inverse=True)[1]
    group = np.array([np.flatnonzero(group == g)[0] for g in range(group.max() + 1)])[group]
    done = np.zeros(len(sets), bool)
    while True:
        counts = np.bincount(group, minlength=len(sets))
        open_ = np.flatnonzero(~done & (group != counts.argmax())) if done.any() else np.array([0])
        if not len(open_):
            break
        p = open_[0]
        done[p] = True
        if not size[p]:
            continue
        both = np.bincount(owner[sets[p][np.minimum(np.searchsorted(sets[p], every), size[p] - 1)] == every], minlength=len(sets))
        near = DEN * both >= NUM * (size + size[p] - both)
        joined = np.isin(group, group[near])
        group[joined] = group[joined].min()
    out = np.empty(len(sets), np.int64)
    for g in np.unique(group):
        out[group == g] = ids[group == g].min()
    return out


def _verify(batches):
    held: tuple[list, list] = ([], [])
    now = None

    def out(ids, sets):
        i = np.array(ids, np.int64)
        return pa.RecordBatch.from_arrays([pa.array(i), pa.array(verified(i, sets))], ["node", "component"])

    for batch in batches:
        for c, i, t in zip(*(batch.column(k) for k in range(3)), strict=True):
            if c.as_py() != now and held[0]:
                yield out(*held)
                held = ([], [])
            now = c.as_py()
            held[0].append(i.as_py())
            held[1].append(shingles(t.as_py()))
    if held[0]:
        yield out(*held)


def _verified_blocks(rows: DataFrame, members: DataFrame) -> DataFrame:
    """(node, component) of the links within blocks: members(k, doc_id), of which a task compares a block at a time."""
    n = shuffle_width(rows.sparkSession)
    met = members.distinct().join(rows, "doc_id").select("k", "doc_id", "text")
    return stage(met.repartition(n, "k").sortWithinPartitions("k").mapInArrow(_verify, "node long, component long").where("node <> component"))


def _stars(edges: DataFrame, most: int) -> DataFrame:
    """Blocks of a member and at most `most` of those whose smallest neighbour below them it is."""
    ends = edges.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))
    up = rank_within(ends.groupBy("b").agg(F.min("a").alias("a")), ["a"], ["b"], "r").select(F.concat_ws(":", "a", F.floor(F.col("r") / most)).alias("k"), "a", "b")
    return up.select("k", F.col("b").alias("doc_id")).unionByName(up.select("k", F.col("a").alias("doc_id")))


def _named(links: DataFrame, found: DataFrame) -> DataFrame:
    """(a, b) of links between different parts, by the parts' names; found(node, component): parts, a node in none is its own."""
    out = links
    for c in ("a", "b"):
        named = found.select(F.col("node").alias(c), F.col("component").alias("_p"))
        out = out.join(named, c, "left").withColumn(c, F.coalesce("_p", c)).drop("_p")
    return out.where("a <> b").select("a", "b").distinct()


def _rest(edges: DataFrame, found: DataFrame, most: int) -> DataFrame:
    """Blocks that hold, of the parts that candidate links still connect, every pair with an end outside the largest part."""
    near = components(_named(edges, found), few=FEW).select(F.col("node").alias("part"), "component")
    nodes = edges.select(F.col("a").alias("node")).unionByName(edges.select(F.col("b").alias("node"))).distinct()
    parts = nodes.join(found, "node", "left").select(F.col("node").alias("doc_id"), F.coalesce("component", "node").alias("part"))
    told = stage(parts.join(near, "part"))
    sizes = told.groupBy("component", "part").agg(F.count(F.lit(1)).alias("n"))
    open_ = sizes.groupBy("component").agg(F.max(F.struct("n", "part")).alias("top"), F.sum("n").alias("m"))
    cuts = lambda n: F.ceil(n / F.lit(most)).cast("int")
    open_ = open_.select("component", F.col("top.part").alias("top"), cuts(F.col("m") - F.col("top.n")).alias("outer"), cuts(F.col("m")).alias("every"))
    met = told.join(open_, "component")
    mine = lambda n: F.pmod(F.xxhash64("doc_id"), F.col(n)).cast("int")
    all_of = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    outside = met.where("part <> top").select("component", mine("outer").alias("o"), all_of("every").alias("e"), "doc_id")
    inside = met.select("component", all_of("outer").alias("o"), mine("every").alias("e"), "doc_id")
    return outside.unionByName(inside).select(F.concat_ws(":", "component", "o", "e").alias("k"), "doc_id")


def _fingerprint_links(rows: DataFrame, reps: DataFrame) -> DataFrame:
    """(a, b): each text with the smallest doc_id that SimHash fingerprints, at 2 or fewer differing bits a link, reach from it."""
    linked = simhash.link(simhash.fingerprints(rows.join(reps.select("doc_id"), "doc_id", "left_semi")), few=FEW)
    return linked.where("component_id <> doc_id").select(F.col("component_id").alias("a"), F.col("doc_id").alias("b"))


def first_copies(docs: DataFrame, most: int = TOGETHER) -> DataFrame:
    """(doc_id) of the smallest of each component over pairs with 5-word Jaccard similarity of 0.8 or more.

    Equal sets collapse first. Of the rest, what SimHash fingerprints link is a
    candidate, and, as edits within the similarity may change more bits, so is
    what shares a key and agrees in its sketch, at most once a member and run; whole sets decide, in
    blocks of about `most` members a side: first along these links, then, of
    what they connect, every pair that could still join two parts. So a task
    holds two blocks, however many texts are alike. Texts without words are
    equal; a row without doc_id links nothing; an empty table gives no rows."""
    rows = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("binary").alias("text")).where("doc_id is not null")
    cut = rows.mapInArrow(_sketches, "doc_id long, digest long, keys array<long>, sketch binary")
    reps = stage(cut.groupBy("digest").agg(F.min(F.struct("doc_id", "keys", "sketch")).alias("m")).select("m.*"))
    n = shuffle_width(docs.sparkSession)
    keyed = reps.select(F.explode("keys").alias("key"), "doc_id", "sketch")
    edges = stage(keyed.repartition(n, "key").sortWithinPartitions("key").mapInArrow(_scan, "a long, b long").unionByName(_fingerprint_links(rows, reps)).distinct())
    links = lambda linked: linked.select(F.col("node").alias("a"), F.col("component").alias("b"))
    found = components(links(_verified_blocks(rows, _stars(edges, most))), few=FEW)
    more = _verified_blocks(rows, _rest(edges, found, most))
    # names of parts are their smallest members, so a part that joins a smaller one goes as a whole
    joined = components(_named(links(more), found), few=FEW)
    later = found.where("node <> component").select("node").unionByName(joined.where("node <> component").select("node"))
    later = later.select(F.col("node").alias("doc_id")).distinct()
    return reps.select("doc_id").distinct().join(later, "doc_id", "left_anti")
