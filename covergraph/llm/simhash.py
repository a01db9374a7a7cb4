"""SimHash near-duplicates by Golay-code fuzzy hashing."""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import shuffle_width, stage, table
from .components import components

#: The (23, 12) Golay code's generator polynomial; XXH64's seed.
GENERATOR, SEED = 0xAE3, 42
MOST = 2
#: A bucket of more distinct fingerprints than this is solved by probing neighbours in a join.
BUCKET = 20_000


def fingerprint(words: list[bytes]) -> int:
    """64 majority bits over the XXH64 of the 3-word shingles; fewer words: one shingle; none: zero."""
    from xxhash import xxh64_intdigest

    if not words:
        return 0
    shingles = [a + b" " + b + b" " + c for a, b, c in zip(words, words[1:], words[2:], strict=False)] if len(words) > 2 else [b" ".join(words)]
    ones, n = np.zeros(64, np.int64), len(shingles)
    for at in range(0, n, 1 << 16):
        h = np.array([xxh64_intdigest(s, SEED) for s in shingles[at : at + (1 << 16)]], "<u8")
        ones += np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * ones > n, bitorder="little").tobytes(), "little")


def fingerprints(docs: DataFrame) -> DataFrame:
    """(doc_id, fp): fp as a signed 64-bit number, of every whole text in lower-cased A-Z; null: empty."""

    def run(batches):
        for batch in batches:
            fps = [fingerprint((x.as_py() or b"").lower().split()) for x in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.array(fps, np.uint64).view(np.int64))], ["doc_id", "fp"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("binary")).mapInArrow(run, "doc_id long, fp long")


def golay() -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Remainders of the low 12 and high 11 bits of a word; for each remainder the (up to 6) error patterns of 4 bits or fewer, -1 for none."""

    def remainder(x: int) -> int:
        for bit in range(22, 10, -1):
            if x >> bit & 1:
                x ^= GENERATOR << (bit - 11)
        return x

    low, high = np.array([remainder(i) for i in range(1 << 12)]), np.array([remainder(i << 12) for i in range(1 << 11)])
    errors, used = np.full((1 << 11, 6), -1), np.zeros(1 << 11, int)
    for weight in range(5):
        for bits in combinations(range(23), weight):
            e = sum(1 << b for b in bits)
            s = low[e & 0xFFF] ^ high[e >> 12]
            errors[s, used[s]] = e
            used[s] += 1
    return low, high, errors


def codewords(x: np.ndarray, tables: tuple) -> np.ndarray:
    """12-bit indices of the codewords within 4 bits of each 23-bit word: one, or six where the nearest is 3 away; -1 fills the rest.

    The code's balls of radius 3 cover all words. Words at distance 2 or less
    have a word within 1 bit of both, and its codeword is within 4 of both: they
    share an index."""
    low, high, errors = tables
    e = errors[low[x & 0xFFF] ^ high[x >> 12]]
    return np.where(e < 0, -1, (x[:, None] ^ e) >> 11)


def fuzzy_keys(fp: np.ndarray, tables: tuple) -> tuple[np.ndarray, np.ndarray]:
    """(row, key): two fingerprints at 2 bits or fewer share a key.

    Segments of 23, 23 and 18 bits: two errors leave one of the three exact.
    With the first or second exact the other of them has at most 2 errors, so
    exact bits and one codeword index make a key; with only the third exact, it
    and an index of each of the others."""
    x = fp.view(np.uint64)
    a, b, c = ((x >> np.uint64(s) & np.uint64((1 << n) - 1)).astype(np.int64) for s, n in ((0, 23), (23, 23), (46, 18)))
    ga, gb, n = codewords(a, tables), codewords(b, tables), len(fp)
    both = np.where((ga[:, :, None] < 0) | (gb[:, None, :] < 0), -1, ga[:, :, None] << 12 | gb[:, None, :] & 0xFFF).reshape(n, 36)
    keys = np.concatenate([np.where(gb < 0, -1, a[:, None] << 12 | gb & 0xFFF), np.where(ga < 0, -1, 1 << 60 | b[:, None] << 12 | ga & 0xFFF), np.where(both < 0, -1, 2 << 60 | c[:, None] << 24 | both)], axis=1)
    row, col = np.nonzero(keys >= 0)
    return row, keys[row, col]


def _spread(batches):
    tables = golay()
    for batch in batches:
        fp, rep = (batch.column(i).to_numpy(zero_copy_only=False) for i in (0, 1))
        for at in range(0, len(fp), 8192):
            row, key = fuzzy_keys(fp[at : at + 8192], tables)
            yield pa.RecordBatch.from_arrays([pa.array(key), pa.array(fp[at : at + 8192][row]), pa.array(rep[at : at + 8192][row])], ["key", "fp", "rep"])


def _forest(fp: np.ndarray, rep: np.ndarray, most: int) -> list[tuple[int, int]]:
    """Links that connect what is linked within one bucket: at most one per fingerprint, found block by block."""
    group = np.arange(len(fp))
    out = []
    for i in range(len(fp)):
        near = np.flatnonzero(np.bitwise_count(fp[i] ^ fp[i + 1 :]) <= most) + i + 1
        for g in np.unique(group[near]):
            if g != group[i]:
                j = near[group[near] == g][0]
                out.append((int(rep[i]), int(rep[j])))
                group[group == g] = group[i]
    return out


def _scanner(most: int, bucket: int):
    def scan(batches):
        """Links within the runs of equal keys of a sorted partition; a run goes on over batches. (a, b, fp): fp marks a member of a run above `bucket`."""
        key, fp, rep = np.empty(0, np.int64), np.empty(0, np.uint64), np.empty(0, np.int64)
        hot = None

        def solve(k, f, r):
            links, marks = [], []
            starts = np.flatnonzero(np.r_[True, k[1:] != k[:-1]]) if len(k) else np.empty(0, np.int64)
            lengths = np.diff(np.r_[starts, len(k)])
            for step in range(1, 4):  # runs of up to four: all pairs at once
                i = np.concatenate([starts[lengths <= 4] + o for o in range(4)]) if len(starts) else starts
                ends = np.concatenate([(starts + lengths)[lengths <= 4]] * 4) if len(starts) else starts
                i = i[i + step < ends]
                i = i[np.bitwise_count(f[i] ^ f[i + step]) <= most]
                links.append(np.stack([r[i], r[i + step]], 1))
            for s, n in zip(starts[lengths > 4], lengths[lengths > 4], strict=True):
                if n > bucket:
                    marks.append(f[s : s + n])
                elif found := _forest(f[s : s + n], r[s : s + n], most):
                    links.append(np.array(found))
            return np.concatenate(links) if links else np.empty((0, 2), np.int64), np.concatenate(marks) if marks else np.empty(0, np.uint64)

        def out(links, marks):
            links = links[links[:, 0] != links[:, 1]]
            n, m = len(links), len(marks)
            gap = pa.nulls(m, pa.int64())
            return pa.RecordBatch.from_arrays([pa.concat_arrays([pa.array(links[:, i].astype(np.int64)), gap]) for i in (0, 1)] + [pa.concat_arrays([pa.nulls(n, pa.int64()), pa.array(marks.view(np.int64))])], ["a", "b", "fp"])

        for batch in batches:
            k, f, r = (batch.column(i).to_numpy(zero_copy_only=False) for i in range(3))
            key, fp, rep = np.concatenate([key, k]), np.concatenate([fp, f.view(np.uint64)]), np.concatenate([rep, r])
            if hot is not None or (len(key) and key[0] == key[-1] and len(key) > bucket):
                hot = key[0] if hot is None else hot  # of a run above the limit, no more than a batch is held
                m = int(np.searchsorted(key, hot, "right")) if key[0] == hot else 0
                yield out(np.empty((0, 2), np.int64), fp[:m])
                key, fp, rep = key[m:], fp[m:], rep[m:]
                hot = hot if not len(key) else None
            if len(key):
                cut = int(np.searchsorted(key, key[-1]))
                yield out(*solve(key[:cut], fp[:cut], rep[:cut]))
                key, fp, rep = key[cut:], fp[cut:], rep[cut:]
        yield out(*solve(key, fp, rep))

    return scan


def neighbours(hot: DataFrame, reps: DataFrame, most: int = MOST) -> DataFrame:
    """(a, b) for fingerprints of crowded buckets: each is changed in every way of up to `most` bits and looked up."""
    masks = [sum(1 << b for b in bits) for w in range(1, most + 1) for bits in combinations(range(64), w)]
    signed = np.array(masks, np.uint64).view(np.int64).tolist()
    grid = F.broadcast(hot.sparkSession.createDataFrame([(signed,)], "m array<long>"))
    probes = hot.distinct().join(reps, "fp").select("rep", "fp").crossJoin(grid).select(F.col("rep").alias("a"), F.explode(F.transform("m", lambda m: m.bitwiseXOR(F.col("fp")))).alias("fp"))
    return probes.join(reps, "fp").select("a", F.col("rep").alias("b"))


def link(prints: DataFrame, most: int = MOST, bucket: int = BUCKET, few: int = 0) -> DataFrame:
    """prints(doc_id, fp) with component_id, the smallest doc_id reachable over links of `most` (2 or fewer) differing bits.

    Equal fingerprints collapse to their smallest doc_id before any pair is
    formed; a bucket yields at most one link per member. A row without doc_id
    links nothing and has no component. few: as in components()."""
    prints = stage(prints)
    n = shuffle_width(prints.sparkSession)
    reps = stage(prints.where("doc_id is not null").groupBy("fp").agg(F.min("doc_id").alias("rep")))
    keyed = reps.select("fp", "rep").mapInArrow(_spread, "key long, fp long, rep long")
    found = stage(keyed.repartition(n, "key").sortWithinPartitions("key", "fp").mapInArrow(_scanner(most, bucket), "a long, b long, fp long"))
    edges = found.where("a is not null").select("a", "b")
    crowded = found.where("fp is not null").select("fp")
    if not crowded.isEmpty():
        edges = edges.unionByName(neighbours(crowded, reps, most))
    groups = components(edges, few=few).select(F.col("node").alias("_node"), F.col("component").alias("_component"))
    named = reps.join(groups, F.col("rep") == F.col("_node"), "left").select(F.col("fp").alias("_fp"), F.coalesce("_component", "rep").alias("component_id"))
    joined = prints.join(named, F.col("fp") == F.col("_fp"), "left").drop("_fp")
    return joined.withColumn("component_id", F.when(F.col("doc_id").isNotNull(), F.col("component_id")))


def near_duplicates(docs: DataFrame) -> DataFrame:
    """(doc_id, fingerprint, component_id) of every row. Null and empty texts
    have fingerprint zero; repeated rows meet in one component; other columns
    are left out; an empty table gives no rows."""
    return link(fingerprints(docs)).select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def op6_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"))
