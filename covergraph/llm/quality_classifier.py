"""Quality classifier: a byte-level convolutional network in numpy."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table

#: Bytes of a step; a filter spans two steps, so windows overlap by half. Steps of a chunk; chunks overlap by a step.
STEP, CHUNK = 4, 64
#: Numbers for a byte, starting as its bits; filters.
EMBEDDED, FILTERS = 8, 32
#: The bounded sample that the network learns from: rows, and bytes of a row.
TRAIN_ROWS, TRAIN_BYTES = 3000, 200_000
EPOCHS, BATCH, RATE = 10, 32, 0.01
PAD = 256
#: Bytes of text that are scored at once.
AT_ONCE = 1 << 20


def start(seed: int = 5) -> dict[str, np.ndarray]:
    r = np.random.default_rng(seed)
    bits = np.r_[np.unpackbits(np.arange(256, dtype=np.uint8)[:, None], axis=1) * 2.0 - 1, np.zeros((1, EMBEDDED))]
    wide = STEP * EMBEDDED
    return {"e": bits.astype(np.float32), "w1": r.normal(0, wide**-0.5, (wide, FILTERS)).astype(np.float32), "w2": r.normal(0, wide**-0.5, (wide, FILTERS)).astype(np.float32), "b": np.zeros(FILTERS, np.float32), "u": r.normal(0, 0.1, 3 * FILTERS).astype(np.float32), "c": np.zeros(1, np.float32)}


def lay_out(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """All bytes, each text padded to whole chunks with a step of padding at its end at least; the first chunk of each text."""
    unit = STEP * CHUNK
    sizes = [-(-(len(t) + STEP) // unit) * unit for t in texts]
    ids = np.full(sum(sizes), PAD, np.int16)
    at = np.r_[0, np.cumsum(sizes)]
    for t, s in zip(texts, at, strict=False):
        ids[s : s + len(t)] = np.frombuffer(t, np.uint8)
    return ids.reshape(-1, STEP), at[:-1] // unit


def pooled(m: dict, ids: np.ndarray, first: np.ndarray):
    """Largest answer of each filter in each chunk (and its place), and per text the max, mean and min over its chunks."""
    x = m["e"][ids].reshape(len(ids), -1)
    y = x @ m["w1"] + m["b"]
    y[:-1] += x[1:] @ m["w2"]
    last = np.r_[first[1:], len(ids) // CHUNK] * CHUNK - 1
    y[last] = m["b"]  # a step of padding: what follows is another text
    np.maximum(y, 0, out=y)
    y = y.reshape(-1, CHUNK, FILTERS)
    z = y.max(axis=1)
    n = np.diff(np.r_[first, len(z)])
    per = np.concatenate([np.maximum.reduceat(z, first), np.add.reduceat(z, first) / n[:, None], np.minimum.reduceat(z, first)], axis=1)
    return x, y, z, n, per


def probability(m: dict, per: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(per @ m["u"] + m["c"], -30, 30).astype(np.float64)))


def fit(texts: list[bytes], labels: np.ndarray, seed: int = 5) -> dict[str, np.ndarray]:
    """Adam on the class-balanced logistic loss; the same rows in the same order give the same network."""
    m, r = start(seed), np.random.default_rng(seed)
    if not len(labels) or labels.min() == labels.max():  # one class only: its share is all there is to learn
        m["u"][:] = 0
        m["c"][:] = 0 if not len(labels) else 4.0 * (2 * labels[0] - 1)
        return m
    share = labels.mean()
    moments = {k: (np.zeros_like(v), np.zeros_like(v)) for k, v in m.items()}
    t = 0
    for epoch in range(EPOCHS):
        order = r.permutation(len(texts))
        for s in range(0, len(order), BATCH):
            pick = order[s : s + BATCH]
            ids, first = lay_out([texts[i] for i in pick])
            x, y, z, n, per = pooled(m, ids, first)
            label = labels[pick]
            d = ((probability(m, per) - label) * np.where(label == 1, 0.5 / share, 0.5 / (1 - share)) / len(pick)).astype(np.float32)
            g = {"u": per.T @ d, "c": d.sum(keepdims=True)}
            up, mean, low = (d[:, None] * m["u"][i * FILTERS : (i + 1) * FILTERS] for i in range(3))
            text = np.repeat(np.arange(len(pick)), n)
            dz = mean[text] / n[text, None]
            for part, of in ((up, slice(0, FILTERS)), (low, slice(2 * FILTERS, None))):
                hit = z == per[:, of][text]
                dz = dz + part[text] * hit / np.maximum(np.add.reduceat(hit, first, axis=0, dtype=np.float32), 1)[text]
            dz = np.where(z > 0, dz, 0).astype(np.float32)
            at = y.argmax(axis=1) + np.arange(len(z))[:, None] * CHUNK
            x = np.concatenate([x, np.zeros((1, x.shape[1]), np.float32)])
            a, b = x[at], x[at + 1]
            g["b"], g["w1"], g["w2"] = dz.sum(0), np.einsum("cf,cfk->kf", dz, a), np.einsum("cf,cfk->kf", dz, b)
            g["e"] = np.zeros_like(m["e"])
            grown = np.concatenate([ids, np.full((1, STEP), PAD, ids.dtype)])
            for place, w in ((at, m["w1"]), (at + 1, m["w2"])):
                np.add.at(g["e"], grown[place].reshape(-1, STEP), (dz[:, :, None] * w.T[None]).reshape(-1, STEP, EMBEDDED))
            g["e"][PAD] = 0
            t += 1
            rate = RATE * (1 - epoch / EPOCHS)
            for k in m:
                first_m, second = moments[k]
                first_m += 0.1 * (g[k] - first_m)
                second += 0.001 * (g[k] ** 2 - second)
                m[k] -= rate * (first_m / (1 - 0.9**t)) / (np.sqrt(second / (1 - 0.999**t)) + 1e-8)
    return m


def train(docs: DataFrame, labels: DataFrame, rows: int = TRAIN_ROWS, most_bytes: int = TRAIN_BYTES, seed: int = 5) -> dict[str, np.ndarray]:
    """Learns from at most `rows` labelled rows that are not held out, drawn by a hash of their id; the driver holds those texts alone."""
    known = labels.where("quality is not null and doc_id is not null").where(~held_out(F.col("doc_id"))).groupBy("doc_id").agg(F.min("quality").alias("quality"))
    drawn = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(rows)
    short = docs.where(F.octet_length(F.coalesce("text", F.lit(""))) <= most_bytes)
    found = short.join(F.broadcast(drawn), "doc_id").select("doc_id", F.coalesce("text", F.lit("")).cast("binary").alias("b"), "quality").limit(2 * rows).collect()
    found.sort(key=lambda r: (r["doc_id"], bytes(r["b"])))
    return fit([bytes(r["b"]) for r in found], np.array([int(r["quality"] == 1) for r in found], np.float32), seed)


def held_out(doc_id):
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 3 == 1, F.lit(False))


def score_quality(docs: DataFrame, m: dict[str, np.ndarray]) -> DataFrame:
    """(doc_id, held_out, score, predicted) of every whole text; only the text's bytes enter a score.

    Null texts are empty, and an empty text is one chunk of padding; equal texts
    get equal scores; other columns are left out; an empty table gives no rows."""

    def run(batches):
        for batch in batches:
            texts = [x.as_py() or b"" for x in batch.column(2)]
            out = np.zeros(len(texts))
            s = 0
            while s < len(texts):
                e, size = s + 1, len(texts[s])
                while e < len(texts) and size + len(texts[e]) <= AT_ONCE:
                    size += len(texts[e])
                    e += 1
                out[s:e] = _whole(m, texts[s]) if size > 4 * AT_ONCE else probability(m, pooled(m, *lay_out(texts[s:e]))[-1])
                s = e
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(out), pa.array((out >= 0.5).astype(np.int32))], ["doc_id", "held_out", "score", "predicted"])

    return docs.select(F.col("doc_id").cast("long"), held_out(F.col("doc_id")).alias("held_out"), F.col("text").cast("binary").alias("b")).mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int")


def _whole(m: dict, text: bytes) -> np.ndarray:
    """A very long text in pieces of whole chunks that share a step, so that memory stays bounded."""
    high, low, total, n = np.full(FILTERS, -np.inf), np.full(FILTERS, np.inf), np.zeros(FILTERS), 0
    size = AT_ONCE // (STEP * CHUNK) * STEP * CHUNK
    for s in range(0, len(text) + STEP, size):
        ids, _ = lay_out([text[s : s + size + STEP]])
        z = pooled(m, ids, np.zeros(1, np.int64))[2]
        if s + size < len(text) + STEP:
            z = z[: size // (STEP * CHUNK)]
        high, low, total, n = np.maximum(high, z.max(0)), np.minimum(low, z.min(0)), total + z.sum(0), n + len(z)
    return probability(m, np.concatenate([high, total / n, low])[None])


def op8_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return score_quality(docs, train(docs, table(spark, sf_dir, "labels")))
