"""Removal of repeated byte strings: suffixes sorted by external induced sorting, in shards dealt by content.

Every window of `length` bytes belongs to its minimizer, the leftmost 16 bytes
of least hash in it, so equal windows meet in one shard whatever their
documents. A segment is a run of windows with one minimizer. Segments whose
minimizer stands in one document only can't repeat and stay where they are; of
equal segments one goes to its shard, with the smallest doc_id. A shard sorts
the suffixes of its segments with their common prefixes: a stretch of common
prefixes of `length` or more is one repeated string. A crowded minimizer, as at
the edge of a passage that very many documents go on from differently, would fill one
shard with different segments: they are cut into their windows, which are dealt by all
their bytes, so that no shard holds more than its share of them."""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import pyarrow.compute
import pyarrow.ipc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bucketed, scratch_dir, shuffle_width, squeeze, stage, table, unsqueeze
from .induced_sort import suffixes

LENGTH = 50
#: Bytes of a minimizer; bytes of text in a block (a longer document is one); windows hashed at once; bytes of text to a shard.
ANCHOR, BLOCK, STRETCH, SHARD = 16, 8 << 20, (1 << 20) - 256, 16 << 20
#: Different surroundings from which a minimizer is crowded.
CROWD = 1 << 14
NO_ID = np.iinfo(np.int64).max


BLOCKS = "block long, bytes long, text binary, ends binary, ids binary, segments binary, rest binary"


def _pack(length: int):
    def pack(batches):
        """Blocks of whole documents with their segments, their other columns as an Arrow stream."""
        from pyspark import TaskContext

        part, at, held, size = TaskContext.get().partitionId() << 32, 0, [], 0

        def flush(rows):
            whole = pa.Table.from_batches(rows).combine_chunks()
            texts = whole.column("_bytes").to_pylist()
            rest = whole.drop_columns(["_bytes", "_id"])
            sink = pa.BufferOutputStream()
            with pa.ipc.new_stream(sink, rest.schema) as w:
                w.write_table(rest)
            ids = np.array([NO_ID if x is None else x for x in whole.column("_id").to_pylist()], np.int64)
            text, ends = b"".join(x or b"" for x in texts), np.cumsum([len(x or b"") for x in texts], dtype=np.int64)
            row = (part + at, len(text), text, ends.tobytes(), ids.tobytes(), segments(text, ends, length), sink.getvalue().to_pybytes())
            names = [c.split() for c in BLOCKS.split(", ")]
            return pa.RecordBatch.from_arrays([pa.array([x], pa.int64() if k == "long" else pa.binary()) for x, (_, k) in zip(row, names, strict=True)], [n for n, _ in names])

        for batch in batches:
            lengths = pa.compute.fill_null(pa.compute.binary_length(batch.column(batch.schema.get_field_index("_bytes"))), 0).to_pylist()
            start = 0
            for i, n in enumerate(lengths):
                if size and size + n > BLOCK:
                    held.append(batch.slice(start, i - start))
                    yield flush(held)
                    at, held, size, start = at + 1, [], 0, i
                size += n
            held.append(batch.slice(start))
        if sum(b.num_rows for b in held):
            yield flush(held)

    return pack


def segments(text: bytes, ends: np.ndarray, length: int) -> bytes:
    """Runs of windows with one minimizer: gaps between their first windows, windows, and the minimizer's place in them; built once, a few bytes each."""
    n = len(text) - length + 1
    stop = np.repeat(ends, np.diff(np.r_[0, ends])) if n > 0 else ends
    parts = [_stretch(text, s, min(STRETCH, n - s), stop, length) for s in range(0, n, STRETCH)]
    start, run, anchor = (np.concatenate([p[i] for p in parts]) if parts else np.empty(0, np.int64) for i in range(3))
    gaps = squeeze(np.diff(start, prepend=0))
    return len(start).to_bytes(8, "little") + len(gaps).to_bytes(8, "little") + gaps + squeeze(run.astype(np.uint8)) + (anchor - start).astype(np.uint8).tobytes()


def _hash(text: bytes, places) -> np.ndarray:
    """64-bit hashes of the ANCHOR bytes at places, an array or a slice."""
    n = len(text) - 7
    h = None
    for offset, by in ((0, 0x9E3779B97F4A7C15), (8, 0xC2B2AE3D27D4EB4F)):
        eight = np.ndarray((n - offset,), "<u8", text, offset, (1,))[places] * np.uint64(by)
        h = eight if h is None else h ^ eight
        h ^= h >> np.uint64(29)
        h *= np.uint64(0xD6E8FEB86659FD93)
    return h ^ h >> np.uint64(32)


def _stretch(text: bytes, s: int, n: int, stop: np.ndarray, length: int):
    """(first window, windows, minimizer's place) of the segments of n windows from s on."""
    low = np.uint64((1 << 20) - 1)
    places = n + length - ANCHOR
    h = _hash(text, slice(s, s + places))
    least, width, whole = h & ~low | np.arange(places, dtype=np.uint64), 1, length - ANCHOR + 1
    while 2 * width <= whole:
        least = np.minimum(least[:-width], least[width:])
        width *= 2
    if width < whole:
        least = np.minimum(least[: len(least) - (whole - width)], least[whole - width :])
    inside = np.arange(s + length, s + length + n) <= stop[s : s + n]
    first = np.flatnonzero(np.r_[True, (least[1:] != least[:-1]) | (inside[1:] != inside[:-1])])
    run = np.diff(np.r_[first, n])
    first, run = first[inside[first]], run[inside[first]]
    return first + s, run, (least[first] & low).astype(np.int64) + s


class Block:
    """A block's text, its documents' ends and ids, and its segments: first window, windows, minimizer's hash and place."""

    def __init__(self, row: pa.Table, length: int):
        self.length, self.row = length, row
        self.id = row.column("block")[0].as_py()
        self.text = row.column("text")[0].as_py()
        self.ends, self.ids = (np.frombuffer(row.column(c)[0].as_py(), np.int64) for c in ("ends", "ids"))
        packed = row.column("segments")[0].as_py()
        n, gaps = int.from_bytes(packed[:8], "little"), int.from_bytes(packed[8:16], "little")
        self.start = np.cumsum(unsqueeze(packed[16 : 16 + gaps], np.int64))
        self.run = unsqueeze(packed[16 + gaps : len(packed) - n], np.uint8).astype(np.int64)
        self.anchor = self.start + np.frombuffer(packed[len(packed) - n :], np.uint8)
        self.hash = _hash(self.text, self.anchor) if n else np.empty(0, np.uint64)
        self.doc = np.searchsorted(self.ends, self.start, "right")

    def keys(self) -> np.ndarray:
        return np.unique(self.hash)

    def surroundings(self) -> np.ndarray:
        """How many segments that begin or end differently each of the keys has here; a figure that only tells the crowded apart."""
        keys, of, n = np.unique(self.hash, return_inverse=True, return_counts=True)
        several = np.flatnonzero(n[of] > 1)
        ends = self.start[several] + self.run[several] + self.length - 1 - ANCHOR
        met = np.stack([of[several].astype(np.uint64), _hash(self.text, self.start[several]) ^ _hash(self.text, ends) * np.uint64(3)], 1) if len(several) else np.empty((0, 2), np.uint64)
        met = met[np.lexsort((met[:, 1], met[:, 0]))]
        fresh = np.r_[True, (met[1:] != met[:-1]).any(axis=1)][: len(met)]
        return np.maximum(np.bincount(met[fresh, 0].astype(np.int64), minlength=len(keys)), 1)

    def repeated(self, shards: int, answers: list[tuple[int, bytes, bytes | None]]) -> Parts:
        """The segments whose minimizer stands in another document too, those of crowded minimizers window by window."""
        keys = self.keys()
        of = np.searchsorted(keys, self.hash)
        low, high = np.full(len(keys), NO_ID), np.full(len(keys), np.iinfo(np.int64).min)
        np.minimum.at(low, of, self.ids[self.doc])
        np.maximum.at(high, of, self.ids[self.doc])
        wide, crowded = low != high, np.zeros(len(keys), bool)
        for part, (_, bits, crowd) in zip(deal(keys, shards, [a[0] for a in answers]), answers, strict=True):
            wide[part] |= np.unpackbits(np.frombuffer(bits, np.uint8), count=len(part)).astype(bool)
            if crowd is not None:
                crowded[part] = np.unpackbits(np.frombuffer(crowd, np.uint8), count=len(part)).astype(bool)
        whole, cut = np.flatnonzero((wide & ~crowded)[of]), np.flatnonzero((wide & crowded)[of])
        n = self.run[cut]
        windows = _ranges(self.start[cut], n)
        every = np.zeros(len(windows), np.uint64)
        for o in [*range(0, self.length - ANCHOR, ANCHOR), self.length - ANCHOR] if len(cut) else []:
            every = every * np.uint64(0x9E3779B97F4A7C15) ^ _hash(self.text, windows + o)
        join = lambda a, b: np.concatenate([a, b])
        start, run = join(self.start[whole], windows), join(self.run[whole], np.ones_like(windows))
        offset = join(self.anchor[whole] - self.start[whole], np.repeat(self.anchor[cut], n) - windows)
        return Parts(self.text, self.length, start, run, offset, join(self.hash[whole], every), self.ids[join(self.doc[whole], np.repeat(self.doc[cut], n))])


class Parts:
    """Parts of a block that others are asked about: their places, the keys they are dealt by, their documents' ids; which
    content each has; of the distinct contents the first part and the smallest id."""

    def __init__(self, text: bytes, length: int, start, run, offset, key, mine):
        self.start, self.run, self.offset, self.key, self.mine = start, run, offset, key, mine
        known: dict[bytes, int] = {}
        self.which = np.array([known.setdefault(text[i:j], len(known)) for i, j in zip(start.tolist(), (start + run + length - 1).tolist(), strict=True)], np.int64)
        self.contents = list(known)
        self.first = np.unique(self.which, return_index=True)[1]
        self.least = np.full(len(known), NO_ID)
        np.minimum.at(self.least, self.which, mine)


def deal(keys: np.ndarray, shards: int, wanted: list[int]) -> list[np.ndarray]:
    """Places of the keys of each wanted shard, in order."""
    shard = (keys % np.uint64(shards)).astype(np.int64)
    order = np.argsort(shard, kind="stable")
    at = np.searchsorted(shard[order], np.arange(shards + 1))
    return [order[at[s] : at[s + 1]] for s in wanted]


def _tables(rows: list[tuple], names: list[str]) -> pa.Table:
    kinds = [pa.int64() if c in ("shard", "block") else pa.binary() for c in names]
    return pa.table([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], names=names)


ASKED, ANSWERED = ["shard", "block", "keys", "around"], ["shard", "block", "bits", "crowded", "windows"]


def _ask_anchors(length: int, shards: int):
    def ask(batches):
        for batch in batches:
            for i in range(batch.num_rows):
                b = Block(pa.Table.from_batches([batch.slice(i, 1)]), length)
                keys, around = b.keys(), np.minimum(b.surroundings(), np.iinfo(np.uint32).max).astype(np.uint32)
                rows = [(s, b.id, keys[p].tobytes(), around[p].tobytes()) for s, p in enumerate(deal(keys, shards, range(shards))) if len(p)]
                yield from _tables(rows, ASKED).to_batches()

    return ask


def _elsewhere(crowd: int):
    def elsewhere(group: pa.Table) -> pa.Table:
        """One shard's minimizers: whether each stands in another block too, and which are crowded."""
        keys, around = ([np.frombuffer(x.as_py(), kind) for x in group.column(c)] for c, kind in (("keys", np.uint64), ("around", np.uint32)))
        _, where, count = np.unique(np.concatenate(keys), return_inverse=True, return_counts=True)
        more, at = count[where] > 1, np.cumsum([0, *map(len, keys)])
        many = (np.bincount(where, np.concatenate(around)) > crowd)[where]
        bits = lambda x: np.packbits(x).tobytes()
        rows = [(s, b, bits(more[i:j]), bits(many[i:j]) if many[i:j].any() else None, None) for s, b, i, j in zip(group.column("shard").to_pylist(), group.column("block").to_pylist(), at[:-1], at[1:], strict=True)]
        return _tables(rows, ANSWERED)

    return elsewhere


def _answers(answers: pa.Table, name: str, *also: str) -> list[tuple]:
    found = zip(*(answers.column(c).to_pylist() for c in ("shard", name, *also)), strict=True)
    return sorted((row for row in found if row[1] is not None), key=lambda row: row[0])


SENT = ["shard", "block", "keys", "ids", "runs", "offsets", "text"]


def _ask_segments(length: int, shards: int):
    def ask(key, blocks: pa.Table, answers: pa.Table) -> pa.Table:
        from zstandard import ZstdCompressor

        if not blocks.num_rows:
            return _tables([], SENT)
        b = Block(blocks, length)
        parts = b.repeated(shards, _answers(answers, "bits", "crowded"))
        rows = []
        for s, p in enumerate(deal(parts.key[parts.first], shards, range(shards))):
            if len(p):
                i = parts.first[p]
                rows.append((s, b.id, parts.key[i].astype(np.uint32).tobytes(), parts.least[p].tobytes(), parts.run[i].astype(np.uint16).tobytes(), parts.offset[i].astype(np.uint16).tobytes(), ZstdCompressor(level=1).compress(b"".join([parts.contents[k] for k in p.tolist()]))))
        return _tables(rows, SENT)

    return ask


def _ranges(starts: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """starts[0], starts[0] + 1, ... for each start and count."""
    return np.repeat(starts - np.r_[0, np.cumsum(counts)[:-1]], counts) + np.arange(counts.sum())


def _sort(length: int, scratch: str | None):
    def sort(group: pa.Table) -> pa.Table:
        """One shard: the smallest id in which each window stands, and for each block which windows of its segments stand in a smaller one."""
        from zstandard import ZstdDecompressor

        get = lambda c, kind: [np.frombuffer(x.as_py(), kind) for x in group.column(c)]
        ids, runs, offsets, keys = (get(c, k) for c, k in (("ids", np.int64), ("runs", np.uint16), ("offsets", np.uint16), ("keys", np.uint32)))
        known: dict[bytes, int] = {}
        which = []
        for text, run in zip(group.column("text"), runs, strict=True):
            raw = ZstdDecompressor().decompress(text.as_py())
            at = np.r_[0, np.cumsum(run.astype(np.int64) + length - 1)].tolist()
            which.append(np.array([known.setdefault(raw[i:j], len(known)) for i, j in zip(at[:-1], at[1:], strict=True)], np.int64))
        contents, every = list(known), np.concatenate(which)
        first = np.unique(every, return_index=True)[1]
        least = np.full(len(contents), NO_ID)
        np.minimum.at(least, every, np.concatenate(ids))
        run, offset, key = (np.concatenate(x)[first] for x in (runs, offsets, keys))
        window_at = np.r_[0, np.cumsum(run.astype(np.int64))]
        smallest = np.repeat(least, run)
        chosen = rivals(contents, key, offset, length)
        if len(chosen):
            text = b"".join(contents[i] + b"\x00" for i in chosen.tolist())
            t = np.frombuffer(text, np.uint8).astype(np.int64) + 2
            sizes = run[chosen].astype(np.int64) + length
            ends = np.cumsum(sizes)
            t[ends - 1] = 1  # no match crosses a segment's end
            order, common = suffixes(np.r_[t, 0], length, scratch=scratch)
            owner = np.full(len(t) + 1, NO_ID)
            places = _ranges(ends - sizes, run[chosen].astype(np.int64))
            owner[places] = np.repeat(least[chosen], run[chosen])
            heads = np.flatnonzero(np.r_[True, common[1:] < length])
            found = np.repeat(np.minimum.reduceat(owner[order], heads), np.diff(np.r_[heads, len(order)]))
            back = np.empty(len(order), np.int64)
            back[order] = found
            smallest[_ranges(window_at[chosen], run[chosen].astype(np.int64))] = back[places]
        rows = []
        for s, b, w, i in zip(group.column("shard").to_pylist(), group.column("block").to_pylist(), which, ids, strict=True):
            n = run[w].astype(np.int64)
            rows.append((s, b, None, None, np.packbits(smallest[_ranges(window_at[w], n)] < np.repeat(i, n)).tobytes()))
        return _tables(rows, ANSWERED)

    return sort


def rivals(contents: list[bytes], key: np.ndarray, offset: np.ndarray, length: int) -> np.ndarray:
    """Contents that may share a window with a different one: a window around a minimizer reaches half of its other
    bytes to the left of it or to the right, so one of these two strings is in another content too."""
    _, of, n = np.unique(key, return_inverse=True, return_counts=True)
    half = (length - ANCHOR + 1) // 2
    met: dict[tuple[bool, bytes], int] = {}
    near, out = [], np.zeros(len(contents), bool)
    for i in np.flatnonzero(n[of] > 1).tolist():
        c, o = contents[i], int(offset[i])
        for side, x in ((False, c[o - half : o + ANCHOR] if o >= half else b""), (True, c[o : o + ANCHOR + half])):
            if len(x) == ANCHOR + half:
                other = met.setdefault((side, x), i)
                if other != i:
                    near.append(other)
                    out[i] = True
    out[near] = True
    return np.flatnonzero(out)


def _finish(length: int, shards: int, digest: bool, names: list[str]):
    def finish(key, blocks: pa.Table, answers: pa.Table) -> pa.Table:
        b = Block(blocks, length)
        parts = b.repeated(shards, _answers(answers, "bits", "crowded"))
        hit = np.zeros(len(b.text) + 1, np.int8)
        run = parts.run[parts.first]
        bit_at = np.r_[0, np.cumsum(run)]
        bits = np.zeros(bit_at[-1], bool)
        windows = _answers(answers, "windows")
        for p, (_, x) in zip(deal(parts.key[parts.first], shards, [a[0] for a in windows]), windows, strict=True):
            count = run[p]
            bits[_ranges(bit_at[p], count)] = np.unpackbits(np.frombuffer(x, np.uint8), count=int(count.sum())).astype(bool)
        if len(parts.start):
            hit[_ranges(parts.start, parts.run)] = bits[_ranges(bit_at[parts.which], parts.run)] | np.repeat(parts.mine > parts.least[parts.which], parts.run)
        run = np.cumsum(hit[:-1], dtype=np.int32)
        run[length:] -= run[:-length].copy() if len(run) > length else 0
        gone = run > 0
        ends, starts = b.ends, np.r_[0, b.ends[:-1]]
        total = np.r_[0, np.cumsum(gone)]
        fresh = gone & ~np.r_[False, gone[:-1]]
        fresh[starts[starts < len(gone)]] |= gone[starts[starts < len(gone)]]
        spans = np.r_[0, np.cumsum(fresh)]
        n_removed = total[ends] - total[starts]
        kept = np.frombuffer(b.text, np.uint8)
        rest = pa.ipc.open_stream(blocks.column("rest")[0].as_py()).read_all()
        if digest:
            left = [kept[s:e][~gone[s:e]].tobytes() if r else b.text[s:e] for s, e, r in zip(starts, ends, n_removed, strict=True)]
            new = {"_n_bytes": pa.array(ends - starts), "_n_removed": pa.array(n_removed), "_n_spans": pa.array(spans[ends] - spans[starts]), "_kept_sha256": pa.array([hashlib.sha256(x).hexdigest() for x in left])}
        else:
            inner = (kept & 0xC0) == 0x80
            gone = whole_characters(gone, inner)
            new = {"_text": pa.array([kept[s:e][~gone[s:e]].tobytes().decode("utf-8", "replace") for s, e in zip(starts, ends, strict=True)])}
        return pa.table({c: new[c] if c in new else rest.column(c) for c in names})

    return finish


def whole_characters(gone: np.ndarray, inner: np.ndarray) -> np.ndarray:
    """Removed bytes, less those of characters that are removed in part."""
    first = np.flatnonzero(~inner)
    if not len(first):
        return gone & False
    size = np.diff(np.r_[first, len(gone)])
    all_gone = np.logical_and.reduceat(gone[first[0] :], first - first[0])
    return np.r_[np.zeros(first[0], bool), np.repeat(all_gone, size)]


def remove_repeats(docs: DataFrame, length: int = LENGTH, digest: bool = False, crowd: int = CROWD) -> DataFrame:
    """docs with every byte removed that a string of `length` (32 to 254) bytes covers which also starts in a document of smaller doc_id.

    digest: the other columns with n_bytes, n_removed, n_spans and kept_sha256
    (replaced where the caller has such) instead of the text; else the text keeps whole characters (one that would be
    cut stays), null becomes empty. A null doc_id comes after all others; rows of
    one id don't remove each other's bytes; an empty table gives no rows. Blocks
    of text lie in a table in the shared folder, bucketed by block, so answers
    travel to the text and not the text to them. crowd: different surroundings
    from which a minimizer's segments are dealt window by window; results are the same."""
    spark = docs.sparkSession
    names = docs.columns
    kept = [f"_c{i}" for i, c in enumerate(names) if c != "text"]  # the caller's names may clash with ours, these don't
    rest = [c for c in names if c != "text"]
    packed = docs.select(*[F.col(f"`{c}`").alias(k) for k, c in zip(kept, rest, strict=True)], F.col("doc_id").cast("long").alias("_id"), F.col("text").cast("binary").alias("_bytes")).mapInArrow(_pack(length), BLOCKS)
    blocks = bucketed(packed, "block", "text_blocks", docs)
    size = blocks.agg(F.coalesce(F.sum("bytes"), F.lit(0))).first()[0]
    shards = max(shuffle_width(spark), -(-size // SHARD))
    kinds = lambda names: ", ".join(f"{c} {'long' if c in ('shard', 'block') else 'binary'}" for c in names)
    light = blocks.select("block", "text", "ends", "ids", "segments")
    anchors = light.mapInArrow(_ask_anchors(length, shards), kinds(ASKED))
    elsewhere = stage(anchors.groupBy("shard").applyInArrow(_elsewhere(crowd), kinds(ANSWERED)))
    sent = light.groupBy("block").cogroup(elsewhere.groupBy("block")).applyInArrow(_ask_segments(length, shards), kinds(SENT))
    windows = stage(sent.groupBy("shard").applyInArrow(_sort(length, scratch_dir(spark)), kinds(ANSWERED)))
    kind = lambda c: docs.schema[c].dataType.simpleString()
    new = [("_n_bytes", "n_bytes", "long"), ("_n_removed", "n_removed", "long"), ("_n_spans", "n_spans", "long"), ("_kept_sha256", "kept_sha256", "string")] if digest else [("_text", "text", "string")]
    schema = ", ".join([*[f"{k} {kind(c)}" for k, c in zip(kept, rest, strict=True)], *[f"{k} {t}" for k, _, t in new]])
    done = blocks.groupBy("block").cogroup(elsewhere.unionByName(windows).groupBy("block")).applyInArrow(_finish(length, shards, digest, [*kept, *[k for k, _, _ in new]]), schema)
    called = dict([*zip(rest, kept, strict=True), *[(c, k) for k, c, _ in new]])
    order = [*[c for c in rest if c not in RESULT], *RESULT] if digest else names
    return done.select(*[F.col(called[c]).alias(c) for c in order])


RESULT = ("n_bytes", "n_removed", "n_spans", "kept_sha256")


def op4_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeats(table(spark, sf_dir, "documents").select("doc_id", "text"), digest=True)
