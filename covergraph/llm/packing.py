"""Best-fit packing planned on the histogram of lengths."""

from __future__ import annotations

import bisect
import json
import re
import zlib
from array import array

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import rank_within, stage, table

LIMIT, END = 4096, 1
#: Words kept by each half of a task's cache.
CACHE = 300_000


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def _bytes_as_letters() -> list[str]:
    """The printable letter of each byte in byte-level vocabularies: itself where printable, else the next free one from 256 on."""
    own = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in own]
    return [chr(b if b in own else 256 + rest.index(b)) for b in range(256)]


class WordIds(dict):
    """Word -> its ids as little-endian 32-bit integers.

    A vocabulary that drops white space and splits by a pattern never joins
    across white space, so a text's ids are those of its words one after
    another. Words of ASCII and Latin-1 letters are lower-cased and split here
    and go straight to the merges; other words, and other kinds of vocabulary,
    take the library's whole path."""

    PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
    PLAIN = re.compile("[\x21-\x7eÀ-ÖØ-öø-ÿ]+")
    PARTS = re.compile("'s|'t|'re|'ve|'m|'ll|'d|[a-zß-öø-ÿ]+|[0-9]|[^a-z0-9ß-öø-ÿ]+")

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        super().__init__()
        self.encode, self.merge = (t := Tokenizer.from_file(path)).encode, t.model.tokenize
        made = json.loads(t.to_str())
        kinds = [x["type"] for x in (made["normalizer"] or {}).get("normalizers", [])]
        cut = (made["pre_tokenizer"] or {}).get("pretokenizers", [])
        self.by_word = kinds == ["NFC", "Replace", "Lowercase"] and [x["type"] for x in cut] == ["Split", "ByteLevel"] and cut[0]["pattern"] == {"Regex": self.PATTERN} and made["model"]["type"] == "BPE"
        self.special = [x["content"] for x in made["added_tokens"]]
        self.letters, self.older, self.parts = _bytes_as_letters(), {}, {}

    def part(self, part: str) -> bytes:
        found = self.parts.get(part)
        if found is None:
            if len(self.parts) >= CACHE:
                self.parts.clear()
            letters = part if part.isascii() else "".join(self.letters[b] for b in part.encode())
            found = array("I", [x.id for x in self.merge(letters)]).tobytes()
            if len(part) <= 40:
                self.parts[part] = found
        return found

    def __missing__(self, word: str) -> bytes:
        packed = self.older.get(word)
        if packed is None:
            if self.PLAIN.fullmatch(word) and not any(x in word for x in self.special):
                packed = b"".join(map(self.part, self.PARTS.findall(word.lower())))
            else:
                packed = array("I", self.encode(word, add_special_tokens=False).ids).tobytes()
        if len(word) <= 40:
            if len(self) >= CACHE:  # frequent words come back from the older half
                self.older = dict(self)
                self.clear()
            self[word] = packed
        return packed

    def ids(self, text: str) -> bytes:
        if not self.by_word:
            return array("I", self.encode(text, add_special_tokens=False).ids).tobytes()
        return b"".join(map(self.__getitem__, text.replace("\n", " ").split(" ")))


def pieces(docs: DataFrame, tokenizer: str, limit: int = LIMIT, end: int = END) -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32) of every whole text; a null text is empty and gives the end id alone."""
    tail = array("I", [end]).tobytes()

    def cut(batches):
        words = WordIds(tokenizer)
        for batch in batches:
            out = []
            for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                data = words.ids(text.as_py() or "") + tail
                for k, at in enumerate(range(0, len(data), 4 * limit)):
                    part = data[at : at + 4 * limit]
                    out.append((doc_id, k, at // 4, len(part) // 4, zlib.crc32(part)))
            kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True) if out else [()] * 5, kinds, strict=True)], ["doc_id", "piece", "start", "length", "ids_crc32"])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(cut, "doc_id long, piece int, start long, length long, ids_crc32 long")


def plan(counts: dict[int, int], limit: int = LIMIT) -> list[tuple[int, int, int, int, int]]:
    """Best fit, longest first, over counts: runs (length, first_rank, per_sequence, first_sequence, offset).

    Sequences with the same room left are one group, taken whole or split once,
    so time and runs follow the number of lengths (at most `limit`), not the
    number of documents. Rank r of a length goes to sequence
    first_sequence + (r - first_rank) // per_sequence of its run."""
    room: dict[int, list[tuple[int, int]]] = {}
    rooms: list[int] = []
    runs, opened = [], 0

    def put(left: int, first: int, n: int) -> None:
        if left and n:
            if left not in room:
                room[left] = []
                bisect.insort(rooms, left)
            room[left].append((first, n))

    for length in sorted(counts, reverse=True):
        left, rank = counts[length], 0
        while left:
            i = bisect.bisect_left(rooms, length)
            if i < len(rooms):
                space = rooms[i]
                first, n = room[space].pop()
                if not room[space]:
                    del room[space], rooms[i]
            else:
                space, first, n = limit, opened, -(-left // (limit // length))
                opened += n
            each = space // length
            full = min(n, left // each)
            runs += [(length, rank, each, first, limit - space)] * bool(full)
            put(space - each * length, first, full)
            rank, left = rank + full * each, left - full * each
            first, n = first + full, n - full
            if left and n:  # the last sequence takes fewer
                runs.append((length, rank, left, first, limit - space))
                put(space - left * length, first, 1)
                rank, left, first, n = rank + left, 0, first + 1, n - 1
            put(space, first, n)
    return runs


def pack(cut: DataFrame, limit: int = LIMIT) -> DataFrame:
    """Adds sequence_id and offset to staged pieces. The driver holds one count per length, at most `limit` of them."""
    counts = {int(k): int(n) for k, n in cut.groupBy("length").count().collect()}
    runs = np.array(sorted(plan(counts, limit)) or [(0, 0, 1, 0, 0)], np.int64)
    keys = (runs[:, 0] << 44) + runs[:, 1]
    names = [*cut.columns, "sequence_id", "offset"]

    def place(batches):
        for batch in batches:
            length, rank = (batch.column(batch.schema.get_field_index(c)).to_numpy(zero_copy_only=False) for c in ("length", "rank"))
            run = runs[np.searchsorted(keys, (length << 44) + rank, "right") - 1]
            at = rank - run[:, 1]
            yield pa.RecordBatch.from_arrays([batch.column(batch.schema.get_field_index(c)) for c in names[:-2]] + [pa.array(run[:, 3] + at // run[:, 2]), pa.array(run[:, 4] + at % run[:, 2] * length)], names)

    ranked = rank_within(cut, ["length"], ["doc_id", "piece"])
    return ranked.mapInArrow(place, ", ".join(f"{k} {t}" for k, t in cut.dtypes) + ", sequence_id long, offset long")


def pack_documents(docs: DataFrame, tokenizer: str | None = None, limit: int = LIMIT, end: int = END) -> DataFrame:
    """One row per piece with its place. An empty table gives no rows; repeated
    rows are packed each on its own; columns other than doc_id and text are left out."""
    return pack(stage(pieces(docs, tokenizer or default_tokenizer(), limit, end)), limit)


def op1_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(table(spark, sf_dir, "documents"))
