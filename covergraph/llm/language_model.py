"""LM scoring with a weighted backoff automaton.

States are the n-grams, up to ORDER - 1 words, that training texts hold twice or
more (single words: once); an arc leaves a state for each word seen after it, and
a failure arc leads to the state that is one word shorter, down to the root.
Documents become blocks of local word numbers. Order by order a block asks the
shards of the corpus for the arcs of the states that its texts reach, so it gets
its part of the automaton, whatever the size of the whole model."""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bucketed, pieces, shuffle_width, squeeze, stage, table, unsqueeze

#: Fixed by the contract: additive smoothing of single words.
ADD = 0.1
#: Words of the longest arc, with the state that it leaves; weight of a failure arc against a state's count (held-out texts
#: of sf0.1: log10 of -3.76 a token, -4.13 with a weight of 1, -4.26 by single words).
ORDER, FAIL = 4, 8.0
#: Occurrences that make an n-gram of two words or more a state.
SEEN = 2
#: Tokens of a block (a longer document is a block of its own); tokens of the corpus to a shard; bytes split at once.
BLOCK, SHARD, PIECE = 1 << 20, 1 << 22, 1 << 22
#: Bits of an n-gram's key beyond those that number all tokens: one n-gram in 2**SPARE shares a key, at any size.
SPARE = 24
END, START = b"", b"\n"  # no word is empty or holds white space


def held_out(doc_id) -> bool:
    """crc32 of the id as text, mod 10; a null id is text of no characters."""
    return zlib.crc32(b"" if doc_id is None else str(doc_id).encode()) % 10 == 0


BLOCKS = "block long, n long, docs binary, no_id binary, ends binary, tokens binary, words binary"


def _table(rows: list[tuple], schema: str) -> pa.Table:
    kinds = {"long": pa.int64(), "binary": pa.binary()}
    names = [c.split() for c in schema.split(", ")]
    return pa.table([pa.array([r[i] for r in rows], kinds[k]) for i, (_, k) in enumerate(names)], names=[n for n, _ in names])


class Numbers(dict):
    """Word -> its number in the block."""

    def __missing__(self, word: bytes) -> int:
        n = self[word] = len(self)
        return n


def _blocks(batches):
    """Blocks of whole documents: token numbers into the block's words, which are 128-bit hashes in order."""
    from pyspark import TaskContext
    from xxhash import xxh3_128_digest

    part, at = TaskContext.get().partitionId(), 0
    numbers = Numbers()
    ids, ends, tokens, n = [], [], [], 0

    def flush():
        keys = np.frombuffer(b"".join(map(xxh3_128_digest, numbers)), ">u8").reshape(-1, 2).astype(np.uint64)
        order = np.lexsort((keys[:, 1], keys[:, 0]))
        back = np.empty(len(order), np.uint32)
        back[order] = np.arange(len(order), dtype=np.uint32)
        keys = keys[order]
        row = (part << 32 | at, n, squeeze(np.array([d or 0 for d in ids], np.int64)), squeeze(np.array([d is None for d in ids])), squeeze(np.array(ends, np.int64)), squeeze(back[np.concatenate(tokens)]), squeeze(np.diff(keys[:, 0], prepend=np.uint64(0))) + keys[:, 1].tobytes())
        return _table([row], BLOCKS).to_batches()[0]

    for batch in batches:
        for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
            seen = [np.array([numbers[START]], np.uint32)]
            for piece in pieces((text.as_py() or b"").lower(), PIECE):
                seen.append(np.array(list(map(numbers.__getitem__, piece.split())), np.uint32))
            seen.append(np.array([numbers[END]], np.uint32))
            size = sum(map(len, seen))
            ids.append(doc_id)
            tokens += seen
            n += size
            ends.append(n)
            if n >= BLOCK:
                yield flush()
                numbers, ids, ends, tokens, n, at = Numbers(), [], [], [], 0, at + 1
    if ids:
        yield flush()


def _mix(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """A 64-bit hash of two."""
    h = a * np.uint64(0x9E3779B97F4A7C15) ^ (b + np.uint64(0x7F4A7C15)) * np.uint64(0xC2B2AE3D27D4EB4F)
    for _ in range(2):
        h ^= h >> np.uint64(29)
        h *= np.uint64(0x165667B19E3779F9)
    return h ^ h >> np.uint64(32)


class Block:
    """A block's documents, each with a start before its tokens, and the n-grams that end at each place."""

    def __init__(self, row: pa.Table, bits: int):
        get = lambda c, kind: unsqueeze(row.column(c)[0].as_py(), kind)
        self.id, self.bits = row.column("block")[0].as_py(), np.uint64(64 - bits)
        self.docs, self.no_id, self.ends = get("docs", np.int64), get("no_id", bool), get("ends", np.int64)
        self.tokens = get("tokens", np.uint32).astype(np.int64)
        words = row.column("words")[0].as_py()
        n = int(self.tokens.max()) + 1
        self.low = np.frombuffer(words[len(words) - 8 * n :], np.uint64)
        self.high = np.cumsum(unsqueeze(words[: len(words) - 8 * n], np.uint64), dtype=np.uint64)
        self.first = np.r_[0, self.ends[:-1]]
        self.held = np.array([held_out(None if x else d) for d, x in zip(self.docs.tolist(), self.no_id.tolist(), strict=True)])
        self.train = np.repeat(~self.held, np.diff(np.r_[0, self.ends]))
        self.word = _mix(self.high, self.low)[self.tokens]
        self.place = np.arange(len(self.tokens)) - np.repeat(self.first, np.diff(np.r_[0, self.ends]))
        self.gram = self.word

    def arcs(self, order: int, states: np.ndarray | None):
        """The next order's arcs: (places they end at, their distinct keys in order, which is each place's). Called for 2, 3, ...

        states: occurrences of the n-gram of order - 1 that ends at each place."""
        self.gram = np.r_[np.uint64(0), _mix(self.gram[:-1], self.word[1:])]
        open_ = self.place >= order - 1
        if states is not None:
            open_[1:] &= states[:-1] >= SEEN
        at = np.flatnonzero(open_)
        keys, which = np.unique(self.gram[at] >> self.bits, return_inverse=True)
        return at, keys, which

    def counted(self, answers: list[list[tuple[int, bytes]]]):
        """Yields (order, places, occurrences of the arc that ends there, of the state that it leaves) for each order answered."""
        states = None
        for order, mine in enumerate(answers, 2):
            at, _, which = self.arcs(order, states)
            counts = np.concatenate([unsqueeze(x, np.uint64) for _, x in sorted(mine)]).astype(np.int64) if mine else np.empty(0, np.int64)
            after = np.zeros(len(self.tokens), np.int64)
            after[at] = counts[which]
            yield order, at, after, states
            states = after


def _cuts(keys: np.ndarray, shards: int, bits: int) -> np.ndarray:
    """Where each shard, a range of keys, begins among keys in order."""
    bounds = np.array([s * (1 << bits) // shards for s in range(1, shards)], np.uint64)
    return np.r_[0, np.searchsorted(keys, bounds), len(keys)].tolist()


ARCS, ARC_ANSWERS = "shard long, block long, keys binary, counts binary", "shard long, block long, arc long, counts binary"
WORDS, WORD_ANSWERS = "shard long, block long, keys binary, low binary, counts binary", "shard long, block long, arc long, counts binary, v long"


def _messages(b: Block, keys: np.ndarray, counts: np.ndarray, shards: int, bits: int) -> list[tuple]:
    at = _cuts(keys, shards, bits)
    return [(s, b.id, squeeze(np.diff(keys[i:j], prepend=np.uint64(s * (1 << bits) // shards))), squeeze(counts[i:j].astype(np.uint32))) for s, (i, j) in enumerate(zip(at[:-1], at[1:], strict=True)) if i < j]


def _asked(b: Block, order: int, states: np.ndarray | None, shards: int, bits: int) -> pa.Table:
    at, keys, which = b.arcs(order, states)
    return _table(_messages(b, keys, np.bincount(which[b.train[at]], minlength=len(keys)), shards, bits), ARCS)


def _listed(answers: pa.Table, orders) -> list[list[tuple[int, bytes]]]:
    out = {k: [] for k in orders}
    for k, s, x in zip(answers.column("arc").to_pylist(), answers.column("shard").to_pylist(), answers.column("counts").to_pylist(), strict=True):
        out[k].append((s, x))
    return [out[k] for k in orders]


def _ask_first(shards: int, bits: int):
    def ask(batches):
        for batch in batches:
            for i in range(batch.num_rows):
                yield from _asked(Block(pa.Table.from_batches([batch.slice(i, 1)]), bits), 2, None, shards, bits).to_batches()

    return ask


def _ask_next(order: int, shards: int, bits: int):
    def ask(key, blocks: pa.Table, answers: pa.Table) -> pa.Table:
        """Arcs of an order from the states that the answers for shorter ones show."""
        if not blocks.num_rows:
            return _table([], ARCS)
        b = Block(blocks, bits)
        for _, _, after, _ in b.counted(_listed(answers, range(2, order))):
            states = after
        return _asked(b, order, states, shards, bits)

    return ask


def _sum_arcs(order: int, shards: int, bits: int):
    def total(group: pa.Table) -> pa.Table:
        """One shard: occurrences of each arc over all blocks."""
        shard, blocks = group.column("shard").to_pylist(), group.column("block").to_pylist()
        keys = [np.cumsum(unsqueeze(x.as_py(), np.uint64), dtype=np.uint64) + np.uint64(s * (1 << bits) // shards) for s, x in zip(shard, group.column("keys"), strict=True)]
        count = np.concatenate([unsqueeze(x.as_py(), np.uint32) for x in group.column("counts")])
        distinct, where = np.unique(np.concatenate(keys), return_inverse=True)
        answer = np.bincount(where, count, len(distinct)).astype(np.uint64)[where]
        at = np.cumsum([0, *map(len, keys)])
        return _table([(s, b, order, squeeze(answer[i:j])) for s, b, i, j in zip(shard, blocks, at[:-1], at[1:], strict=True)], ARC_ANSWERS)

    return total


def _ask_words(shards: int):
    def ask(batches):
        for batch in batches:
            for i in range(batch.num_rows):
                b = Block(pa.Table.from_batches([batch.slice(i, 1)]), 64)
                counts = np.bincount(b.tokens[b.train], minlength=len(b.high))
                at = _cuts(b.high, shards, 64)
                rows = [(s, b.id, b.high[i:j].tobytes(), b.low[i:j].tobytes(), squeeze(counts[i:j])) for s, (i, j) in enumerate(zip(at[:-1], at[1:], strict=True)) if i < j]
                yield from _table(rows, WORDS).to_batches()

    return ask


def _sum_words(group: pa.Table) -> pa.Table:
    """One shard: occurrences of each word, by all 128 bits, over all blocks; v: words that training texts hold, starts among them."""
    high, low = (np.concatenate([np.frombuffer(x.as_py(), np.uint64) for x in group.column(c)]) for c in ("keys", "low"))
    parts = [unsqueeze(x.as_py(), np.int64) for x in group.column("counts")]
    order = np.lexsort((low, high))
    fresh = np.r_[True, (high[order][1:] != high[order][:-1]) | (low[order][1:] != low[order][:-1])]
    where = np.empty(len(order), np.int64)
    where[order] = np.cumsum(fresh) - 1
    sums = np.bincount(where, np.concatenate(parts)).astype(np.int64)
    answer, at = sums[where], np.cumsum([0, *map(len, parts)])
    rows = [(s, b, 1, squeeze(answer[i:j].astype(np.uint64)), 0) for s, b, i, j in zip(group.column("shard").to_pylist(), group.column("block").to_pylist(), at[:-1], at[1:], strict=True)]
    rows[0] = (*rows[0][:-1], int((sums > 0).sum()))
    return _table(rows, WORD_ANSWERS)


class Automaton:
    """Weighted backoff automaton over one block.

    After each token the state is the longest n-gram ending there that is one;
    it is at most a word longer than the state before. A state of count c gives
    the arc of a word seen n times after it (n + FAIL * w) / (c + FAIL), where w
    is what the shorter state gives the word, and its failure arc
    FAIL / (c + FAIL); so the weights of a state sum to one."""

    def __init__(self, root: np.ndarray):
        self.weight = root  # of single words, at each place

    def follow(self, places: np.ndarray, arcs: np.ndarray, states: np.ndarray) -> None:
        """Goes from the shorter states to those of the next order, at the places whose state is that long."""
        c = states[places - 1]
        known = c > 0
        at, c = places[known], c[known]
        self.weight[at] = (arcs[at] + FAIL * self.weight[at]) / (c + FAIL)

    def traverse(self, first: np.ndarray, start: np.ndarray) -> np.ndarray:
        """Log-probabilities summed along each text, the start, which is given, left out."""
        self.weight[start] = 1.0
        return np.add.reduceat(np.log10(self.weight), first)


SCORES = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"


def _score(order: int, bits: int, total: int, vocabulary: int):
    def score(key, blocks: pa.Table, answers: pa.Table) -> pa.Table:
        b = Block(blocks, bits)
        words, *arcs = _listed(answers, range(1, order + 1))
        c = np.concatenate([unsqueeze(x, np.uint64) for _, x in sorted(words)]).astype(np.int64)[b.tokens]
        root = (c + ADD) / (total + ADD * (vocabulary + 1))
        root[b.first] = 1.0
        base = np.add.reduceat(np.log10(root), b.first)
        known = c > 0
        known[b.first] = False
        model, states = Automaton(root), c
        for _, at, after, _ in b.counted(arcs):
            model.follow(at, after, states)
            states = after
        return pa.table({"doc_id": pa.array(b.docs, mask=b.no_id), "held_out": b.held, "n_tokens": b.ends - b.first - 1, "n_known": np.add.reduceat(known.astype(np.int64), b.first), "train_tokens": np.full(len(b.ends), total), "base_score": base, "score": model.traverse(b.first, b.first)})

    return score


def score_documents(docs: DataFrame, order: int = ORDER) -> DataFrame:
    """A row per document: token counts, the unigram score and the automaton's log10 probability of the whole text.

    Learns from rows whose id is not held out; counts take in every such row.
    Words meet by 128-bit hashes, n-grams by keys that grow with the corpus, of
    which one in 2**SPARE is shared. A null or empty text is the end token
    alone; repeated rows count and score each on its own; an empty table gives no
    rows; other columns are left out. order: 2 or more."""
    spark = docs.sparkSession
    blocks = bucketed(docs.select(F.col("doc_id").cast("long"), F.col("text").cast("binary")).mapInArrow(_blocks, BLOCKS), "block", "token_blocks", docs)
    size = blocks.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    bits, shards = min(64, SPARE + max(1, int(size).bit_length())), max(shuffle_width(spark), -(-size // SHARD))
    words = stage(blocks.mapInArrow(_ask_words(shards), WORDS).groupBy("shard").applyInArrow(_sum_words, WORD_ANSWERS))
    asked = blocks.mapInArrow(_ask_first(shards, bits), ARCS)
    answers = None
    for k in range(2, order + 1):
        one = stage(asked.groupBy("shard").applyInArrow(_sum_arcs(k, shards, bits), ARC_ANSWERS))
        answers = one if answers is None else answers.unionByName(one)
        if k < order:
            asked = blocks.groupBy("block").cogroup(answers.groupBy("block")).applyInArrow(_ask_next(k + 1, shards, bits), ARCS)
    vocabulary = words.agg(F.coalesce(F.sum("v"), F.lit(0))).first()[0]
    total = blocks.mapInArrow(_trained, "n long, texts long").agg(F.coalesce(F.sum("n"), F.lit(0)), F.coalesce(F.sum("texts"), F.lit(0))).first()
    every = answers.unionByName(words.drop("v"))
    return blocks.groupBy("block").cogroup(every.groupBy("block")).applyInArrow(_score(order, bits, int(total[0]), int(vocabulary) - (total[1] > 0)), SCORES)


def _trained(batches):
    """Training tokens, without starts, and texts of each block."""
    for batch in batches:
        for i in range(batch.num_rows):
            get = lambda c, kind, i=i: unsqueeze(batch.column(batch.schema.get_field_index(c))[i].as_py(), kind)  # noqa: B023, E731
            docs, no_id, ends = get("docs", np.int64), get("no_id", bool), get("ends", np.int64)
            mine = np.array([not held_out(None if x else d) for d, x in zip(docs.tolist(), no_id.tolist(), strict=True)])
            yield pa.RecordBatch.from_pydict({"n": [int((np.diff(np.r_[0, ends]) - 1)[mine].sum())], "texts": [int(mine.sum())]})


def op5_language_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score_documents(table(spark, sf_dir, "documents"))
