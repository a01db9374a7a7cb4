"""External induced sorting of suffixes with common-prefix lengths.

Suffixes that follow a descent into an ascent (seeds) are sorted by recursion;
every other suffix is induced from its successor by two sweeps over a monotone
priority queue keyed by first letter. A queue's tuples (place, common prefix)
go to a task's scratch file when they outgrow its memory and are read back when
their letter's turn comes. Work is done a letter at a time on whole arrays."""

from __future__ import annotations

import os
import tempfile

import numpy as np

#: Bytes of tuples that a queue keeps in memory; names of a recursion that are ordered in memory by doubling.
MEMORY, INTERNAL = 64 << 20, 1 << 24
NONE = 255


class LetterQueue:
    """Monotone priority queue: tuples leave by letter, and within a letter in the order they came."""

    def __init__(self, memory: int = MEMORY, scratch: str | None = None):
        self.memory, self.scratch, self.held, self.file = memory, scratch, 0, None
        self.live: dict[int, list] = {}
        self.spilled: dict[int, list[tuple[int, int]]] = {}

    def push(self, letters: np.ndarray, places: np.ndarray, common: np.ndarray) -> None:
        """Letters must be sorted."""
        cuts = np.flatnonzero(np.r_[True, letters[1:] != letters[:-1]])
        for s, e in zip(cuts, np.r_[cuts[1:], len(letters)], strict=True):
            self.live.setdefault(int(letters[s]), []).append((places[s:e], common[s:e]))
        self.held += 9 * len(letters)
        if self.held > self.memory:
            self.spill()

    def spill(self) -> None:
        self.file = self.file or tempfile.TemporaryFile(dir=self.scratch or os.environ.get("SPARK_LOCAL_DIRS", "").split(",")[0] or None)
        self.file.seek(0, os.SEEK_END)
        for letter, parts in self.live.items():
            places, common = (np.concatenate(x) for x in zip(*parts, strict=True))
            self.spilled.setdefault(letter, []).append((self.file.tell(), len(places)))
            self.file.write(places.astype(np.int64).tobytes() + common.astype(np.uint8).tobytes())
        self.live, self.held = {}, 0

    def pop(self, letter: int) -> tuple[np.ndarray, np.ndarray]:
        parts = []
        for at, n in self.spilled.pop(letter, []):
            self.file.seek(at)
            parts.append((np.frombuffer(self.file.read(8 * n), np.int64), np.frombuffer(self.file.read(n), np.uint8)))
        got = self.live.pop(letter, [])
        self.held -= 9 * sum(len(p) for p, _ in got)
        parts += got
        if not parts:
            return np.empty(0, np.int64), np.empty(0, np.uint8)
        return np.concatenate([p for p, _ in parts]).astype(np.int64), np.concatenate([c for _, c in parts])

    def close(self) -> None:
        if self.file:
            self.file.close()


def ascending(t: np.ndarray) -> np.ndarray:
    """Whether each suffix is smaller than the next one; the last is."""
    step = np.sign(np.diff(t.astype(np.int64)))
    last = np.where(step != 0, np.arange(len(step)), len(t))
    known = np.minimum.accumulate(last[::-1])[::-1]
    return np.r_[np.r_[step, 1][np.minimum(known, len(step))] > 0, True]


def runs_of(t: np.ndarray, depth: int) -> np.ndarray:
    """Equal letters from each place on, at most `depth`."""
    ends = np.where(np.r_[t[1:] != t[:-1], True], np.arange(len(t)), len(t))
    return np.minimum(np.minimum.accumulate(ends[::-1])[::-1] - np.arange(len(t)) + 1, depth).astype(np.uint8)


class _Least:
    """Least common prefix since the last tuple that went to each letter."""

    def __init__(self, letters: int, depth: int):
        self.since, self.depth = np.full(letters, -1, np.int16), depth  # -1: none yet, so its first tuple has 0 in common

    def induced(self, common: np.ndarray, index: np.ndarray, letter: np.ndarray) -> np.ndarray:
        """Common prefixes of tuples induced from sources `index` (rising within a letter; letters sorted): one more
        than the least among the sources since the tuple before."""
        table = [common]
        while 2 << (len(table) - 1) <= len(common):
            w = 1 << (len(table) - 1)
            table.append(np.minimum(table[-1][:-w], table[-1][w:]))

        def least(a, b):  # over [a, b), none: NONE
            n = b - a
            out = np.full(len(a), NONE, np.int16)
            level = np.zeros(len(a), np.int64)
            level[n > 0] = np.log2(n[n > 0]).astype(np.int64)
            for k in np.unique(level[n > 0]):
                i = (level == k) & (n > 0)
                out[i] = np.minimum(table[k][a[i]], table[k][b[i] - (1 << k)])
            return out

        new = np.r_[True, letter[1:] != letter[:-1]]
        out = least(np.where(new, 0, np.r_[0, index[:-1] + 1]), index + 1)
        out[new] = np.minimum(out[new], self.since[letter[new]])
        every = common.min()
        last = np.r_[new[1:], True]
        self.since = np.minimum(self.since, every)
        self.since[letter[last]] = least(index[last] + 1, np.full(last.sum(), len(common)))
        return np.minimum(out + 1, self.depth).astype(np.uint8)


def induce(t: np.ndarray, up: np.ndarray, seeds: np.ndarray, seed_common: np.ndarray | None, depth: int, memory: int = MEMORY, scratch: str | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Order of all suffixes and each one's common prefix with the one before, from the order of the seeds."""
    letters = int(t.max()) + 1
    run = runs_of(t, depth)
    want = seed_common is not None
    seed_letter = t[seeds]
    at = np.searchsorted(seed_letter, np.arange(letters + 1))
    present = np.unique(t)
    queue, done = LetterQueue(memory, scratch), LetterQueue(memory, scratch)

    def send(places, common, keep, least):
        source = np.flatnonzero(places > 0)
        before = places[source] - 1
        letter = t[before].astype(np.int64)
        go = keep(letter, before)
        source, before, letter = source[go], before[go], letter[go]
        by = np.argsort(letter, kind="stable")
        source, before, letter = source[by], before[by], letter[by]
        if len(source):
            return letter, before, least.induced(common, source, letter) if want else np.zeros(len(source), np.uint8)
        if want and len(common):
            least.since = np.minimum(least.since, common.min())
        return letter, before, np.empty(0, np.uint8)

    def route(letter, before, common, c):
        other = letter != c
        if other.any():
            queue.push(letter[other], before[other], common[other])
        return before[~other], common[~other]

    try:
        least = _Least(letters, depth)
        for c in present:  # suffixes larger than the next one, smallest letter first
            places, common = queue.pop(int(c))
            last = None
            while len(places):
                done.push(np.full(len(places), c), places, common)
                last = places[-1]
                places, common = route(*send(places, common, lambda x, _: x >= c, least), c)
            mine = seeds[at[c] : at[c + 1]]
            if len(mine):
                common = seed_common[at[c] : at[c + 1]].copy() if want else np.zeros(len(mine), np.uint8)
                common[0] = 0 if last is None else min(run[last], run[mine[0]])
                route(*send(mine, common, lambda x, _: x > c, least), c)
        least = _Least(letters, depth)
        orders, commons = [], []
        for c in present[::-1]:  # the others, largest letter first
            places, common = queue.pop(int(c))
            if c == 0:
                places, common = np.array([len(t) - 1]), np.zeros(1, np.uint8)
            rising = []
            while len(places):
                rising.append((places, common))
                places, common = route(*send(places, common, lambda x, _: x <= c, least), c) if c else (places[:0], common[:0])
            falling, falling_common = done.pop(int(c))
            s, sc = (np.concatenate(x) for x in zip(*rising, strict=True)) if rising else (np.empty(0, np.int64), np.empty(0, np.uint8))
            seam = min(run[falling[-1]], run[s[-1]]) if len(falling) and len(s) else 0
            if len(falling):
                route(*send(falling[::-1], np.r_[seam, falling_common[:0:-1]].astype(np.uint8), lambda x, _: x < c, least), c)
            orders.append(np.r_[falling, s[::-1]])
            commons.append(np.r_[falling_common, seam if len(s) else np.empty(0), sc[:0:-1]].astype(np.uint8))
        return np.concatenate(orders[::-1]), np.concatenate(commons[::-1])
    finally:
        queue.close()
        done.close()


def doubling(names: np.ndarray, depth: int) -> np.ndarray:
    """Order of the suffixes of a sequence by their first `depth` names, in memory."""
    rank, width = names.astype(np.int64), 1
    while True:
        after = np.r_[rank[width:], np.full(min(width, len(rank)), -1)]
        order = np.lexsort((after, rank))
        fresh = np.r_[False, (rank[order][1:] != rank[order][:-1]) | (after[order][1:] != after[order][:-1])]
        rank = np.empty_like(rank)
        rank[order] = np.cumsum(fresh)
        width *= 2
        if width >= depth or rank[order[-1]] == len(rank) - 1:
            return order


def agree(t: np.ndarray, a: np.ndarray, b: np.ndarray, depth: int) -> np.ndarray:
    """Equal letters from a and from b on, at most `depth`."""
    out = np.zeros(len(a), np.int64)
    live = np.arange(len(a))
    for j in range(depth):
        x, y = a[live] + j, b[live] + j
        ok = (x < len(t)) & (y < len(t))
        ok[ok] = t[x[ok]] == t[y[ok]]
        live = live[ok]
        if not len(live):
            break
        out[live] += 1
    return out


def suffixes(t: np.ndarray, depth: int, memory: int = MEMORY, internal: int = INTERNAL, scratch: str | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Order of the suffixes of t by their first `depth` letters at least, and common prefixes, at most `depth` (under 255).

    t ends with its only 0. Seeds get names by sorting the substrings between
    them with the same two sweeps; where names repeat, the sequence of names is
    sorted in turn: by recursion while it is longer than `internal`, then in
    memory."""
    up = ascending(t)
    seeds = np.flatnonzero(up & ~np.r_[True, up[:-1]])
    if not len(seeds):
        return np.arange(len(t))[::-1], np.r_[0, agree(t, np.arange(len(t))[:0:-1], np.arange(len(t) - 1)[::-1], depth)].astype(np.uint8)
    by_letter = seeds[np.argsort(t[seeds], kind="stable")]
    order, _ = induce(t, up, by_letter, None, depth, memory, scratch)
    is_seed = np.zeros(len(t), bool)
    is_seed[seeds] = True
    ranked = order[is_seed[order]]
    length = np.ones(len(t), np.int64)
    length[seeds[:-1]] = np.diff(seeds) + 1
    a, b = ranked[:-1], ranked[1:]
    same = length[a] == length[b]
    most = int(length[seeds].max())
    same[same] = agree(t, a[same], b[same], most) >= length[a[same]]
    names = np.empty(len(t), np.int64)
    names[ranked] = np.r_[0, np.cumsum(~same)]
    reduced = names[seeds]
    if same.any():
        whole = depth // 2 + 2  # a name adds two letters at least
        inner = suffixes(reduced, min(whole, 254), memory, internal, scratch)[0] if len(reduced) > internal else doubling(reduced, whole)
        ranked = seeds[inner]
    common = np.r_[0, agree(t, ranked[:-1], ranked[1:], depth)].astype(np.uint8)
    return induce(t, up, ranked, common, depth, memory, scratch)
