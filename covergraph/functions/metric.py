"""Distances: block kernels for Arrow batches and column expressions for SQL plans."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

#: Lattice of the exact mode: coordinates become floor(x * 2**24).
SCALE = 1 << 24


def lattice(vec: Column) -> Column:
    return F.transform(vec.cast("array<double>"), lambda x: F.floor(x * SCALE).cast("double"))


def l2sq(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Squared Euclidean; exact for integers while 4 * |x|^2 stays below 2**53. Where the sums cancel, differences are taken instead."""
    a, b = a.astype(float, copy=False), b.astype(float, copy=False)
    na, nb = (a * a).sum(1), (b * b).sum(1)
    d = na[:, None] + nb[None] - 2 * (a @ b.T)
    i, j = np.nonzero(d < 1e-9 * (na[:, None] + nb[None]))
    for s in range(0, len(i), 4096):
        d[i[s : s + 4096], j[s : s + 4096]] = ((a[i[s : s + 4096]] - b[j[s : s + 4096]]) ** 2).sum(1)
    return np.maximum(d, 0)


def l1(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    b = b.astype(float, copy=False)
    return np.stack([np.abs(x - b).sum(1) for x in a.astype(float, copy=False)]) if len(a) else np.empty((0, len(b)))


def linf(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    b = b.astype(float, copy=False)
    return np.stack([np.abs(x - b).max(1) for x in a.astype(float, copy=False)]) if len(a) else np.empty((0, len(b)))


def cosine(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """1 - cosine; a zero vector is at distance 1 from everything."""
    a, b = a.astype(float, copy=False), b.astype(float, copy=False)
    na, nb = np.sqrt((a * a).sum(1)), np.sqrt((b * b).sum(1))
    return 1 - a @ b.T / np.maximum(na[:, None] * nb[None], 1e-300)


def jaccard(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """1 - shared / all members of sets given as vectors of 0 and 1; two empty sets are equal."""
    a, b = a.astype(float, copy=False), b.astype(float, copy=False)
    both = a @ b.T
    return 1 - both / np.maximum(a.sum(1)[:, None] + b.sum(1)[None] - both, 1) - ((a.sum(1)[:, None] + b.sum(1)[None]) == 0)


KERNELS = {"l2sq": l2sq, "l1": l1, "linf": linf, "cosine": cosine, "jaccard": jaccard}


#: Dimensions up to which points are kept in boxes, most of which lie on one side of what separates two points; points of a box.
NARROW, BOX = 16, 40


def whole_numbers(vecs: np.ndarray) -> tuple[np.ndarray, bool]:
    """Squared norms, and whether squared Euclidean distances of such vectors are exact in double precision, in whatever order they are added up."""
    norms, whole = np.zeros(len(vecs)), True
    for s in range(0, len(vecs), 16384):
        v = vecs[s : s + 16384].astype(float)
        norms[s : s + 16384] = (v * v).sum(1)
        whole = whole and bool((v == np.floor(v)).all())
    return norms, whole and 4 * norms.max(initial=0) < 2**53


class Boxes:
    """Points dealt into boxes by halving the widest side: box i holds the places order[start[i] : start[i + 1]]; coarser boxes, eight times as large each, in levels."""

    def __init__(self, vecs: np.ndarray):
        n, depth = len(vecs), max(0, int(np.ceil(np.log2(max(1, len(vecs)) / BOX))))
        self.order = np.arange(n)
        for level in range(depth):
            ends = (np.arange((2 << level) + 1) * n) >> (level + 1)
            for s, mid, e in zip(ends[:-2:2].tolist(), ends[1:-1:2].tolist(), ends[2::2].tolist(), strict=True):
                some = self.order[s:e]
                v = vecs[some]
                self.order[s:e] = some[np.argpartition(v[:, np.ptp(v, axis=0).argmax()], mid - s)]
        self.vecs, self.levels = vecs[self.order].astype(float), []
        for level in range(depth % 3, depth + 1, 3):  # eight boxes in each of the level before
            self.start = (np.arange((1 << level) + 1) * n) >> level
            low, high = np.minimum.reduceat(self.vecs, self.start[:-1]), np.maximum.reduceat(self.vecs, self.start[:-1])
            self.centre, self.half, self.sizes = (low + high) / 2, (high - low) / 2, np.diff(self.start)
            self.levels.append((self.centre, self.half, self.sizes))

    def inside(self, some: np.ndarray) -> np.ndarray:
        """Rows of vecs (and of order) in these boxes."""
        sizes = self.sizes[some]
        return np.repeat(self.start[some] - np.r_[0, np.cumsum(sizes)[:-1]], sizes) + np.arange(sizes.sum())


class Owners:
    """How many of a set's points each member of a chunk is nearest to; what the set tells is taken once, for many chunks."""

    #: Members, and points of the set, of one product.
    MEMBERS, POINTS = 512, 512

    def __init__(self, vecs: np.ndarray, metric: str = "l2sq"):
        self.vecs, self.metric, self.whole = vecs, metric, metric == "l2sq"
        self.order, self.norms = np.arange(len(vecs)), np.zeros(len(vecs))
        self.boxes = None
        if self.whole:
            self.norms, self.whole = whole_numbers(vecs)
            self.order = np.argsort(self.norms, kind="stable")  # so that most products are of short vectors
            self.boxes = Boxes(vecs) if self.whole and vecs.shape[1] <= NARROW and len(vecs) > 64 * BOX else None

    def boxed(self, own: np.ndarray) -> np.ndarray:
        """Counts of one chunk: a box that one member owns as a whole is counted at once, others by the boxes or points in them. Vectors are whole numbers, so nothing is rounded."""
        b, a = self.boxes, own.astype(float)
        norms, sides, owned = (a * a).sum(1), np.abs(a[:, None] - a), np.zeros(len(a), np.int64)
        some = np.arange(len(b.levels[0][2]))
        for level, (centre, half, sizes) in enumerate(b.levels):
            some = (some[:, None] * 8 + np.arange(8)).ravel() if level else some
            d = norms[:, None] - 2 * a @ centre[some].T
            first = d.argmin(axis=0)
            may = d - d[first, np.arange(len(some))] <= 2 * np.einsum("mud,ud->mu", sides[:, first], half[some])
            many = np.count_nonzero(may, axis=0)
            owned += np.bincount(first[many == 1], sizes[some[many == 1]], len(a)).astype(np.int64)
            some, first, may, many = some[many > 1], first[many > 1], may[:, many > 1], many[many > 1]
        two = np.flatnonzero(many == 2)
        if len(two):
            u = first[two]
            may[u, two] = False
            v = may[:, two].argmax(axis=0)
            rep = np.repeat(np.arange(len(two)), sizes[some[two]])
            further = (norms[v] - norms[u])[rep] - 2 * np.einsum("pd,pd->p", (a[v] - a[u])[rep], b.vecs[b.inside(some[two])])
            owned += np.bincount(u[rep[further >= 0]], minlength=len(a)) + np.bincount(v[rep[further <= 0]], minlength=len(a))
        rest = b.vecs[b.inside(some[many > 2])]
        if len(rest):
            d = norms[:, None] - 2 * a @ rest.T
            owned += np.count_nonzero(d == d.min(axis=0), axis=1)
        return owned

    def counts(self, own: np.ndarray, size: int) -> np.ndarray:
        """Of each row of whole chunks, `size` rows each: the points it is nearest to in its chunk, ties to all nearest.
        Whole numbers are compared without the norm of the point, which is the same for a whole chunk."""
        lean, owned = self.whole, np.zeros(len(own), np.int64)
        if not len(own):
            return owned
        norms = np.zeros(len(own))
        if lean:
            norms, lean = whole_numbers(own)
        if lean and self.boxes is not None and size <= 64:  # a box is compared with all pairs of a chunk's members
            return np.concatenate([self.boxed(own[s : s + size]) for s in range(0, len(own), size)])
        turn = np.argsort(norms.reshape(-1, size).max(axis=1), kind="stable")
        turn = (turn[:, None] * size + np.arange(size)).ravel()
        rows = max(1, self.MEMBERS // size) * size
        sides = [turn[at : at + rows] for at in range(0, len(turn), rows)]
        # single precision holds whole numbers below 2**24, and no sum on the way to a distance is above this
        tops = [norms[some].max() for some in sides]
        ready: dict[type, list] = {}

        def side(kind):
            if kind not in ready:
                ready[kind] = [np.c_[-2 * own[some].astype(float), norms[some]].astype(kind) if lean else own[some].astype(kind) for some in sides]
            return ready[kind]

        room = {kind: np.empty(min(rows, len(own)) * self.POINTS, kind) for kind in (np.float32, np.float64)}
        for k in range(0, len(self.vecs), self.POINTS):
            at = self.order[k : k + self.POINTS]
            top, m = self.norms[at].max(), {}
            for i, some in enumerate(sides):
                if lean:
                    kind = np.float32 if 2 * np.sqrt(top * tops[i]) + tops[i] < 2**24 - 1 else np.float64
                    if kind not in m:
                        m[kind] = np.concatenate([self.vecs[at].astype(kind).T, np.ones((1, len(at)), kind)])
                    d = np.matmul(side(kind)[i], m[kind], out=room[kind][: len(some) * len(at)].reshape(len(some), len(at)))
                else:
                    if not m:
                        m[float] = self.vecs[at].astype(float)
                    d = KERNELS[self.metric](side(float)[i], m[float])
                d = d.reshape(-1, size, len(at))
                hit = d == d.min(axis=1, keepdims=True)
                if len(at) % 8:
                    owned[some] += np.count_nonzero(hit, axis=2).ravel()
                else:  # eight counts in a word: none of them passes POINTS / 8
                    words = np.add.reduce(hit.reshape(len(some), -1).view(np.uint64), axis=1)
                    owned[some] += words.view(np.uint8).reshape(-1, 8).sum(axis=1, dtype=np.int64)
        return owned


def owned_by(own: np.ndarray, size: int, vecs: np.ndarray, metric: str = "l2sq") -> np.ndarray:
    """Of each row of whole chunks, `size` rows each: how many of vecs it is nearest to in its chunk, ties to all nearest."""
    return Owners(vecs, metric).counts(own, size)


class Rows:
    """Distances from points of a set to all of it, of many points at once; norms of squared Euclidean distances are taken once."""

    def __init__(self, vecs: np.ndarray, metric: str):
        self.vecs, self.kernel, self.euclid = vecs, KERNELS[metric], metric == "l2sq"
        if self.euclid:
            self.norms = np.concatenate([np.empty(0), *((vecs[s : s + 16384].astype(float) ** 2).sum(1) for s in range(0, len(vecs), 16384))])
            self.top = self.norms.max(initial=0)

    def full(self, which: np.ndarray) -> np.ndarray:
        """Distances of the points at `which` to all."""
        out = np.empty((len(which), len(self.vecs)))
        a = self.vecs[which].astype(float)
        for s in range(0, len(self.vecs), 4096):
            b, d = self.vecs[s : s + 4096].astype(float), out[:, s : s + 4096]
            if not self.euclid:
                d[:] = self.kernel(a, b)
                continue
            np.matmul(-2 * a, b.T, out=d)
            d += self.norms[s : s + 4096]
            d += self.norms[which, None]
            i, j = np.nonzero(d < 1e-9 * (self.norms[which, None] + self.top))
            for k in range(0, len(i), 4096):  # where the sums cancel, as in l2sq()
                d[i[k : k + 4096], j[k : k + 4096]] = ((a[i[k : k + 4096]] - b[j[k : k + 4096]]) ** 2).sum(1)
        return out

    def part(self, at: np.ndarray) -> tuple[np.ndarray, np.ndarray | None]:
        """What row() needs of the points at `at`."""
        return self.vecs[at].astype(float), self.norms[at] if self.euclid else None

    def row(self, x: int, part: tuple[np.ndarray, np.ndarray | None]) -> np.ndarray:
        """Distances of the point at x to those of a part."""
        v, norms = part
        own = self.vecs[x].astype(float)
        if not self.euclid:
            return self.kernel(own[None], v)[0]
        d = v @ (-2 * own)
        d += norms
        d += self.norms[x]
        near = np.flatnonzero(d < 1e-9 * (self.norms[x] + self.top))
        for k in range(0, len(near), 4096):
            d[near[k : k + 4096]] = ((v[near[k : k + 4096]] - own) ** 2).sum(1)
        return d


def expression(metric: str, a: Column, b: Column) -> Column:
    """The same distances, and those of sets and strings, as columns."""
    add = lambda f: F.aggregate(F.zip_with(a, b, f), F.lit(0.0), lambda s, x: s + x)
    if metric == "l2sq":
        return add(lambda x, y: (x - y) * (x - y))
    if metric == "l1":
        return add(lambda x, y: F.abs(x - y))
    if metric == "linf":
        return F.array_max(F.zip_with(a, b, lambda x, y: F.abs(x - y)))
    if metric == "cosine":
        norm = lambda v: F.sqrt(F.aggregate(v, F.lit(0.0), lambda s, x: s + x * x))
        return 1 - add(lambda x, y: x * y) / (norm(a) * norm(b))
    if metric == "jaccard":
        return 1 - F.size(F.array_intersect(a, b)) / F.greatest(F.size(F.array_union(a, b)), F.lit(1))
    if metric == "levenshtein":
        return F.levenshtein(a, b)
    raise ValueError(f"no metric {metric}")
