"""Every pipeline stage on a small table."""

import corpus_pipeline
import numpy as np
from covergraph.llm import near_text, simhash
from covergraph.llm.common import stage

from test_llm import SCHEMA, lower, removed, texts


def test_stages(spark):
    rows = [(i, t, "en", ["a", "b"][i % 2], None, 1, "x", "y") for i, t in enumerate(texts())]
    docs, seen = spark.createDataFrame(rows, SCHEMA).select("doc_id", "text", "lang", "source", "n_chars"), {}
    for name, step in corpus_pipeline.STAGES:
        before = docs
        docs = stage(step(spark, docs, ""))
        seen[name] = docs
        if name != "packed":
            assert docs.columns == before.columns
    ids = {k: sorted(r["doc_id"] for r in d.select("doc_id").collect()) for k, d in seen.items()}
    assert 0 not in ids["quality"] and 6 not in ids["quality"] and 7 in ids["quality"] and 17 in ids["quality"]
    assert 7 in ids["near_copies"] and 8 not in ids["near_copies"] and ids["repeats"] == ids["near_copies"]
    kept = {r["doc_id"]: r["text"] for r in seen["near_copies"].collect()}
    gone = removed([(i, t.encode()) for i, t in kept.items()])
    left = {r["doc_id"]: r["text"] for r in seen["repeats"].collect()}
    assert all(t.isascii() is False or left[i] == "".join(c for c, g in zip(t, gone[i], strict=True) if not g) for i, t in kept.items())
    assert max(ids["mixture"].count(i) for i in ids["mixture"]) <= 2 and set(ids["mixture"]) <= set(ids["repeats"])
    assert sorted(r["doc_id"] for r in seen["packed"].where("piece = 0").collect()) == ids["mixture"]
    assert lower("AÉ") == "aÉ"


def test_empty(spark):
    docs = spark.createDataFrame([], SCHEMA).select("doc_id", "text", "lang", "source", "n_chars")
    for _, step in corpus_pipeline.STAGES:
        docs = stage(step(spark, docs, ""))
    assert docs.count() == 0


def test_near_copies_are_whole(spark):
    """Edited copies, far beyond 2 bits, against brute force over all pairs; chains and texts just below the share stay right."""
    r = np.random.default_rng(8)
    words = [f"w{i}" for i in range(3000)]
    out = [None, "", "Short text", "short  TEXT", "one two"]
    for n in (60, 150, 400, 2000):
        for edits in (1, 2, 3, 4, 6):
            base = [words[i] for i in r.integers(0, 3000, n)]
            out.append(" ".join(base))
            for _ in range(3):
                copy = list(base)
                for at in r.choice(n, max(1, edits * n // 150), replace=False):
                    copy[at] = "edited"
                out.append(" ".join(copy))
    chain = [words[i] for i in r.integers(0, 3000, 100)]
    out += [" ".join(chain[k * 8 :] + [f"c{k}_{j}" for j in range(k)]) for k in range(5)]
    crowd = [words[i] for i in r.integers(0, 3000, 80)]
    out += [" ".join(crowd[:i] + ["x"] + crowd[i + 1 :]) for i in range(80)]
    sets = []
    for t in out:
        w = (t or "").lower().split()
        sets.append({tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else {()})
    group = list(range(len(out)))
    far = 0
    prints = [simhash.fingerprint((t or "").lower().encode().split()) for t in out]
    for i in range(len(out)):
        for j in range(i):
            if 5 * len(sets[i] & sets[j]) >= 4 * len(sets[i] | sets[j]):
                far += (prints[i] ^ prints[j]).bit_count() > 2
                a, b = group[i], group[j]
                group = [min(a, b) if g in (a, b) else g for g in group]
    assert far > 100
    rows = [(i, t, "en", "a", 1) for i, t in enumerate(out)] + [(None, "short text", "en", "a", 1), (2, "Short text", "en", "a", 1)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").repartition(5)
    got = sorted(-1 if x["doc_id"] is None else x["doc_id"] for x in corpus_pipeline.near_copies(spark, docs, "").collect())
    assert got == [-1, *sorted(set(group))]


def test_near_copies_in_small_blocks(spark):
    """Chains, crowds and parts that only some pair joins, against all pairs, in blocks of any size."""
    import numpy as np

    from covergraph.llm import near_text

    r = np.random.default_rng(12)
    word = lambda: "".join(chr(97 + c) for c in r.integers(0, 26, 6))
    texts = []
    for _ in range(4):
        base = [word() for _ in range(120)]
        for _ in range(30):
            copy = list(base)
            for at in r.integers(0, 120, int(r.integers(0, 9))):
                copy[at] = word()
            texts.append(" ".join(copy))
        for step in range(25):  # a chain that leaves its start behind
            base[int(4 * step) % 120] = word()
            texts.append(" ".join(base))
    texts += [None, "", " ", texts[0], texts[40].upper(), "a b", "a b", "x y z"]
    sets = [set(near_text.shingles((t or "").encode()).tolist()) for t in texts]
    group = list(range(len(texts)))
    for i in range(len(texts)):
        for j in range(i):
            both = len(sets[i] & sets[j])
            if sets[i] == sets[j] or 5 * both >= 4 * (len(sets[i]) + len(sets[j]) - both) > 0:
                low, high = sorted((group[i], group[j]))
                group = [low if g == high else g for g in group]
    table = spark.createDataFrame([(i, t, 1, "x") for i, t in enumerate(texts)], "doc_id long, text string, component int, k string").repartition(5)
    for most in (2, 16, 256):
        assert sorted(x[0] for x in near_text.first_copies(table, most).collect()) == sorted(set(group)), most
    assert near_text.first_copies(table.where("false")).count() == 0


def test_near_copies_come_from_fingerprints(spark, monkeypatch):
    """SimHash finds candidates of its own, without a min-hash key; whole sets still decide."""
    r = np.random.default_rng(9)
    docs, want = [], []
    for k in range(40):
        base = [f"v{i}" for i in r.integers(0, 4000, 1500)]
        copy = list(base)
        copy[int(r.integers(0, 1500))] = "edited"
        a, b = (simhash.fingerprint([w.encode() for w in t]) for t in (base, copy))
        if (a ^ b).bit_count() <= 2:
            docs += [(2 * k, " ".join(base)), (2 * k + 1, " ".join(copy))]
            want.append(2 * k)
    # these share nothing
    docs += [(900, "one two three"), (901, "four five six")]
    monkeypatch.setattr(near_text, "_scan", lambda batches: (b.select(["key", "doc_id"]).rename_columns(["a", "b"]).slice(0, 0) for b in batches))
    got = near_text.first_copies(spark.createDataFrame(docs, "doc_id long, text string"))
    assert len(want) > 5 and sorted(r["doc_id"] for r in got.collect()) == [*want, 900, 901]
