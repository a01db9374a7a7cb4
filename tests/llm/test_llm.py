"""Training-data operators against brute force, on awkward rows."""

import collections
import hashlib
import math
import re
import zlib

import numpy as np
import pytest

from covergraph.llm import embedding_dedup, induced_sort, language_model, license_scan, mixing, packing, quality_classifier, quality_rules, simhash, suffix_dedup, url_filter
from covergraph.llm.common import pieces, rank_within
from covergraph.llm.components import components

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, rank int, size string, component string"
PROSE = "The quick brown fox jumps over the lazy dog while seven wizards brew a potion of rare herbs. "


def texts():
    r = np.random.default_rng(3)
    words = ["".join(chr(97 + c) for c in r.integers(0, 26, r.integers(2, 9))) for _ in range(400)]
    prose = lambda n: " ".join(words[i] for i in r.integers(0, 400, n))
    base, passage = prose(120), prose(30)
    out = [None, "", " \n\t ", "word", "a b", "é ñ ü Straße K", PROSE * 40, base, base, base + " tail", passage + "\n" + prose(80), prose(60) + passage, "De " * 300, "de " * 300, "naïve café " * 60, "x" * 5000, "#$% | & " * 90, prose(6000)]
    return out + [prose(int(n)) for n in r.integers(1, 200, 20)] + [base.replace(words[0], "zz")]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, "en", [None, "b", "a"][i % 3], None, 1, "x", "y") for i, t in enumerate(texts())]
    return spark.createDataFrame(rows, SCHEMA).repartition(3).cache()


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def by_id(df):
    return {r["doc_id"]: r for r in df.collect()}


def lower(t):
    return (t or "").translate({i: i + 32 for i in range(65, 91)})


def test_rank_within_is_dense(spark):
    df = spark.range(1000).selectExpr("id", "case when id % 3 = 0 then null else id % 2 end as k")
    for _, g in rank_within(df, ["k"], ["id"]).toPandas().groupby("k", dropna=False):
        assert sorted(g["rank"]) == list(range(len(g)))


def test_rank_within_at_any_width(spark):
    """The shuffle's width sets how many ranges a key is cut into, not the ranks; hot, null and repeated rows included."""
    df = spark.range(3000).selectExpr("id", "case when id % 3 = 0 then null else id % 5 div 4 end as k")
    df = df.unionByName(df.where("id < 20"))
    name, seen = "spark.sql.shuffle.partitions", []
    before = spark.conf.get(name)
    try:
        for width in (3, 64, 65, 700):
            spark.conf.set(name, str(width))
            seen.append(sorted((r["id"], r["rank"]) for r in rank_within(df, ["k"], ["id"]).collect()))
    finally:
        spark.conf.set(name, before)
    assert all(x == seen[0] for x in seen)
    assert rank_within(df.where("false"), ["k"], ["id"]).count() == 0


def test_components(spark):
    edges = [(1, 2), (2, 3), (5, 4), (9, 9), (None, 1), *[(i, i + 1) for i in range(100, 160)], *[(200, i) for i in range(201, 260)]]
    got = {r["node"]: r["component"] for r in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got[3] == 1 and got[5] == 4 and got[160] == 100 and got[259] == 200 and 9 not in got
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_few_links_need_no_rounds(spark, monkeypatch):
    """Rounds of small jobs filled the driver in near_copies."""
    from covergraph.llm import components as module

    r = np.random.default_rng(5)
    edges = [(i, i + 1) for i in range(0, 300)] + [(5000, 900), (900, 4000)] + [tuple(map(int, x)) for x in r.integers(10_000, 10_200, (120, 2))] + [(None, 7), (8, 8)]
    frame = spark.createDataFrame(edges, "a long, b long").repartition(3)
    want = sorted(map(tuple, components(frame).collect()))
    staged = []
    monkeypatch.setattr(module, "stage", lambda df, real=module.stage: staged.append(1) or real(df))
    assert sorted(map(tuple, components(frame, few=1000).collect())) == want
    assert len(staged) == 2
    assert sorted(map(tuple, components(frame, few=100).collect())) == want  # more than a task may join
    assert components(spark.createDataFrame([], "a long, b long"), few=10).count() == 0


def test_components_of_hubs(spark):
    """Hubs above HOT_ROWS, at both ends of the order, with equal links and a path between them."""
    far = 9_000
    edges = [(1, i) for i in range(1000, 2200)] * 2 + [(far, i) for i in range(3000, 4200)] + [(4199, 5000), (5000, 5001), (5001, 2199)] + [(7000 + i, 7001 + i) for i in range(700)] + [(None, 5), (6, 6)]
    got = {r["node"]: r["component"] for r in components(spark.createDataFrame(edges, "a long, b long").repartition(8)).collect()}
    assert len(got) == 2 + 1200 + 1200 + 2 + 701
    assert {got[x] for x in (1, far, 1000, 3000, 5000)} == {1} and {got[7000 + i] for i in range(701)} == {7000}


def test_packing(docs, empty):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(packing.default_tokenizer())
    got = packing.pack_documents(docs).toPandas()
    want = {}
    for i, x in enumerate(texts()):
        ids = np.array(t.encode(x or "", add_special_tokens=False).ids + [1], "<u4")
        want |= {(i, k // 4096): (k, len(ids[k : k + 4096]), zlib.crc32(ids[k : k + 4096].tobytes())) for k in range(0, len(ids), 4096)}
    assert {(r.doc_id, r.piece): (r.start, r.length, r.ids_crc32) for r in got.itertuples()} == want
    for _, g in got.sort_values(["sequence_id", "offset"]).groupby("sequence_id"):
        assert list(g.offset) == [0, *np.cumsum(g.length)[:-1]] and g.length.sum() <= 4096
    assert packing.pack_documents(empty).count() == 0


def test_best_fit_plan():
    r = np.random.default_rng(0)
    for _ in range(50):
        counts = {int(k): int(n) for k, n in zip(r.integers(1, 101, 12), r.integers(1, 60, 12), strict=True)}
        used, seen = collections.Counter(), collections.Counter()
        runs = packing.plan(counts, 100)
        for j, (length, first, each, at, offset) in enumerate(runs):
            end = min([x[1] for x in runs if x[0] == length and x[1] > first] + [counts[length]])
            for rank in range(first, end):
                s = at + (rank - first) // each
                assert used[s] == offset + (rank - first) % each * length
                used[s] += length
                seen[length] += 1
        assert seen == counts and max(used.values()) <= 100
        plain = []  # best fit, longest first, one by one
        for length in sorted(counts, reverse=True):
            for _ in range(counts[length]):
                fits = [i for i, room in enumerate(plain) if room >= length]
                if fits:
                    plain[min(fits, key=plain.__getitem__)] -= length
                else:
                    plain.append(100 - length)
        assert len(used) == len(plain)


def test_mixing(docs, empty):
    got = mixing.mix(docs)
    again = by_id(mixing.mix(docs))
    assert {k: r["copies"] for k, r in by_id(got).items()} == {k: r["copies"] for k, r in again.items()}
    per = collections.defaultdict(list)
    for i, r in again.items():
        assert r["copies"] in (0, 1, 2)
        per[r["source"]].append(r)
    assert math.isclose(sum(g[0]["target"] for g in per.values()), 1.5 * sum(g[0]["source_size"] for g in per.values()))
    for g in per.values():
        taken = sum(r["copies"] * int(r["size"]) for r in g)
        assert abs(taken - g[0]["target"]) <= max(int(r["size"]) for r in g) / 2 + 1
    assert mixing.mix(empty).count() == 0
    assert mixing.targets({"a": 100, "b": 10, None: 0}, {"a": 3, "b": 1, None: 2}) == {"a": 145.0, "b": 20.0, None: 0.0}


def test_license(docs, empty, spark):
    def words(t):
        return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", lower(t))

    assert {i: r["n_words"] for i, r in by_id(license_scan.scan_licenses(docs)).items()} == {i: len(words(t)) for i, t in enumerate(texts())}
    cases = ["Under the MIT License. x under THE mit-license", "the Apache License, Version 2.0", "CC BY-NC 4.0 cc by nc", "This work is licensed under the GNU General Public License, version 3.", "Released under the Mit  Licensee", "Permission is hereby granted, free of charge, to any person obtaining a copy", "license", None]
    got = by_id(license_scan.scan_licenses(spark.createDataFrame(list(enumerate(cases)), "doc_id long, text string")))
    assert [(got[i]["n_base"], got[i]["first_word"], got[i]["last_word"], got[i]["base_labels"]) for i in range(8)] == [(2, 0, 5, "mit"), (1, 1, 1, "apache-2"), (2, 0, 5, "cc-by-nc"), (0, None, None, ""), (0, None, None, ""), (0, None, None, ""), (0, None, None, ""), (0, None, None, "")]
    assert [got[i]["labels"] for i in range(8)] == ["mit", "apache-2", "cc-by-nc", "gpl-3", "", "mit", "", ""]
    assert all(0 <= r["score"] <= 1 for r in got.values()) and got[3]["score"] == 1 and got[6]["score"] == 0
    assert license_scan.scan_licenses(empty).count() == 0


def test_license_of_many_notices(spark):
    """A file of all notices has every label, and one amid rarer words keeps its whole score."""
    every = " / ".join(t.text for t in license_scan.TEMPLATES)
    gpl = "this work is licensed under the gnu general public license version 3"
    rare = "merchant " + " ".join(w for w in "redistribution source binary forms modification permitted granted permission charge person obtaining copy associated documentation files unencumbered mozilla".split())
    notice = " . ".join([license_scan.TEMPLATES[1].text, license_scan.TEMPLATES[9].text, gpl, "licensed under cc by 4 0"])
    cases = [every, rare + " " + gpl, notice] + [gpl] * 40
    got = by_id(license_scan.scan_licenses(spark.createDataFrame(list(enumerate(cases)), "doc_id long, text string")))
    assert set(got[0]["labels"].split(",")) == {t.label for t in license_scan.TEMPLATES}
    assert got[1]["labels"] == "gpl-3" and got[1]["score"] == 1
    assert got[2]["labels"] == "bsd,cc-by,gpl-3,mit"


def test_license_by_brute_force(docs, spark):
    """Places, labels and weighted shares of whole and cut licences among other texts, nulls, ties and clashing columns."""
    words = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", lower(t))
    full = [t.text for t in license_scan.TEMPLATES]
    rows = [None, "", *full, *[t[: len(t) // 2] for t in full], *[t[len(t) // 5 :] for t in full], " / ".join(full), *texts()[:12], "under the mit license " * 300, full[13], full[13]]
    table = spark.createDataFrame([(i, t, 7, "no") for i, t in enumerate(rows)], "doc_id long, text string, n_words int, labels string").repartition(5)
    got = by_id(license_scan.scan_licenses(table))
    held = collections.Counter(w for t in rows for w in set(words(t)))
    weight = {w: 1 + math.log((len(rows) + 1) / (n + 1)) for w, n in held.items()}
    find = lambda w, p: [i for i in range(len(w) - len(p) + 1) if w[i : i + len(p)] == p]
    for i, t in enumerate(rows):
        w, labels, share = words(t), set(), 0.0
        base = {label: find(w, p.split()) for p, label in license_scan.BASE}
        for x in license_scan.TEMPLATES:
            own = [(q, y, weight[y]) for q, y in enumerate(x.words()) if y not in license_scan.STOP]
            for s in find(w, x.key.split()):
                labels.add(x.label)
                o = s - x.key_place()
                share = max(share, sum(v for q, y, v in own if 0 <= o + q < len(w) and w[o + q] == y) / sum(v for _, _, v in own))
        places = sorted(p for ps in base.values() for p in ps)
        mine = {k for k, ps in base.items() if ps}
        assert (got[i]["n_words"], got[i]["n_base"], got[i]["first_word"], got[i]["last_word"]) == (len(w), len(places), places[0] if places else None, places[-1] if places else None)
        assert (got[i]["base_labels"], got[i]["labels"]) == (",".join(sorted(mine)), ",".join(sorted(mine | labels))), i
        assert got[i]["score"] == pytest.approx(1.0 if mine else min(share, 1.0))


def test_induced_sort():
    r = np.random.default_rng(1)
    for k in range(120):
        t = np.r_[r.integers(1, r.integers(2, 5), r.integers(1, 70)), 0] if k % 3 else np.r_[np.tile(r.integers(1, 4, r.integers(1, 5)), 12), 0]
        depth = int(r.choice([5, 12, 100]))
        order, common = induced_sort.suffixes(t, depth, memory=int(r.choice([1, 100, 1 << 20])), internal=int(r.choice([0, 3, 1 << 20])))
        heads = [tuple(t[i : i + depth]) for i in order]
        assert heads == sorted(tuple(t[i : i + depth]) for i in range(len(t))) and sorted(order.tolist()) == list(range(len(t)))
        assert common.tolist() == [0] + [next((j for j in range(min(len(a), len(b))) if a[j] != b[j]), min(len(a), len(b))) for a, b in zip(heads, heads[1:], strict=False)]


def removed(rows):
    first = {}
    for i, t in sorted(rows):
        for p in range(len(t) - 49):
            first.setdefault(t[p : p + 50], i)
    out = {}
    for i, t in rows:
        gone = np.zeros(len(t), bool)
        for p in range(len(t) - 49):
            if first[t[p : p + 50]] < i:
                gone[p : p + 50] = True
        out[i] = gone
    return out


def test_suffix_dedup(docs, empty):
    rows = [(i, (t or "").encode()) for i, t in enumerate(texts())]
    want = removed(rows)
    got = by_id(suffix_dedup.remove_repeats(docs.select("doc_id", "text", "size"), digest=True))
    for i, t in rows:
        g = want[i]
        kept = np.frombuffer(t, np.uint8)[~g].tobytes()
        spans = int((g & ~np.r_[False, g[:-1]]).sum()) if len(g) else 0
        assert (got[i]["n_bytes"], got[i]["n_removed"], got[i]["n_spans"], got[i]["kept_sha256"], got[i]["size"]) == (len(t), int(g.sum()), spans, hashlib.sha256(kept).hexdigest(), "x"), i
    left = by_id(suffix_dedup.remove_repeats(docs))
    assert left[8]["text"] == "" and left[7]["text"] == texts()[7] and left[7]["component"] == "y"
    assert suffix_dedup.remove_repeats(empty).count() == 0
    assert suffix_dedup.whole_characters(np.array([1, 0, 1, 1], bool), np.array([0, 1, 0, 1], bool)).tolist() == [False, False, True, True]


@pytest.mark.parametrize("crowd", [0, 5, 1 << 14])
def test_crowded_minimizers_are_cut_into_windows(spark, crowd):
    """A passage that every text goes on from differently, some alike for a while: the same bytes go however few surroundings crowd."""
    t = texts()
    passage = t[7][:90]
    rows = [(i, (t[20 + i % 7][: i % 40] + passage + ("abcdefghijk" * 9)[i % 6 :][: i % 19] + t[25 + i % 11]).encode()) for i in range(60)]
    want = removed(rows)
    table = spark.createDataFrame([(i, x.decode()) for i, x in rows], "doc_id long, text string").repartition(7)
    got = by_id(suffix_dedup.remove_repeats(table, digest=True, crowd=crowd))
    for i, x in rows:
        kept = np.frombuffer(x, np.uint8)[~want[i]].tobytes()
        assert (got[i]["n_removed"], got[i]["kept_sha256"]) == (int(want[i].sum()), hashlib.sha256(kept).hexdigest()), i


def test_language_model(docs, empty, spark, monkeypatch):
    """Counts and scores against n-grams counted by hand, at several orders and block sizes, with repeated rows and null ids."""
    rows = [(i, t) for i, t in enumerate(texts())]
    rows += [(1000 + i, t) for i, t in rows[10:20]] + [(None, rows[20][1]), (5, rows[5][1]), (5, rows[5][1])] + [(2000 + i, rows[7][1] + " " + rows[20][1]) for i in range(12)]
    tokens = [[b"\n", *lower(t).encode().split(), b""] for _, t in rows]
    held = [zlib.crc32(b"" if i is None else str(i).encode()) % 10 == 0 for i, _ in rows]
    grams = collections.Counter(tuple(t[e - k : e]) for t, h in zip(tokens, held, strict=True) if not h for k in range(1, 6) for e in range(k, len(t) + 1))
    words = collections.Counter(w for t, h in zip(tokens, held, strict=True) if not h for w in t[1:])
    n, v = sum(words.values()), len(words)
    table = spark.createDataFrame([(*r, "x", 1) for r in rows], "doc_id long, text string, tokens string, n int").repartition(3)
    for order, block in ((2, 1 << 20), (4, 300), (5, 50)):
        monkeypatch.setattr(language_model, "BLOCK", block)
        want = []
        for (i, _), t, h in zip(rows, tokens, held, strict=True):
            base = model = 0.0
            for e in range(1, len(t)):
                p = (words[t[e]] + 0.1) / (n + 0.1 * (v + 1))
                base += math.log10(p)
                for k in range(1, order):
                    c = grams[tuple(t[e - k : e])] if e >= k else 0
                    if c >= (1 if k == 1 else language_model.SEEN):
                        p = (grams[tuple(t[e - k : e + 1])] + language_model.FAIL * p) / (c + language_model.FAIL)
                model += math.log10(p)
            want.append((i, h, len(t) - 1, sum(words[w] > 0 for w in t[1:]), n, round(base, 6), round(model, 6)))
        got = [(r[0], r[1], r[2], r[3], r[4], round(r[5], 6), round(r[6], 6)) for r in language_model.score_documents(table, order).collect()]
        assert sorted(got, key=str) == sorted(want, key=str), order
    assert language_model.score_documents(empty).count() == 0


def test_long_texts_are_split_in_pieces():
    for t in (b"", b"one two  three\tfour", b"x" * 40, b"x" * 40 + b" yy z", b" a b c d e f g h "):
        assert [w for p in pieces(t, 7) for w in p.split()] == t.split()


def test_golay_keys_meet():
    r = np.random.default_rng(4)
    tables = simhash.golay()
    assert sorted(set((tables[2] >= 0).sum(axis=1))) == [1, 6]
    fp = r.integers(0, 1 << 63, 400, dtype=np.uint64)
    for flips in (0, 1, 2):
        other = fp.copy()
        for i in range(len(fp)):
            for b in r.choice(64, flips, replace=False):
                other[i] ^= np.uint64(1) << np.uint64(b)
        keys = []
        for x in (fp, other):
            row, key = simhash.fuzzy_keys(x, tables)
            keys.append([set(key[row == i].tolist()) for i in range(len(fp))])
        assert all(a & b for a, b in zip(*keys, strict=True))


@pytest.mark.parametrize("bucket", [20_000, 3])
def test_simhash_links(spark, bucket):
    r = np.random.default_rng(5)
    seeds = r.integers(0, 1 << 63, 30, dtype=np.uint64)
    fps = [int(s) for s in seeds]
    for s in seeds[:10]:
        for _ in range(25):
            x = int(s)
            for b in r.choice(64, r.integers(0, 4), replace=False):
                x ^= 1 << int(b)
            fps.append(x)
    fps = np.array(fps, np.uint64)
    order = r.permutation(len(fps))
    rows = [(int(i), int(fps[i].astype(np.int64))) for i in order] + [(None, 5)]
    got = {x["doc_id"]: x["component_id"] for x in simhash.link(spark.createDataFrame(rows, "doc_id long, fp long"), bucket=bucket).collect()}
    group = np.arange(len(fps))
    for i in range(len(fps)):
        for j in np.flatnonzero(np.bitwise_count(fps ^ fps[i]) <= 2):
            group[group == max(group[i], group[j])] = min(group[i], group[j])
    assert got.pop(None) is None
    assert got == dict(enumerate(group.tolist()))


def test_simhash_documents(docs, empty):
    got = by_id(simhash.near_duplicates(docs))
    assert got[0]["fingerprint"] == "0" * 16 and got[1]["component_id"] == 0 and got[2]["component_id"] == 0 and got[8]["component_id"] == 7 and got[13]["component_id"] == 12
    assert simhash.near_duplicates(empty).count() == 0


def test_fingerprint_bits(docs):
    """Each bit by counting over the shingles, repeats included."""
    from xxhash import xxh64_intdigest

    got = by_id(simhash.near_duplicates(docs))
    for i, t in enumerate(texts()):
        w = lower(t).encode().split()
        hashes = [xxh64_intdigest(b" ".join(w[k : k + 3]), 42) for k in range(max(1, len(w) - 2))] if w else []
        bits = sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))
        assert got[i]["fingerprint"] == f"{bits:016x}", i


def test_quality_rules(docs, empty):
    got = by_id(docs.select("doc_id", *[f(docs["text"]).alias(k) for k, f in quality_rules.MEASURES.items()], quality_rules.word_measures(docs["text"]).alias("m")))
    for i, t in enumerate(texts()):
        w = [x.decode() for x in (t or "").encode().split()]
        win = collections.Counter(zip(w, w[1:], w[2:], strict=False))
        again = {p + k for p in range(len(w) - 2) if win[tuple(w[p : p + 3])] > 1 for k in range(3)}
        lines = [x for x in (t or "").split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
        assert (got[i]["n_words"], got[i]["word_chars"], got[i]["n_symbols"], got[i]["n_dup_lines"], got[i]["n_repeat_words"]) == (len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t or "")), len(lines) - len(set(lines)), len(again)), i
        assert tuple(got[i]["m"]) == (len(w), sum(map(len, w)), len(again))
    verdicts = by_id(quality_rules.apply_rules(docs))
    assert verdicts[0]["failed_rule"] and verdicts[6]["failed_rule"] == "repeated_windows" and verdicts[17]["failed_rule"] is None
    assert quality_rules.apply_rules(empty).count() == 0


def test_rule_cascade(docs, spark):
    """The order is the same on every run and however rows are dealt; any order gives the same verdicts; names that clash are replaced."""
    names = [r.name for r in quality_rules.order_rules(docs)]
    assert sorted(names) == sorted(r.name for r in quality_rules.RULES)
    assert names == [r.name for r in quality_rules.order_rules(docs.repartition(7, "text"))] == [r.name for r in quality_rules.order_rules(docs)]
    told = docs.withColumn("failed_rule", docs["rank"])
    some = by_id(quality_rules.apply_rules(told))
    other = by_id(quality_rules.cascade(docs, quality_rules.RULES[::-1]))
    assert {i: r["failed_rule"] is None for i, r in some.items()} == {i: r["failed_rule"] is None for i, r in other.items()}
    words = " ".join(f"word{i}" for i in range(60))
    odd = [words, words + " lorem IPSUM", "\n".join(f"- {w} and {w}x" for w in words.split()), "\n".join(f"{w} {w}x ..." for w in words.split()), " ".join(f"{i}{i}" for i in range(60)), words, None]
    got = by_id(quality_rules.apply_rules(spark.createDataFrame(list(enumerate(odd)), "doc_id long, text string"), sample_rows=3))
    assert [got[i]["failed_rule"] for i in range(7)] == [None, "placeholder", "bullet_lines", "ellipsis_lines", "few_letters", None, "few_words"]


def test_rule_order_by_hand(spark):
    """A cheap rule that rejects much comes first; a rule whose rejections are all taken goes last."""
    rule = lambda name, below, cost: quality_rules.Rule(name, lambda t: t.n_words < below, lambda t: quality_rules.F.lit(cost))
    rows = spark.createDataFrame([(i, "a " * n) for i, n in enumerate([1, 1, 1, 5, 5, 9, 9, 9])], "doc_id long, text string")
    made = [rule("dear", 6, 100), rule("cheap", 3, 1), rule("all", 10, 1000), rule("none", 0, 1)]
    assert [r.name for r in quality_rules.order_rules(rows, made)] == ["cheap", "dear", "all", "none"]


def test_classifier(docs, empty, spark):
    good, bad = [PROSE.lower() * k for k in range(1, 25)], [PROSE.upper().replace(" ", "!! ") * k for k in range(1, 25)]
    both = good + bad
    table = spark.createDataFrame(list(enumerate(both)), "doc_id long, text string")
    labels = spark.createDataFrame([(i, int(i < 24)) for i in range(48)] + [(None, 1), (3, None)], "doc_id long, quality int")
    m = quality_classifier.train(table, labels)
    scored = by_id(quality_classifier.score_quality(table, m))
    assert sum(scored[i]["predicted"] == int(i < 24) for i in range(48)) >= 46
    long = (PROSE * 60000).encode()
    ids, first = quality_classifier.lay_out([long])
    whole = quality_classifier.probability(m, quality_classifier.pooled(m, ids, first)[-1])
    assert np.allclose(quality_classifier._whole(m, long), whole, atol=1e-6)
    assert all(0 <= r["score"] <= 1 for r in quality_classifier.score_quality(docs, m).collect())
    assert quality_classifier.score_quality(empty, quality_classifier.train(empty, labels.limit(0))).count() == 0


def test_classifier_on_held_out_rows(spark):
    """Labels of rows that training never saw: area under the curve."""
    sf = "/root/testdata/sf0.01"
    labels = {r["doc_id"]: r["quality"] for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    rows = [(r["score"], labels[r["doc_id"]]) for r in quality_classifier.op8_quality_classifier(spark, sf).collect() if r["held_out"] and labels.get(r["doc_id"]) is not None]
    good, bad = ([x for x, y in rows if y == k] for k in (1, 0))
    assert len(good) > 20 and len(bad) > 5
    assert sum((a > b) + (a == b) / 2 for a in good for b in bad) / (len(good) * len(bad)) > 0.9


def test_urls(spark):
    pages = [(1, "https://a.example.net/en/x", ""), (2, "http://b.net/", None), (3, "http://EXAMPLE.com/de/", '<link href="https://alias.io/p" rel="canonical">'), (4, "https://alias.io/p#top", "<html>"), (5, "https://far.io/q", '<meta http-equiv="refresh" content="0; url=https://alias.io/p">'), (6, "https://x.org/fr/", '<link rel=canonical href=https://alias.io/p>'), (7, None, None), (8, "no scheme", None), (9, "http://net", ""), (10, "https://ok.io/", '<link rel="canonical" href="/same">'), (4, "https://alias.io/p#top", "<html>")]
    got = url_filter.judge_urls(spark.createDataFrame(pages, "page_id long, url string, html string")).collect()
    verdict = {r["page_id"]: (r["rule"], r["verdict"]) for r in got}
    assert len(got) == 11
    assert verdict == {1: ("example.net/en/", "allow"), 2: ("net/", "block"), 3: ("example.com/de/", "block"), 4: (None, "block"), 5: (None, "block"), 6: ("org/fr/", "allow"), 7: (None, "allow"), 8: (None, "allow"), 9: (None, "allow"), 10: (None, "allow")}
    assert url_filter.judge_urls(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


def test_url_targets(spark):
    """Relative targets as urllib reads them; entities, empty paths and second links reach their page."""
    from html import unescape
    from urllib.parse import urljoin

    urls = ["https://h.io/a/b/c?q=1#f", "https://h.io", "https://h.io/a/"]
    targets = ["page.html", "?id=5", "../x", "../../../x/", "./", "..", "/a/../b?x=/../y", "//o.io/z", "https://o.io/p", "d/e?u=http://w.io/", "#top", "mailto:a@b.c"]
    got = spark.createDataFrame([(u, t) for u in urls for t in targets], "url string, t string").select("url", "t", url_filter.resolved(url_filter.F.col("t"), url_filter.F.col("url")).alias("r")).collect()
    assert [(r["url"], r["t"], r["r"].replace("h.io/#", "h.io#")) for r in got] == [(r["url"], r["t"], urljoin(r["url"], r["t"]).replace("h.io/#", "h.io#").replace("h.io?", "h.io?")) for r in got]
    coded = ["?a=1&amp;b=2", "a&#38;b&#x26;c", "&eacute;&unknown;&", "&amp;amp;", "&#x1F600;x"]
    assert [r["d"] for r in spark.createDataFrame([(c,) for c in coded], "c string").select(url_filter.decoded(url_filter.F.col("c")).alias("d")).collect()] == [unescape(c) for c in coded]
    link = '<link rel="canonical" href="{}">'.format
    bad = "http://x.example.com/de/s/t"
    pages = [(0, bad, link("../u") + link("https://two.io/?a=1&amp;b=2") + link("https://three.io")), (1, "http://x.example.com/de/u", ""), (2, "https://two.io/?a=1&b=2", ""), (3, "https://three.io/", ""), (4, "https://five.io/s/p", link("q.html")), (5, "https://five.io/s/q.html", '<meta http-equiv=refresh content="0;url=r"><meta http-equiv=refresh content="0;url=' + bad + '">'), (6, "https://five.io/s/r", ""), (7, "https://five.io/q.html", ""), (8, "https://six.io/a", '<base href="/deep/er/">' + link("x")), (9, "https://six.io/deep/er/x", link(bad))]
    verdict = {r["page_id"]: r["verdict"] for r in url_filter.judge_urls(spark.createDataFrame(pages, "page_id long, url string, html string")).collect()}
    assert verdict == {k: "allow" if k == 7 else "block" for k in range(10)}
    redirects = spark.createDataFrame([(bad, "../../moved")], "from_url string, to_url string")
    moved = spark.createDataFrame([(1, "http://x.example.com/moved", "")], "page_id long, url string, html string")
    assert url_filter.judge_urls(moved, redirects=redirects).first()["verdict"] == "block"


@pytest.mark.parametrize("block", [16, 1024])
def test_embeddings(spark, block):
    r = np.random.default_rng(6)
    seeds = r.normal(size=(12, 16))
    vecs = np.concatenate([seeds, *[s + r.normal(size=(25, 16)) * r.choice([0.01, 0.05, 0.2]) for s in seeds], seeds[:3], seeds[:2] * 2])
    labels = [int(x) for x in r.integers(0, 2, len(vecs))]
    rows = [(i, [float(x) for x in v], y) for i, (v, y) in enumerate(zip(vecs, labels, strict=True))]
    n = len(rows)
    rows += [(n, None, 1), (n + 1, [0.0] * 16, 1), (n + 2, [float("nan")] + [1.0] * 15, 1), (n + 3, rows[0][1], None), (n + 4, [None] + [1.0] * 15, 1), (n + 5, [], 0), (n + 6, [1.0, 2.0], 0)]
    got = {x["vec_id"]: x for x in embedding_dedup.link_vectors(spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int"), block=block).collect()}
    u = vecs / np.linalg.norm(vecs, axis=1, keepdims=True)
    near = (u @ u.T >= 0.98) & (np.array(labels)[:, None] == np.array(labels)[None])
    group = np.arange(n)
    for i in range(n):
        for j in np.flatnonzero(near[i]):
            group[group == max(group[i], group[j])] = min(group[i], group[j])
    assert [(got[i]["n_links"], got[i]["component_id"]) for i in range(n)] == [(int(near[i].sum()) - 1, int(group[i])) for i in range(n)]
    assert all((got[i]["n_links"], got[i]["component_id"]) == (0, i) for i in range(n, n + 7))


def test_embedding_blocks_are_skipped(spark, empty):
    """On clustered vectors most pairs of blocks are never formed; repeated rows beyond the broadcast bound and other columns do no harm."""
    r = np.random.default_rng(8)
    centres = r.normal(size=(64, 32))
    vecs = np.repeat(centres, 40, axis=0) + r.normal(size=(2560, 32)) * 0.03
    rows = [(i, [float(x) for x in v], 0, 1, "x", 2) for i, v in enumerate(vecs)]
    rows += [(len(rows) + i, rows[0][1], 0, 1, "x", 2) for i in range(700)]
    table = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int, n long, block string, rep int")
    _, blocks, pairs = embedding_dedup.classes_of(embedding_dedup.checked(table), 0.98, block=64)
    formed, every = embedding_dedup.pairs_report(blocks, pairs).first()
    assert blocks.count() <= formed < every / 4
    got = {x["vec_id"]: x for x in embedding_dedup.link_vectors(table, block=64).collect()}
    u = vecs / np.linalg.norm(vecs, axis=1, keepdims=True)
    near = u @ u.T >= 0.98
    assert len(got) == len(rows) and all(got[i]["n_links"] == near[i].sum() - 1 + (700 if near[i, 0] else 0) for i in range(0, 2560, 7))
    assert all(got[i]["component_id"] == 0 for i in range(2560, 3260))
    none = spark.createDataFrame([], "vec_id long, embedding array<float>, label int")
    assert embedding_dedup.link_vectors(none).count() == 0
