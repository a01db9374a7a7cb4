"""License scans through a positional index of rare licence words, with DataFrame functions only."""

from __future__ import annotations

import math
import re
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import ascii_lower, let, table

#: Fixed by the contract: what separates words, after A-Z are lower-cased; phrases and their labels.
GAP = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
BASE = [("under the mit license", "mit"), ("apache license version 2", "apache-2"), ("cc by nc", "cc-by-nc")]

#: Function words, which the index leaves out.
STOP = set("a all an and any are as at be by for from in is it may not of on or that the this to under use with you your".split())


@dataclass(frozen=True)
class Template:
    """`text` as it is printed; `key` is a phrase of it that a match must hold at its place."""

    label: str
    text: str
    key: str

    def words(self) -> list[str]:
        return [w for w in re.split(GAP, self.text.lower()) if w]

    def key_place(self) -> int:
        text, key = self.words(), self.key.split()
        return next(i for i in range(len(text)) if text[i : i + len(key)] == key)


#: Notices of public licences, and the phrase without which each does not count.
TEMPLATES = [
    Template("mit", "released under the mit license", "under the mit license"),
    Template("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files", "permission is hereby granted free of charge to any person"),
    Template("apache-2", "licensed under the apache license version 2 0", "apache license version 2"),
    Template("cc-by-nc", "licensed under cc by nc 4 0", "cc by nc"),
    Template("cc-by", "licensed under cc by 4 0", "licensed under cc by 4"),
    Template("cc-by-sa", "licensed under cc by sa 4 0", "cc by sa"),
    Template("gpl-3", "this work is licensed under the gnu general public license version 3", "gnu general public license version 3"),
    Template("gpl-2", "this program is licensed under the gnu general public license version 2", "gnu general public license version 2"),
    Template("lgpl", "licensed under the gnu lesser general public license", "gnu lesser general public license"),
    Template("bsd", "redistribution and use in source and binary forms with or without modification are permitted", "redistribution and use in source and binary forms"),
    Template("isc", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted", "permission to use copy modify and or distribute this software"),
    Template("mpl-2", "subject to the terms of the mozilla public license v 2 0", "mozilla public license v 2"),
    Template("unlicense", "this is free and unencumbered software released into the public domain", "unencumbered software released into the public domain"),
    Template(
        "mit",
        """Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation
        files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy,
        modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software
        is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be
        included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY
        KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND
        NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY,
        WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR
        OTHER DEALINGS IN THE SOFTWARE.""",
        "permission is hereby granted free of charge to any person",
    ),
    Template(
        "bsd",
        """Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following
        conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the
        following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and
        the following disclaimer in the documentation and/or other materials provided with the distribution. 3. Neither the name of
        the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software
        without specific prior written permission.""",
        "redistribution and use in source and binary forms",
    ),
    Template(
        "isc",
        """Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted,
        provided that the above copyright notice and this permission notice appear in all copies.""",
        "permission to use copy modify and or distribute this software",
    ),
    Template(
        "apache-2",
        """Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the
        License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0. Unless required by applicable law
        or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR
        CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and
        limitations under the License.""",
        "apache license version 2",
    ),
    Template(
        "gpl-3",
        """This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as
        published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.""",
        "gnu general public license as published by the free software foundation either version 3",
    ),
    Template(
        "gpl-2",
        """This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as
        published by the Free Software Foundation; either version 2 of the License, or (at your option) any later version.""",
        "gnu general public license as published by the free software foundation either version 2",
    ),
    Template(
        "lgpl",
        """This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public
        License as published by the Free Software Foundation; either version 2.1 of the License, or (at your option) any later version.""",
        "gnu lesser general public license",
    ),
    Template(
        "agpl",
        """This program is free software: you can redistribute it and/or modify it under the terms of the GNU Affero General Public
        License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.""",
        "gnu affero general public license",
    ),
    Template(
        "mpl-2",
        """This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed
        with this file, You can obtain one at http://mozilla.org/MPL/2.0/.""",
        "mozilla public license v 2",
    ),
    Template(
        "unlicense",
        """This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use,
        compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or
        non-commercial, and by any means.""",
        "unencumbered software released into the public domain",
    ),
    Template(
        "zlib",
        """This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for
        any damages arising from the use of this software. Permission is granted to anyone to use this software for any purpose,
        including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions""",
        "to alter it and redistribute it freely",
    ),
    Template("cc-by", "This work is licensed under a Creative Commons Attribution 4.0 International License", "creative commons attribution 4 0 international"),
    Template("cc-by-sa", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License", "creative commons attribution sharealike"),
    Template("cc-by-nc", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License", "creative commons attribution noncommercial"),
    Template("cc0", "To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work", "has waived all copyright and related or neighboring rights"),
]


def rarity(frequency: dict[str, int], n: int):
    """Weight of a word by the documents that hold it: 1 plus its inverse document frequency, so 1 for a word of all."""
    return lambda word: 1 + math.log((n + 1) / (frequency.get(word, 0) + 1))


class Index:
    """Postings of the templates' words (function words left out), each a place in a template and a weight, and the key
    phrases, posted under the rarest word of each: a file looks up these words only."""

    def __init__(self, templates: list[Template] | None = None, base=BASE, frequency: dict[str, int] | None = None, n: int = 0):
        self.templates = TEMPLATES if templates is None else templates
        weight = rarity(frequency or {}, n)
        self.phrases = list(dict.fromkeys([*(tuple(p.split()) for p, _ in base), *(tuple(t.key.split()) for t in self.templates)]))
        self.anchors = [min((i for i, w in enumerate(p) if w not in STOP), key=lambda i, p=p: (-weight(p[i]), i)) for p in self.phrases]
        self.looked_up = sorted({p[i] for p, i in zip(self.phrases, self.anchors, strict=True)})
        self.postings = [[(q, w, weight(w)) for q, w in enumerate(t.words()) if w not in STOP] for t in self.templates]
        self.vocabulary = sorted({w for t in self.postings for _, w, _ in t} | {w for p in self.phrases for w in p if w not in STOP})


def tokens(text: Column) -> Column:
    return F.array_remove(F.split(ascii_lower(F.coalesce(text, F.lit(""))), GAP), "")


def document_frequency(docs: DataFrame, words: list[str]) -> tuple[dict[str, int], int]:
    """How many documents hold each of the words, over all documents; a row per word comes back."""
    known = F.array(*map(F.lit, words))
    held = docs.select(F.explode(F.array_intersect(tokens(F.col("text")), known)).alias("w")).groupBy("w").count()
    return {r[0]: r[1] for r in held.collect()}, docs.count()


def _starts(w: Column, found: Column, phrase: tuple[str, ...], at: int) -> Column:
    """Places where the phrase stands, tried only where its rarest word does."""
    whole = F.array(*map(F.lit, phrase))
    here = F.filter(F.transform(w, lambda x, i: F.when(x == phrase[at], i - at)), lambda p: p >= 0)
    stand = F.filter(here, lambda p: F.slice(w, p + 1, len(phrase)) == whole)
    return F.when(F.array_contains(found, phrase[at]), stand).otherwise(F.array().cast("array<int>"))


def _agreement(w: Column, starts: Column, place: int, postings: list[tuple[int, str, float]]) -> Column:
    """The largest weighted share of a template's words that stand where it would have them, over the places of its key phrase."""
    places, words, weights = (F.array(*map(F.lit, x)) for x in zip(*postings, strict=True))
    total = sum(x for _, _, x in postings)
    one = lambda s: F.aggregate(F.sequence(F.lit(0), F.lit(len(postings) - 1)), F.lit(0.0), lambda acc, i: acc + F.when(F.get(w, s - place + F.get(places, i)).eqNullSafe(F.get(words, i)), F.get(weights, i)).otherwise(0.0))
    return F.coalesce(F.array_max(F.transform(starts, one)) / total, F.lit(0.0))


def scan_licenses(docs: DataFrame, templates: list[Template] | None = None, base=BASE) -> DataFrame:
    """docs without text, with n_words, n_base, first_word, last_word, base_labels, labels and score; columns of these names are replaced.

    The licence words' document frequencies, over all documents, choose the
    rarest word of each key phrase; a file looks up these. Where one stands, its
    key phrase is verified in place, and the template's other words are met by
    their places relative to it. score: the largest weighted share of a found
    template's words that agree, 1 with a base label, 0 with no label. Every
    place of a phrase counts, in texts of any length. A null or empty text has
    no word and no label; equal texts get equal results; an empty table gives
    no rows."""
    frequency, n = document_frequency(docs, Index(templates, base).vocabulary)
    index = Index(templates, base, frequency, n)
    number = {p: i for i, p in enumerate(index.phrases)}
    of = [number[tuple(t.key.split())] for t in index.templates]
    rare = F.array(*map(F.lit, index.looked_up))
    shape = "struct<n_words:bigint,starts:array<array<int>>,score:double>"
    size = lambda w: F.size(w).cast("long").alias("n_words")
    none = lambda w: F.struct(size(w), F.array_repeat(F.array().cast("array<int>"), len(index.phrases)).alias("starts"), F.lit(0.0).alias("score")).cast(shape)
    best = lambda w, st: F.greatest(F.lit(0.0), F.lit(0.0), *[F.when(F.size(st[of[k]]) > 0, _agreement(w, st[of[k]], t.key_place(), index.postings[k])).otherwise(0.0) for k, t in enumerate(index.templates)])
    met = lambda w, st: F.struct(size(w), st.alias("starts"), F.when(F.exists(st, lambda x: F.size(x) > 0), best(w, st)).otherwise(0.0).alias("score")).cast(shape)
    some = lambda w, found: let(F.array(*[_starts(w, found, p, at) for p, at in zip(index.phrases, index.anchors, strict=True)]), lambda st: met(w, st))
    scan = let(tokens(F.col("text")), lambda w: let(F.array_intersect(w, rare), lambda found: F.when(F.size(found) == 0, none(w)).otherwise(some(w, found))))
    named = [c for c in docs.columns if c not in ("text", *RESULT)]
    out = docs.select(*named, scan.alias("_scan"))
    starts = F.col("_scan.starts")
    held = lambda i, label: F.when(F.size(starts[i]) > 0, F.lit(label))
    own = F.array_distinct(F.array_compact(F.array(*[held(number[tuple(p.split())], label) for p, label in base])))
    more = F.array_compact(F.array(*[held(of[k], t.label) for k, t in enumerate(index.templates)]))
    places = F.flatten(F.array(*[starts[number[tuple(p.split())]] for p, _ in base]))
    return out.select(
        *named,
        F.col("_scan.n_words").alias("n_words"),
        F.size(places).cast("long").alias("n_base"),
        F.array_min(places).cast("long").alias("first_word"),
        F.array_max(places).cast("long").alias("last_word"),
        F.array_join(F.array_sort(own), ",").alias("base_labels"),
        F.array_join(F.array_sort(F.array_union(own, more)), ",").alias("labels"),
        F.when(F.size(own) > 0, 1.0).otherwise(F.least(F.col("_scan.score"), F.lit(1.0))).alias("score"),
    )


RESULT = ("n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score")


def op3_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_licenses(table(spark, sf_dir, "documents").select("doc_id", "text"))
