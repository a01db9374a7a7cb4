"""Quality rules as a short-circuit cascade, with DataFrame functions only."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import SPACE, ascii_lower, let, table

#: Rows of the sample on which a rule's cost and selectivity are estimated.
SAMPLE_ROWS = 2000
#: A word without a letter.
LETTERLESS = r"(?<![^\x20\x09-\x0D])[^\x20\x09-\x0D\p{L}]++(?![^\x20\x09-\x0D])"
#: A line with a word; a line that begins as the item of a list; a line that breaks off.
LINE = r"(?:^|\n)[\x20\x09\x0B-\x0D]*[^\x20\x09-\x0D]"
BULLET, ELLIPSIS = r"(?:^|\n)[\x20\x09]*[\x{2022}\x{25CF}\x{2023}*\x2D]", r"(?:\.\.\.|\x{2026})[\x20\x09\x0B-\x0D]*(?:\n|\z)"


def words(text: Column) -> Column:
    return F.array_remove(F.split(F.coalesce(text, F.lit("")), SPACE), "")


def n_words(text: Column) -> Column:
    return F.size(words(text)).cast("long")


def word_chars(text: Column) -> Column:
    return F.length(F.regexp_replace(F.coalesce(text, F.lit("")), SPACE, "")).cast("long")


def n_symbols(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(r"[#*$%&|<>]")), F.lit(0)).cast("long")


def n_dup_lines(text: Column) -> Column:
    """Lines with a word that equal an earlier line."""
    lines = F.filter(F.split(F.coalesce(text, F.lit("")), "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    return let(lines, lambda x: F.size(x) - F.size(F.array_distinct(x))).cast("long")


def n_repeat_words(text: Column) -> Column:
    """Words inside a 3-word window that occurs twice or more in the text.

    Windows become 64-bit hashes with their place; equal ones meet by sorting
    within the row, so a text of n words takes O(n log n)."""
    return let(words(text), _repeats)


def _repeats(w: Column) -> Column:
    windows = F.transform(F.sequence(F.lit(0), F.size(w) - 3), lambda i: F.struct(F.xxhash64(w[i], w[i + 1], w[i + 2]).alias("h"), i.alias("i")))
    again = lambda s: F.filter(F.sequence(F.lit(1), F.size(s) - 1), lambda j: s[j]["h"] == s[j - 1]["h"])
    covered = lambda s: F.flatten(F.transform(again(s), lambda j: F.array(*[s[k]["i"] + step for k in (j - 1, j) for step in range(3)])))
    return F.when(F.size(w) < 4, F.lit(0)).otherwise(let(F.sort_array(windows), lambda s: F.size(F.array_distinct(covered(s))))).cast("long")


def word_measures(text: Column) -> Column:
    """struct(n_words, word_chars, n_repeat_words) from one split of the text."""
    return let(words(text), lambda w: F.struct(F.size(w).cast("long").alias("n_words"), F.length(F.array_join(w, "")).cast("long").alias("word_chars"), _repeats(w).alias("n_repeat_words")))


@dataclass(frozen=True)
class Text:
    """What rules look at: the text, its words, and measures, each evaluated when a rule reaches it.

    `known`: the measures are there already and cost nothing more."""

    raw: Column
    words: Column | None
    known: dict[str, Column] | None = None

    def __getattr__(self, name: str) -> Column:
        if name not in MEASURES:
            raise AttributeError(name)
        if self.known:
            return self.known[name]
        of_words = {"n_words": lambda w: F.size(w).cast("long"), "word_chars": lambda w: F.length(F.array_join(w, "")).cast("long"), "n_repeat_words": _repeats}
        return of_words[name](self.words) if name in of_words else MEASURES[name](self.raw)

    def many_lines(self, pattern: str, percent: int) -> Column:
        """Whether more than `percent` of the lines with a word match; lines are counted where any matches."""
        return let(F.regexp_count(self.raw, F.lit(pattern)), lambda n: (n > 0) & (100 * n > percent * F.regexp_count(self.raw, F.lit(LINE))))


@dataclass(frozen=True)
class Rule:
    """Rejects a text where `fails` is true; null counts as false. `cost`: the steps it takes, counted, not timed."""

    name: str
    fails: Callable[[Text], Column]
    cost: Callable[[Text], Column]


def _measured(steps: Callable[[Text], Column]) -> Callable[[Text], Column]:
    return lambda t: F.lit(1) if t.known else steps(t)


def _chars(times: int) -> Callable[[Text], Column]:
    return lambda t: F.length(t.raw) * times + 1


def _sorting(t: Text) -> Column:
    n = F.size(t.words)
    return n * F.ceil(F.log2(n + F.lit(2))) * 8


RULES = [
    Rule("few_words", lambda t: t.n_words < 50, lambda t: F.lit(1)),
    Rule("repeated_windows", lambda t: 100 * t.n_repeat_words > 50 * t.n_words, _measured(_sorting)),
    Rule("symbols", lambda t: 10 * t.n_symbols > t.n_words, _measured(_chars(2))),
    Rule("duplicate_lines", lambda t: 20 * t.n_dup_lines > t.n_words, _measured(_chars(2))),
    Rule("word_length", lambda t: (t.word_chars < 2 * t.n_words) | (t.word_chars > 20 * t.n_words), _measured(_chars(1))),
    Rule("few_letters", lambda t: 100 * F.regexp_count(t.raw, F.lit(LETTERLESS)) > 40 * t.n_words, _chars(2)),
    Rule("bullet_lines", lambda t: t.many_lines(BULLET, 90), _chars(3)),
    Rule("ellipsis_lines", lambda t: (F.contains(t.raw, F.lit("...")) | F.contains(t.raw, F.lit("\u2026"))) & t.many_lines(ELLIPSIS, 30), _chars(3)),
    Rule("placeholder", lambda t: F.contains(ascii_lower(t.raw), F.lit("lorem ipsum")), _chars(2)),
]
MEASURES = {"n_words": n_words, "word_chars": word_chars, "n_symbols": n_symbols, "n_dup_lines": n_dup_lines, "n_repeat_words": n_repeat_words}


def _steps(docs: DataFrame, rules: list[Rule], sample_rows: int, known: bool) -> list[tuple]:
    """(which rules fail, texts, steps of each rule), summed over a sample by the texts' hash: the same rows on every run.

    Equal texts are summed up before anything is measured, so a hot text is one."""
    n = docs.count()
    if not n:
        return []
    top = 1 << 30
    cut = min(top, -(-sample_rows * top // n))
    raw = F.coalesce(F.col("text"), F.lit(""))
    sample = docs.where(F.pmod(F.xxhash64("text"), F.lit(top)) < cut).groupBy("text").agg(F.count(F.lit(1)).alias("n")).select("n", raw.alias("raw"), words(F.col("text")).alias("w"))
    t = Text(F.col("raw"), F.col("w"))
    costs = Text(t.raw, t.words, {"n_words": F.lit(1)}) if known else t
    mask = F.concat(*[F.coalesce(r.fails(t), F.lit(False)).cast("int").cast("string") for r in rules])
    by = sample.select("n", mask.alias("mask"), *[(r.cost(costs) * F.col("n")).cast("long").alias(f"c{i}") for i, r in enumerate(rules)])
    rows = by.groupBy("mask").agg(F.sum("n"), *[F.sum(f"c{i}") for i in range(len(rules))]).collect()
    return sorted((r[0], r[1], tuple(r[2:])) for r in rows)


def order_rules(docs: DataFrame, rules: list[Rule] | None = None, sample_rows: int = SAMPLE_ROWS, known: bool = False) -> list[Rule]:
    """Sorts rules by rejections per cost on a sample of about `sample_rows` rows, each rule by what the ones before it leave.

    Cost is counted in steps, so every run finds the same order; it changes the
    time that verdicts take and which failure is named first, never the
    verdicts. Rules that reject nothing more go last, the cheaper first. An
    empty table leaves the order as it is."""
    rules = RULES if rules is None else rules
    left, open_, out = _steps(docs, rules, sample_rows, known), list(range(len(rules))), []
    while open_ and left:
        gain = lambda i: sum(n for mask, n, _ in left if mask[i] == "1")  # noqa: B023, E731
        cost = lambda i: sum(c[i] for _, _, c in left)  # noqa: B023, E731
        best = min(open_, key=lambda i: (-gain(i) / max(cost(i), 1), cost(i), i))
        out.append(rules[best])
        open_.remove(best)
        left = [x for x in left if x[0][best] == "0"]
    return out + [rules[i] for i in open_]


def first_failure(rules: list[Rule], t: Text) -> Column:
    """The name of the first rule that rejects, null if none does; later rules are not evaluated then."""
    out = F.lit(None).cast("string")
    for rule in reversed(rules):
        out = F.when(F.coalesce(rule.fails(t), F.lit(False)), F.lit(rule.name)).otherwise(out)
    return out


def cascade(docs: DataFrame, ordered: list[Rule]) -> DataFrame:
    """docs with `failed_rule` (null: kept; a column of that name is replaced): the text is split once, and each rule looks at it when it is reached."""
    raw = F.coalesce(F.col("text"), F.lit(""))
    return docs.withColumn("failed_rule", let(words(F.col("text")), lambda w: first_failure(ordered, Text(raw, w))))


def apply_rules(docs: DataFrame, rules: list[Rule] | None = None, sample_rows: int = SAMPLE_ROWS) -> DataFrame:
    """docs with `failed_rule` (null: kept). A null or empty text has no words and fails few_words; equal rows get equal
    verdicts, on every run the same; other columns stay as they are, null or not."""
    return cascade(docs, order_rules(docs, rules, sample_rows))


def op7_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Base counts of every text and the verdict. The counts are asked for, so they are evaluated for every row and cost
    the cascade nothing; the rules on letters, lines and placeholders are reached only by rows that nothing before rejects."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    ordered = order_rules(docs, known=True)
    split = docs.select("doc_id", "text", word_measures(F.col("text")).alias("m"), n_symbols(F.col("text")).alias("n_symbols"), n_dup_lines(F.col("text")).alias("n_dup_lines"))
    measured = split.select("doc_id", "text", "m.n_words", "m.word_chars", "n_symbols", "n_dup_lines", "m.n_repeat_words")
    t = Text(F.coalesce(F.col("text"), F.lit("")), None, {k: F.col(k) for k in MEASURES})
    base = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    kept = F.when(base, F.lit(False)).otherwise(first_failure(ordered, t).isNull())
    return measured.select("doc_id", *MEASURES, base.alias("base_failed"), kept.alias("kept"))


ORACLE = r"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
w AS (SELECT doc_id, t, regexp_extract_all(t, '[^\x20\x09-\x0D]+') AS w FROM d),
x AS (SELECT doc_id, len(w) AS n, unnest(range(len(w) - 2)) AS i, w FROM w WHERE len(w) >= 3),
y AS (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, w[i + 1], w[i + 2], w[i + 3]) AS c FROM x),
r AS (SELECT doc_id, count(DISTINCT p) AS n_repeat_words FROM (SELECT doc_id, unnest([i, i + 1, i + 2]) AS p FROM y WHERE c > 1) GROUP BY 1),
l AS (SELECT doc_id, list_filter(string_split(t, chr(10)), lambda q: regexp_matches(q, '[^\x20\x09-\x0D]')) AS l FROM d),
m AS (SELECT w.doc_id, CAST(len(w) AS BIGINT) AS n_words,
  CAST(length(regexp_replace(t, '[\x20\x09-\x0D]+', '', 'g')) AS BIGINT) AS word_chars,
  CAST(len(regexp_extract_all(t, '[#*$%&|<>]')) AS BIGINT) AS n_symbols,
  CAST(len(l) - len(list_distinct(l)) AS BIGINT) AS n_dup_lines,
  CAST(coalesce(n_repeat_words, 0) AS BIGINT) AS n_repeat_words,
  100 * len(list_filter(w, lambda q: regexp_matches(q, '\p{L}'))) < 60 * len(w) AS few_letters,
  100 * len(list_filter(l, lambda q: regexp_matches(q, '^[\x20\x09]*[\x{2022}\x{25CF}\x{2023}*\x2D]'))) > 90 * len(l) AS bullets,
  100 * len(list_filter(l, lambda q: regexp_matches(q, '(\.\.\.|\x{2026})[\x20\x09\x0B-\x0D]*$'))) > 30 * len(l) AS ellipses,
  contains(translate(t, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), 'lorem ipsum') AS placeholder
  FROM w JOIN l USING (doc_id) LEFT JOIN r USING (doc_id))
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, (n_words < 50 OR 100 * n_repeat_words > 50 * n_words) AS base_failed,
  NOT (n_words < 50 OR 100 * n_repeat_words > 50 * n_words OR 10 * n_symbols > n_words OR 20 * n_dup_lines > n_words
       OR word_chars < 2 * n_words OR word_chars > 20 * n_words OR few_letters OR bullets OR ellipses OR placeholder) AS kept
FROM m
"""
