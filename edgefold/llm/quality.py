"""Quality rules: a table of thresholds compiled into one projection.

Measures are Column expressions over one pass of words and lines; a rule is a row (name, measure,
least, most, per, share) and compiles to an exact integer comparison. No user function runs, no rows move.

Words are runs of characters outside x20 and x09-x0D; lines are split at \\n and count when they hold
a word. Cases: null text has no words, every count is 0 and the base fails; null ids and repeated
rows are judged each; empty tables give empty results; very long texts are measured whole.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Separators, the counted symbols, window length of repeats.
SPACES = " \t\n\x0b\x0c\r"
SYMBOLS = "#*$%&|<>"
WINDOW = 8
#: Frequent function words of English, German, French and Spanish.
STOP_WORDS = (
    "the of and to in is that it for on with as was by this be are from or at an "
    "der die das und zu den von mit ist im ein nicht sich auf für dem des eine "
    "le la les et des du un une en que qui dans est pour au il pas avec "
    "el los las y del se por con para una su al lo como más"
).split()


@dataclass(frozen=True)
class Rule:
    """``least <= measure`` and ``100 * measure <= most_percent * per``; None leaves a side open."""

    name: str
    measure: str
    least: int | None = None
    most_percent: int | None = None
    per: str = "n_words"
    least_percent: int | None = None

    def holds(self) -> Column:
        value, tests = F.col(self.measure), []
        if self.least is not None:
            tests.append(value >= self.least)
        if self.most_percent is not None:
            tests.append(100 * value <= self.most_percent * F.col(self.per))
        if self.least_percent is not None:
            tests.append(100 * value >= self.least_percent * F.col(self.per))
        out = tests[0]
        for t in tests[1:]:
            out = out & t
        return out

    def sql(self) -> str:
        parts = []
        if self.least is not None:
            parts.append(f"{self.measure} >= {self.least}")
        if self.most_percent is not None:
            parts.append(f"100 * {self.measure} <= {self.most_percent} * {self.per}")
        if self.least_percent is not None:
            parts.append(f"100 * {self.measure} >= {self.least_percent} * {self.per}")
        return " AND ".join(parts)


BASE_RULES = (Rule("length", "n_words", least=20), Rule("repeats", "n_repeat_words", most_percent=30))
METHOD_RULES = (
    Rule("word length", "word_chars", most_percent=1000, least_percent=300),
    Rule("symbols", "n_symbols", most_percent=10),
    Rule("exclamations", "n_exclamations", most_percent=30),
    Rule("stop words", "n_stop_words", least=2),
    Rule("repeated lines", "n_dup_lines", most_percent=50, per="n_lines"),
    Rule("ellipsis lines", "n_ellipsis_lines", most_percent=50, per="n_lines"),
    Rule("bullet lines", "n_bullet_lines", most_percent=90, per="n_lines"),
)
MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
MORE = ("n_exclamations", "n_stop_words", "n_lines", "n_ellipsis_lines", "n_bullet_lines")


def _bound(value: str, name: str, body: str) -> str:
    """SQL that evaluates ``value`` once and uses it as ``name`` in ``body``."""
    return f"element_at(transform(array({value}), {name} -> {body}), 1)"


def repeat_words_sql(words: str, window: int = WINDOW) -> str:
    """Words covered by windows that occur at least twice in the array ``words``.

    Windows are compared by hash. Only when some hash repeats are (hash, position) pairs sorted to
    find the positions; each covers ``window`` words, less what the next one covers.
    """
    hashes = f"transform(sequence(0, size({words}) - {window}), i -> xxhash64(slice({words}, i + 1, {window})))"
    pairs = "sort_array(transform(h, (x, i) -> struct(x AS x, i AS i)))"
    twice = "filter(s, (p, k) -> (k > 0 AND s[k - 1].x = p.x) OR (k < size(s) - 1 AND s[k + 1].x = p.x))"
    at = f"sort_array(transform({_bound(pairs, 's', twice)}, p -> p.i))"
    covered = f"aggregate(transform(p, (v, k) -> CASE WHEN k < size(p) - 1 THEN least({window}, p[k + 1] - v) ELSE {window} END), 0, (a, v) -> a + v)"
    repeated = f"CASE WHEN size(array_distinct(h)) = size(h) THEN 0 ELSE {_bound(at, 'p', covered)} END"
    return f"CASE WHEN size({words}) < {window} + 1 THEN 0 ELSE {_bound(hashes, 'h', repeated)} END"


def measures(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """Add every measure of :data:`MEASURES` and :data:`MORE` as long columns."""
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    less = lambda drop: F.length(text) - F.length(F.translate(text, drop, ""))
    has_word = r"l RLIKE '[^\\x20\\x09-\\x0D]'"
    stops = "array(" + ", ".join(f"'{w}'" for w in STOP_WORDS) + ")"
    words = _bound(r"array_remove(split(`_text`, '[\\x20\\x09-\\x0D]+'), '')", "w", f"named_struct('n', size(w), 'r', {repeat_words_sql('w')}, 's', size(array_intersect(w, {stops})))")
    lines = _bound(
        rf"filter(split(`_text`, '\n'), l -> {has_word})",
        "ls",
        r"named_struct('n', size(ls), 'd', size(ls) - size(array_distinct(ls)), 'e', size(filter(ls, l -> l RLIKE '(\\.\\.\\.|…)[\\x20\\x09-\\x0D]*$')), 'b', size(filter(ls, l -> l RLIKE '^[\\x20\\x09-\\x0D]*[-*•]')))",
    )
    counted = docs.withColumn("_text", text).withColumn("_words", F.expr(words)).withColumn("_lines", F.expr(lines))
    new = {
        "n_words": F.col("_words.n"),
        "word_chars": F.length(F.translate(text, SPACES, "")),
        "n_symbols": less(SYMBOLS),
        "n_dup_lines": F.col("_lines.d"),
        "n_repeat_words": F.col("_words.r"),
        "n_exclamations": less("!"),
        "n_stop_words": F.col("_words.s"),
        "n_lines": F.col("_lines.n"),
        "n_ellipsis_lines": F.col("_lines.e"),
        "n_bullet_lines": F.col("_lines.b"),
    }
    return counted.withColumns({k: v.cast("long") for k, v in new.items()}).drop("_words", "_lines", "_text")


def every(rules: tuple[Rule, ...]) -> Column:
    out = F.lit(True)
    for rule in rules:
        out = out & rule.holds()
    return out


def judge(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", rules: tuple[Rule, ...] = METHOD_RULES) -> DataFrame:
    """(id, measures, base_failed, kept) for every row of ``docs``."""
    only = docs.select(F.col(id_col).alias("_id"), F.col(text_col).alias("_t"))
    judged = measures(only, "_t").withColumn("base_failed", ~every(BASE_RULES))
    judged = judged.withColumn("kept", ~F.col("base_failed") & every(rules))
    return judged.select(F.col("_id").alias(id_col), *MEASURES, "base_failed", "kept", *MORE)


def keep(docs: DataFrame, text_col: str = "text", rules: tuple[Rule, ...] = METHOD_RULES) -> DataFrame:
    """The rows of ``docs`` that every rule accepts, with their own columns only."""
    packed = docs.select(F.struct(*docs.columns).alias("_row"), F.col(text_col).alias("_t"))
    return measures(packed, "_t").where(every(BASE_RULES) & every(rules)).select("_row.*")


def oracle() -> str:
    """DuckDB SQL for :func:`judge` over ``documents``."""
    stops = ", ".join(f"'{w}'" for w in STOP_WORDS)
    method = " AND ".join(f"({r.sql()})" for r in METHOD_RULES)
    return rf"""
WITH t AS (SELECT doc_id, coalesce(text, '') AS text FROM documents),
w AS (SELECT doc_id, text, list_filter(string_split_regex(text, '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws,
  list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS ls FROM t),
win AS (SELECT doc_id, i, array_to_string(ws[i:i+{WINDOW - 1}], ' ') AS g FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - {WINDOW - 2})) AS i FROM w WHERE len(ws) >= {WINDOW})),
twice AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, g) AS c FROM win) WHERE c > 1),
cov AS (SELECT doc_id, count(DISTINCT i + k) AS n FROM twice, (SELECT unnest(range(0, {WINDOW})) AS k) GROUP BY doc_id),
m AS (SELECT w.doc_id, len(ws)::BIGINT AS n_words, length(regexp_replace(text, '[\x20\x09-\x0D]+', '', 'g'))::BIGINT AS word_chars,
  length(regexp_replace(text, '[^#*$%&|<>]', '', 'g'))::BIGINT AS n_symbols,
  (len(ls) - len(list_distinct(ls)))::BIGINT AS n_dup_lines, coalesce(cov.n, 0)::BIGINT AS n_repeat_words,
  length(regexp_replace(text, '[^!]', '', 'g'))::BIGINT AS n_exclamations,
  len(list_distinct(list_filter(ws, lambda x: list_contains([{stops}], x))))::BIGINT AS n_stop_words, len(ls)::BIGINT AS n_lines,
  len(list_filter(ls, lambda x: regexp_matches(x, '(\.\.\.|…)[\x20\x09-\x0D]*$')))::BIGINT AS n_ellipsis_lines,
  len(list_filter(ls, lambda x: regexp_matches(x, '^[\x20\x09-\x0D]*[-*•]')))::BIGINT AS n_bullet_lines
  FROM w LEFT JOIN cov USING (doc_id))
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words,
  (n_words < 20 OR 100 * n_repeat_words > 30 * n_words) AS base_failed,
  NOT (n_words < 20 OR 100 * n_repeat_words > 30 * n_words) AND {method} AS kept,
  n_exclamations, n_stop_words, n_lines, n_ellipsis_lines, n_bullet_lines FROM m
"""
