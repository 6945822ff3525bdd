"""Quality rules: a table of thresholds compiled into one projection of built-in expressions.

Rows: every input row comes out once, other columns untouched unless they carry the name of a measure, which is
then replaced. Three-word windows are compared by 64-bit hash within one text. Null or empty text has no words, so every count is 0 and the base test fails it. Repeated rows get
equal verdicts; an empty table gives an empty table. Very long texts cost n log n in their words.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import documents

# Frequent function words of the four languages that the rules know.
STOP_WORDS = (
    "the of and to in is that it for was on are as with his they at be this have from or by he an you not "
    "der die das und in zu den mit von ist des sich auf dem ein eine nicht im auch als "
    "de la le et les des en un du une que est pour qui dans par sur au plus "
    "el los las y que se del por con una su para es al lo como"
).split()
SYMBOLS = "#*$%&|<>"

_WS = r"[\\x20\\x09-\\x0D]+"
_TRIM = r"btrim({0}, ' \t\n\x0B\f\r')".replace(r"\x0B", "\x0b").replace(r"\f", "\x0c").replace(r"\t", "\t").replace(r"\n", "\n").replace(r"\r", "\r")


def _let(value: str, name: str, body: str) -> str:
    """``body`` with ``name`` bound to ``value``, which is computed once."""
    return f"element_at(transform(array({value}), {name} -> {body}), 1)"


def measures(text: str = "text") -> dict[str, Column]:
    """The counts that rules may name, each one built-in expression over the words array ``_w`` or the text."""
    t = f"coalesce({text}, '')"
    hashes = "transform(slice(_w, 1, size(_w) - 2), (a, i) -> xxhash64(a, _w[i + 1], _w[i + 2]))"
    repeated = _let("sort_array(h)", "s", "filter(s, (x, j) -> j > 0 AND s[j - 1] = x)")
    cover = "aggregate({0}, struct(0L AS c, -3 AS p), (a, i) -> struct(a.c + least(3, i - a.p) AS c, i AS p), a -> a.c)"
    few = cover.format("filter(transform(h, (x, i) -> if(array_contains(r, x), i, -1)), i -> i >= 0)")
    windows = "sort_array(transform(h, (x, i) -> struct(x AS g, i AS i)))"
    twice = "filter(s, (x, j) -> (j > 0 AND s[j - 1].g = x.g) OR (j < size(s) - 1 AND s[j + 1].g = x.g))"
    many = _let(windows, "s", _let(twice, "d", cover.format("sort_array(transform(d, x -> x.i))")))
    found = _let(repeated, "r", f"CASE WHEN size(r) = 0 THEN 0L WHEN size(r) <= 12 THEN {few} ELSE {many} END")
    repeat = f"CASE WHEN size(_w) < 4 THEN 0L ELSE {_let(hashes, 'h', found)} END"
    lines = f"filter(split({t}, '\\n', -1), l -> {_TRIM.format('l')} != '')"
    stops = ", ".join(f"'{w}', '{w.capitalize()}', '{w.upper()}'" for w in STOP_WORDS)
    return {
        "n_words": F.expr("CAST(size(_w) AS BIGINT)"),
        "word_chars": F.expr("CAST(length(array_join(_w, '')) AS BIGINT)"),
        "n_symbols": F.expr(f"CAST(length({t}) - length(regexp_replace({t}, '[{SYMBOLS}]+', '')) AS BIGINT)"),
        "n_lines": F.expr(f"CAST(size({lines}) AS BIGINT)"),
        "n_dup_lines": F.expr(_let(lines, "ls", "CAST(size(ls) - size(array_distinct(ls)) AS BIGINT)")),
        "n_repeat_words": F.expr(repeat),
        "n_stop_words": F.expr(f"CAST(size(filter(_w, w -> w IN ({stops}))) AS BIGINT)"),
    }


@dataclass(frozen=True)
class Rule:
    """``low <= 100 * top / base <= high`` in integers; ``base`` None compares ``top`` itself. A zero base passes."""

    name: str
    top: str
    base: str | None
    low: int | None
    high: int | None

    def passes(self) -> Column:
        left = F.col(self.top) * F.lit(100 if self.base else 1)
        unit = F.col(self.base) if self.base else F.lit(1)
        ok = F.lit(True)
        if self.low is not None:
            ok = ok & (left >= F.lit(self.low) * unit)
        if self.high is not None:
            ok = ok & (left <= F.lit(self.high) * unit)
        return ok


BASE_RULES = (
    Rule("few_words", "n_words", None, 50, None),
    Rule("repeated_windows", "n_repeat_words", "n_words", None, 50),
)
RULES = (
    Rule("short_or_long_words", "word_chars", "n_words", 200, 1500),
    Rule("symbols", "n_symbols", "n_words", None, 60),
    Rule("duplicate_lines", "n_dup_lines", "n_lines", None, 50),
    Rule("stop_words", "n_stop_words", "n_words", 2, None),
)


def quality_rules(df: DataFrame, text: str = "text", rules: tuple[Rule, ...] = RULES, base: tuple[Rule, ...] = BASE_RULES) -> DataFrame:
    """``df`` with the measures, ``base_failed``, ``failed`` (names of failed rules) and ``kept``.

    One narrow stage: scan, projection of the words array, projection of the measures and verdicts. No shuffle.
    """
    names = measures(text)
    plain = df.drop(*[c for c in df.columns if c in (*names, "base_failed", "failed", "kept", "_w")])
    trimmed = _TRIM.format(f"coalesce({text}, '')")
    words = plain.withColumn("_w", F.expr(f"CASE WHEN {trimmed} = '' THEN array() ELSE split({trimmed}, '{_WS}', -1) END"))
    counted = words.select(*plain.columns, *[c.alias(k) for k, c in names.items()])
    verdicts = [F.when(~r.passes(), F.lit(r.name)) for r in (*base, *rules)]
    failed_base = ~F.lit(True)
    for r in base:
        failed_base = failed_base | ~r.passes()
    return counted.withColumns({"base_failed": failed_base, "failed": F.array_compact(F.array(*verdicts))}).withColumn("kept", F.size("failed") == 0)


def op8_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents; the threshold table's counts and verdicts."""
    docs = documents(spark, sf_dir).select("doc_id", "text")
    return quality_rules(docs).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def _sql() -> str:
    stops = ", ".join(f"'{w}', '{w.capitalize()}', '{w.upper()}'" for w in STOP_WORDS)
    ws = r"[\x20\x09-\x0D]+"
    checks = []
    for r in RULES:
        left, unit = (f"100 * {r.top}", r.base) if r.base else (r.top, "1")
        checks += [f"{left} >= {r.low} * {unit}"] * (r.low is not None) + [f"{left} <= {r.high} * {unit}"] * (r.high is not None)
    return rf"""
WITH t AS (SELECT doc_id, coalesce(text, '') AS x FROM documents),
w AS (SELECT doc_id, x, regexp_extract_all(x, '[^\x20\x09-\x0D]+') AS w,
             list_filter(string_split(x, chr(10)), lambda l: regexp_matches(l, '[^\x20\x09-\x0D]')) AS ls FROM t),
g AS (SELECT doc_id, unnest(range(1, len(w) - 1)) AS i, unnest(list_transform(range(1, len(w) - 1), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2])) AS g FROM w WHERE len(w) > 2),
r AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, g) AS c FROM g) WHERE c > 1),
p AS (SELECT doc_id, count(DISTINCT pos) AS n FROM (SELECT doc_id, unnest([i, i + 1, i + 2]) AS pos FROM r) GROUP BY 1),
m AS (SELECT w.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(length(regexp_replace(x, '{ws}', '', 'g')) AS BIGINT) AS word_chars,
      CAST(length(x) - length(translate(x, '{SYMBOLS}', '')) AS BIGINT) AS n_symbols, CAST(len(ls) AS BIGINT) AS n_lines,
      CAST(len(ls) - len(list_distinct(ls)) AS BIGINT) AS n_dup_lines, CAST(coalesce(p.n, 0) AS BIGINT) AS n_repeat_words,
      CAST(len(list_filter(w, lambda y: y IN ({stops}))) AS BIGINT) AS n_stop_words
      FROM w LEFT JOIN p ON w.doc_id = p.doc_id),
b AS (SELECT *, (n_words < 50 OR 100 * n_repeat_words > 50 * n_words) AS base_failed FROM m)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
       NOT base_failed AND {" AND ".join(checks)} AS kept FROM b
"""


QUERIES = {"op8_quality_rules": op8_quality_rules}
ORACLES = {"op8_quality_rules": _sql()}
