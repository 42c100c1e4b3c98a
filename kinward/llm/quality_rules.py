"""Quality rules as a short-circuit cascade, in Spark's own functions only.

A bounded hash sample tells what each rule costs (nanoseconds a row, the measures that it reads
included) and the share that it rejects; rules run in order of rejection per cost, and a document
leaves at the first rule that rejects it. ``keep_passing`` computes a measure when a rule first
asks for it and nothing after the first rejection. The order moves the cost only: a document is
kept if it passes every rule, whatever the order.

Cases: null text counts as empty (no words, so it fails the base rule); repeated rows get the same
verdict each; ties between rules keep their listed order; other columns are ignored, or passed
through untouched by ``keep_passing``; an empty table gives an empty result.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from kinward.llm.native import GAP, SPACES, has_ink, let, lines_of, words_of

WINDOW = 8
MIN_WORDS, REPEAT_PERCENT = 20, 30
SYMBOLS = r"[#*$%&|<>]"


@dataclass(frozen=True)
class Rule:
    """``rejects`` takes the text and a mapping of measures by name (those in ``reads``), and tells whether the document goes."""

    name: str
    reads: tuple[str, ...]
    rejects: Callable[[Column, Column | dict[str, Column]], Column]


def _share_above(part: Column, whole: Column, percent: int) -> Column:
    return part * 100 > whole * percent


RULES = (
    Rule("few_words", ("n_words",), lambda t, q: q["n_words"] < MIN_WORDS),
    Rule("repeated_words", ("n_words", "n_repeat_words"), lambda t, q: _share_above(q["n_repeat_words"], q["n_words"], REPEAT_PERCENT)),
    Rule("symbols", ("n_symbols", "n_words"), lambda t, q: _share_above(q["n_symbols"], q["n_words"], 10)),
    Rule("repeated_lines", ("n_lines", "n_dup_lines"), lambda t, q: _share_above(q["n_dup_lines"], q["n_lines"], 30)),
    Rule("word_length", ("n_words", "word_chars"), lambda t, q: (q["word_chars"] < q["n_words"] * 2) | (q["word_chars"] > q["n_words"] * 15)),
    Rule("shouting", ("n_upper", "word_chars"), lambda t, q: _share_above(q["n_upper"], q["word_chars"], 40)),
    Rule("bullets", ("n_bullets", "n_lines"), lambda t, q: _share_above(q["n_bullets"], q["n_lines"], 90) & (q["n_lines"] > 5)),
    Rule("filler", (), lambda t, q: F.lower(t).contains("lorem ipsum")),
)
BASE = ("few_words", "repeated_words")


def repeat_words(hashes: Column, n: Column) -> Column:
    """Words in windows whose word sequence is found twice or more in the text."""

    def marked(wins: Column) -> Column:
        ordered = F.sort_array(F.transform(wins, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))

        def covered(s: Column) -> Column:
            last = F.size(s) - 1
            twin = F.filter(
                s,
                lambda x, j: ((j > 0) & (F.get(s, F.greatest(j - 1, F.lit(0)))["h"] == x["h"]))
                | ((j < last) & (F.get(s, F.least(j + 1, last))["h"] == x["h"])),
            )
            starts = F.sort_array(F.transform(twin, lambda x: x["i"]))
            zero = F.struct(F.lit(0).cast("long").alias("total"), F.lit(-WINDOW).alias("at"))
            return F.aggregate(
                starts,
                zero,
                lambda a, i: F.struct(
                    (a["total"] + F.least(i - a["at"], F.lit(WINDOW))).cast("long").alias("total"), i.alias("at")
                ),
                lambda a: a["total"],
            )

        return F.when(F.size(F.array_distinct(wins)) == F.size(wins), F.lit(0).cast("long")).otherwise(let(ordered, covered))

    windows = F.transform(
        F.sequence(F.lit(0), n - WINDOW), lambda i: F.xxhash64(*[F.get(hashes, i + k) for k in range(WINDOW)])
    )
    return F.when(n < WINDOW, F.lit(0).cast("long")).otherwise(let(windows, marked))


def _n_words(t: Column) -> Column:
    """Words, without listing them: the runs of space inside the trimmed text, and one."""
    return let(F.btrim(t, F.lit(SPACES)), lambda x: F.when(x == "", F.lit(0)).otherwise(F.regexp_count(x, F.lit(GAP)) + 1)).cast("long")


def _inked_lines(t: Column) -> Column:
    return F.filter(lines_of(t), has_ink)


#: Every measure as a function of the text alone.
MEASURES: dict[str, Callable[[Column], Column]] = {
    "n_words": _n_words,
    "word_chars": lambda t: F.length(F.regexp_replace(t, GAP, "")).cast("long"),
    "n_symbols": lambda t: F.regexp_count(t, F.lit(SYMBOLS)).cast("long"),
    "n_dup_lines": lambda t: let(_inked_lines(t), lambda x: (F.size(x) - F.size(F.array_distinct(x))).cast("long")),
    "n_lines": lambda t: F.size(_inked_lines(t)).cast("long"),
    "n_repeat_words": lambda t: let(F.transform(words_of(t), lambda x: F.xxhash64(x)), lambda h: repeat_words(h, F.size(h))),
    "n_upper": lambda t: F.regexp_count(t, F.lit(r"\p{Lu}")).cast("long"),
    "n_bullets": lambda t: F.regexp_count(t, F.lit(r"(?m)^[\x20\x09]*[-•]")).cast("long"),
}
CONTRACT = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines")


def measures(text: Column) -> Column:
    """All measures of a text as one struct; words and lines are listed once."""
    text = F.coalesce(text.cast("string"), F.lit(""))

    def of_words(w: Column) -> Column:
        def of_lines(x: Column) -> Column:
            return F.struct(
                F.size(w).cast("long").alias("n_words"),
                F.length(F.array_join(w, "")).cast("long").alias("word_chars"),
                MEASURES["n_symbols"](text).alias("n_symbols"),
                (F.size(x) - F.size(F.array_distinct(x))).cast("long").alias("n_dup_lines"),
                let(F.transform(w, lambda v: F.xxhash64(v)), lambda h: repeat_words(h, F.size(h))).alias("n_repeat_words"),
                F.size(x).cast("long").alias("n_lines"),
            )

        return let(_inked_lines(text), of_lines)

    return let(words_of(text), of_words)


def base_failed(q: Column) -> Column:
    return (q["n_words"] < MIN_WORDS) | (q["n_repeat_words"] * 100 > q["n_words"] * REPEAT_PERCENT)


def _text(text_col: str) -> Column:
    return F.coalesce(F.col(text_col).cast("string"), F.lit(""))


def _nanoseconds(sample: DataFrame, value: Column, n: int, bare: float) -> float:
    """What a row of the sample costs beyond ``bare``: the lesser of two passes over it."""
    took = []
    for _ in range(2):
        began = time.perf_counter_ns()
        sample.agg(F.bit_xor(F.xxhash64(value))).first()
        took.append(time.perf_counter_ns() - began)
    return max(min(took) / n - bare, 1.0)


def order_rules(docs: DataFrame, text_col: str = "text", rules=RULES, sample_rows: int = 1000) -> list[Rule]:
    """Rules by share rejected per nanosecond, from about ``sample_rows`` documents drawn by a hash of their text.

    Costs of measures are counted for the first rule of the order that reads them: the best rule is
    placed, its measures become free, and the rest is ranked anew.
    """
    total = docs.count()
    if not total:
        return list(rules)
    drawn = docs.select(_text(text_col).alias("text"))
    if total > sample_rows:
        drawn = drawn.filter(F.pmod(F.xxhash64("text"), F.lit(1 << 30)) < F.lit(max(1, (sample_rows << 30) // total)))
    sample = drawn.limit(4 * sample_rows).cache()  # copies of one text fall in or out together
    try:
        n = sample.count()
        if not n:
            return list(rules)
        t = F.col("text")
        every = {name: f(t) for name, f in MEASURES.items()}
        hits = sample.select(*[F.count_if(F.coalesce(r.rejects(t, every), F.lit(False))).alias(r.name) for r in rules]).first()
        bare = _nanoseconds(sample, F.length(t), n, 0.0)
        cost = {name: _nanoseconds(sample, every[name], n, bare) for name in sorted({m for r in rules for m in r.reads})}
        own = {r.name: 1.0 if r.reads else _nanoseconds(sample, r.rejects(t, every), n, bare) for r in rules}
    finally:
        sample.unpersist()
    left, known, ordered = list(rules), set(), []
    while left:
        price = {r.name: own[r.name] + sum(cost[m] for m in r.reads if m not in known) for r in left}
        best = max(left, key=lambda r: hits[r.name] / n / price[r.name])  # the first of equals
        ordered.append(best)
        known |= set(best.reads)
        left.remove(best)
    return ordered


def cascade(text: Column, q, rules) -> Column:
    """Name of the first rule that rejects, or null; later rules, and measures only they read, are not evaluated."""
    chain = None
    for rule in rules:
        chain = (F if chain is None else chain).when(rule.rejects(text, q), F.lit(rule.name))
    return F.lit(None).cast("string") if chain is None else chain


#: Measures that are read off the list of words or of inked lines, and how.
LISTED: dict[str, tuple[str, Callable[[Column], Column]]] = {
    "n_words": ("words", lambda w: F.size(w).cast("long")),
    "word_chars": ("words", lambda w: F.length(F.array_join(w, "")).cast("long")),
    "n_repeat_words": ("words", lambda w: let(F.transform(w, lambda x: F.xxhash64(x)), lambda h: repeat_words(h, F.size(h)))),
    "n_lines": ("lines", lambda x: F.size(x).cast("long")),
    "n_dup_lines": ("lines", lambda x: (F.size(x) - F.size(F.array_distinct(x))).cast("long")),
}


def short_circuit(text: Column, rules) -> Column:
    """``cascade`` of a text alone: lists and measures are made when the first rule asks, once, and none after a rejection."""
    made = {"words": words_of, "lines": _inked_lines}

    def bind(names: list[str], known: dict[str, Column], then: Callable[[dict[str, Column]], Column]) -> Column:
        if not names:
            return then(known)
        name, rest = names[0], names[1:]
        if name in known:
            return bind(rest, known, then)
        if name in made:
            value = made[name](text)
        elif name in LISTED:
            source, read = LISTED[name]
            if source not in known:
                return bind([source, *names], known, then)
            value = read(known[source])
        else:
            value = MEASURES[name](text)
        return let(value, lambda c: bind(rest, known | {name: c}, then))

    def step(i: int, known: dict[str, Column]) -> Column:
        if i == len(rules):
            return F.lit(None).cast("string")
        rule = rules[i]
        judged = lambda q: F.when(rule.rejects(text, q), F.lit(rule.name)).otherwise(step(i + 1, q))
        return bind(list(rule.reads), known, judged)

    return step(0, {})


def _extra(text: Column) -> dict[str, Column]:
    """Measures that the contract's struct lacks, computed where a rule asks."""
    return {name: f(text) for name, f in MEASURES.items() if name not in CONTRACT}


def judge(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", rules=RULES, sample_rows: int = 1000) -> DataFrame:
    """One row per document: its measures, the first rule that rejects it, and whether it stays."""
    ordered = order_rules(docs, text_col, rules, sample_rows)
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), _text(text_col).alias("text"))
    rows = rows.withColumn("q", measures(F.col("text")))
    q = {name: F.col(f"q.{name}") for name in CONTRACT} | _extra(F.col("text"))
    rows = rows.withColumn("failed_rule", cascade(F.col("text"), q, ordered))
    return rows.select(
        "doc_id", *[F.col(f"q.{c}") for c in CONTRACT], base_failed(F.col("q")).alias("base_failed"),
        F.col("failed_rule").isNull().alias("kept"), "failed_rule",
    )


def keep_passing(docs: DataFrame, text_col: str = "text", rules=RULES, sample_rows: int = 1000) -> DataFrame:
    """The documents that pass, with all their columns."""
    ordered = order_rules(docs, text_col, rules, sample_rows)
    return docs.filter(short_circuit(_text(text_col), ordered).isNull()).select(*[F.col(f"`{c}`") for c in docs.columns])


ORACLE = rf"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
m AS (
  SELECT doc_id, t,
    list_filter(regexp_split_to_array(t, '{GAP}'), lambda x: x <> '') AS w,
    list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS ls,
    len(regexp_extract_all(t, '{SYMBOLS}')) AS n_symbols,
    len(regexp_extract_all(t, '\p{{Lu}}')) AS n_upper,
    len(regexp_extract_all(t, '(?m)^[\x20\x09]*[-\x{{2022}}]')) AS n_bullets
  FROM d),
win AS (
  SELECT doc_id, i, array_to_string(w[i:i+7], ' ') AS k
  FROM (SELECT doc_id, w, unnest(range(1, len(w) - 6)) AS i FROM m WHERE len(w) >= 8)),
rep AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, k) AS c FROM win) WHERE c > 1),
cov AS (SELECT doc_id, count(DISTINCT p) AS n FROM (SELECT doc_id, unnest(range(i, i + 8)) AS p FROM rep) GROUP BY doc_id),
q AS (
  SELECT m.doc_id, m.t, len(w)::BIGINT AS n_words, length(array_to_string(w, ''))::BIGINT AS word_chars, n_symbols::BIGINT AS n_symbols,
    (len(ls) - len(list_distinct(ls)))::BIGINT AS n_dup_lines, coalesce(cov.n, 0)::BIGINT AS n_repeat_words, len(ls)::BIGINT AS n_lines,
    n_upper, n_bullets
  FROM m LEFT JOIN cov ON m.doc_id = cov.doc_id),
b AS (SELECT *, n_words < 20 OR 100 * n_repeat_words > 30 * n_words AS base_failed FROM q)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
  NOT (base_failed OR 100 * n_symbols > 10 * n_words OR 100 * n_dup_lines > 30 * n_lines
    OR word_chars < 2 * n_words OR word_chars > 15 * n_words OR 100 * n_upper > 40 * word_chars
    OR (100 * n_bullets > 90 * n_lines AND n_lines > 5) OR contains(lower(t), 'lorem ipsum')) AS kept
FROM b
"""
