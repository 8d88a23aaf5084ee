"""Quality rules: a table of thresholds compiled into one Spark projection.

Every measure is a built-in expression; no user function runs.  A document is
kept when no base rule fails and each measure of the table lies within its
bounds.  Null texts count as empty; an empty text has no words and fails the
base rule; a measure whose denominator is zero is 0; repeated rows are judged
alike, each on its own; columns of the input other than the id and the text
pass through untouched by :func:`measure` (new columns win a clash of names).
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rowsketch.llm.common import named, text_or_empty, word_array

#: Frequent function words of English, German, French and Spanish.
STOP_WORDS = (
    "the and of to in is that it for on with as was be by this are at from or an "
    "der die das und ist von zu den mit auf ein für dem nicht sich des "
    "le la les et de des un une est dans que pour sur par au avec qui en il "
    "el los las del y es se por con una su al lo para"
).split()


@dataclass(frozen=True)
class Rule:
    """A measure (SQL over the columns of :func:`measure`) and its inclusive bounds."""

    name: str
    measure: str
    low: float | None = None
    high: float | None = None


#: Production thresholds.
RULES = (
    Rule("mean_word_length", "word_chars / greatest(n_words, 1)", 1.5, 20.0),
    Rule("symbols_per_word", "n_symbols / greatest(n_words, 1)", None, 0.2),
    Rule("stop_words_present", "n_stop_words", 1.0, None),
    Rule("duplicate_line_share", "n_dup_lines / greatest(n_lines, 1)", None, 0.5),
    Rule("capital_share", "n_capitals / greatest(word_chars, 1)", None, 0.5),
    Rule("bullet_line_share", "n_bullet_lines / greatest(n_lines, 1)", None, 0.9),
    Rule("exclamations_per_word", "n_exclamations / greatest(n_words, 1)", None, 0.3),
)


def _repeat_words() -> Column:
    """Words inside five-word windows that occur at least twice in the text.

    Windows are compared by a chained 64-bit hash of their words.  Equal hashes
    are neighbours after sorting; the start positions so found, in order, each
    cover five words less what the next one covers again.
    """
    found = """
        flatten(array_compact(zip_with(win_sorted, slice(win_sorted, 2, size(win_sorted)),
                (a, b) -> if(a.h = b.h, array(a.i, b.i), cast(null as array<int>)))))
    """
    starts = f"sort_array(array_distinct({found}))"
    return F.expr(f"""
        case when win_sorted is null then 0L
        else aggregate(transform(array({starts}), s ->
                 aggregate(zip_with(s, slice(s, 2, size(s)), (a, b) -> least(b - a, 5)), 0L, (t, x) -> t + x)), 0L, (t, x) -> t + x)
        end
    """)


def measure(df: DataFrame, text: str = "text") -> DataFrame:
    """Adds the measures: n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words and the helpers of the rule table."""
    body = text_or_empty(text)
    stop = F.array(*[F.lit(w) for w in STOP_WORDS])
    names = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_stop_words", "n_capitals", "n_bullet_lines", "n_exclamations")
    keep = [c for c in df.columns if c not in names]
    # the input's columns travel as one, so that none is mistaken for a working column
    staged = df.select(F.struct(*[named(c) for c in keep]).alias("row"), word_array(body).alias("_words"), F.expr(f"filter(split(coalesce(cast(`{text}` as string), ''), '\\n'), l -> l rlike '[^\\\\x20\\\\x09-\\\\x0D]')").alias("_lines"), body.alias("_body"))
    # hashes of the five-word windows; null where no window can repeat
    staged = staged.select("*", F.expr("case when size(_words) >= 6 then transform(sequence(1, size(_words) - 4), i -> xxhash64(slice(_words, i, 5))) end").alias("_win"))
    staged = staged.select("*", F.expr("case when size(array_distinct(_win)) < size(_win) then sort_array(transform(_win, (h, i) -> struct(h as h, i as i))) end").alias("win_sorted"))
    as_long = lambda c: c.cast("long")
    return staged.select(
        *[F.col("row").getField(c).alias(c) for c in keep],
        as_long(F.size("_words")).alias("n_words"),
        as_long(F.length(F.array_join("_words", ""))).alias("word_chars"),
        as_long(F.regexp_count("_body", F.lit(r"[#*$%&|<>]"))).alias("n_symbols"),
        as_long(F.size("_lines") - F.size(F.array_distinct("_lines"))).alias("n_dup_lines"),
        _repeat_words().alias("n_repeat_words"),
        as_long(F.size("_lines")).alias("n_lines"),
        as_long(F.size(F.array_intersect("_words", stop))).alias("n_stop_words"),
        as_long(F.regexp_count("_body", F.lit("[A-Z]"))).alias("n_capitals"),
        as_long(F.expr("size(filter(_lines, l -> l rlike '^[\\\\x20\\\\x09-\\\\x0D]*[-*|•]'))")).alias("n_bullet_lines"),
        as_long(F.regexp_count("_body", F.lit("!"))).alias("n_exclamations"),
    )


def base_failed() -> Column:
    return (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))


def verdict(rules: tuple[Rule, ...] = RULES) -> Column:
    """The rule table as one boolean expression over the measures."""
    parts = []
    for r in rules:
        x = F.expr(r.measure).cast("double")
        if r.low is not None:
            parts.append(x >= F.lit(float(r.low)))
        if r.high is not None:
            parts.append(x <= F.lit(float(r.high)))
    out = ~base_failed()
    for p in parts:
        out = out & p
    return out


def apply_rules(df: DataFrame, rules: tuple[Rule, ...] = RULES, text: str = "text") -> DataFrame:
    """The input with its measures, ``base_failed`` and ``kept``."""
    base = df.drop("base_failed", "kept")
    return measure(base, text).select("*", base_failed().alias("base_failed"), verdict(rules).alias("kept"))


def oracle(rules: tuple[Rule, ...] = RULES) -> str:
    """DuckDB SQL for the contract's columns."""
    tests = []
    for r in rules:
        x = f"CAST({r.measure} AS DOUBLE)"
        if r.low is not None:
            tests.append(f"{x} >= {float(r.low)}")
        if r.high is not None:
            tests.append(f"{x} <= {float(r.high)}")
    stop = ", ".join("'" + w + "'" for w in STOP_WORDS)
    return f"""
WITH t AS (SELECT doc_id, coalesce(text, '') AS body, row_number() OVER () AS rid FROM documents),
w AS (SELECT rid, doc_id, body, regexp_extract_all(body, '[^\\x20\\x09-\\x0D]+') AS words,
             list_filter(string_split(body, chr(10)), lambda l: regexp_matches(l, '[^\\x20\\x09-\\x0D]')) AS lines FROM t),
g AS (SELECT rid, i, list_slice(words, i, i + 4) AS win FROM (SELECT rid, words, unnest(generate_series(1, len(words) - 4)) AS i FROM w)),
d AS (SELECT rid, i FROM (SELECT rid, i, count(*) OVER (PARTITION BY rid, win) AS n FROM g) WHERE n > 1),
r AS (SELECT rid, sum(least(coalesce(nxt - i, 5), 5)) AS n_repeat_words FROM (SELECT rid, i, lead(i) OVER (PARTITION BY rid ORDER BY i) AS nxt FROM d) GROUP BY rid),
m AS (SELECT w.doc_id, len(words)::BIGINT AS n_words, length(array_to_string(words, ''))::BIGINT AS word_chars,
             length(regexp_replace(body, '[^#*$%&|<>]', '', 'g'))::BIGINT AS n_symbols,
             (len(lines) - len(list_distinct(lines)))::BIGINT AS n_dup_lines,
             coalesce(n_repeat_words, 0)::BIGINT AS n_repeat_words,
             len(lines)::BIGINT AS n_lines,
             len(list_filter([{stop}], lambda s: list_contains(words, s)))::BIGINT AS n_stop_words,
             length(regexp_replace(body, '[^A-Z]', '', 'g'))::BIGINT AS n_capitals,
             len(list_filter(lines, lambda l: regexp_matches(l, '^[\\x20\\x09-\\x0D]*[-*|•]')))::BIGINT AS n_bullet_lines,
             length(regexp_replace(body, '[^!]', '', 'g'))::BIGINT AS n_exclamations
      FROM w LEFT JOIN r USING (rid)),
v AS (SELECT *, (n_words < 10 OR 100 * n_repeat_words > 20 * n_words) AS base_failed FROM m)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
       (NOT base_failed AND {" AND ".join(tests)}) AS kept FROM v
"""
