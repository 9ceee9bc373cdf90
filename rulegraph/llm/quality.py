"""Quality rules that clean lines first and then judge the document. DataFrame functions only.

Each line is tested for punctuation (symbols, shouting, no mark in a long line),
navigation (bars between items), boilerplate phrases and repetition of few words.
Failing lines are taken out; a document that loses more than a part of its words
with them is rejected. Before that come base rules: too few words, or too many
words in 8-word windows that occur twice or more in the text.

Defined results: null text is empty; empty texts have no words and fail the base
rules; lines without a word are kept as they are and never judged; rows are
judged one by one, so repeated rows get equal results; other columns pass through.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

SPACES = "[\\x20\\x09-\\x0D]+"
WORDS = "[^\\x20\\x09-\\x0D]+"
SYMBOLS = "#*$%&|<>"
BOILERPLATE = (
    "(all rights reserved|licensed under|released under|terms of (use|service)|privacy policy|cookie policy|"
    "accept cookies|enable javascript|subscribe to our|sign up for|powered by|click here)"
)


@dataclass(frozen=True)
class QualityRules:
    """Limits of the rules; the defaults are those of the registered query."""

    min_words: int = 20
    max_repeat_percent: int = 30
    max_lost_percent: int = 50
    max_symbol_percent: int = 10
    max_shout_percent: int = 50
    long_line_words: int = 8
    repetitive_words: int = 10
    min_distinct_percent: int = 30


def _chars_of(col: Column, chars: str) -> Column:
    return F.length(col) - F.length(F.translate(col, chars, ""))


def _repeat_words(df: DataFrame, words: str) -> DataFrame:
    """Adds n_repeat_words: positions covered by 8-word windows whose words occur at another position too."""
    df = df.withColumn("_h", F.transform(words, lambda w: F.xxhash64(w)))
    keys = F.when(F.size("_h") >= 9, F.transform(F.sequence(F.lit(0), F.size("_h") - 8), lambda i: F.xxhash64(*[F.get("_h", i + k) for k in range(8)])))
    df = df.withColumn("_k", keys)
    found = F.when(F.size(F.array_distinct("_k")) < F.size("_k"), F.array_sort(F.transform("_k", lambda k, i: F.struct(k.alias("k"), i.alias("i")))))
    df = df.withColumn("_s", found)
    at = F.transform("_s", lambda s, j: F.when((F.get("_s", j - 1)["k"] == s["k"]) | (F.get("_s", j + 1)["k"] == s["k"]), s["i"]))
    df = df.withColumn("_p", F.array_sort(F.array_compact(at)))
    covered = F.aggregate(
        "_p",
        F.struct(F.lit(0).cast("bigint").alias("n"), F.lit(-8).alias("last")),
        lambda acc, p: F.struct((acc["n"] + F.least(F.lit(8), p - acc["last"])).alias("n"), p.alias("last")),
        lambda acc: acc["n"],
    )
    return df.withColumn("n_repeat_words", F.coalesce(covered, F.lit(0).cast("bigint"))).drop("_h", "_k", "_s", "_p")


def line_failures(line: Column, n: Column, rules: QualityRules) -> Column:
    """Name of the first rule that a line with n words fails, or null."""
    distinct = F.size(F.array_distinct(F.split(F.lower(line), SPACES)))
    return (
        F.when(line.rlike("\\|[^|]*\\||\\|\\s*$"), "navigation")
        .when(_chars_of(line, SYMBOLS) * 100 > n * rules.max_symbol_percent, "symbols")
        .when((n >= 3) & (F.regexp_count(line, F.lit("!!")) * 100 > n * rules.max_shout_percent), "shouting")
        .when((n >= rules.long_line_words) & ~line.rlike("[.,;:!?]"), "punctuation")
        .when((n >= rules.repetitive_words) & (distinct * 100 < n * rules.min_distinct_percent), "repetition")
        .when(F.lower(line).rlike(BOILERPLATE), "boilerplate")
    )


def quality_signals(docs: DataFrame, *, text: str = "text", rules: QualityRules = QualityRules()) -> DataFrame:
    """docs with the base counts, ``n_lost_words``, ``clean_text``, ``base_failed`` and ``kept``."""
    t = F.coalesce(F.col(text), F.lit(""))
    df = docs.withColumn("_t", t)
    df = df.withColumn("_w", F.filter(F.split("_t", SPACES), lambda w: w != ""))
    df = df.withColumn("n_words", F.size("_w").cast("bigint"))
    df = df.withColumn("word_chars", (F.length("_t") - _chars_of(F.col("_t"), " \t\n\x0b\f\r")).cast("bigint"))
    df = df.withColumn("n_symbols", _chars_of(F.col("_t"), SYMBOLS).cast("bigint"))
    df = _repeat_words(df, "_w").drop("_w")
    df = df.withColumn("_lines", F.split("_t", "\n"))
    df = df.withColumn("_with", F.filter("_lines", lambda x: x.rlike(WORDS)))
    df = df.withColumn("n_dup_lines", (F.size("_with") - F.size(F.array_distinct("_with"))).cast("bigint")).drop("_with")
    df = df.withColumn("_counted", F.transform("_lines", lambda x: F.struct(x.alias("line"), F.regexp_count(x, F.lit(WORDS)).alias("n")))).drop("_lines")
    df = df.withColumn("_judged", F.transform("_counted", lambda x: F.struct(x["line"].alias("line"), x["n"].alias("n"), F.when(x["n"] > 0, line_failures(x["line"], x["n"], rules)).alias("fails")))).drop("_counted")
    lost = F.aggregate("_judged", F.lit(0).cast("bigint"), lambda acc, x: acc + F.when(x["fails"].isNotNull(), x["n"]).otherwise(0))
    df = df.withColumn("n_lost_words", lost)
    df = df.withColumn("clean_text", F.concat_ws("\n", F.transform(F.filter("_judged", lambda x: x["fails"].isNull()), lambda x: x["line"]))).drop("_judged", "_t")
    base = (F.col("n_words") < rules.min_words) | (F.col("n_repeat_words") * 100 > F.col("n_words") * rules.max_repeat_percent)
    df = df.withColumn("base_failed", base)
    return df.withColumn("kept", ~F.col("base_failed") & (F.col("n_lost_words") * 100 <= F.col("n_words") * rules.max_lost_percent))


QUALITY_SQL = r"""
with d as (select row_number() over () as rid, doc_id, coalesce(text, '') as t from documents),
w as (select rid, regexp_extract_all(t, '[^\x20\x09-\x0D]+') as ws from d),
win as (select rid, unnest(range(1, len(ws) - 6)) as i, ws from w where len(ws) >= 9),
keyed as (select rid, i, array_to_string(ws[i:i + 7], ' ') as k from win),
rep as (select rid, i, count(*) over (partition by rid, k) as c from keyed),
cov as (select rid, count(distinct p) as n_repeat from (select rid, unnest(range(i, i + 8)) as p from rep where c >= 2) group by rid),
l as (select rid, unnest(string_split(t, chr(10))) as line from d),
ln as (select rid, line, len(regexp_extract_all(line, '[^\x20\x09-\x0D]+')) as n from l),
lj as (select rid, line, n,
    regexp_matches(line, '\|[^|]*\||\|\s*$')
    or len(regexp_extract_all(line, '[#*$%&|<>]')) * 100 > n * 10
    or (n >= 3 and len(regexp_extract_all(line, '!!')) * 100 > n * 50)
    or (n >= 8 and not regexp_matches(line, '[.,;:!?]'))
    or (n >= 10 and len(list_distinct(regexp_split_to_array(lower(line), '[\x20\x09-\x0D]+'))) * 100 < n * 30)
    or regexp_matches(lower(line), '(all rights reserved|licensed under|released under|terms of (use|service)|privacy policy|cookie policy|accept cookies|enable javascript|subscribe to our|sign up for|powered by|click here)') as bad
    from ln where n > 0),
la as (select rid, sum(case when bad then n else 0 end) as lost, count(*) - count(distinct line) as dup from lj group by rid),
f as (select d.doc_id, len(w.ws)::bigint as n_words,
    length(regexp_replace(d.t, '[\x20\x09-\x0D]', '', 'g'))::bigint as word_chars,
    len(regexp_extract_all(d.t, '[#*$%&|<>]'))::bigint as n_symbols,
    coalesce(la.dup, 0)::bigint as n_dup_lines, coalesce(cov.n_repeat, 0)::bigint as n_repeat_words, coalesce(la.lost, 0)::bigint as n_lost_words
    from d join w using (rid) left join cov using (rid) left join la using (rid))
select *, (n_words < 20 or 100 * n_repeat_words > 30 * n_words) as base_failed,
    not (n_words < 20 or 100 * n_repeat_words > 30 * n_words) and 100 * n_lost_words <= 50 * n_words as kept
from f
"""
