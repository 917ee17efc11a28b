"""Line-first quality rules, DataFrame functions only.

Every line of a text is judged by itself, by three groups of rules; failing lines go, and a
document that loses too much of its text goes as a whole. A few counts over the whole text
(words, symbols, repeated lines and repeated five-word windows) form a base test beside it.

Defined results: a null text counts as empty (no words: base test failed, not kept, cleaned
text empty); blank lines are neither judged nor counted as loss and stay in the cleaned text;
rows are judged one by one, so repeated rows and ties get equal answers; an empty table gives
an empty one; columns of the input that have a name of an output column are replaced by :func:`judge` and pass through :func:`keep_clean`.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import let, numbered, place_of, total, words_of

# Characters and phrases that the rules look for.
SYMBOLS = "#*$%&|<>"
MARKS = "#*$%&|<>!?~^_=+{}[]\\"
BOILERPLATE = (
    "all rights reserved|cookie policy|privacy policy|terms of use|terms of service|terms and conditions"
    "|use of cookies|accept cookies|subscribe to our|sign up for our|click here|read more|powered by"
    "|javascript is disabled|enable javascript|lorem ipsum|skip to content|back to top"
)
NAVIGATION = "home|menu|search|login|log in|log out|sign in|sign up|register|contact|contact us|about|about us|share|tweet|print|next|previous|sitemap|help|faq"


@dataclass(frozen=True)
class LineRules:
    """``mark_percent``: most marks among a line's characters, in hundredths.
    ``short_line``: lines of up to so many characters can be navigation or boilerplate.
    ``bare_words``: from so many words on a line needs a mark of punctuation.
    ``loss_percent``: most characters (other than blanks) that removed lines may take from a document."""

    mark_percent: int = 8
    short_line: int = 200
    bare_words: int = 16
    loss_percent: int = 30
    min_words: int = 10
    repeat_percent: int = 20
    window: int = 5


BLANK = r"[\x20\x09-\x0D]"


def _only(text: Column, characters: str) -> Column:
    """How many of ``characters`` the text has."""
    return F.length(F.regexp_replace(text, "[^" + re.escape(characters) + "]+", ""))


def _has_word(line: Column) -> Column:
    return F.regexp_like(line, F.lit(r"[^\x20\x09-\x0D]"))


def line_passes(line: Column, rules: LineRules) -> Column:
    """True for lines that stay. Each rule is one expression over the line."""
    long = F.length(line) > rules.short_line
    marked = 100 * _only(line, MARKS) > rules.mark_percent * F.length(line)
    bare = ~F.regexp_like(line, F.lit("[.,;:!?…。，]")) & (F.size(words_of(line)) >= rules.bare_words)
    navigation = F.regexp_like(line, F.lit(rf"^(?i:{BLANK}*(?:{NAVIGATION})(?=$|{BLANK}|[|»›>/·-])[\x20\x09-\x0D|»›>/·-]*)+$"))
    boilerplate = F.regexp_like(line, F.lit(rf"\b(?i:{BOILERPLATE})\b"))
    return ~_has_word(line) | ~(marked | bare | (~long & (navigation | boilerplate)))


def repeated_words(words: Column, window: int = 5) -> Column:
    """How many words stand in a window of ``window`` words that the text has twice or more.

    Windows are compared by 64-bit hashes. Texts whose windows all differ end at the first
    test; for others, windows are sorted with their places, so the work is n log n for the text."""

    def spread(places: Column) -> Column:
        return total(F.transform(places, lambda p, k: F.least(F.lit(window), F.coalesce(F.get(places, k + 1) - p, F.lit(window)))))

    def found(windows: Column) -> Column:
        ranked = F.sort_array(F.transform(windows, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
        twice = lambda s: F.filter(s, lambda e, k: F.coalesce(F.get(s, k + 1)["h"] == e["h"], F.lit(False)) | F.coalesce(F.get(s, k - 1)["h"] == e["h"], F.lit(False)))
        places = let(ranked, lambda s: F.sort_array(F.transform(twice(s), lambda e: e["i"])))
        return F.when(F.size(F.array_distinct(windows)) == F.size(windows), F.lit(0).cast("bigint")).otherwise(let(places, spread))

    hashes = F.transform(words, lambda w: F.xxhash64(w))
    windows = lambda h: F.transform(F.sequence(F.lit(0), F.size(h) - window), lambda i: F.xxhash64(*(F.get(h, i + k) for k in range(window))))
    return F.when(F.size(words) < window + 1, F.lit(0).cast("bigint")).otherwise(let(hashes, lambda h: let(windows(h), found)))


def judge(docs: DataFrame, text_col: str = "text", rules: LineRules = LineRules()) -> DataFrame:
    """``docs`` with ``n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_removed_lines,
    lost_chars, clean_text, base_failed, kept``. No shuffle; one pass over each text."""

    def measures(t: Column) -> Column:
        lines = F.split(t, "\n")
        return let(words_of(t), lambda w: let(F.filter(lines, _has_word), lambda full: let(F.filter(lines, lambda x: line_passes(x, rules)), lambda good: F.struct(
            F.size(w).cast("bigint").alias("n_words"),
            F.length(F.array_join(w, "")).cast("bigint").alias("word_chars"),
            _only(t, SYMBOLS).cast("bigint").alias("n_symbols"),
            (F.size(full) - F.size(F.array_distinct(full))).cast("bigint").alias("n_dup_lines"),
            repeated_words(w, rules.window).alias("n_repeat_words"),
            (F.size(lines) - F.size(good)).cast("bigint").alias("n_removed_lines"),
            F.array_join(good, "\n").alias("clean_text"),
        ))))

    # numbered columns on the way, so that no name of a caller's meets one from here
    held, own = numbered(docs), F.coalesce(F.col(f"_{place_of(docs, text_col)}"), F.lit(""))
    # a generator of one row keeps later filters and projections from computing the measures anew
    out = held.select("*", F.explode(F.array(let(own, measures))).alias("m")).select(*held.columns, "m.*")
    left = F.length(F.regexp_replace("clean_text", BLANK + "+", "")).cast("bigint")
    out = out.withColumn("lost_chars", F.when(F.col("n_removed_lines") == 0, F.lit(0).cast("bigint")).otherwise(F.col("word_chars") - left))
    failed = (F.col("n_words") < rules.min_words) | (100 * F.col("n_repeat_words") > rules.repeat_percent * F.col("n_words"))
    out = out.withColumns({"base_failed": failed, "kept": ~failed & (100 * F.col("lost_chars") <= rules.loss_percent * F.col("word_chars"))})
    made = out.columns[len(docs.columns) :]
    stay = [(f"_{k}", c) for k, c in enumerate(docs.columns) if c.lower() not in made]
    return out.select(*(n for n, _ in stay), *made).toDF(*(c for _, c in stay), *made)


def keep_clean(docs: DataFrame, text_col: str = "text", rules: LineRules = LineRules()) -> DataFrame:
    """Documents that pass, in their own columns, without the lines that failed; other columns stay as they are, whatever
    their names."""
    held, text = numbered(docs), f"_{place_of(docs, text_col)}"
    judged = judge(held, text, rules).where("kept").withColumn(text, F.col("clean_text"))
    if "n_chars" in docs.columns:
        judged = judged.withColumn(f"_{docs.columns.index('n_chars')}", F.length(text).cast(docs.schema["n_chars"].dataType))
    return judged.select(*held.columns).toDF(*docs.columns)
