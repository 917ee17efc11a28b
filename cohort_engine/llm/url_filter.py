"""URL filters: host rules, and beyond them a ratio of character language models.

Two variable-order Markov models over the characters of host and path, one for accepted and one for
rejected URLs, are trained on URLs that have a weak label: a URL is taken as rejected if a
word of its host is in a list of unwanted words, and as accepted if there is no such word and no rule blocks it
(rules that block whole sections say nothing about the look of a URL, so these URLs train neither model).
Hosts are split by a hash: those of one part are counted, and the labelled URLs of the other part
calibrate the threshold, which is the one of least balanced error on hosts that the models haven't seen.
The score of a URL is the difference of its two log-likelihoods divided by its length. URLs that a rule judges keep the rule's verdict.

A model mixes orders 0 to 5: each order's estimate is smoothed towards that of the order below (an
order counts for as much as it has seen of the context). Counts are exact and stay distributed: a table of the distinct
windows of six characters, which grows with the input as texts of more kinds are seen. Every lower order is a sum over it, and what a
window adds to a score is worked out once for each distinct window and joined with the windows of the distinct URLs. All of it is DataFrame functions.

Defined results: a null URL or one without ``://`` has an empty host and path, fits no rule, and gets the verdict
of the models' threshold at score 0; repeated rows get equal answers; with no labelled URLs the built-in
seeds alone train the models, and where one of the labels is missing from the calibrating part the threshold is 0; an empty table
gives an empty one; other columns are not read.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import cut, let

# Rules as host and start of path, and words that mark a host as unwanted.
RULES = {"org/": "allow", "example.org/es/": "block", "example.org/en/1": "block", "com/fr/": "allow", "com/de/": "block"}
UNWANTED = (
    "adult", "porn", "xxx", "sex", "escort", "casino", "poker", "bet", "betting", "slots", "jackpot", "gambling", "lottery",
    "bets", "spam", "ads", "adserver", "popunder", "tracker", "track", "pills", "viagra", "cialis", "pharmacy", "replica", "warez", "torrent", "crack", "keygen", "payday", "loans", "dating", "hookup", "malware", "phishing",
)
WELCOME = ("news", "blog", "wiki", "docs", "library", "museum", "school", "university", "journal", "weather", "garden", "history", "science", "music", "travel", "archive", "recipes", "research", "forum", "books")
ORDER = 5
#: How much the estimate of the order below counts for, in characters seen.
WEIGHT = 4.0
#: One host in so many calibrates.
PARTS = 4
#: Scores are summed as whole numbers of this part, so that no sum depends on the order of rows.
UNIT = 1 << 30
_START = "\u0002"
_BINS, _SPAN = 4000, 8.0
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def host_and_path(url: Column) -> tuple[Column, Column]:
    form = r"(?s)^.*?://([^/?#]*)([^?#]*)"
    part = lambda k: F.coalesce(F.regexp_extract(url, form, k), F.lit(""))
    return F.translate(part(1), _UPPER, _LOWER), part(2)


def rule_of(host: Column, path: Column, rules: dict[str, str] = RULES) -> Column:
    """The longest rule that fits a host (or one above it) and the start of a path; null if none does."""
    out = None
    for rule in sorted(rules, key=lambda r: (-len(r), r)):
        name, slash, rest = rule.partition("/")
        fits = ((host == name) | host.endswith("." + name)) & path.startswith(slash + rest)
        out = F.when(fits, rule) if out is None else out.when(fits, rule)
    return out if out is not None else F.lit(None).cast("string")


def judged_by_rules(pages: DataFrame, id_col: str, url_col: str, rules: dict[str, str]) -> DataFrame:
    """``id, host, path, rule, ruled`` and the weak label: 1 accepted, 0 rejected, null neither."""
    host, path = host_and_path(F.col(url_col))
    out = pages.select(F.col(id_col).cast("bigint").alias("id"), host.alias("host"), path.alias("path"))
    out = out.withColumn("rule", rule_of(F.col("host"), F.col("path"), rules))
    verdicts = F.lit(None).cast("string")
    for rule, verdict in rules.items():
        verdicts = F.when(F.col("rule") == rule, verdict).otherwise(verdicts)
    unwanted = F.regexp_like("host", F.lit(rf"(^|[^a-z])({'|'.join(UNWANTED)})([^a-z]|$)"))
    label = F.when(F.length("host") == 0, None).when(unwanted, 0).when(F.coalesce(verdicts != "block", F.lit(True)), 1)
    return out.withColumns({"ruled": verdicts, "label": label})


def _seeds() -> tuple[list[str], list[str]]:
    """Hosts made of the two word lists, as accepted and rejected URLs."""
    pairs = lambda words: [f"{w}.{t}" for w in words for t in ("com", "net", "org")] + [f"{a}-{b}.com" for a, b in zip(words, words[1:], strict=False)]
    return pairs(WELCOME), pairs(UNWANTED)


def windows(text: Column) -> Column:
    """For each character of a text the window that ends with it: ``ORDER`` characters before it, and itself."""
    chars = F.split(F.concat(F.lit(_START * ORDER), text), "")
    made = let(chars, lambda c: F.transform(F.sequence(F.lit(0), F.size(c) - ORDER - 1), lambda i: F.concat(*(F.get(c, i + k) for k in range(ORDER + 1)))))
    return F.when(F.length(text) > 0, made).otherwise(F.array().cast("array<string>"))


def _estimates(table: DataFrame) -> DataFrame:
    """``w, gain`` from ``w, n1, n0`` with a row for each distinct window.

    A window's last two characters of context decide the partition, so all orders from two on are summed without another shuffle."""
    table = cut(table)
    total = table.agg(F.sum("n1").alias("t1"), F.sum("n0").alias("t0")).first()
    last = lambda n: F.substring("w", ORDER + 2 - n, n)
    context = lambda k: F.substring("w", ORDER + 1 - k, k)

    def summed(key: Column, name: str) -> DataFrame:
        return table.groupBy(key.alias(name)).agg(*(F.sum(f"n{x}").alias(f"{name}_{x}") for x in (1, 0)))

    held = table.withColumn("pair", context(2)).repartition("pair")
    for k in range(ORDER, 1, -1):
        for name, key in ((f"c{k}", context(k)), (f"e{k}", last(k + 1))):
            over = Window.partitionBy("pair", key)
            held = held.withColumns({f"{name}_{x}": F.sum(f"n{x}").over(over) for x in (1, 0)}) if name != f"e{ORDER}" else held.withColumns({f"{name}_{x}": F.col(f"n{x}") for x in (1, 0)})
    # the two lowest orders: a row for each character, and for each pair of characters
    held = held.withColumns({"e0": last(1), "e1": last(2), "c1": context(1)})
    for name, key in (("e0", last(1)), ("e1", last(2)), ("c1", context(1))):
        held = held.join(summed(key, name), name)
    held = held.withColumns({f"c0_{x}": F.lit(total[f"t{x}"] or 0) for x in (1, 0)})

    def likelihood(x: int) -> Column:
        p = F.lit(1 / 256)
        for k in range(ORDER + 1):
            p = (F.col(f"e{k}_{x}") + WEIGHT * p) / (F.col(f"c{k}_{x}") + WEIGHT)
        return p

    return held.select("w", F.round((F.ln(likelihood(1)) - F.ln(likelihood(0))) * UNIT).cast("bigint").alias("gain"))


def _seed_rows(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(u, x, False) for x, urls in zip((1, 0), _seeds(), strict=True) for u in urls], "url string, label int, held boolean")


def gains(urls: DataFrame) -> DataFrame:
    """``w, gain`` for every window of ``urls`` (``url, label, held``): what it adds to the log-likelihood ratio, in parts of
    ``UNIT``. Labelled URLs that aren't held back are counted, and so are the seeds."""
    every = urls.unionByName(_seed_rows(urls.sparkSession))
    counted = lambda x: F.when((F.col("label") == x) & ~F.col("held"), 1).otherwise(0)
    flat = every.select(F.explode(windows(F.col("url"))).alias("w"), counted(1).alias("n1"), counted(0).alias("n0"))
    return _estimates(flat.groupBy("w").agg(F.sum("n1").alias("n1"), F.sum("n0").alias("n0")))


def scored(judged: DataFrame) -> DataFrame:
    """``judged`` (``host, path, label`` and more) with ``held`` and ``score``.

    Scores are worked out once for each distinct URL, known by 128 bits of hash, so a URL that many rows share costs no more than another."""
    held = F.pmod(F.xxhash64("host"), F.lit(PARTS)) == 0
    rows = judged.withColumns({"url": F.concat("host", "path"), "held": held})
    rows = rows.withColumns({"_a": F.xxhash64("url"), "_b": F.xxhash64(F.lit(1), "url")})
    model = gains(rows.select("url", "label", "held"))
    distinct = rows.groupBy("_a", "_b").agg(F.min("url").alias("url"))
    places = distinct.select("_a", "_b", F.explode(windows(F.col("url"))).alias("w")).groupBy("_a", "_b", "w").agg(F.count("*").alias("n"))
    sums = places.join(model, "w").groupBy("_a", "_b").agg((F.sum(F.col("gain") * F.col("n")) / UNIT / F.sum("n")).alias("score"))
    return rows.join(sums, ["_a", "_b"], "left").withColumn("score", F.round(F.coalesce("score", F.lit(0.0)), 9)).drop("_a", "_b", "url")


def threshold(rows: DataFrame) -> float:
    """The score of least balanced error over the labelled URLs that weren't counted."""
    place = F.least(F.greatest(F.floor((F.col("score") + _SPAN / 2) / _SPAN * _BINS), F.lit(0)), F.lit(_BINS - 1)).cast("int")
    seen = rows.where("label is not null and held").groupBy("label", place.alias("bin")).count().collect()  # at most 2 * _BINS rows
    held = np.zeros((2, _BINS))
    for r in seen:
        held[r["label"], r["bin"]] = r["count"]
    if not held.sum(1).all():
        return 0.0
    below = np.concatenate([np.zeros((2, 1)), np.cumsum(held, 1)], 1) / held.sum(1, keepdims=True)
    error = below[1] + 1 - below[0]  # accepted below the threshold, and rejected at or above it
    best = np.flatnonzero(error <= error.min() + 1e-12)
    return float((best[0] + best[-1]) / 2 / _BINS * _SPAN - _SPAN / 2)


def judge(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", rules: dict[str, str] = RULES) -> DataFrame:
    """A row for each URL: ``id_col, host, path, rule, verdict, score``."""
    rows = cut(scored(cut(judged_by_rules(pages, id_col, url_col, rules))))
    verdict = F.coalesce("ruled", F.when(F.col("score") >= threshold(rows), "allow").otherwise("block"))
    return rows.select(F.col("id").alias(id_col), "host", "path", "rule", verdict.alias("verdict"), "score")
