"""Quality rules as weak supervision: rules vote or abstain, expectation-maximisation weighs them.

Only DataFrame functions run on the executors: one map stage makes the features, one small
aggregate counts vote patterns over all documents, and the posterior is a closed expression.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import BLANKS, let, trimmed, written

#: Frequent short words of the four languages.
STOP_WORDS = (
    "the be to of and that have with in is it for on as at by "
    "le la les de des et un une que en est pour dans "
    "der die das und ist von zu den mit im "
    "el los las y es con por para una se"
).split()
#: How rules vote on good and bad texts, before anything is learned, and how many rows that is worth.
GOOD, BAD, PRIOR_ROWS = {1: 0.75, 0: 0.2, -1: 0.05}, {1: 0.35, 0: 0.25, -1: 0.4}, 50.0
SYMBOLS = r"[^#*$%&|<>]"


def repeated_words(w: Column, width: int = 3) -> Column:
    """Words inside windows of `width` words that occur twice or more in the text, the first included."""
    hashed = F.transform(w, lambda x, i: F.xxhash64(x, *[F.get(w, i + k) for k in range(1, width)]))
    hashed = F.slice(hashed, F.lit(1), F.greatest(F.size(w) - (width - 1), F.lit(0)))

    def covered(h: Column) -> Column:
        pairs = F.sort_array(F.transform(h, lambda x, i: F.struct(x.alias("h"), i.alias("p"))))
        again = let(
            pairs,
            lambda z: F.transform(
                F.filter(z, lambda e, i: (e["h"] == F.get(z, i - 1)["h"]) | (e["h"] == F.get(z, i + 1)["h"])),
                lambda e: e["p"],
            ),
        )
        start = F.struct(F.lit(0).cast("long").alias("n"), F.lit(-width).alias("last"))
        return F.aggregate(
            F.sort_array(again),
            start,
            lambda acc, p: F.struct((acc["n"] + F.least(F.lit(width), p - acc["last"])).alias("n"), p.alias("last")),
            lambda acc: acc["n"],
        )

    none = F.lit(0).cast("long")
    return let(hashed, lambda h: F.when(F.size(F.array_distinct(h)) == F.size(h), none).otherwise(covered(h)))


def features(docs: DataFrame) -> DataFrame:
    """Counts of each document, over the whole text. Null text: as an empty one."""
    text = F.coalesce(F.col("text"), F.lit(""))
    stops = F.array(*[F.lit(x) for x in STOP_WORDS])
    base = docs.select("doc_id", text.alias("text"), trimmed(F.col("text")).alias("_t"))
    # Every use of the words sits under one binding, so that the text is split once.
    split = F.when(F.col("_t") == "", F.array().cast("array<string>")).otherwise(F.split("_t", BLANKS))
    lines = F.filter(F.split("text", "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    by_word = let(
        split,
        lambda w: F.struct(
            F.size(w).cast("long").alias("n_words"),
            F.length(F.array_join(w, "")).cast("long").alias("word_chars"),
            repeated_words(w).alias("n_repeat_words"),
            F.size(F.array_intersect(w, stops)).cast("long").alias("n_stops"),
            F.size(F.array_distinct(w)).cast("long").alias("n_distinct"),
        ),
    )
    by_line = let(
        lines,
        lambda x: F.struct(
            F.size(x).cast("long").alias("n_lines"),
            (F.size(x) - F.size(F.array_distinct(x))).cast("long").alias("n_dup_lines"),
        ),
    )
    made = base.select(
        "doc_id",
        by_word.alias("w"),
        by_line.alias("l"),
        F.length(F.regexp_replace("text", SYMBOLS, "")).cast("long").alias("n_symbols"),
        F.length(F.regexp_replace("text", r"[^\p{L}]", "")).cast("long").alias("n_letters"),
    )
    return made.select("doc_id", "w.*", "l.*", "n_symbols", "n_letters")


def votes() -> dict[str, Column]:
    """1 for good, -1 for bad, 0 to abstain. A rule abstains where a text gives it too little."""
    n, c = F.col("n_words"), F.col

    def rule(bad: Column, good: Column) -> Column:
        return F.when(bad, -1).when(good, 1).otherwise(0)

    some = n >= 20
    return {
        "length": rule(n < 50, n >= 100),
        "word_length": rule(some & ((c("word_chars") < 2.5 * n) | (c("word_chars") > 12 * n)), some & c("word_chars").between(3 * n, 10 * n)),
        "symbols": rule(some & (10 * c("n_symbols") > n), some & (100 * c("n_symbols") <= n)),
        "lines": rule(10 * c("n_dup_lines") > 3 * c("n_lines"), (c("n_lines") >= 3) & (c("n_dup_lines") == 0)),
        "repeats": rule(some & (100 * c("n_repeat_words") > 50 * n), some & (100 * c("n_repeat_words") < 20 * n)),
        "stop_words": rule(some & (c("n_stops") < 2), some & (c("n_stops") >= 3)),
        "letters": rule(some & (10 * c("n_letters") < 7 * c("word_chars")), some & (10 * c("n_letters") >= 8 * c("word_chars"))),
        "variety": rule((n >= 100) & (20 * c("n_distinct") < n), (n >= 100) & (10 * c("n_distinct") > n)),
    }


def fit(patterns: list[tuple[tuple[int, ...], int]], rounds: int = 60, prior: float = 0.8) -> tuple[float, list[dict[int, float]]]:
    """Expectation-maximisation over counts of vote patterns.

    Returns the prior's log odds and, for each rule, the log odds that each vote adds. Rules are
    held to be better than chance: a vote for good never lowers the posterior, one against never raises it.
    """
    k = len(patterns[0][0]) if patterns else 0
    good, bad = [GOOD] * k, [BAD] * k
    for _ in range(rounds):
        # What is assumed beforehand counts as PRIOR_ROWS rows, so that a handful of documents cannot turn the classes round.
        g, b = ([{v: PRIOR_ROWS * x for v, x in (GOOD if c else BAD).items()} for _ in range(k)] for c in (1, 0))
        share, total = PRIOR_ROWS * 0.8, PRIOR_ROWS
        for p, n in patterns:
            odds = math.log(prior / (1 - prior)) + sum(math.log(good[j][v] / bad[j][v]) for j, v in enumerate(p))
            q = 1 / (1 + math.exp(-max(-50.0, min(50.0, odds))))
            share += n * q
            total += n
            for j, v in enumerate(p):
                g[j][v] += n * q
                b[j][v] += n * (1 - q)
        prior = min(0.99, max(0.05, share / total))
        good = [{v: x / sum(t.values()) for v, x in t.items()} for t in g]
        bad = [{v: x / sum(t.values()) for v, x in t.items()} for t in b]
    weights = []
    for g, b in zip(good, bad, strict=True):
        w = {v: math.log(g[v] / b[v]) for v in (-1, 0, 1)}
        weights.append({-1: min(0.0, w[-1]), 0: 0.0, 1: max(0.0, w[1])})
    return math.log(prior / (1 - prior)), weights


def quality(docs: DataFrame, threshold: float = 0.5) -> DataFrame:
    """docs(doc_id, text, ...) -> the counts, base_failed, quality (posterior) and kept, a row for each row.

    Null and empty texts have no words: counts of 0, base_failed true. Repeated rows are judged alike.
    An empty table gives an empty result. Other columns are ignored.
    """
    made = written(features(docs), "quality")
    rules = votes()
    voted = made.select("*", *[v.alias(f"_v_{k}") for k, v in rules.items()])
    # At most 3 ** 8 patterns, whatever the number of documents.
    found = voted.groupBy(*[f"_v_{k}" for k in rules]).count().collect()
    odds, weights = fit([(tuple(r[:-1]), r[-1]) for r in found])
    score = F.lit(odds)
    for k, w in zip(rules, weights, strict=False):
        score = score + F.when(F.col(f"_v_{k}") == 1, F.lit(w[1])).when(F.col(f"_v_{k}") == -1, F.lit(w[-1])).otherwise(F.lit(0.0))
    failed = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    posterior = 1 / (1 + F.exp(-score))
    return voted.select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words",
        failed.alias("base_failed"), (~failed & (posterior >= threshold)).alias("kept"), posterior.alias("quality"),
    )
