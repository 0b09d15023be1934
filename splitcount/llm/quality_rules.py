"""Weak supervision for text quality (DataFrame functions only).

Rules vote good, bad or abstain on counts of each whole text.  Expectation-maximisation over the counts
of vote patterns (at most 3 ** rules rows, whatever the corpus size) estimates how often each rule gives
each vote on good and on bad texts, and the share of good texts; a text's posterior probability of being
good then follows from its votes.  A text is kept if the fixed limits hold and the posterior reaches the
threshold, so that one failed soft rule no longer rejects it by itself.

Repeated three-word windows are found inside each row: a window's hash stands above its place in one long
(as many bits for the place as the row's words need, 24 at least), one primitive sort brings equal hashes
together, and only those candidates are compared as text.

Defined results: a null or empty text has no words, so the fixed limits reject it; rows that repeat stay;
an empty table gives no rows.
"""

from __future__ import annotations

from dataclasses import dataclass
from math import exp, log

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from splitcount.llm.common import cut, text_of

_SPLIT = r"[\x20\x09-\x0D]+"
_HAS_WORD = r"[^\x20\x09-\x0D]"
_PLACE_BITS = 24


def _equal_neighbour(arr: Column, x: Column, i: Column, key) -> Column:
    before, after = F.get(arr, i - 1), F.get(arr, i + 1)
    return (F.coalesce(key(before) == key(x), F.lit(False))) | (F.coalesce(key(after) == key(x), F.lit(False)))


def text_counts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_words, word_chars, n_symbols, n_lines, n_dup_lines, n_repeat_words, n_upper, n_ends, n_punct."""
    t = F.col("t")
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), text_of(text_col).alias("t"))
    lines = F.filter(F.split(t, "\n"), lambda s: s.rlike(_HAS_WORD))
    left = lambda keep: F.length(F.regexp_replace(t, keep, "")).cast("long")
    rows = rows.select(
        "doc_id",
        F.filter(F.split(t, _SPLIT), lambda w: w != "").alias("words"),
        lines.alias("lines"),
        left(r"[^#*$%&|<>]+").alias("n_symbols"),
        left(r"[^A-Z]+").alias("n_upper"),
        left(r"[^.!?]+").alias("n_ends"),
        left(r"[^!-/:-@\[-`{-~]+").alias("n_punct"),
    )
    rows = rows.select(
        "doc_id",
        "words",
        F.size("words").cast("long").alias("n_words"),
        F.length(F.array_join("words", "")).cast("long").alias("word_chars"),
        "n_symbols",
        F.size("lines").cast("long").alias("n_lines"),
        (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"),
        "n_upper",
        "n_ends",
        "n_punct",
        F.transform("words", lambda w: F.xxhash64(w)).alias("wh"),
        F.greatest(F.lit(_PLACE_BITS), F.length(F.bin(F.size("words").cast("long")))).alias("bits"),
    )
    counts = ["n_words", "word_chars", "n_symbols", "n_lines", "n_dup_lines", "n_upper", "n_ends", "n_punct"]
    wh, bits = F.col("wh"), F.col("bits")
    keys = F.transform(
        F.slice(wh, 1, F.greatest(F.col("n_words").cast("int") - 2, F.lit(0))),
        lambda h, i: F.call_function("shiftleft", F.xxhash64(h, F.get(wh, i + 1), F.get(wh, i + 2)), bits).bitwiseOR(i.cast("long")),
    )
    rows = rows.select("doc_id", *counts, "words", "bits", F.sort_array(keys).alias("s"))
    s = F.col("s")
    place = F.call_function("shiftleft", F.lit(1).cast("long"), bits) - 1
    cand = F.transform(
        F.filter(s, lambda x, i: _equal_neighbour(s, x, i, lambda k: F.call_function("shiftright", k, bits))),
        lambda x: x.bitwiseAND(place).cast("int"),
    )
    rows = rows.select("doc_id", *counts, "words", cand.alias("cand"), F.size("s").alias("windows"))
    words = F.col("words")
    as_text = F.transform("cand", lambda p: F.struct(F.concat_ws(" ", F.get(words, p), F.get(words, p + 1), F.get(words, p + 2)).alias("w"), p.alias("p")))
    rows = rows.select("doc_id", *counts, F.sort_array(as_text).alias("c"), "windows")
    c = F.col("c")
    again = F.filter(c, lambda x, i: _equal_neighbour(c, x, i, lambda k: k["w"]))
    rows = rows.select("doc_id", *counts, F.sort_array(F.transform(again, lambda x: x["p"])).alias("p"), "windows")
    p = F.col("p")
    covered = F.aggregate(p, F.struct(F.lit(-3).alias("last"), F.lit(0).cast("long").alias("n")), lambda a, x: F.struct(x.alias("last"), (a["n"] + F.least(x - a["last"], F.lit(3)).cast("long")).alias("n")), lambda a: a["n"])
    return rows.select("doc_id", *counts, covered.alias("n_repeat_words"))


@dataclass(frozen=True)
class Rule:
    """Votes good (1) or bad (0) by two conditions on the counts; abstains (2) between them."""

    name: str
    good: str
    bad: str

    def vote(self) -> Column:
        return F.when(F.expr(self.bad), 0).when(F.expr(self.good), 1).otherwise(2)


RULES = (
    Rule("length", "n_words >= 60", "n_words < 50"),
    Rule("symbols", "50 * n_symbols <= n_words", "10 * n_symbols > n_words"),
    Rule("word_size", "word_chars between 3 * n_words and 10 * n_words", "2 * word_chars < 5 * n_words or word_chars > 14 * n_words"),
    Rule("capitals", "100 * n_upper <= 15 * word_chars", "100 * n_upper > 40 * word_chars"),
    Rule("lines", "n_dup_lines = 0", "10 * n_dup_lines > 3 * n_lines"),
    Rule("repeats", "5 * n_repeat_words <= n_words", "100 * n_repeat_words > 50 * n_words"),
    Rule("marks", "4 * n_punct <= n_words", "5 * n_punct > 2 * n_words"),
    Rule("sentences", "60 * n_ends >= n_words and 3 * n_ends <= n_words", "200 * n_ends < n_words or 2 * n_ends > n_words"),
)


@dataclass(frozen=True)
class VoteModel:
    """good: share of good texts; table[j][y][v]: chance of vote v of rule j on texts of class y."""

    good: float
    table: tuple


def fit_votes(patterns: list[tuple[tuple[int, ...], int]], n_rules: int, rounds: int = 100, tol: float = 1e-9) -> VoteModel:
    """Expectation-maximisation over distinct vote patterns with their counts.

    Starts with a bad vote counting far more than a good one, since most rules pass on most texts of either
    class.  Smoothing adds ``n/200 + 1`` texts' worth of belief that a rule's
    votes agree with the class four times in five, which keeps the two classes from trading places.
    """
    n = sum(c for _, c in patterns) or 1
    belief = n / 200 + 1

    def start(votes: tuple[int, ...]) -> float:
        return 1 / (1 + exp(3.0 * votes.count(0) - 0.4 * votes.count(1) - 1.0))

    post = [start(v) for v, _ in patterns]
    model, before = VoteModel(0.8, ()), None
    for _ in range(rounds):
        good = (sum(p * c for p, (_, c) in zip(post, patterns, strict=True)) + 0.8 * belief) / (n + belief)
        table = []
        for j in range(n_rules):
            counts = [[0.8 * belief, 0.2 * belief, belief], [0.2 * belief, 0.8 * belief, belief]]
            for p, (v, c) in zip(post, patterns, strict=True):
                counts[1][v[j]] += p * c
                counts[0][v[j]] += (1 - p) * c
            table.append(tuple(tuple(x / sum(row) for x in row) for row in counts))
        model = VoteModel(good, tuple(table))
        post = [posterior(model, v) for v, _ in patterns]
        if before is not None and abs(before - good) < tol:
            break
        before = good
    return model


def log_odds(model: VoteModel) -> tuple[float, list[list[float]]]:
    return log(model.good / (1 - model.good)), [[log(t[1][v] / t[0][v]) for v in range(3)] for t in model.table]


def posterior(model: VoteModel, votes: tuple[int, ...]) -> float:
    bias, add = log_odds(model)
    x = bias + sum(add[j][v] for j, v in enumerate(votes))
    return 1 / (1 + exp(-x)) if x > -700 else 0.0


def posterior_column(model: VoteModel, rules: tuple[Rule, ...] = RULES) -> Column:
    bias, add = log_odds(model)
    x = F.lit(bias)
    for r, a in zip(rules, add, strict=True):
        v = r.vote()
        x = x + F.when(v == 0, a[0]).when(v == 1, a[1]).otherwise(a[2])
    return 1 / (1 + F.exp(-x))


def vote_patterns(counts: DataFrame, rules: tuple[Rule, ...] = RULES) -> list[tuple[tuple[int, ...], int]]:
    """Distinct patterns and their counts; at most 3 ** len(rules) rows reach the driver."""
    named = counts.select(*(r.vote().alias(f"v{j}") for j, r in enumerate(rules)))
    got = named.groupBy(*named.columns).count().collect()
    return sorted((tuple(r[:-1]), r[-1]) for r in got)


def judge(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", rules: tuple[Rule, ...] = RULES, threshold: float = 0.25) -> DataFrame:
    """Counts, ``base_failed``, ``quality`` (posterior, 6 decimals) and ``kept`` per row.

    The threshold rejects what is at least three times as likely bad as good.
    """
    counts = cut(text_counts(docs, id_col, text_col))
    model = fit_votes(vote_patterns(counts, rules), len(rules))
    failed = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    p = posterior_column(model, rules)
    return counts.select("*", failed.alias("base_failed"), F.round(p, 6).alias("quality"), (~failed & (p >= threshold)).alias("kept"))


def op1_quality_rules(spark, sf_dir: str) -> DataFrame:
    rows = judge(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return rows.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "quality")
