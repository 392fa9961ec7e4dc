"""Quality by weak supervision; DataFrame functions only.

Eight rules vote good (1), bad (-1) or abstain (0) on each document. Expectation-maximisation
over the table of vote patterns (at most 3**8 rows, whatever the corpus) estimates the share of
good documents and, for each rule and class, how often it votes which way; the posterior probability
of good from those replaces a rule that all votes must pass.

Null and empty texts have no words, fail the base test and are not kept. Repeated rows are counted and
returned each. A posterior of just KEEP is kept. On an empty table nothing is estimated, no rows are returned and the starting values hold.
A task holds a row's words and its 3-word windows (some 20 bytes a window) at a time, whatever the text's length.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from bucketnet.llm.common import columns_of, cut, fresh

WHITE = r"[\x20\x09-\x0D]+"
MIN_WORDS, KEEP = 50, 0.5
FEATURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_capitals", "n_bangs", "n_stops")
ROUNDS, PSEUDO = 40, 2.0


def _without(col: Column, chars: str) -> Column:
    for c in chars:
        col = F.replace(col, F.lit(c), F.lit(""))
    return col


def measure(docs: DataFrame) -> DataFrame:
    """docs with its FEATURES, all long, from the whole text."""
    t = F.coalesce(F.col("text").cast("string"), F.lit(""))
    d = docs.withColumn("__t", t).withColumn("__w", F.filter(F.split("__t", WHITE), lambda x: x != ""))
    # equal 3-word windows stand side by side once their hashes are sorted
    n = F.size("__w")
    windows = F.when(n >= 3, F.transform(F.sequence(F.lit(0), n - 3), lambda i: F.struct(F.xxhash64(F.get("__w", i), F.get("__w", i + 1), F.get("__w", i + 2)).alias("h"), i.alias("i"))))
    d = d.withColumn("__s", F.sort_array(F.coalesce(windows, F.array().cast("array<struct<h:bigint,i:int>>"))))
    h = lambda k: F.get("__s", k)["h"]
    twice = F.filter("__s", lambda x, k: x["h"].eqNullSafe(h(k - 1)) | x["h"].eqNullSafe(h(k + 1)))
    d = d.withColumn("__p", F.sort_array(F.transform(twice, lambda x: x["i"])))
    m = F.size("__p")
    covered = F.aggregate(F.transform("__p", lambda p, k: F.least(F.lit(3), F.coalesce(F.get("__p", k + 1) - p, F.lit(3)))), F.lit(0).cast("long"), lambda a, x: a + x)
    lines = F.filter(F.split("__t", "\n", -1), lambda x: F.octet_length(_without(x, " \t\x0b\x0c\r")) > 0)
    d = d.withColumn("__n", lines)
    gone = lambda chars: F.octet_length("__t") - F.octet_length(_without(F.col("__t"), chars))
    return d.withColumns({
        "n_words": n.cast("long"),
        "word_chars": (F.char_length("__t") - gone(" \t\n\x0b\x0c\r")).cast("long"),
        "n_symbols": gone("#*$%&|<>").cast("long"),
        "n_dup_lines": (F.size("__n") - F.size(F.array_distinct("__n"))).cast("long"),
        "n_repeat_words": F.when(m > 0, covered).otherwise(0).cast("long"),
        "n_lines": F.size("__n").cast("long"),
        "n_capitals": F.regexp_count("__t", F.lit("[A-Z]")).cast("long"),
        "n_bangs": gone("!").cast("long"),
        "n_stops": gone(".").cast("long"),
    }).drop("__t", "__w", "__s", "__p", "__n")


def _vote(good: Column | None, bad: Column | None) -> Column:
    """1 or -1 where a condition holds, else (or where a share is undefined) 0."""
    out = F.lit(0)
    if good is not None:
        out = F.when(F.coalesce(good, F.lit(False)), 1).otherwise(out)
    return out if bad is None else F.when(F.coalesce(bad, F.lit(False)), -1).otherwise(out)


def rule_votes() -> dict[str, Column]:
    """The rules over the measured columns.

    A rule that looks for one kind of junk abstains where it finds none: the lack of one kind says
    little about the others, and votes of good there would let EM call a rare kind of junk good.
    """
    c = {k: F.col(k).cast("double") for k in FEATURES}
    share = lambda a, b: F.try_divide(c[a], c[b])
    symbols, repeats, lines = share("n_symbols", "n_words"), share("n_repeat_words", "n_words"), share("n_dup_lines", "n_lines")
    capitals, length, bangs, stops = share("n_capitals", "word_chars"), share("word_chars", "n_words"), share("n_bangs", "n_words"), share("n_stops", "n_words")
    return {
        "symbols": _vote(None, symbols > 0.1),
        "repeats": _vote(None, repeats > 0.4),
        "lines": _vote(None, lines > 0.5),
        "capitals": _vote(None, capitals > 0.3),
        "bangs": _vote(None, bangs > 0.2),
        "stops": _vote(stops.between(0.02, 0.5), stops < 0.004),
        "length": _vote(length.between(3.0, 12.0), (length < 2.0) | (length > 16.0)),
        "prose": _vote((symbols < 0.02) & (capitals < 0.12) & (bangs < 0.05), None),
    }


class VoteModel:
    """Share of good documents and, for each rule, chances of each vote in a good and in a bad one."""

    def __init__(self, rules: list[str]):
        self.rules, self.good = rules, 0.8
        self.chance = {r: {1: {1: 0.7, -1: 0.02, 0: 0.28}, 0: {1: 0.4, -1: 0.35, 0: 0.25}} for r in rules}

    def log_odds(self, votes: tuple) -> float:
        return math.log(self.good / (1 - self.good)) + sum(math.log(self.chance[r][1][v] / self.chance[r][0][v]) for r, v in zip(self.rules, votes, strict=True))

    def fit(self, patterns: list[tuple[tuple, int]], rounds: int = ROUNDS, pseudo: float = PSEUDO) -> VoteModel:
        """Expectation-maximisation; the starting chances count as pseudo documents of each class."""
        start = self.chance
        total = sum(n for _, n in patterns)
        for _ in range(rounds if total else 0):
            weight = {p: n / (1 + math.exp(-max(-500.0, min(500.0, self.log_odds(p))))) for p, n in patterns}
            kept = sum(weight.values())
            self.good = (kept + pseudo) / (total + 2 * pseudo)
            chance = {}
            for k, r in enumerate(self.rules):
                of = {1: dict.fromkeys((1, -1, 0), 0.0), 0: dict.fromkeys((1, -1, 0), 0.0)}
                for p, n in patterns:
                    of[1][p[k]] += weight[p]
                    of[0][p[k]] += n - weight[p]
                chance[r] = {y: {v: (of[y][v] + pseudo * start[r][y][v]) / (sum(of[y].values()) + pseudo) for v in (1, -1, 0)} for y in (1, 0)}
            self.chance = chance
        return self

    def accuracy(self, rule: str) -> float:
        """How often the rule is right when it votes."""
        g, b = self.chance[rule][1], self.chance[rule][0]
        right = self.good * g[1] + (1 - self.good) * b[-1]
        return right / (right + self.good * g[-1] + (1 - self.good) * b[1])

    def posterior(self, votes: dict[str, Column]) -> Column:
        odds = F.lit(math.log(self.good / (1 - self.good)))
        for r in self.rules:
            gain = {v: math.log(self.chance[r][1][v] / self.chance[r][0][v]) for v in (1, -1, 0)}
            odds = odds + F.when(votes[r] == 1, gain[1]).when(votes[r] == -1, gain[-1]).otherwise(gain[0])
        return 1 / (1 + F.exp(-odds))


def judge(measured: DataFrame) -> DataFrame:
    """measured (durable, as from cut) with base_failed, quality_posterior and kept; the model is fitted to all its rows that have words."""
    rules = rule_votes()
    names = list(rules)
    voted = measured.withColumns({f"__v_{r}": v for r, v in rules.items()})
    counts = voted.where("n_words > 0").groupBy(*[f"__v_{r}" for r in names]).agg(F.count(F.lit(1)).alias("n")).collect()  # at most 3**8 rows
    model = VoteModel(names).fit(sorted((tuple(r[:-1]), r[-1]) for r in counts))
    base = (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    p = model.posterior({r: F.col(f"__v_{r}") for r in names})
    out = voted.withColumns({"base_failed": base, "quality_posterior": p})
    return out.withColumn("kept", ~F.col("base_failed") & (F.col("quality_posterior") >= KEEP)).drop(*[f"__v_{r}" for r in names])


def score_quality(docs: DataFrame) -> DataFrame:
    """doc_id, the FEATURES, base_failed, quality_posterior, kept for every row of docs."""
    return judge(cut(measure(docs.select("doc_id", "text")).drop("text")))


def keep_good(docs: DataFrame) -> DataFrame:
    """The rows of docs whose verdict is kept, with all their columns.

    Verdicts are joined back by doc_id and text hash, so rows of one id with other texts have their own.
    """
    g_id, g_th, th = fresh(docs, "__id", "__th", "__text_hash")
    key = docs.select("doc_id", F.xxhash64("text").alias("__th"), "text")
    measured = cut(measure(key).drop("text"))
    good = judge(measured).where("kept").select(F.col("doc_id").alias(g_id), F.col("__th").alias(g_th)).distinct()
    rows = docs.withColumn(th, F.xxhash64("text"))
    return rows.join(good, F.col("doc_id").eqNullSafe(F.col(g_id)) & (F.col(th) == F.col(g_th)), "left_semi").select(*columns_of(docs))
