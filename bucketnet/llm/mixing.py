"""Mixing to target weights with soft membership of domains.

Domains come from the labelled table: toxic (toxic = 1), junk (else quality = 0), good (else).
A softmax regression, fitted on a bounded sample of labelled rows (sample_rows), over the presence of
tokens that tell the domains apart (by 62-bit hashes, so that rare words do not share a place with telling
ones), gives each document a posterior p over domains. With t tokens and
a rate r >= 0 a document gives r * t * p expected tokens to the domains; the rates minimise

    sum over domains of c * (expected tokens - target)**2 / (all tokens)**2  +  pull * sum over documents of t * (r - 1)**2 / (all tokens)

where c is 1, but for a domain whose share of all tokens is below FLOOR, FLOOR / share: otherwise the pull would outweigh a rare
domain. A projected-gradient step in the metric of t leaves the rates where they are when r = max(0, 1 - p . y)
with y = c * (expected tokens - target) / (all tokens) / pull, one number a domain; these few numbers are found by
Newton steps with a line search until the equations hold to CLOSE. A step needs one distributed sum of
few numbers, and no rates are stored between steps.

Null and empty texts have no tokens and rate 1. Rows are kept one for one by mix_rates. Without labels every
posterior is equal and rates only meet the total. Rows with equal doc_id and text get equal rates. An empty table gives no rows. A text longer than a
run (2 MB) is a run of its own, and a task then holds its tokens' hashes (8 bytes a token).
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from bucketnet.llm import words
from bucketnet.llm.common import columns_of, cut, fresh, hash_sample
from bucketnet.llm.quality_net import tokens

DOMAINS = ("good", "junk", "toxic")
SPACE = 1 << 62
SLOTS = 20  # bits of the table that most tokens are ruled out by
EVIDENCE = 3.0  # a token counts if its seen * log(seen / expected) in a domain is above this and the log of the number of tokens: beyond chance among so many
FEATURES, SAMPLE_ROWS = 600, 8000
STEPS, STEP, PULL = 40, 0.9, 1e-3
FLOOR, CLOSE, MOST = 0.01, 1e-9, 100  # of shares of all tokens; equations' error; Newton steps that are not expected to be needed
WEIGHTS = {"good": 0.90, "junk": 0.06, "toxic": 0.04}


def domain_of(labels: DataFrame) -> DataFrame:
    """l_id and domain number of labelled ids; of several rows of an id the worst counts."""
    toxic, quality = F.coalesce(F.max("toxic"), F.lit(0)), F.coalesce(F.min("quality"), F.lit(1))
    grouped = labels.where("doc_id is not null and (toxic is not null or quality is not null)").groupBy(F.col("doc_id").cast("long").alias("l_id"))
    return grouped.agg(F.when(toxic == 1, 2).when(quality == 0, 1).otherwise(0).alias("domain"))


def token_hashes(buf: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hashes of all tokens and shape words of all texts, the n + 1 offsets by text, and the texts' numbers of plain tokens."""
    word, per = tokens(buf, offsets, SPACE)
    return word, per, np.diff(per) - words.sum_by_text((word >= SPACE - 2).astype(np.int64), per)


class DomainModel:
    """Softmax regression on the presence of selected tokens; without classes to tell apart, equal posteriors."""

    def __init__(self, domains: int = len(DOMAINS)):
        self.known, self.slot = np.zeros(0, dtype=np.int64), np.zeros(1 << SLOTS, dtype=bool)
        self.weights, self.bias = np.zeros((0, domains)), np.zeros(domains)

    def find(self, word: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Which of the hashes are selected tokens, and which ones."""
        maybe = np.flatnonzero(self.slot[word & ((1 << SLOTS) - 1)]) if len(self.known) else np.zeros(0, np.int64)
        at = np.minimum(np.searchsorted(self.known, word[maybe]), max(0, len(self.known) - 1))
        hit = self.known[at] == word[maybe] if len(maybe) else np.zeros(0, bool)
        return maybe[hit], at[hit]

    def fit(self, rows: list[np.ndarray], y: np.ndarray, steps: int = 300, rate: float = 0.05, decay: float = 1e-3) -> DomainModel:
        """rows: each document's distinct hashes."""
        k = len(self.bias)
        if len(set(y.tolist())) < 2:
            return self
        text = np.repeat(np.arange(len(rows)), [len(r) for r in rows])
        every, place = np.unique(np.concatenate(rows), return_inverse=True)
        seen = np.stack([np.bincount(place[y[text] == c], minlength=len(every)) for c in range(k)], axis=1)
        share = np.bincount(y, minlength=k) / len(y)
        expected = seen.sum(axis=1, keepdims=True) * share + 1e-9
        evidence = seen * np.log(np.maximum(seen, 1) / expected)
        best = np.unique(np.concatenate([np.argsort(-evidence[:, c], kind="stable")[: FEATURES // k] for c in range(k)]))
        best = best[evidence[best].max(axis=1) > EVIDENCE + np.log(len(every))]
        self.known = every[best]
        self.slot[self.known & ((1 << SLOTS) - 1)] = True
        x = np.zeros((len(rows), len(best)), dtype=np.float32)
        at, which = self.find(np.concatenate(rows))
        x[text[at], which] = 1
        truth = np.eye(k)[y]
        w, b = np.zeros((len(best), k)), np.log(share + 1e-3)
        m, v = np.zeros_like(w), np.zeros_like(w)
        for t in range(1, steps + 1):
            p = self._softmax(x @ w + b)
            g = x.T @ ((p - truth) / len(y)) + decay * w / len(y)
            m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
            w = w - rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-8)
            b = b - rate * (p - truth).mean(axis=0)
        self.weights, self.bias = w, b
        return self

    @staticmethod
    def _softmax(z: np.ndarray) -> np.ndarray:
        p = np.exp(z - z.max(axis=1, keepdims=True))
        return p / p.sum(axis=1, keepdims=True)

    def posteriors(self, word: np.ndarray, per: np.ndarray) -> np.ndarray:
        n = len(per) - 1
        at, which = self.find(word)
        text = np.searchsorted(per, at, side="right") - 1
        both = np.unique(text * max(1, len(self.known)) + which)
        text, which = both // max(1, len(self.known)), both % max(1, len(self.known))
        z = np.stack([np.bincount(text, weights=self.weights[which, c], minlength=n) for c in range(len(self.bias))], axis=1)
        return self._softmax(z + self.bias)


def fit_domains(docs: DataFrame, labels: DataFrame, sample_rows: int = SAMPLE_ROWS) -> DomainModel:
    """The model from the sample_rows labelled ids of smallest hash that docs has texts for."""
    sample = hash_sample(domain_of(labels), ["l_id"], sample_rows)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in words.slices(batch, limit=2 << 20):
                word, per, _ = token_hashes(*words.text_bytes(part.column("text")))
                lists = [np.unique(word[a:b]) for a, b in zip(per[:-1], per[1:], strict=True)]
                yield pa.RecordBatch.from_arrays([part.column("l_id"), part.column("domain"), pa.array(lists, pa.list_(pa.int64()))], ["l_id", "domain", "x"])

    # bounded by sample_rows texts
    drawn = docs.join(F.broadcast(sample), F.col("doc_id") == F.col("l_id")).select("l_id", "domain", F.col("text").cast("string").alias("text")).mapInArrow(words.tidy(run), "l_id long, domain int, x array<long>")
    got = drawn.toArrow().sort_by("l_id")
    rows = [np.asarray(x, dtype=np.int64) for x in got.column("x").combine_chunks().to_numpy(zero_copy_only=False)] if got.num_rows else []
    return DomainModel().fit(rows, np.array(got.column("domain").to_pylist(), dtype=np.int64))


def domain_posteriors(docs: DataFrame, model: DomainModel) -> DataFrame:
    """docs less its text, with n_tokens (long) and p (array<double>)."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    kept = [c for c in docs.columns if c != "text"]
    schema = ", ".join(f"`{c}` {t}" for c, t in docs.dtypes if c != "text") + ", n_tokens long, p array<double>"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in words.slices(batch, limit=2 << 20):
                word, per, n = token_hashes(*words.text_bytes(part.column("text")))
                p = shared.value.posteriors(word, per)
                yield pa.RecordBatch.from_arrays([*[part.column(c) for c in kept], pa.array(n.astype(np.int64)), pa.array(list(p), pa.list_(pa.float64()))], [*kept, "n_tokens", "p"])

    return docs.mapInArrow(words.tidy(run), schema)


def rate_of(p: Column, residuals: list[list[float]], pull: float = PULL, step: float = STEP) -> Column:
    """A document's rate after steps with these residuals (expected - target, over all tokens)."""
    if not residuals:
        return F.lit(1.0)
    table = F.array(*[F.array(*[F.lit(float(x)) for x in r]) for r in residuals])

    def move(r: Column, g: Column) -> Column:
        slope = F.aggregate(F.zip_with(p, g, lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x)
        return F.greatest(F.lit(0.0), r - F.lit(step) * (slope + F.lit(pull) * (r - 1)))

    return F.aggregate(table, F.lit(1.0), move)


def fit_rates(measured: DataFrame, weights: dict[str, float], total: float | None = None, steps: int = STEPS) -> list[list[float]]:
    """Residuals of so many plain projected-gradient steps (c = 1), which need not have converged: settle_rates does.

    measured: durable, with n_tokens and p. total: of the mix, by default that of measured.
    """
    have = float(measured.agg(F.sum("n_tokens")).first()[0] or 0)
    if not have:
        return []
    targets = [weights[d] * (have if total is None else total) / sum(weights.values()) for d in DOMAINS]
    residuals: list[list[float]] = []
    for _ in range(steps):
        r = rate_of(F.col("p"), residuals) * F.col("n_tokens")
        got = measured.agg(*[F.sum(r * F.get("p", F.lit(i))).alias(f"s{i}") for i in range(len(DOMAINS))]).first()
        residuals.append([(s - t) / have for s, t in zip(got, targets, strict=True)])
    return residuals


def settled_rate(p: Column, y: np.ndarray) -> Column:
    """The rate at which a projected-gradient step moves nothing."""
    return F.greatest(F.lit(0.0), F.lit(1.0) - sum((F.get(p, F.lit(i)) * F.lit(float(x)) for i, x in enumerate(y)), F.lit(0.0)))


def settle_rates(measured: DataFrame, weights: dict[str, float], total: float | None = None, pull: float = PULL, floor: float = FLOOR) -> np.ndarray:
    """y of the rates that minimise. measured: durable, with n_tokens and p. total: of the mix, by default that of measured."""
    k = len(DOMAINS)
    p = [F.get("p", F.lit(i)) for i in range(k)]
    have, *now = (float(x or 0) for x in measured.agg(F.sum("n_tokens"), *[F.sum(F.col("n_tokens") * x) for x in p]).first())
    y = np.zeros(k)
    if not have:
        return y
    want = np.array([weights[d] for d in DOMAINS]) * (1.0 if total is None else total / have) / sum(weights.values())
    c = np.maximum(1.0, floor / np.maximum(np.array(now) / have, 1e-9))

    def at(y: np.ndarray) -> tuple[float, np.ndarray, np.ndarray]:
        """Value, gradient and second derivatives of the convex dual."""
        r, t = settled_rate(F.col("p"), y), F.col("n_tokens") / have
        pairs = [(i, j) for i in range(k) for j in range(i, k)]
        got = measured.agg(F.sum(t * r * r), *[F.sum(t * r * x) for x in p], *[F.sum(F.when(r > 0, t * p[i] * p[j]).otherwise(0.0)) for i, j in pairs]).first()
        second = np.diag(pull / c)
        for (i, j), x in zip(pairs, got[1 + k :], strict=True):
            second[i, j] += x
            if i != j:
                second[j, i] += x
        return got[0] / 2 + want @ y + pull * (y * y / c).sum() / 2, pull * y / c + want - np.array(got[1 : 1 + k]), second

    value, slope, second = at(y)
    for _ in range(MOST):
        if np.abs(slope).max() <= CLOSE:
            return y
        move, size = -np.linalg.solve(second, slope), 1.0
        new = at(y + move)
        while new[0] > value + 1e-4 * size * (slope @ move) + 1e-15 and size > 1e-9:
            size /= 2
            new = at(y + size * move)
        y, (value, slope, second) = y + size * move, new
    raise RuntimeError(f"rates have not settled in {MOST} steps: {np.abs(slope).max()} left")


def copies_of(rate: Column, key: Column) -> Column:
    """Whole copies whose mean over keys is the rate: the whole part, and one more with the chance of the rest."""
    chance = F.pmod(F.xxhash64(key, F.lit("mixing")), F.lit(1 << 30)) / float(1 << 30)
    return F.floor(rate + chance).cast("int")


def mix_rates(docs: DataFrame, labels: DataFrame, weights: dict[str, float] | None = None, total: float | None = None, sample_rows: int = SAMPLE_ROWS) -> DataFrame:
    """doc_id, text hash (__th), n_tokens, p, rate, copies for every row of docs."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("__th"), F.col("text").cast("string").alias("text"))
    measured = cut(domain_posteriors(rows, fit_domains(rows, labels, sample_rows)))
    y = settle_rates(measured, weights or WEIGHTS, total)
    rated = measured.withColumn("rate", F.when(F.col("n_tokens") == 0, 1.0).otherwise(settled_rate(F.col("p"), y)))
    return rated.withColumn("copies", copies_of(F.col("rate"), F.coalesce("doc_id", F.lit(-1))))


def without_domain(docs: DataFrame, labels: DataFrame, domain: str = "toxic", sample_rows: int = SAMPLE_ROWS, model: DomainModel | None = None) -> DataFrame:
    """docs mixed so that domain goes and all else stays as it is: the rows whose rate rounds to 1 or more, as often.

    Each document counts for its most likely domain alone: the small posteriors of many clean documents add up to a
    total that only clean documents could be taken out for. The targets are the other domains' present totals, and 0. A rate is
    rounded to the nearest whole number, not at random, so that no document is lost to chance.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("__th"), F.col("text").cast("string").alias("text"))
    soft = domain_posteriors(rows, model or fit_domains(rows, labels, sample_rows))
    best = F.transform("p", lambda x: (x == F.array_max("p")).cast("double"))
    ties = F.aggregate(best, F.lit(0.0), lambda s, x: s + x)
    measured = cut(soft.withColumn("p", F.transform(best, lambda x: x / ties)))
    now = measured.agg(*[F.sum(F.col("n_tokens") * F.get("p", F.lit(i))) for i in range(len(DOMAINS))]).first()
    weights = {d: 0.0 if d == domain else float(s or 0) for d, s in zip(DOMAINS, now, strict=True)}
    if not sum(weights.values()):
        return docs
    y = settle_rates(measured, weights, sum(weights.values()))
    rate = F.when(F.col("n_tokens") == 0, 1.0).otherwise(settled_rate(F.col("p"), y))
    g_id, g_th, times, th, n = fresh(docs, "__id", "__th", "__copies", "__text_hash", "__n")
    rated = measured.select(F.col("doc_id").alias(g_id), F.col("__th").alias(g_th), F.floor(rate + 0.5).cast("int").alias(times))
    gone = rated.where(F.col(times) != 1).distinct()
    joined = docs.withColumn(th, F.xxhash64("text")).join(gone, F.col("doc_id").eqNullSafe(F.col(g_id)) & (F.col(th) == F.col(g_th)), "left")
    copies = F.coalesce(times, F.lit(1))
    repeated = joined.where(copies > 0).withColumn(n, F.explode(F.sequence(F.lit(1), copies)))
    return repeated.select(*columns_of(docs))
