"""Quality classifier: random-indexing word vectors, pooled per document, and a two-layer network with calibrated probabilities.

Tokens are runs of letters, of digits and of other signs; each is hashed to one of BUCKETS words. Beside a
token stand a shape word for capitals and one for a repeat of the token before. Every word has a
sparse ternary index vector; its context vector is the sum of the index vectors of the words at most
two places away, over all documents (one distributed sum; what reaches the driver is BUCKETS x
DIMENSION numbers). A document is the mean of its words' context vectors and of their index vectors. The
network is fitted with numpy on a bounded sample of labelled rows (sample_rows), its temperature on a
seventh of them that it did not see.

Null and empty texts pool to zero and are scored like any other; without labels of both kinds every score is the
share of label 1 (0.5 without labels). Rows are kept one for one; other columns are not read; an empty table gives no rows. A score of just THRESHOLD
is predicted 1. A text longer than a run (2 MB) is a run of its own, and a task then holds its words' numbers and context rows (some 80 bytes a word).
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from bucketnet.llm import words
from bucketnet.llm.common import hash_sample

BUCKETS, DIMENSION, NONZERO, REACH = 4096, 32, 4, 2
SAMPLE_ROWS = 20_000
THRESHOLD = 0.3
LETTER, DIGIT, SIGN = 1, 2, 3
KIND = np.full(256, SIGN, dtype=np.uint8)
KIND[list(range(65, 91)) + list(range(97, 123)) + list(range(128, 256))] = LETTER
KIND[48:58] = DIGIT
KIND[words.SPACE] = 0
UPPER = np.zeros(256, dtype=bool)
UPPER[65:91] = True


def index_vectors() -> np.ndarray:
    """BUCKETS x DIMENSION of -1, 0, 1, with NONZERO entries drawn from the bucket's number."""
    out = np.zeros((BUCKETS, DIMENSION), dtype=np.int8)
    for k in range(NONZERO):
        h = words.mix(np.arange(BUCKETS, dtype=np.uint64) * np.uint64(NONZERO) + np.uint64(k + 1))
        out[np.arange(BUCKETS), (h % np.uint64(DIMENSION)).astype(np.int64)] = np.where(h >> np.uint64(63), 1, -1)
    return out


def tokens(buf: np.ndarray, offsets: np.ndarray, buckets: int = BUCKETS, shapes: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of all tokens (and their shape words) of all texts, in order, and the n + 1 offsets by text."""
    kind = KIND[buf]
    breaks = np.zeros(len(buf), dtype=bool)
    breaks[1:] = kind[1:] != kind[:-1]
    starts, ends, per = words.word_spans(buf, offsets, breaks=breaks)
    h = words.span_hashes(words.LOWER[buf], starts, ends)
    word = (h % np.uint64(buckets)).astype(np.int64)
    if not shapes or len(starts) == 0:
        return word, per
    ups = np.concatenate([[0], np.cumsum(UPPER[buf])])
    capitals = (ups[ends] - ups[starts] > 1) & (2 * (ups[ends] - ups[starts]) > ends - starts)
    repeat = np.zeros(len(h), dtype=bool)
    repeat[1:] = h[1:] == h[:-1]
    repeat[per[:-1][np.diff(per) > 0]] = False
    n = 1 + capitals.astype(np.int64) + repeat
    at = np.cumsum(n) - n
    out = np.empty(int(n.sum()), dtype=np.int64)
    out[at] = word
    out[(at + 1)[capitals]] = buckets - 1
    out[(at + n - 1)[repeat]] = buckets - 2
    return out, np.concatenate([[0], np.cumsum(n)])[per]


def context_sums(word: np.ndarray, per: np.ndarray, index: np.ndarray) -> np.ndarray:
    """BUCKETS x DIMENSION sums of the index vectors near each word."""
    out = np.zeros((BUCKETS, DIMENSION), dtype=np.int64)
    if len(word) == 0:
        return out
    owner = np.repeat(np.arange(len(per) - 1), np.diff(per))
    near = np.zeros((len(word), DIMENSION), dtype=np.int8)
    own = index[word]
    for k in range(1, REACH + 1):
        same = (owner[k:] == owner[:-k])[:, None]
        near[k:] += own[:-k] * same
        near[:-k] += own[k:] * same
    order = np.argsort(word, kind="stable")
    at = np.flatnonzero(np.diff(word[order], prepend=-1))
    out[word[order][at]] = np.add.reduceat(near[order], at, axis=0, dtype=np.int64)
    return out


def corpus_vectors(docs: DataFrame) -> np.ndarray:
    """Context vectors of all words over all of docs, each scaled to length 1."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, index = np.zeros((BUCKETS, DIMENSION), dtype=np.int64), index_vectors()
        for batch in batches:
            for part in words.slices(batch, limit=2 << 20):
                total += context_sums(*tokens(*words.text_bytes(part.column("text"))), index)
        has = np.flatnonzero(total.any(axis=1))
        yield pa.RecordBatch.from_arrays([pa.array(has), *[pa.array(total[has, d]) for d in range(DIMENSION)]], ["word", *[f"v{d}" for d in range(DIMENSION)]])

    names = [f"v{d}" for d in range(DIMENSION)]
    partial = docs.selectExpr("cast(text as string) text").mapInArrow(words.tidy(run), "word long, " + ", ".join(f"{n} long" for n in names))
    rows = partial.groupBy("word").agg(*[F.sum(n).alias(n) for n in names]).collect()  # BUCKETS rows at most
    out = np.zeros((BUCKETS, DIMENSION))
    for r in rows:
        out[r.word] = r[1:]
    norm = np.linalg.norm(out, axis=1, keepdims=True)
    return np.divide(out, norm, out=np.zeros_like(out), where=norm > 0).astype(np.float32)


def pool(buf: np.ndarray, offsets: np.ndarray, table: np.ndarray) -> np.ndarray:
    """The means of table's rows over each text's words, 0 for a text without."""
    word, per = tokens(buf, offsets)
    n = np.diff(per)
    out = np.zeros((len(n), table.shape[1]), dtype=np.float64)
    has = np.flatnonzero(n)
    if len(has) == 0:
        return out
    if len(word) < 256 * len(has):  # short texts: their words' rows
        out[has] = np.add.reduceat(table[word], per[:-1][has], axis=0, dtype=np.float64)
    else:  # long texts: counts of buckets times the table, some texts at a time
        for i in range(0, len(n), 256):
            j = min(i + 256, len(n))
            owner = np.repeat(np.arange(j - i), n[i:j])
            counts = np.bincount(owner * BUCKETS + word[per[i] : per[j]], minlength=(j - i) * BUCKETS).reshape(-1, BUCKETS)
            out[i:j] = counts.astype(np.float32) @ table
    return out / np.maximum(n, 1)[:, None]


class Network:
    """tanh layer, logistic layer, temperature."""

    def __init__(self, hidden: int = 24, seed: int = 7):
        self.hidden, self.seed, self.base, self.w = hidden, seed, 0.5, None

    def _forward(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        a, b, c, d = self.w
        h = np.tanh(x @ a + b)
        return h, h @ c + d

    def fit(self, x: np.ndarray, y: np.ndarray, epochs: int = 60, batch: int = 128, rate: float = 3e-3, decay: float = 1e-4) -> Network:
        self.base = float(y.mean()) if len(y) else 0.5
        if len(y) < 14 or y.min() == y.max():
            return self
        rng = np.random.default_rng(self.seed)
        self.mean, self.scale = x.mean(axis=0), x.std(axis=0) + 1e-6
        x = (x - self.mean) / self.scale
        aside = np.arange(len(y)) % 7 == 0
        held_x, held_y, x, y = x[aside], y[aside], x[~aside], y[~aside]
        self.w = [rng.normal(0, 1 / np.sqrt(x.shape[1]), (x.shape[1], self.hidden)), np.zeros(self.hidden), rng.normal(0, 1 / np.sqrt(self.hidden), self.hidden), np.zeros(())]
        m, v, t = [np.zeros_like(p) for p in self.w], [np.zeros_like(p) for p in self.w], 0
        steps = max(epochs, 1500 * batch // len(y))
        for _ in range(min(steps, 600)):
            order = rng.permutation(len(y))
            for i in range(0, len(y), batch):
                k = order[i : i + batch]
                h, z = self._forward(x[k])
                g = (1 / (1 + np.exp(-z)) - y[k]) / len(k)
                back = np.outer(g, self.w[2]) * (1 - h * h)
                grads = [x[k].T @ back + decay * self.w[0], back.sum(axis=0), h.T @ g + decay * self.w[2], g.sum()]
                t += 1
                for j, gr in enumerate(grads):
                    m[j] = 0.9 * m[j] + 0.1 * gr
                    v[j] = 0.999 * v[j] + 0.001 * gr * gr
                    self.w[j] = self.w[j] - rate * (m[j] / (1 - 0.9**t)) / (np.sqrt(v[j] / (1 - 0.999**t)) + 1e-8)
        z = self._forward(held_x)[1]
        heat = np.exp(np.linspace(0.0, 2.5, 51))  # never sharper than fitted: a few rows set apart perfectly prove no more
        loss = [np.mean(np.logaddexp(0, np.where(held_y > 0, -z, z) / h)) for h in heat]
        self.heat = float(heat[int(np.argmin(loss))])
        return self

    def score(self, x: np.ndarray) -> np.ndarray:
        if self.w is None:
            return np.full(len(x), self.base)
        z = self._forward((x - self.mean) / self.scale)[1] / self.heat
        return 1 / (1 + np.exp(-np.clip(z, -50, 50)))


def held_out(modulus: int, rest: int, col: str = "doc_id") -> Column:
    """Whether crc32 of the id's decimal text leaves rest; false for a null id."""
    return F.coalesce(F.pmod(F.crc32(F.col(col).cast("string").cast("binary")), F.lit(modulus)) == rest, F.lit(False))


def score_quality(docs: DataFrame, labels: DataFrame, modulus: int = 5, rest: int = 0, sample_rows: int = SAMPLE_ROWS) -> DataFrame:
    """doc_id, held_out, score, predicted for every row; labels of held-out ids are not looked at.

    The sample: the sample_rows labelled ids of smallest hash. Of several labels of an id the mean counts, rounded.
    """
    spark = docs.sparkSession
    rows = docs.selectExpr("cast(doc_id as long) doc_id", "cast(text as string) text")
    vectors = corpus_vectors(rows)
    shared = spark.sparkContext.broadcast(np.concatenate([vectors, index_vectors().astype(np.float32)], axis=1))

    marked = labels.where("quality is not null and doc_id is not null").where(~held_out(modulus, rest))
    marked = marked.groupBy(F.col("doc_id").cast("long").alias("l_id")).agg(F.round(F.avg("quality")).cast("int").alias("y"))
    sample = hash_sample(marked, ["l_id"], sample_rows)

    def pooled(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in words.slices(batch, limit=2 << 20):
                x = pool(*words.text_bytes(part.column("text")), shared.value)
                yield pa.RecordBatch.from_arrays([part.column("l_id"), part.column("y"), pa.array(list(x))], ["l_id", "y", "x"])

    # the sample is bounded by sample_rows, so it can go to all executors, and its vectors to the driver
    drawn = rows.join(F.broadcast(sample), F.col("doc_id") == F.col("l_id")).select("l_id", "y", "text").mapInArrow(words.tidy(pooled), "l_id long, y int, x array<double>")
    drawn = sorted((r.l_id, r.y, r.x) for r in drawn.collect())
    width = 2 * DIMENSION
    net = Network().fit(np.array([r[2] for r in drawn]).reshape(-1, width), np.array([r[1] for r in drawn], dtype=float))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in words.slices(batch, limit=2 << 20):
                s = net.score(pool(*words.text_bytes(part.column("text")), shared.value))
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(s)], ["doc_id", "score"])

    scored = rows.mapInArrow(words.tidy(run), "doc_id long, score double")
    return scored.select("doc_id", held_out(modulus, rest).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
