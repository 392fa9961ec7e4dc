"""Language of each word in code-switched text: a linear-chain conditional random field.

A word is a run of letters (ASCII letters and all bytes from 0x80), lower-cased. Its features are the 2-, 3- and
4-grams of its bytes between marks for begin and end, so those with a mark are affixes, and the word
itself (lexicon), all hashed into one table of weights per language. Transitions between languages are
learned with them, by the gradient of the conditional likelihood: expected words and pairs of neighbours, both from the same
forward and backward messages, less the true ones. Training sequences come from a bounded sample of labelled documents: at most WINDOWS windows of
BLOCK words of each, spread over its whole text, and windows spliced from documents of several languages, as code-switching is. Marginals come from
forward-backward over the whole word chain of a text: products of transfer matrices over blocks of
BLOCK words, a scan over blocks, and passes within all blocks at once.

A document's language has the largest mean marginal over its words, which is its score. Null texts and texts without a
letter are `und` with score 0. Of equally likely languages the first by name is taken. With no labelled document every text is `und`;
an empty table gives no rows. A text longer than a run (2 MB) is a run of its own, so a task then holds its features (some 100 bytes a byte of distinct words) and
messages (about 8 numbers a word and language).
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bucketnet.llm import words
from bucketnet.llm.common import hash_sample
from bucketnet.llm.quality_net import held_out

SLOTS = 1 << 15
BLOCK = 32
SAMPLE_ROWS, WINDOWS = 2000, 8
OTHER = np.ones(256, dtype=bool)
OTHER[list(range(65, 91)) + list(range(97, 123)) + list(range(128, 256))] = False
BEGIN, END = 1, 2


def word_features(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Feature slots of all words, grouped by word, and the number of features of each. buf in lower case."""
    size = ends - starts + 2
    upto = np.cumsum(size)
    total = int(upto[-1]) if len(size) else 0
    owner = np.repeat(np.arange(len(size)), size)
    place = np.arange(total) - np.repeat(upto - size, size)
    source = np.clip(np.repeat(starts, size) + place - 1, 0, max(0, len(buf) - 1))
    text = buf[source].astype(np.uint64) if total else np.zeros(0, np.uint64)
    text[place == 0] = BEGIN
    text[place == size[owner] - 1] = END
    found, who = [], []
    h = text.copy()
    for n in (2, 3, 4):
        h = h[: max(0, total - n + 1)] * np.uint64(257) + text[n - 1 :]
        fits = np.flatnonzero(place[: len(h)] + n <= size[owner[: len(h)]])
        found.append(words.mix(h[fits] + np.uint64(n << 40)) % np.uint64(SLOTS))
        who.append(owner[fits])
    found.append(words.span_hashes(buf, starts, ends) % np.uint64(SLOTS))
    who.append(np.arange(len(size)))
    who = np.concatenate(who)
    order = np.argsort(who, kind="stable")
    return np.concatenate(found).astype(np.int64)[order], np.bincount(who, minlength=len(size))


class Chain:
    """Weights (SLOTS x languages), transitions, and the passes over them."""

    def __init__(self, languages: list[str]):
        k = len(languages)
        self.languages, self.weights, self.moves = languages, np.zeros((SLOTS, k)), np.zeros((k, k))

    def emissions(self, slots: np.ndarray, count: np.ndarray) -> np.ndarray:
        if len(count) == 0:
            return np.zeros((0, len(self.languages)))
        return np.add.reduceat(self.weights[slots], np.cumsum(count) - count, axis=0)

    def marginals(self, e: np.ndarray, per: np.ndarray) -> np.ndarray:
        """Marginals of each word; e: emissions of all words, text after text, per: the texts' n + 1 offsets."""
        forward, backward = self.messages(e, per)
        both = forward * backward
        return both / both.sum(axis=1, keepdims=True) if len(e) else both

    def pairs(self, e: np.ndarray, per: np.ndarray, forward: np.ndarray, backward: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Numbers of the words that follow another one of their text, and the joint marginals of the word before and them."""
        after = np.ones(len(e), dtype=bool)
        after[per[:-1][np.diff(per) > 0]] = False
        j = np.flatnonzero(after)
        into = np.exp(e[j] - e[j].max(axis=1, keepdims=True)) * backward[j] if len(j) else e[j]
        joint = forward[j - 1][:, :, None] * np.exp(self.moves - self.moves.max())[None] * into[:, None, :]
        return j, joint / joint.sum(axis=(1, 2), keepdims=True)

    def gradients(self, e: np.ndarray, per: np.ndarray, labels: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Of the negative log likelihood of the labels: by each word's emissions, and by the transitions."""
        k = e.shape[1]
        forward, backward = self.messages(e, per)
        both = forward * backward
        m = both / both.sum(axis=1, keepdims=True)
        j, joint = self.pairs(e, per, forward, backward)
        true = np.bincount(labels[j - 1] * k + labels[j], minlength=k * k).reshape(k, k)
        return m - np.eye(k)[labels], joint.sum(axis=0) - true

    def messages(self, e: np.ndarray, per: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Forward messages of each word, its emission included, and backward ones, without it; each word's up to a factor."""
        k = e.shape[1]
        n = np.diff(per)
        if len(e) == 0:
            return np.zeros((0, k)), np.zeros((0, k))
        power, step = np.exp(e - e.max(axis=1, keepdims=True)), np.exp(self.moves - self.moves.max())
        blocks = -(-n // BLOCK)
        nb = int(blocks.sum())
        first = np.cumsum(blocks) - blocks  # of each text
        text_of = np.repeat(np.arange(len(n)), blocks)
        number = np.arange(nb) - first[text_of]
        begin = per[:-1][text_of] + number * BLOCK
        length = np.minimum(BLOCK, per[1:][text_of] - begin)
        opens = number == 0
        padded = np.ones((nb, BLOCK, k))
        at = np.repeat(begin - np.cumsum(length) + length, length) + np.arange(len(e))
        where = (np.repeat(np.arange(nb), length), np.arange(len(e)) - np.repeat(np.cumsum(length) - length, length))
        padded[where] = power[at]
        identity = np.eye(k)
        product = np.broadcast_to(identity, (nb, k, k)).copy()
        for t in range(BLOCK):  # past a block's end nothing moves
            on = length > t
            nxt = (product[on] @ step) * padded[on, t][:, None, :]
            if t == 0:
                nxt[opens[on]] = identity * padded[on, 0][opens[on]][:, None, :]
            product[on] = nxt / nxt.max(axis=(1, 2), keepdims=True)
        into, out = np.ones((nb, k)), np.ones((nb, k))  # forward before, backward after each block
        for j in range(1, int(blocks.max())):
            b = first[blocks > j] + j
            v = np.einsum("bi,bij->bj", into[b - 1], product[b - 1])
            into[b] = v / v.max(axis=1, keepdims=True)
        for j in range(int(blocks.max()) - 1, 0, -1):
            b = first[blocks > j] + j
            v = np.einsum("bij,bj->bi", product[b], out[b])
            out[b - 1] = v / v.max(axis=1, keepdims=True)
        ahead = np.empty((nb, BLOCK, k))
        v = into
        for t in range(BLOCK):
            u = v @ step
            if t == 0:
                u[opens] = 1.0
            u = u * padded[:, t]
            v = u / u.max(axis=1, keepdims=True)
            ahead[:, t] = v
        behind = np.empty((nb, BLOCK, k))
        v = out
        for t in range(BLOCK - 1, -1, -1):
            last = (length <= t + 1)[:, None]  # at a block's last word and in its padding
            if t < BLOCK - 1:
                u = (v * padded[:, t + 1]) @ step.T
                v = np.where(last, out, u / u.max(axis=1, keepdims=True))
            behind[:, t] = v
        forward, backward = np.empty_like(e), np.empty_like(e)
        forward[at], backward[at] = ahead[where], behind[where]
        return forward, backward

    def fit(self, sequences: list[tuple[np.ndarray, np.ndarray]], features: tuple[np.ndarray, np.ndarray], epochs: int = 2, batch: int = 64, rate: float = 0.1, seed: int = 5) -> Chain:
        """AdaGrad on the conditional likelihood. sequences: (word numbers, labels)."""
        slots, count = features
        begin = np.cumsum(count) - count
        k = len(self.languages)
        rng = np.random.default_rng(seed)
        seen, seen_moves = np.full((SLOTS, k), 1e-3), np.full((k, k), 1e-3)
        for _ in range(epochs):
            order = rng.permutation(len(sequences))
            for i in range(0, len(order), batch):
                part = [sequences[j] for j in order[i : i + batch]]
                ids, labels = np.concatenate([p[0] for p in part]), np.concatenate([p[1] for p in part])
                per = np.concatenate([[0], np.cumsum([len(p[0]) for p in part])])
                size = count[ids]
                own = slots[np.repeat(begin[ids] - np.cumsum(size) + size, size) + np.arange(size.sum())]
                e = self.emissions(own, size)
                by_word, by_move = self.gradients(e, per, labels)
                g = np.repeat(by_word / len(part), size, axis=0)
                touched, back = np.unique(own, return_inverse=True)
                grad = np.stack([np.bincount(back, weights=g[:, c], minlength=len(touched)) for c in range(k)], axis=1)
                seen[touched] += grad**2
                self.weights[touched] -= rate * grad / np.sqrt(seen[touched])
                gm = by_move / len(part)
                seen_moves += gm**2
                self.moves -= rate * gm / np.sqrt(seen_moves)
        return self


def training_sequences(texts: list[bytes], labels: np.ndarray, seed: int = 3) -> tuple[list[tuple[np.ndarray, np.ndarray]], tuple[np.ndarray, np.ndarray]]:
    """texts: windows of documents. Those, windows spliced from several of them, and the distinct words' features."""
    buf = words.LOWER[np.frombuffer(b"".join(texts), dtype=np.uint8)]
    offsets = np.concatenate([[0], np.cumsum([len(t) for t in texts])]).astype(np.int64)
    starts, ends, per = words.word_spans(buf, offsets, space=OTHER)
    codes, first = words.distinct_spans(buf, starts, ends)
    features = word_features(buf, starts[first], ends[first])
    rng = np.random.default_rng(seed)
    out = []
    full = np.flatnonzero(np.diff(per) > 0)
    for d in full:
        a, b = per[d], per[d + 1]
        for s in range(a, b, BLOCK):
            w = codes[s : min(b, s + BLOCK)]
            out.append((w, np.full(len(w), labels[d])))
    for _ in range(-(-len(full) // 4)):
        w, y = [], []
        while sum(map(len, w)) < BLOCK:
            d = full[rng.integers(len(full))]
            a, b = per[d], per[d + 1]
            s = a + rng.integers(b - a)
            got = codes[s : min(b, s + 3 + rng.integers(10))]
            w.append(got)
            y.append(np.full(len(got), labels[d]))
        out.append((np.concatenate(w)[:BLOCK], np.concatenate(y)[:BLOCK]))
    return out, features


def windows_of(buf: np.ndarray, offsets: np.ndarray, count: int, seed: int = 11) -> list[list[bytes]]:
    """At most count windows of BLOCK words of each text: all of a short text, else one at a drawn place in each of count equal stretches."""
    starts, ends, per = words.word_spans(words.LOWER[buf], offsets, space=OTHER)
    raw, out = buf.tobytes(), []
    for i, (a, b) in enumerate(zip(per[:-1].tolist(), per[1:].tolist(), strict=True)):
        if b - a <= count * BLOCK:
            at = np.arange(a, b, BLOCK)
        else:  # drawn by the text's length alone, so any partitioning gives the same
            draw = np.random.default_rng([seed, int(offsets[i + 1] - offsets[i])]).random(count)
            at = a + ((np.arange(count) + draw) * (b - a - BLOCK) / count).astype(np.int64)
        out.append([raw[starts[s] : ends[min(s + BLOCK, b) - 1]] for s in at.tolist()])
    return out


def train(docs: DataFrame, sample_rows: int = SAMPLE_ROWS, windows: int = WINDOWS) -> Chain | None:
    """A chain from windows of the documents with a lang whose ids have the smallest hashes (sample_rows ids, at most twice as many rows); None without any."""
    rows = docs.where("lang is not null and doc_id is not null")
    ids = hash_sample(rows.select("doc_id"), ["doc_id"], sample_rows)  # read without the texts
    drawn = rows.join(F.broadcast(ids), "doc_id", "left_semi").select("doc_id", "lang", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in words.slices(batch, limit=2 << 20):
                found = windows_of(*words.text_bytes(part.column("text")), windows)
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("lang"), pa.array(found, pa.list_(pa.binary()))], ["doc_id", "lang", "windows"])

    cut_out = drawn.mapInArrow(words.tidy(run), "doc_id long, lang string, windows array<binary>")
    found = cut_out.orderBy("doc_id", "lang", F.xxhash64("windows")).limit(2 * sample_rows).collect()
    found = sorted({(r.doc_id, r.lang, tuple(bytes(w) for w in r.windows)) for r in found})
    languages = sorted({lang for _, lang, _ in found})
    if not languages:
        return None
    texts = [(w, lang) for _, lang, all_windows in found for w in all_windows]
    at = {x: i for i, x in enumerate(languages)}
    sequences, features = training_sequences([w for w, _ in texts], np.array([at[lang] for _, lang in texts], dtype=np.int64))
    return Chain(languages).fit(sequences, features) if sequences else Chain(languages)


def word_marginals(chain: Chain, buf: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """starts, ends and marginals of all words of all texts, and the texts' n + 1 offsets of words."""
    low = words.LOWER[buf]
    starts, ends, per = words.word_spans(low, offsets, space=OTHER)
    codes, first = words.distinct_spans(low, starts, ends)
    e = chain.emissions(*word_features(low, starts[first], ends[first]))
    return starts, ends, chain.marginals(e[codes] if len(codes) else e, per), per


def label_words(chain: Chain, text: str) -> list[tuple[str, str, float]]:
    """(word, language, marginal) of each word of one code-switched text."""
    raw = np.frombuffer(text.encode(), dtype=np.uint8)
    starts, ends, m, _ = word_marginals(chain, raw, np.array([0, len(raw)]))
    best = m.argmax(axis=1)
    return [(raw[s:e].tobytes().decode(), chain.languages[b], float(p[b])) for s, e, p, b in zip(starts, ends, m, best, strict=True)]


def predict_language(docs: DataFrame, modulus: int = 3, rest: int = 1, sample_rows: int = SAMPLE_ROWS) -> DataFrame:
    """doc_id, held_out, lang_pred, score for every row; rows held out are not learned from."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), F.col("lang").cast("string").alias("lang"))
    chain = train(rows.where(~held_out(modulus, rest)), sample_rows)
    shared = docs.sparkSession.sparkContext.broadcast(chain)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        chain = shared.value
        for batch in batches:
            for part in words.slices(batch, limit=2 << 20):
                buf, offsets = words.text_bytes(part.column("text"))
                name, score = ["und"] * part.num_rows, np.zeros(part.num_rows)
                if chain is not None:
                    _, _, m, per = word_marginals(chain, buf, offsets)
                    n = np.diff(per)
                    has = np.flatnonzero(n)
                    if len(has):
                        mean = np.add.reduceat(m, per[:-1][has], axis=0) / n[has][:, None]
                        ascii_letter = np.concatenate([[0], np.cumsum(~OTHER[buf] & (buf < 128))])
                        plain = ascii_letter[offsets[1:]] - ascii_letter[offsets[:-1]] > 0
                        for i, best, p in zip(has.tolist(), mean.argmax(axis=1).tolist(), mean.max(axis=1).tolist(), strict=True):
                            if plain[i] or any(c.isalpha() for c in part.column("text")[i].as_py()):
                                name[i], score[i] = chain.languages[best], min(1.0, p)
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(name), pa.array(score)], ["doc_id", "lang_pred", "score"])

    out = rows.select("doc_id", "text").mapInArrow(words.tidy(run), "doc_id long, lang_pred string, score double")
    return out.select("doc_id", held_out(modulus, rest).alias("held_out"), "lang_pred", "score")
