"""Token counts under a unigram vocabulary, by dynamic programming over a trie of distinct words.

A pre-token is a word (words.py) with U+2581 before it. The distinct pre-tokens of a run of
documents form a byte trie; the best forward score of each trie node is computed once, however
many words share that prefix, and the count at a word's terminal node goes to all its occurrences.
The trie is walked level by level with numpy: the words are sorted, and a node at depth d is a run
of neighbours that agree in their first d bytes. Nothing is shuffled, and memory depends on the
run of documents (4 MB of text, or one longer text) alone.

A pre-token of over WIDE bytes, as in scripts without spaces, is first cut wherever no piece of the vocabulary reaches over:
every segmentation breaks there, so its parts go into the trie like words and their counts add up. Only
a part that is still longer than WIDE is counted by itself.

The vocabulary comes from a public sentencepiece file. Its pieces have ranks, not log
probabilities, so a piece of rank r scores -ln(r + 2.7) - ln(H), the Zipf-Mandelbrot law with its
norm H, in units of 2**-UNIT so that sums are exact in any order; each byte can stand for itself (byte fallback) at a score below all pieces. Of equal scores
the segmentation whose last piece is shortest is taken, at each node.

Null and empty texts have no words and no tokens; rows are kept one for one, ties and repeated
rows included; an empty table gives no rows; columns other than doc_id and text are not read.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from bucketnet.llm import words

MARK = "▁".encode()
WIDE = 48  # bytes of a pre-token that goes into the trie whole
UNIT = 32
BLOCK = 1 << 18
_SLOTS = 20
_STEP = np.uint64(0x9E3779B97F4A7C15)
LEAST = -(1 << 62)


class Vocabulary:
    """Pieces as bytes with their scores (whole numbers), and hash tables of them and of their ends for numpy.

    A polynomial hash modulo 2**64 tells strings of at most the longest piece's bytes apart; texts made to meet under it
    are a thousand bytes long.
    """

    def __init__(self, pieces: dict[bytes, int], byte_score: int):
        self.pieces, self.byte_score = pieces, byte_score
        self.longest = max(map(len, pieces), default=1)
        hashed, ends = [], set()
        for piece, score in pieces.items():
            h, grown = 0, 1
            for c in reversed(piece):
                grown = grown * int(_STEP) % 2**64
                h = (h + (c + 1) * grown) % 2**64
                ends.add(h)
            hashed.append((h, score))
        hashed.sort()
        self.hashes = np.array([h for h, _ in hashed], dtype=np.uint64)
        self.scores = np.array([s for _, s in hashed], dtype=np.int64)
        self.slot, self.end_slot = np.zeros(1 << _SLOTS, dtype=bool), np.zeros(4 << _SLOTS, dtype=bool)
        self.slot[(self.hashes >> np.uint64(64 - _SLOTS)).astype(np.int64)] = True
        self.end_slot[(np.array(sorted(ends), dtype=np.uint64) >> np.uint64(62 - _SLOTS)).astype(np.int64)] = True

    def find(self, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Which of the hashes are pieces, and their scores."""
        maybe = np.flatnonzero(self.slot[(h >> np.uint64(64 - _SLOTS)).astype(np.int64)])
        at = np.minimum(np.searchsorted(self.hashes, h[maybe]), len(self.hashes) - 1)
        hit = self.hashes[at] == h[maybe]
        return maybe[hit], self.scores[at[hit]]

    def ending(self, buf: np.ndarray, begin: np.ndarray, lo: int, hi: int) -> Iterator[tuple[np.ndarray, int, np.ndarray]]:
        """By length: where pieces end in (lo, hi], the length, and the scores. begin: of each byte, where its pre-token begins."""
        ends, h, grown = np.arange(lo + 1, hi + 1), np.zeros(hi - lo, dtype=np.uint64), 1
        first = begin[lo:hi]
        for length in range(1, self.longest + 1):
            grown = grown * int(_STEP) % 2**64
            go = ends - length >= first
            ends, first = ends[go], first[go]
            h = h[go] + (buf[ends - length].astype(np.uint64) + np.uint64(1)) * np.uint64(grown)
            go = self.end_slot[(h >> np.uint64(62 - _SLOTS)).astype(np.int64)]  # no piece ends in these bytes
            ends, first, h = ends[go], first[go], h[go]
            if len(ends) == 0:
                return
            hit, gain = self.find(h)
            if len(hit):
                yield ends[hit], length, gain


@lru_cache(maxsize=4)
def load_vocabulary(model_file: str) -> Vocabulary:
    """The ordinary pieces of a sentencepiece file, scored by rank."""
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=model_file)
    plain = [i for i in range(sp.vocab_size()) if not (sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i) or sp.is_unused(i))]
    plain.sort(key=lambda i: -sp.get_score(i))
    norm = math.log(sum(1 / (r + 2.7) for r in range(len(plain))) or 1)
    pieces = {sp.id_to_piece(i).encode(): round((-math.log(r + 2.7) - norm) * 2**UNIT) for r, i in enumerate(plain)}
    return Vocabulary(pieces, min(pieces.values()) - (10 << UNIT))


def count_alone(word: bytes, v: Vocabulary) -> int:
    """Tokens of one part that no place cuts, by the plain recurrence over the pieces found in it; holds as many scores as the longest piece has bytes."""
    buf, begin = np.frombuffer(word, dtype=np.uint8), np.zeros(len(word), dtype=np.int64)
    ring = v.longest + 1
    best, count = [0] * ring, [0] * ring
    for lo in range(0, len(word), BLOCK):
        hi = min(len(word), lo + BLOCK)
        found = [(e, np.full(len(e), n), g) for e, n, g in v.ending(buf, begin, lo, hi)]
        ends, lengths, gains = (np.concatenate(x) if found else np.zeros(0, np.int64) for x in zip(*found, strict=True)) if found else (np.zeros(0, np.int64),) * 3
        order = np.lexsort((lengths, ends))
        rows = iter(zip(ends[order].tolist(), lengths[order].tolist(), gains[order].tolist(), strict=True))
        row = next(rows, None)
        for d in range(lo + 1, hi + 1):
            back = (d - 1) % ring
            top, n = best[back] + v.byte_score, count[back] + 1
            while row and row[0] == d:
                back = (d - row[1]) % ring
                total = best[back] + row[2]
                if total > top or row[1] == 1:
                    top, n = total, count[back] + 1
                row = next(rows, None)
            best[d % ring], count[d % ring] = top, n
    return count[len(word) % ring]


def parts_of(buf: np.ndarray, offsets: np.ndarray, v: Vocabulary) -> np.ndarray:
    """The n + 1 offsets of the parts of long pre-tokens, which lie end to end: no piece reaches over one of them."""
    begin = np.repeat(offsets[:-1], np.diff(offsets))
    over = np.zeros(len(buf) + 2, dtype=np.int32)
    for lo in range(0, len(buf), BLOCK):
        for ends, length, _ in v.ending(buf, begin, lo, min(len(buf), lo + BLOCK)):
            if length > 1:
                over[ends - length + 1] += 1  # of one length no two begin or end together
                over[ends] -= 1
    free = np.cumsum(over[:-1]) == 0
    free[offsets] = True
    return np.flatnonzero(free)


def count_trie(rows: np.ndarray, lengths: np.ndarray, v: Vocabulary) -> np.ndarray:
    """Tokens of each pre-token. rows: sorted distinct zero-padded bytes, one row a word."""
    n, width = rows.shape
    out = np.zeros(n, dtype=np.int64)
    if n == 0:
        return out
    same = rows[1:] == rows[:-1]
    shared = np.where(same.all(axis=1), width, same.argmin(axis=1))
    shared = np.concatenate([[-1], np.minimum(shared, np.minimum(lengths[1:], lengths[:-1]))])
    # of each depth: the node of each row, and the nodes' best scores and counts
    node = [np.zeros(n, dtype=np.int32)]
    best, count = [np.zeros(1, dtype=np.int64)], [np.zeros(1, dtype=np.int32)]
    live = np.arange(n)
    for d in range(1, width + 1):
        live = live[lengths[live] >= d]
        if len(live) == 0:
            break
        # a run of rows that share d bytes has every row alive, so a node starts where less is shared
        head = shared[live] < d
        reps = live[head]
        own = np.zeros(n, dtype=np.int32)
        own[live] = np.cumsum(head) - 1
        score = np.full(len(reps), LEAST)
        tokens = np.zeros(len(reps), dtype=np.int32)
        h = np.zeros(len(reps), dtype=np.uint64)
        grown = int(_STEP)
        for length in range(1, min(v.longest, d) + 1):
            h = h + (rows[reps, d - length].astype(np.uint64) + np.uint64(1)) * np.uint64(grown)
            grown = grown * int(_STEP) % 2**64
            back = d - length
            if length == 1:
                up = node[back][reps]
                score, tokens = best[back][up] + v.byte_score, count[back][up] + 1
            hit, gain = v.find(h)
            if len(hit):
                up = node[back][reps[hit]]
                total = best[back][up] + gain
                better = total > score[hit] if length > 1 else np.ones(len(hit), dtype=bool)
                to = hit[better]
                score[to], tokens[to] = total[better], count[back][up[better]] + 1
        node.append(own)
        best.append(score)
        count.append(tokens)
        if d > v.longest:  # no piece reaches back so far
            node[d - v.longest - 1] = best[d - v.longest - 1] = count[d - v.longest - 1] = None
        ends = live[lengths[live] == d]
        out[ends] = tokens[own[ends]]
    return out


def count_parts(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray, v: Vocabulary, lead: bytes = MARK) -> np.ndarray:
    """Tokens of each of some distinct spans with lead before it, of at most WIDE bytes together, through one trie."""
    size = ends - starts
    total = size + len(lead)
    rows = np.zeros((len(starts), WIDE), dtype=np.uint8)
    rows[:, : len(lead)] = np.frombuffer(lead, dtype=np.uint8)
    for k in range(int(size.max()) if len(size) else 0):
        has = np.flatnonzero(size > k)
        rows[has, len(lead) + k] = buf[starts[has] + k]
    # sorted by bytes and then by length: a byte can be 0, as the padding is
    order = np.lexsort((total, rows.view(f"S{WIDE}").ravel()))
    out = np.zeros(len(starts), dtype=np.int64)
    out[order] = count_trie(rows[order], total[order], v)
    return out


def count_long(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray, v: Vocabulary) -> np.ndarray:
    """Tokens of each long pre-token, cut into parts."""
    if len(starts) == 0:
        return np.zeros(0, dtype=np.int64)
    texts = [MARK + buf[a:b].tobytes() for a, b in zip(starts, ends, strict=True)]
    flat = np.frombuffer(b"".join(texts), dtype=np.uint8)
    offsets = np.concatenate([[0], np.cumsum([len(t) for t in texts])])
    bounds = parts_of(flat, offsets, v)
    a, b = bounds[:-1], bounds[1:]
    codes, first = words.distinct_spans(flat, a, b)
    a, b = a[first], b[first]
    tokens = np.zeros(len(first), dtype=np.int64)
    short = np.flatnonzero(b - a <= WIDE)
    tokens[short] = count_parts(flat, a[short], b[short], v, b"")
    for i in np.flatnonzero(b - a > WIDE):
        tokens[i] = count_alone(flat[a[i] : b[i]].tobytes(), v)
    total = np.concatenate([[0], np.cumsum(tokens[codes])])
    return np.diff(total[np.searchsorted(bounds, offsets)])


def word_token_counts(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray, v: Vocabulary) -> np.ndarray:
    """Tokens of each word of a buffer; the trie holds the distinct ones."""
    codes, first = words.distinct_spans(buf, starts, ends)
    s, e = starts[first], ends[first]
    out = np.zeros(len(first), dtype=np.int64)
    fits = e - s + len(MARK) <= WIDE
    out[fits] = count_parts(buf, s[fits], e[fits], v)
    out[~fits] = count_long(buf, s[~fits], e[~fits], v)
    return out[codes]


def count_tokens(docs: DataFrame, model_file: str) -> DataFrame:
    """doc_id, n_words, n_tokens (both long) of every row of docs. A text longer than a run (4 MB) is a run of its own."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        v = load_vocabulary(model_file)
        for batch in batches:
            for part in words.slices(batch):
                buf, offsets = words.text_bytes(part.column("text"))
                starts, ends, per = words.word_spans(buf, offsets)
                tokens = words.sum_by_text(word_token_counts(buf, starts, ends, v), per)
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(np.diff(per)), pa.array(tokens)], ["doc_id", "n_words", "n_tokens"])

    rows = docs.selectExpr("cast(doc_id as long) doc_id", "cast(text as string) text")
    return rows.mapInArrow(words.tidy(run), "doc_id long, n_words long, n_tokens long")
