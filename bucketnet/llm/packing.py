"""Order-preserving packing: window cuts by dynamic programming with a monotone queue.

Documents of a partition, in their order, form one stream of token ids, each document's ids
followed by an end id. A cut may stand after a document (free), after a word that ends a sentence
(a small penalty: the document goes on in the next window) or, in a sentence of over STEP tokens, after each
STEP tokens (a larger penalty). Among all sequences of cuts with at most window tokens between
neighbours the one of least padding plus penalties is taken:

    cost(j) = penalty(j) + window - at(j) + min over i with at(j) - window <= at(i) < at(j) of cost(i) + at(i)

and the minimum comes from a queue kept in increasing order of cost(i) + at(i), so each cut is
put in and taken out once. A run of documents is solved at a time; what its last window
holds goes on into the next run, so only a partition's last window is short; it is split into
powers of two, which need no padding. There is no shuffle.

Tokens: the distinct units of a run are tokenised once, between separators, and put back by number; a
task remembers up to MEMORY of them. A unit is a word (words.py) in lower case, cut where an
ASCII letter or digit meets one of PUNCTUATION. That equals tokenising whole texts for a tokenizer
that lower-cases and whose pre-tokens never cross white space or such a place, as with the public
file used. Runs of documents with a special token's "<|" in them are cut at white space alone.
"""

from __future__ import annotations

import zlib
from collections import deque
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from bucketnet.llm import words

STEP = 16
SENTENCE_COST, HARD_COST = 2.0, 8.0
SEPARATOR = "\x01"


ALNUM = np.zeros(256, dtype=bool)
ALNUM[[*range(48, 58), *range(65, 91), *range(97, 123)]] = True
PUNCTUATION = np.zeros(256, dtype=bool)
PUNCTUATION[list(b".,!?;:*#$%&|")] = True
MEMORY = 400_000


@lru_cache(maxsize=2)
def load_tokenizer(file: str):
    """The tokenizer and the id of the separator, a character that is a token of its own."""
    import os

    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(file)
    (separator,) = t.encode(SEPARATOR, add_special_tokens=False).ids
    return t, separator


class UnitMemory:
    """Ids of the units met so far in this task; forgets all of them when it is full."""

    def __init__(self, tokenizer_file: str):
        self.file = tokenizer_file
        self._clear()

    def _clear(self) -> None:
        self.known: dict[bytes, int] = {}
        self.flat, self.of = np.zeros(0, np.uint32), np.zeros(1, np.int64)

    def look_up(self, keys: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """For each of some distinct units its number, and the ids of all numbers end to end with their offsets."""
        if len(self.known) > MEMORY:
            self._clear()
        new = [k for k in keys if k not in self.known]
        if new:
            flat, of = encode_words([k.decode() for k in new], self.file)
            base = len(self.known)
            self.known.update((k, base + n) for n, k in enumerate(new))
            self.flat = np.concatenate([self.flat, flat])
            self.of = np.concatenate([self.of, self.of[-1] + of[1:]])
        known = self.known
        return np.fromiter((known[k] for k in keys), dtype=np.int64, count=len(keys)), self.flat, self.of


@lru_cache(maxsize=2)
def memory(tokenizer_file: str) -> UnitMemory:
    return UnitMemory(tokenizer_file)


def units(buf: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """The bytes to tokenise, and the units' starts, ends and offsets by text."""
    if b"<|" in buf.tobytes():
        return buf, *words.word_spans(buf, offsets)
    low = words.LOWER[buf]
    breaks = np.zeros(len(low), dtype=bool)
    breaks[1:] = ALNUM[low[:-1]] & PUNCTUATION[low[1:]]
    return low, *words.word_spans(low, offsets, breaks=breaks)


def encode_words(texts: list[str], tokenizer_file: str) -> tuple[np.ndarray, np.ndarray]:
    """Ids of some white-space-free words, end to end, and the n + 1 offsets of each word's ids."""
    t, separator = load_tokenizer(tokenizer_file)
    odd = [i for i, w in enumerate(texts) if SEPARATOR in w]
    plain = [w for w in texts if SEPARATOR not in w] if odd else texts
    ids, size = [], np.zeros(len(texts), dtype=np.int64)
    lengths = []
    for i in range(0, len(plain), 20_000):
        part = plain[i : i + 20_000]
        got = np.array(t.encode_batch_fast([f" {SEPARATOR} ".join([*part, ""])], add_special_tokens=False)[0].ids, dtype=np.uint32)
        stop = got == separator
        lengths.append(np.diff(np.flatnonzero(stop), prepend=-1) - 1)
        ids.append(got[~stop])
    keep = np.ones(len(texts), dtype=bool)
    keep[odd] = False
    size[keep] = np.concatenate(lengths) if lengths else 0
    flat = np.concatenate(ids) if ids else np.zeros(0, np.uint32)
    if odd:
        extra = {i: np.array(t.encode(texts[i], add_special_tokens=False).ids, dtype=np.uint32) for i in odd}
        at = np.concatenate([[0], np.cumsum(size)])
        flat = np.concatenate([extra[i] if i in extra else flat[at[i] : at[i + 1]] for i in range(len(texts))] or [flat])
        for i, x in extra.items():
            size[i] = len(x)
    return flat, np.concatenate([[0], np.cumsum(size)])


def choose_cuts(at: np.ndarray, penalty: np.ndarray, window: int) -> tuple[list[int], float]:
    """Numbers of the chosen cuts, the last included, and their cost. at: increasing positions above 0, none over window from the one before; the stream begins at 0."""
    place = [0, *at.tolist()]
    fee = [0.0, *penalty.tolist()]
    cost, back = [0.0] * len(place), [0] * len(place)
    queue: deque[tuple[float, int]] = deque([(0.0, 0)])
    for j in range(1, len(place)):
        p = place[j]
        while place[queue[0][1]] < p - window:
            queue.popleft()
        least, i = queue[0]
        back[j] = i
        cost[j] = fee[j] + window - p + least
        key = cost[j] + p
        while queue and queue[-1][0] >= key:
            queue.pop()
        queue.append((key, j))
    out, j = [], len(place) - 1
    while j:
        out.append(j - 1)
        j = back[j]
    return out[::-1], cost[-1]


class Packer:
    """Packs one stream; feed() gives pieces whose sequences are settled, finish() the rest."""

    def __init__(self, tokenizer_file: str, window: int, end_id: int, first_sequence: int):
        self.file, self.window, self.end_id, self.sequence = tokenizer_file, window, end_id, first_sequence
        self.rest: list[tuple] = []  # (doc_id, start, ids, doc_tokens) not yet in a sequence

    def feed(self, ids: list, column: pa.Array) -> list[tuple]:
        buf, starts, ends, per = units(*words.text_bytes(column))
        codes, first = words.distinct_spans(buf, starts, ends)
        raw = buf.tobytes()
        number, flat, of = memory(self.file).look_up([raw[a:b] for a, b in zip(starts[first].tolist(), ends[first].tolist(), strict=True)])
        stops = np.isin(buf[ends[first] - 1], np.frombuffer(b".!?", dtype=np.uint8)) if len(first) else np.zeros(0, bool)
        unit = number[codes]
        size = np.diff(of)[unit]
        # the stream: the rest of the run before, then each text's words and its end id
        owner = np.repeat(np.arange(len(ids)), np.diff(per))
        lead = sum(len(x[2]) for x in self.rest)
        upto = np.cumsum(size)
        word_end = lead + upto + owner
        text_tokens = words.sum_by_text(size, per)
        text_end = lead + np.cumsum(text_tokens + 1)
        total = int(text_end[-1]) if len(ids) else lead
        stream = np.full(total, self.end_id, dtype=np.uint32)
        if self.rest:
            stream[:lead] = np.concatenate([x[2] for x in self.rest])
        if len(codes):
            n = int(upto[-1])
            source = np.repeat(of[unit] - (upto - size), size) + np.arange(n)
            stream[np.repeat(owner + lead, size) + np.arange(n)] = flat[source]
        bounds = [(d, s, n) for d, s, _, n in self.rest]
        piece_end = [*np.cumsum([len(x[2]) for x in self.rest]).tolist(), *text_end.tolist()]
        bounds += [(d, 0, int(n) + 1) for d, n in zip(ids, text_tokens.tolist(), strict=True)]
        sentence = np.unique(word_end[stops[codes]]) if len(codes) else np.zeros(0, np.int64)
        return self._settle(stream, np.array(piece_end, dtype=np.int64), bounds, sentence)

    def _settle(self, stream, piece_end, bounds, sentence) -> list[tuple]:
        soft = np.setdiff1d(sentence, piece_end)
        at = np.concatenate([piece_end, soft])
        fee = np.concatenate([np.zeros(len(piece_end)), np.full(len(soft), SENTENCE_COST)])
        order = np.argsort(at)
        at, fee = at[order], fee[order]
        gap = np.diff(at, prepend=0)
        many = np.maximum(0, (gap - 1) // STEP)  # hard cuts inside long sentences
        if many.any():
            base = np.repeat(at - gap, many)
            k = np.arange(many.sum()) - np.repeat(np.cumsum(many) - many, many) + 1
            at, fee = np.concatenate([at, base + k * STEP]), np.concatenate([fee, np.full(len(base), HARD_COST)])
            order = np.argsort(at)
            at, fee = at[order], fee[order]
        if len(at) == 0:
            return []
        chosen, _ = choose_cuts(at, fee, self.window)
        cuts = at[chosen]
        last = int(cuts[-2]) if len(cuts) > 1 else 0
        out = []
        rest = []
        i, here = 0, 0
        targets = [*cuts[:-1].tolist(), len(stream)]
        begin = np.concatenate([[0], piece_end[:-1]])
        for w, stop in enumerate(targets):
            offset, settled = 0, w < len(targets) - 1
            while here < stop:
                take = min(stop, int(piece_end[i])) - here
                doc, start, n = bounds[i]
                at_doc = start + here - int(begin[i])
                ids = stream[here : here + take]
                if settled:
                    out.append((doc, at_doc, take, zlib.crc32(ids.tobytes()), n, self.sequence, offset))
                else:
                    rest.append((doc, at_doc, ids.copy(), n))
                offset += take
                here += take
                if here == int(piece_end[i]):
                    i += 1
            self.sequence += settled
        assert here == len(stream) and last <= here
        self.rest = rest
        return out

    def finish(self) -> list[tuple]:
        """The last window, in powers of two."""
        out, left, room, offset = [], sum(len(x[2]) for x in self.rest), 0, 0
        for doc, start, ids, n in self.rest:
            while len(ids):
                if room == 0:
                    room = min(self.window, 1 << (left.bit_length() - 1))
                    self.sequence += bool(out)
                    offset = 0
                k = min(room, len(ids))
                out.append((doc, start, k, zlib.crc32(ids[:k].tobytes()), n, self.sequence, offset))
                ids, start, room, left, offset = ids[k:], start + k, room - k, left - k, offset + k
        self.rest = []
        return out


def pack_documents(docs: DataFrame, tokenizer_file: str, window: int = 2048, end_id: int = 1) -> DataFrame:
    """doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset: one row per piece of every row of docs.

    Null and empty texts have the end id alone. Repeated rows are packed each. Of equally cheap cuts the one whose
    last window is shortest is taken. A partition's
    sequences are numbered from its number * 2**40. window must be over STEP. An empty table gives no rows; other columns are
    not read. A text longer than a run (4 MB) is a run of its own, so a task then holds that text, its ids and its cuts.
    """
    names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        packer = Packer(tokenizer_file, window, end_id, TaskContext.get().partitionId() << 40)

        def table(rows: list[tuple]) -> pa.RecordBatch:
            cols = list(zip(*rows, strict=True)) or [()] * len(names)
            return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], names)

        for batch in batches:
            for part in words.slices(batch, limit=4 << 20):
                yield table(packer.feed(part.column("doc_id").to_pylist(), part.column("text")))
        yield table(packer.finish())
        memory.cache_clear()

    rows = docs.selectExpr("cast(doc_id as long) doc_id", "cast(text as string) text")
    return rows.mapInArrow(words.tidy(run), ", ".join(f"{n} long" for n in names))
