"""Order-independent document fingerprints: wide vectors of paragraphs, summed modulo powers of two.

A paragraph is a line. Its vector has 32 lanes modulo 2**16 from a 512-bit digest of its bytes,
which tell multisets of paragraphs apart, and 256 lanes modulo 2**32 of signed counts of its
word pairs (of its word, if it has one), from which likeness can be read. A document's
fingerprint is the sum over its paragraphs, so the order of paragraphs does not matter and a
paragraph can be put in or taken out by adding or subtracting its vector (add, remove). Counts are read back
signed, so likeness is right up to 2**31 equal pairs in a text, more than a Spark string holds.

Null and empty texts have one empty paragraph. Equal texts have equal fingerprints; likeness is 1 for equal fingerprints and
0 where one of two different ones has no word. An empty table gives no rows. A text longer than a run (2 MB) is a run of its own: a
task then holds it, its edited form and its successor.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from bucketnet.llm import words

DIGEST, LANES, LANE_BITS = 32, 256, 32
PART_ROWS = 200_000  # of a task at most, but for rows of equal id and text
LINE_END = np.zeros(256, dtype=bool)
LINE_END[0x0A] = True


class Sketch:
    """Fingerprints of some texts: digest lanes (n, 32) and likeness lanes (n, 256), modulo their powers."""

    def __init__(self, digest: np.ndarray, pairs: np.ndarray):
        self.digest, self.pairs = digest.astype(np.uint16), pairs.astype(np.int64) & ((1 << LANE_BITS) - 1)

    def add(self, other: Sketch) -> Sketch:
        return Sketch(self.digest + other.digest, self.pairs + other.pairs)

    def remove(self, other: Sketch) -> Sketch:
        return Sketch(self.digest - other.digest, self.pairs - other.pairs)

    def take(self, i) -> Sketch:
        return Sketch(self.digest[i], self.pairs[i])

    def text(self) -> list[str]:
        """Hexadecimal, 4 digits a digest lane and then 8 a likeness lane."""
        head, tail = (x.astype(kind).view(np.uint8).reshape(len(x), -1) for x, kind in ((self.digest, ">u2"), (self.pairs, ">u4")))
        return [row.tobytes().hex() for row in np.concatenate([head, tail], axis=1)]

    def likeness(self, other: Sketch) -> np.ndarray:
        """Cosine of the likeness lanes, 0 at least; 1 where the fingerprints are equal."""
        half = 1 << (LANE_BITS - 1)
        a, b = (((x.pairs ^ half) - half).astype(np.float64) for x in (self, other))  # signed again
        norm = np.sqrt((a * a).sum(axis=1)) * np.sqrt((b * b).sum(axis=1))
        cosine = np.divide((a * b).sum(axis=1), norm, out=np.zeros(len(a)), where=norm > 0)
        same = (self.digest == other.digest).all(axis=1) & (self.pairs == other.pairs).all(axis=1)
        return np.where(same, 1.0, np.clip(cosine, 0.0, 1.0))


def sketch(texts: list[bytes]) -> Sketch:
    """The fingerprints of UTF-8 texts."""
    n = len(texts)
    digest = np.zeros((n, DIGEST), dtype=np.uint16)
    for i, t in enumerate(texts):
        lines = b"".join(hashlib.blake2b(line, digest_size=2 * DIGEST).digest() for line in t.split(b"\n"))
        digest[i] = np.frombuffer(lines, dtype="<u2").reshape(-1, DIGEST).sum(axis=0, dtype=np.uint64).astype(np.uint16)
    buf = np.frombuffer(b"".join(texts), dtype=np.uint8)
    offsets = np.concatenate([[0], np.cumsum([len(t) for t in texts])]).astype(np.int64)
    starts, ends, per = words.word_spans(buf, offsets)
    if len(starts) == 0:
        return Sketch(digest, np.zeros((n, LANES), dtype=np.int64))
    h = words.span_hashes(buf, starts, ends)
    owner = np.repeat(np.arange(n), np.diff(per))
    line = np.cumsum(LINE_END[buf])[starts] + owner  # grows from a line to the next and from a text to the next
    line = np.stack([line, owner])
    goes_on = (line[:, 1:] == line[:, :-1]).all(axis=0)
    alone = ~(np.concatenate([goes_on, [False]]) | np.concatenate([[False], goes_on]))
    i = np.flatnonzero(goes_on)
    feature = words.mix(np.concatenate([h[i] * np.uint64(3) + h[i + 1], h[alone]]))
    own = np.concatenate([owner[i], owner[alone]])
    lane = own * LANES + (feature % np.uint64(LANES)).astype(np.int64)
    sign = np.where(feature >> np.uint64(63), 1.0, -1.0)
    pairs = np.bincount(lane, weights=sign, minlength=n * LANES).astype(np.int64).reshape(n, LANES)
    return Sketch(digest, pairs)


def edited(text: str, following: str) -> str:
    """text with its last third replaced by as much of the start of the following text."""
    k = len(text) // 3
    return text[: len(text) - k] + following[:k]


def layout(bounds: list[float]) -> tuple[list[float], list[int], int]:
    """Distinct bounds from the largest down, for each how many parts its own id gets (0: none of its own), and the number of parts.

    bounds: quantiles of the ids; one that comes up several times is an id with so many parts' worth of rows.
    """
    distinct = sorted(set(bounds), reverse=True)
    own = [bounds.count(c) if bounds.count(c) > 1 else 0 for c in distinct] if len(distinct) < len(bounds) else [0] * len(distinct)
    return distinct, own, len(distinct) + sum(own) + 2


def part_of(distinct: list[float], own: list[int]) -> Column:
    """A row's part by doc_id and th: ids from the largest down, nulls last; an id with parts of its own is dealt by ranges of th.

    Bounds are looked up in two steps of about the root of their number.
    """
    x = F.col("doc_id").cast("double")
    start, places = 1, []  # of each bound: the part of ids next to it from above, plus 1
    for n in own:
        places.append(start)
        start += n + 1
    last = start
    width = max(1, int(len(distinct) ** 0.5))
    rows = [[(c, p, n) for c, p, n in zip(distinct[i : i + width], places[i : i + width], own[i : i + width], strict=True)] for i in range(0, len(distinct), width)]
    made = F.array(*[F.array(*[F.struct(F.lit(c).alias("c"), F.lit(p).alias("p"), F.lit(n).alias("n")) for c, p, n in row]) for row in rows])
    group = F.get(made, F.size(F.filter(F.array(*[F.lit(row[0][0]) for row in rows]), lambda c: c >= x)) - 1)
    bound = F.get(group, F.size(F.filter(group, lambda b: b["c"] >= x)) - 1)  # the smallest bound that is not below the id
    share = F.least(F.floor((F.col("th").cast("double") / 2.0**64 + 0.5) * bound["n"]), bound["n"] - 1).cast("int")
    inside = F.when((bound["c"] == x) & (bound["n"] > 0), bound["p"] + share).otherwise(bound["p"] + bound["n"])
    return F.when(F.col("doc_id").isNull(), F.lit(last)).otherwise(F.coalesce(inside, F.lit(0)))


def in_id_order(docs: DataFrame) -> tuple[DataFrame, int]:
    """docs with their place: part (ranges of descending id, then of the text's hash th) and halo, true for a copy of the row that a part's last row needs next; and the number of parts.

    Ranges come from quantiles of the ids alone; the halo has a row a part.
    """
    rows = docs.withColumn("th", F.xxhash64("text"))
    wanted = max(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-docs.count() // PART_ROWS))
    ids = docs.select(F.col("doc_id").cast("double").alias("x")).where("x is not null")
    bounds = ids.approxQuantile("x", [i / wanted for i in range(1, wanted)], 0.2 / wanted) if wanted > 1 else []
    distinct, own, parts = layout([float(x) for x in bounds])
    part = part_of(distinct, own) if distinct else F.when(F.col("doc_id").isNull(), 1).otherwise(0)
    rows = rows.withColumn("part", part)
    tops = rows.groupBy("part").agg(F.max(F.struct("doc_id", F.bitwise_not("th").alias("down"), "text")).alias("top"))
    tops = tops.select("part", "top.doc_id", F.bitwise_not("top.down").alias("th"), F.col("top.text").alias("text"))
    # the part that comes before each part, around the end: as many rows as parts
    w = Window.orderBy("part")
    order = tops.select("part", F.lag("part").over(w).alias("to"), F.max("part").over(Window.partitionBy(F.lit(1))).alias("end"))
    halo = tops.join(order.select(F.col("part").alias("p"), F.coalesce("to", "end").alias("to")), F.col("part") == F.col("p"))
    halo = halo.select("doc_id", "text", "th", F.col("to").alias("part"), F.lit(True).alias("halo"))
    return rows.select("doc_id", "text", "th", "part", F.lit(False).alias("halo")).unionByName(halo), parts


def fingerprint_documents(docs: DataFrame) -> DataFrame:
    """doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next of every row.

    The next document is the next row by descending doc_id (rows of one id by the hash of their text, null
    ids last, nulls count as empty text); after the last comes the first. One shuffle by ranges of
    ids, a part a task; a part is read as a sorted stream, so a task holds a batch and a row.
    """
    texts = docs.selectExpr("cast(doc_id as long) doc_id", "coalesce(cast(text as string), '') text")
    rows, parts = in_id_order(texts)
    ordered = rows.repartitionById(parts, F.col("part")).sortWithinPartitions("part", "halo", F.desc_nulls_last("doc_id"), "th", F.desc("text"))

    def emit(ids: list, texts: list[str], following: list[str]) -> pa.RecordBatch:
        new = [edited(a, b) for a, b in zip(texts, following, strict=True)]
        raw, raw_new = [t.encode() for t in texts], [t.encode() for t in new]
        # texts[i + 1] is following[i] nearly always; what is not sketched yet is sketched here
        own, changed = sketch(raw), sketch(raw_new)
        again = [i for i in range(len(texts)) if i + 1 >= len(texts) or following[i] is not texts[i + 1]]
        rest = sketch([following[i].encode() for i in again])
        to = np.minimum(np.arange(len(texts)) + 1, len(texts) - 1)
        digest, pairs = own.digest[to], own.pairs[to]
        digest[again], pairs[again] = rest.digest, rest.pairs
        after = Sketch(digest, pairs)
        return pa.RecordBatch.from_arrays(
            [pa.array(ids, pa.int64()), pa.array([len(t) for t in texts], pa.int64()), pa.array([hashlib.sha256(t).hexdigest() for t in raw_new]),
             pa.array(own.text()), pa.array(changed.text()), pa.array(own.likeness(changed)), pa.array(own.likeness(after))],
            ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: tuple | None = None  # the row whose next one has not come yet
        for batch in batches:
            for piece in words.slices(batch, limit=2 << 20):
                ids, texts, following = [], [], []
                cols = (piece.column(c).to_pylist() for c in ("doc_id", "text", "part", "halo"))
                for row in zip(*cols, strict=True):
                    if held and not held[3]:
                        ids.append(held[0])
                        texts.append(held[1])
                        following.append(row[1])
                    held = row
                if ids:
                    yield emit(ids, texts, following)

    return ordered.mapInArrow(words.tidy(run), "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double")
