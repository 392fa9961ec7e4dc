"""SimHash near-duplicates: 64-bit fingerprints, and a self-join of binary tries under a Hamming budget.

Fingerprint: bit b is 1 if it is set in over half of the XXH64 hashes (seed 42) of a text's word
shingles, repeats included.

Join: distinct fingerprints are dealt into tables. With a budget of e bits and e + k blocks of
bits, two linked fingerprints agree in k blocks at least, so each choice of k blocks is a
table keyed by those blocks' bits, and no link is lost; k grows with the number of fingerprints so that a
key stays small. In a key, a binary trie over the other bits is joined with itself: node
pairs go down together, the bits in which they differ add up, and a pair goes no further once
they pass the budget. All keys of a run of rows go down at once, level by level, as numpy arrays. A key with
over CHUNK fingerprints is cut into chunks, and each pair of chunks is joined on its own, so a task
holds two chunks whatever the key holds. Links become a spanning forest where they are found;
what leaves a task is a link per fingerprint at most.

Components: alternating large-star and small-star rounds over the links, written to the checkpoint
folder each round, or one task where the links are few; nothing but counts reaches the driver.

group_near stops at the fingerprints: a link is a budget of bits. group_similar confirms: it takes two
fingerprints, lets the tries of the same tables go further than their keys promise (reach) and
takes a pair as a candidate if all 128 bits differ in at most SPREAD places; a link is a candidate pair whose shingle sets have a
similarity of at least 0.8, counted exactly. At first each row names, per table, the nearest of its candidates before and after it, in an order
by hash. Candidates are counted in order of nearness, and those inside one component by then are passed over, so a large group of near copies costs about
a comparison a member, not one a pair. A second walk through the same tables then gives all other candidate pairs whose rows are still in two components and whose
sets may be alike enough, and those are counted too. They may if that is so at the most shingles that two sets can share, given their sizes and their
512-bit parities: a place in which the parities differ is a shingle at least that only one of the sets has. This never leaves out a link.

A text is read whole; one longer than a run (2 MB) is a run of its own, and a task then holds its shingle hashes (8 bytes a word and 64 while bits are counted).
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from bucketnet.llm import words
from bucketnet.llm.common import columns_of, cut, free_shuffles, fresh

SEED = 42
CHUNK = 4096
FEW = 50_000  # hot keys that may be broadcast
LEAF = 32
PAIRS = 1 << 16
RUN = 1 << 16
ONE_TASK = 2_000_000  # links whose components one task finds (about 150 bytes a link)
BUDGET, REACH, SPREAD = 8, 22, 38  # bits: never missed in a fingerprint's tables, followed in them, of both fingerprints together
PARITY = 512  # bits; a multiple of 64
PARITY_COLUMNS = [f"p{i}" for i in range(PARITY // 64)]
TURNS = (2,)  # candidates a row has counted before the next look at components


def shingle_hashes(buf: np.ndarray, offsets: np.ndarray, size: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    """XXH64 of all shingles of all texts, and the n + 1 offsets of each text's shingles."""
    import xxhash

    low = words.LOWER[buf]
    starts, ends, per = words.word_spans(low, offsets)
    n_words = np.diff(per)
    n_shingles = np.where(n_words > 0, np.maximum(1, n_words - size + 1), 0)
    upto = np.concatenate([[0], np.cumsum(n_shingles)])
    if len(starts) == 0:
        return np.zeros(0, np.uint64), upto
    # one space before each word but a text's first; other white space goes
    keep = ~words.SPACE[low]
    gap = np.setdiff1d(starts, starts[per[:-1][n_words > 0]]) - 1
    keep[gap] = True
    low[gap] = 0x20
    at = np.cumsum(keep) - 1
    joined = low[keep].tobytes()
    first = np.arange(upto[-1]) - np.repeat(upto[:-1], n_shingles) + np.repeat(per[:-1], n_shingles)
    last = np.minimum(first + size - 1, np.repeat(per[1:], n_shingles) - 1)
    f = xxhash.xxh64_intdigest
    spans = zip(at[starts[first]].tolist(), (at[ends[last] - 1] + 1).tolist(), strict=True)
    return np.fromiter((f(joined[a:b], seed) for a, b in spans), dtype=np.uint64, count=int(upto[-1])), upto


def simhash(hashes: np.ndarray, upto: np.ndarray) -> np.ndarray:
    """The majority bits of each text's hashes, 0 for a text without any."""
    n = len(upto) - 1
    out = np.zeros(n, dtype=np.uint64)
    count = np.diff(upto)
    has = np.flatnonzero(count > 0)
    if len(has):
        bits = np.unpackbits(hashes.astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        ones = np.add.reduceat(bits, upto[:-1][has], axis=0, dtype=np.int64)
        major = (2 * ones > count[has][:, None]).astype(np.uint8)
        out[has] = np.packbits(major, axis=1, bitorder="little").view("<u8").ravel()
    return out


def fingerprints(docs: DataFrame, shingle: int = 4, count: int = 1) -> DataFrame:
    """docs (without its text) with fp0, fp1, ... (long): fp0 from the hashes themselves, others from the hashes mixed anew."""
    kept = [f for f in docs.schema.fields if f.name != "text"]
    schema = T.StructType([*kept, *[T.StructField(f"fp{i}", T.LongType()) for i in range(count)]])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in words.slices(batch, limit=2 << 20):
                hashes, upto = shingle_hashes(*words.text_bytes(part.column("text")), shingle, SEED)
                found = [simhash(words.mix(hashes + np.uint64(i)) if i else hashes, upto) for i in range(count)]
                yield pa.RecordBatch.from_arrays([*[part.column(f.name) for f in kept], *[pa.array(x.view(np.int64)) for x in found]], [f.name for f in schema.fields])

    return docs.withColumn("text", F.col("text").cast("string")).mapInArrow(words.tidy(run), schema)


class Forest:
    """Union-find over 0 .. n - 1 with whole arrays; a root is the smallest of its tree."""

    def __init__(self, n: int):
        self.parent = np.arange(n)

    def roots(self, x: np.ndarray) -> np.ndarray:
        p = self.parent[x]
        while True:
            q = self.parent[p]
            if (p == q).all():
                return p
            p = q

    def link(self, a: np.ndarray, b: np.ndarray) -> None:
        while len(a):
            a, b = self.roots(a), self.roots(b)
            apart = a != b
            a, b = a[apart], b[apart]
            np.minimum.at(self.parent, np.maximum(a, b), np.minimum(a, b))

    def flat(self) -> np.ndarray:
        return self.roots(np.arange(len(self.parent)))


def trie_join(group: np.ndarray, fp: np.ndarray, side: np.ndarray, budget: int, found: Callable[[np.ndarray, np.ndarray, np.ndarray], None]) -> None:
    """Calls found(i, j, bits) with all pairs of rows of equal group that differ in at most budget bits, many at a time.

    side: 0, or 1 and 2 for rows of which only pairs of different side are wanted.
    """
    n = len(fp)
    if n < 2:
        return
    order = np.lexsort((fp, group))
    key, rank = fp[order], group[order]
    ones: dict[int, np.ndarray] = {}

    def cumulated(d: int) -> np.ndarray:
        if d not in ones:
            ones[d] = np.concatenate([[0], np.cumsum((key >> np.uint64(63 - d)) & np.uint64(1), dtype=np.int64)])
        return ones[d]

    edges = np.flatnonzero(np.concatenate([[True], rank[1:] != rank[:-1], [True]]))
    lo, hi = edges[:-1], edges[1:]
    many = hi - lo > 1
    lo, hi = lo[many], hi[many]
    stack = [(0, lo, hi, lo, hi, np.zeros(len(lo), dtype=np.int64))]
    sides = side[order]

    def settle(alo, ahi, blo, bhi) -> None:
        """Row pairs of small node pairs, tested on all bits."""
        na, nb = ahi - alo, bhi - blo
        total = na * nb
        k = np.arange(total.sum()) - np.repeat(np.cumsum(total) - total, total)
        width = np.repeat(nb, total)
        i, j = np.repeat(alo, total) + k // width, np.repeat(blo, total) + k % width
        near = (i < j) | (np.repeat(alo, total) != np.repeat(blo, total))
        near &= (sides[i] != sides[j]) | (sides[i] == 0)
        i, j = i[near], j[near]
        bits = np.bitwise_count(key[i] ^ key[j])
        good = np.flatnonzero(bits <= budget)
        if len(good):
            found(order[i[good]], order[j[good]], bits[good])

    while stack:
        d, alo, ahi, blo, bhi, diff = stack.pop()
        if len(alo) > PAIRS:
            h = len(alo) // 2
            stack += [(d, alo[h:], ahi[h:], blo[h:], bhi[h:], diff[h:]), (d, alo[:h], ahi[:h], blo[:h], bhi[:h], diff[:h])]
            continue
        small = ((ahi - alo) * (bhi - blo) <= LEAF) | (d == 64)
        if small.any():
            equal = (ahi - alo) * (bhi - blo) > LEAF
            s = small & ~equal
            settle(alo[s], ahi[s], blo[s], bhi[s])
            for x in np.flatnonzero(small & equal):  # runs of equal fingerprints, a row against the other run at a time
                for i in range(alo[x], ahi[x]):
                    b = max(blo[x], i + 1) if alo[x] == blo[x] else blo[x]
                    settle(np.array([i]), np.array([i + 1]), np.array([b]), bhi[x : x + 1])
            alo, ahi, blo, bhi, diff = (v[~small] for v in (alo, ahi, blo, bhi, diff))
        if len(alo) == 0:
            continue
        c = cumulated(d)
        amid, bmid = ahi - (c[ahi] - c[alo]), bhi - (c[bhi] - c[blo])
        own = alo == blo
        nxt = [(alo, amid, blo, bmid, diff), (amid, ahi, bmid, bhi, diff), (alo, amid, bmid, bhi, diff + 1), (amid[~own], ahi[~own], blo[~own], bmid[~own], diff[~own] + 1)]
        alo, ahi, blo, bhi, diff = (np.concatenate(v) for v in zip(*nxt, strict=True))
        go = (ahi > alo) & (bhi > blo) & (diff <= budget) & ((alo != blo) | (ahi - alo > 1))
        if go.any():
            stack.append((d + 1, alo[go], ahi[go], blo[go], bhi[go], diff[go]))


class Partners:
    """Of each row its nearest candidate among those of smaller weight, and among those of larger; ties by weight, so any order of rows gives the same."""

    def __init__(self, fp: np.ndarray, more: np.ndarray, weight: np.ndarray, spread: int):
        self.fp, self.more, self.weight, self.spread = fp, more, weight, spread
        self.nearest = np.full((2, len(fp)), NONE, dtype=np.uint64)

    def found(self, i: np.ndarray, j: np.ndarray, bits: np.ndarray) -> None:
        bits = bits + np.bitwise_count(self.more[i] ^ self.more[j])
        good = np.flatnonzero(bits <= self.spread)
        i, j, bits = i[good], j[good], bits[good].astype(np.uint64) << np.uint64(56)
        turned = self.weight[i] < self.weight[j]
        late, early = np.where(turned, j, i), np.where(turned, i, j)
        np.minimum.at(self.nearest[0], late, bits | (self.weight[early] >> np.uint64(8)))
        np.minimum.at(self.nearest[1], early, bits | (self.weight[late] >> np.uint64(8)))

    def pairs(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Rows, their partners and the bits of both fingerprints in which they differ; a pair named from both sides by the later row alone."""
        order = np.argsort(self.weight)
        place = self.weight[order] >> np.uint64(8)
        which = [np.flatnonzero(near != NONE) for near in self.nearest]
        other = [order[np.searchsorted(place, near[i] & np.uint64((1 << 56) - 1))] for i, near in zip(which, self.nearest, strict=True)]
        back = np.full(len(self.fp), -1)
        back[which[0]] = other[0]
        alone = back[other[1]] != which[1]
        i, j = np.concatenate([which[0], which[1][alone]]), np.concatenate([other[0], other[1][alone]])
        return i, j, np.bitwise_count(self.fp[i] ^ self.fp[j]).astype(np.int64) + np.bitwise_count(self.more[i] ^ self.more[j])


NONE = np.uint64(2**64 - 1)


def tables(count: int, budget: int, chunk: int = 2048) -> list[int]:
    """Masks of the bits that key each table, for at most about chunk of count fingerprints a key, in as few tables as that allows."""
    for k in range(1, 5):
        blocks = budget + k
        bounds = [64 * i // blocks for i in range(blocks + 1)]
        masks = [sum(1 << b for b in range(lo, hi)) for lo, hi in zip(bounds, bounds[1:], strict=False)]
        if count <= chunk << (64 * k // blocks) or k == 4:
            return [sum(c) for c in combinations(masks, k)]
    raise AssertionError


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def dealt(fps: DataFrame, budget: int, chunk: int, tables_for: int | None = None) -> tuple[DataFrame, np.ndarray]:
    """The rows of fps (fp, and more of longs) in each table of the budget, units together in a task, and the tables' masks (those for tables_for rows, if given).

    A row of a table is its place (table, pair of chunks, side) packed into a long, and its columns; the key is cut from the
    fingerprint on both sides of the shuffle rather than sent.
    """
    count = fps.count()
    masks = tables(count if tables_for is None else tables_for, budget, chunk)
    width = int(fps.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    listed = F.array(*[F.lit(_signed(m)).cast("long") for m in masks])
    keyed = fps.select("*", F.explode(F.sequence(F.lit(0), F.lit(len(masks) - 1))).alias("t"))
    keyed = keyed.withColumn("key", F.col("fp").bitwiseAND(F.element_at(listed, F.col("t") + 1)))
    hot = keyed.groupBy("t", "key").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > CHUNK)
    hot = cut(hot.select(F.col("t").alias("ht"), F.col("key").alias("hk"), F.ceil(F.col("n") / CHUNK).cast("int").alias("chunks")))
    many = hot.count()
    if many:  # broadcast only where they are few, and joined by a shuffle beyond that
        rows = keyed.join(F.broadcast(hot) if many <= FEW else hot, (F.col("t") == F.col("ht")) & (F.col("key") == F.col("hk")), "left")
    else:
        rows = keyed.withColumn("chunks", F.lit(1))
    chunks = F.coalesce("chunks", F.lit(1))
    rows = rows.withColumn("mine", F.pmod(F.xxhash64(*fps.columns), chunks).cast("long"))
    rows = rows.withColumn("peer", F.explode(F.sequence(F.lit(0).cast("long"), (chunks - 1).cast("long"))))
    side = F.when(F.col("mine") == F.col("peer"), 0).when(F.col("mine") < F.col("peer"), 1).otherwise(2)
    # table below 2**10, chunks below 2**25 each, side below 2**2
    place = ((F.col("t").cast("long") * (1 << 25) + F.least("mine", "peer")) * (1 << 25) + F.greatest("mine", "peer")) * 4 + side
    rows = rows.select(place.alias("place"), *fps.columns)
    unit = [F.floor(F.col("place") / 4), F.col("fp").bitwiseAND(F.element_at(listed, F.floor(F.col("place") / (1 << 52)).cast("int") + 1))]
    return rows.repartition(max(width, -(-count * len(masks) // 500_000)), *unit).sortWithinPartitions(*unit), np.array(masks, dtype=np.uint64)


def by_unit(rows: DataFrame, masks: np.ndarray, join: Callable[[np.ndarray, list[np.ndarray]], Iterator[list[np.ndarray]]], schema: str) -> DataFrame:
    """join(numbers of the units, columns of rows) over whole units, RUN rows or one unit at least at a time; it yields columns of longs."""
    names, sent = rows.columns, [x.split()[0] for x in schema.split(", ")]

    def units(cols: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        return cols[0] >> 2, cols[1].view(np.uint64) & masks[cols[0] >> 52]

    def out(cols: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
        a, b = units(cols)
        new = np.concatenate([[True], (a[1:] != a[:-1]) | (b[1:] != b[:-1])])
        for got in join(np.cumsum(new), cols):
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in got], sent)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[list[np.ndarray]] = []
        for batch in batches:
            if batch.num_rows:
                held.append([batch.column(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in names])
            if sum(len(h[0]) for h in held) < RUN:
                continue
            cols = [np.concatenate(c) for c in zip(*held, strict=True)]
            a, b = units(cols)
            begin = len(a) - int(((a == a[-1]) & (b == b[-1])).sum())
            if begin:
                yield from out([c[:begin] for c in cols])
            held = [[c[begin:] for c in cols]]
        if held:
            yield from out([np.concatenate(c) for c in zip(*held, strict=True)])

    return rows.mapInArrow(words.tidy(run), schema)


def near_links(fps: DataFrame, budget: int) -> DataFrame:
    """u > v (long): links that join all rows of fps (distinct fp0) within the budget into trees."""
    rows, masks = dealt(fps.select(F.col("fp0").alias("fp")), budget, 2048)

    def join(unit: np.ndarray, cols: list[np.ndarray]) -> Iterator[list[np.ndarray]]:
        forest = Forest(len(unit))
        trie_join(unit, cols[1].view(np.uint64), cols[0] & 3, budget, lambda i, j, bits: forest.link(i, j))
        root = forest.flat()
        linked = np.flatnonzero(root != np.arange(len(root)))
        yield [cols[1][linked], cols[1][root[linked]]]

    links = by_unit(rows, masks, join, "a long, b long")
    return links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u != v").distinct()


def near_candidates(classes: DataFrame, budget: int = BUDGET, reach: int = REACH, spread: int = SPREAD) -> DataFrame:
    """a, b (numbers of classes) and bits: of each class of classes (distinct fp0, fp1) its candidates by either fingerprint's tables."""
    sent = "a0 long, a1 long, b0 long, b1 long, bits long"

    def of(first: str, second: str) -> DataFrame:
        rows, masks = dealt(classes.select(F.col(first).alias("fp"), F.col(second).alias("more")), budget, 2048)

        def join(unit: np.ndarray, cols: list[np.ndarray]) -> Iterator[list[np.ndarray]]:
            x, y = cols[1].view(np.uint64), cols[2].view(np.uint64)
            one, two = (x, y) if first == "fp0" else (y, x)
            partners = Partners(x, y, words.mix(one + words.mix(two)), spread)
            trie_join(unit, x, cols[0] & 3, reach, partners.found)
            i, j, bits = partners.pairs()
            one, two = (c.view(np.int64) for c in (one, two))
            yield [one[i], two[i], one[j], two[j], bits]

        return by_unit(rows, masks, join, sent)

    both = of("fp0", "fp1").unionByName(of("fp1", "fp0"))
    return both.select(F.xxhash64("a0", "a1").alias("a"), F.xxhash64("b0", "b1").alias("b"), "bits").where("a != b").distinct()


def other_candidates(classes: DataFrame, tables_for: int, similarity: float, measure: str, budget: int = BUDGET, reach: int = REACH, spread: int = SPREAD) -> DataFrame:
    """u > v (numbers of classes): all candidates of classes (distinct fp0, fp1; root; n, the size of its set; PARITY_COLUMNS) of unlike root that may be so alike.

    The tables are those of near_candidates over tables_for classes; any class with a candidate in them has to be among these.
    """

    def of(first: str, second: str) -> DataFrame:
        rows, masks = dealt(classes.select(F.col(first).alias("fp"), F.col(second).alias("more"), "root", "n", *PARITY_COLUMNS), budget, 2048, tables_for)

        def join(unit: np.ndarray, cols: list[np.ndarray]) -> Iterator[list[np.ndarray]]:
            x, y, root, n, parity = cols[1].view(np.uint64), cols[2].view(np.uint64), cols[3], cols[4], [c.view(np.uint64) for c in cols[5:]]
            one, two = (cols[1], cols[2]) if first == "fp0" else (cols[2], cols[1])
            held: list[np.ndarray] = []

            def found(i: np.ndarray, j: np.ndarray, bits: np.ndarray) -> None:
                far = (root[i] != root[j]) & (bits + np.bitwise_count(y[i] ^ y[j]) <= spread)
                i, j = i[far], j[far]
                apart = sum((np.bitwise_count(p[i] ^ p[j]).astype(np.int64) for p in parity), np.zeros(len(i), np.int64))
                may = most_alike(n[i], n[j], apart, measure) >= similarity - 1e-9
                held.append(np.stack([i[may], j[may]]).astype(np.int32))

            trie_join(unit, x, cols[0] & 3, reach, found)
            for pairs in held:
                i, j = pairs
                if len(i):
                    yield [one[i], two[i], one[j], two[j]]

        return by_unit(rows, masks, join, "a0 long, a1 long, b0 long, b1 long")

    both = of("fp0", "fp1").unionByName(of("fp1", "fp0")).select(F.xxhash64("a0", "a1").alias("a"), F.xxhash64("b0", "b1").alias("b"))
    return both.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u != v").distinct()


def components_in_one(links: DataFrame) -> DataFrame:
    """components by a single task, which holds all links: the same rows without a round of jobs for each halving."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [[b.column(c).to_numpy() for c in ("u", "v")] for b in batches if b.num_rows]
        if not held:
            return
        u, v = (np.concatenate(x) for x in zip(*held, strict=True))
        nodes = np.unique(np.concatenate([u, v]))  # ascending: the smallest place is the smallest node
        a, b, parent = np.searchsorted(nodes, u), np.searchsorted(nodes, v), np.arange(len(nodes))
        del u, v, held
        while len(a):
            np.minimum.at(parent, np.maximum(a, b), np.minimum(a, b))
            while not np.array_equal(parent, up := parent[parent]):  # halves all depths, however long a chain is
                parent = up
            a, b = parent[a], parent[b]
            a, b = a[a != b], b[a != b]
        root = nodes[parent]
        for a in range(0, len(nodes), RUN):
            yield pa.RecordBatch.from_arrays([pa.array(nodes[a : a + RUN]), pa.array(root[a : a + RUN])], ["node", "root"])

    return links.select("u", "v").coalesce(1).mapInArrow(words.tidy(run), "node long, root long")


def components(links: DataFrame) -> DataFrame:
    """node, root (its component's smallest node) for every node in links (u > v)."""

    def mark(e: DataFrame) -> tuple:
        return tuple(e.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())

    e = cut(links)
    seen = mark(e)
    if seen[0] <= ONE_TASK:
        return components_in_one(e)
    while seen[0]:
        both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        # written, so that a node of many links is a hot key of exchanges, which Spark can split
        least = cut(both.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("c"), F.least("u", "m").alias("m")))
        large = both.join(least, F.col("u") == F.col("c")).where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        large = cut(large)
        least = large.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("c"), "m")
        joined = large.join(least, F.col("u") == F.col("c"))
        small = joined.where("v != m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(joined.select("u", F.col("m").alias("v")))
        e = cut(small.distinct())
        now = mark(e)
        if now == seen:
            break
        seen = now
    return e.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(e.select("v", F.col("v").alias("root")).distinct().withColumnRenamed("v", "node"))


def group_near(docs: DataFrame, shingle: int = 4, budget: int = 4) -> DataFrame:
    """doc_id, fp0, component_id for every row of docs.

    component_id: the smallest doc_id reachable by links, its own included. A link: at most budget bits between the
    fingerprints. Texts without a word (null, empty,
    white space) have fingerprint 0 and link like any other. Rows that share a doc_id stand for themselves each;
    null ids are never the smallest. An empty table gives no rows; other columns are not read.
    """
    rows = cut(fingerprints(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), shingle))
    classes = cut(rows.groupBy("fp0").agg(F.min("doc_id").alias("least")))
    comp = components(near_links(classes.select("fp0"), budget))
    rooted = classes.join(comp, F.col("fp0") == F.col("node"), "left").withColumn("root", F.coalesce("root", "fp0"))
    rooted = cut(rooted.select(F.col("fp0").alias("c_fp0"), "least", "root"))
    final = cut(rooted.groupBy("root").agg(F.min("least").alias("component_id")).withColumnRenamed("root", "r"))
    by_class = cut(rooted.join(final, F.col("root") == F.col("r")).select("c_fp0", "component_id"))
    return rows.join(by_class, F.col("fp0") == F.col("c_fp0")).select("doc_id", "fp0", "component_id")


def shingle_sets(texts: DataFrame, shingle: int) -> DataFrame:
    """texts (node, text) with s, the distinct hashes (32 bits) of the shingles, instead of the text.

    Of two texts with n shingles each n * n / 2**32 different ones meet by chance: a tenth of one for 20,000 words.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in words.slices(batch, limit=2 << 20):
                hashes, upto = shingle_hashes(*words.text_bytes(part.column("text")), shingle, SEED)
                short = (hashes >> np.uint64(32)).astype(np.uint32)
                sets = [np.unique(short[a:b]).view(np.int32) for a, b in zip(upto[:-1], upto[1:], strict=True)]
                yield pa.RecordBatch.from_arrays([part.column("node"), pa.array(sets, pa.list_(pa.int32()))], ["node", "s"])

    return texts.mapInArrow(words.tidy(run), "node long, s array<int>")


def parities(sets: DataFrame) -> DataFrame:
    """node, n (size of s) and PARITY_COLUMNS of sets: bit b of 512 tells whether an odd number of hashes in s end in b."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sizes = batch.column("s").value_lengths()
            flat, per = batch.column("s").flatten().to_numpy() & (PARITY - 1), sizes.to_numpy()
            for lo in range(0, batch.num_rows, 1024):
                begin, of = per[:lo].sum(), per[lo : lo + 1024]
                at = np.repeat(np.arange(len(of)) * PARITY, of) + flat[begin : begin + of.sum()]
                odd = (np.bincount(at, minlength=len(of) * PARITY) & 1).astype(np.uint8).reshape(-1, PARITY)
                bits = np.packbits(odd, axis=1, bitorder="little").view("<i8")
                yield pa.RecordBatch.from_arrays([batch.column("node")[lo : lo + 1024], sizes[lo : lo + 1024].cast(pa.int64()), *[pa.array(c) for c in bits.T.copy()]], ["node", "n", *PARITY_COLUMNS])

    return sets.select("node", "s").mapInArrow(words.tidy(run), ", ".join(f"{c} long" for c in ("node", "n", *PARITY_COLUMNS)))


def most_alike(a: np.ndarray, b: np.ndarray, apart: np.ndarray, measure: str) -> np.ndarray:
    """The largest likeness of sets of a and b elements of which at least apart are in one alone."""
    shared = np.minimum((a + b - apart) // 2, np.minimum(a, b))
    if measure == "cosine":
        return shared / np.sqrt(a.astype(float) * b)
    return shared / (a + b - shared)


def likeness(a: Column, b: Column, measure: str) -> Column:
    """Of two sets: cosine, shared / root of the product of sizes, or jaccard, shared / all."""
    shared = F.size(F.array_intersect(a, b))
    if measure == "cosine":
        return F.try_divide(shared, F.sqrt(F.size(a).cast("double") * F.size(b)))
    if measure == "jaccard":
        return F.try_divide(shared, F.size(a) + F.size(b) - shared)
    raise ValueError(f"no such measure: {measure}")


def group_similar(docs: DataFrame, shingle: int = 5, similarity: float = 0.8, measure: str = "cosine") -> DataFrame:
    """doc_id, th (hash of the text) and head_id, head_th, those of the group's first row, for every distinct pair of doc_id and th in docs.

    Linked are rows whose two fingerprints are equal, and candidates (near_candidates) whose sets of distinct shingles have at least this
    similarity. The cosine is what a SimHash estimates; it is at least as large as the Jaccard similarity, so pairs of Jaccard 0.8 are all
    within a cosine of 0.8. Groups are components of links; a group's first row is that of smallest doc_id (nulls last) and then th.
    Texts without a word (null, empty, white space) are equal in words, and so one group. Rows of one doc_id with other texts are rows of their own.
    An empty table gives no rows. A link is missed only if neither fingerprint's tables hold the pair: at Jaccard
    0.8 they hold 97 % (of 10**8 classes) to 99.9 % (of 10**4), by simulation.
    """
    rows = cut(fingerprints(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("th"), "text"), shingle, 2))
    place = F.struct(F.col("doc_id").isNull().alias("z"), "doc_id", "th")
    classes = cut(rows.groupBy("fp0", "fp1").agg(F.min(place).alias("first")).withColumn("id", F.xxhash64("fp0", "fp1")))
    worded = classes.where("fp0 != 0 or fp1 != 0")
    found = cut(near_candidates(worded.select("fp0", "fp1")))
    nodes = found.select(F.col("a").alias("n")).unionByName(found.select(F.col("b").alias("n"))).distinct()
    wanted = classes.join(nodes, F.col("id") == F.col("n")).select(F.col("id").alias("node"), F.col("first.doc_id").alias("w_id"), F.col("first.th").alias("w_th"))
    texts = docs.select(F.col("doc_id").cast("long").alias("d_id"), F.xxhash64("text").alias("d_th"), F.col("text").cast("string").alias("text"))
    texts = texts.join(wanted, F.col("d_id").eqNullSafe(F.col("w_id")) & (F.col("d_th") == F.col("w_th"))).select("node", "text")
    sets = cut(shingle_sets(texts, shingle).groupBy("node").agg(F.first("s").alias("s")))  # repeated rows have one set
    free_shuffles(docs.sparkSession)
    links, comp = None, None

    def alike(pairs: DataFrame) -> DataFrame:
        one, two = (sets.select(F.col("node").alias(f"n_{x}"), F.col("s").alias(f"s_{x}")) for x in ("u", "v"))
        judged = pairs.join(one, F.col("u") == F.col("n_u")).join(two, F.col("v") == F.col("n_v"))
        return judged.where(likeness(F.col("s_u"), F.col("s_v"), measure) >= similarity).select("u", "v")

    def rooted_pairs(pairs: DataFrame) -> DataFrame:
        """pairs with r_u and r_v, the roots of their components by now, where these differ."""
        if comp is None:
            return pairs.withColumns({"r_u": F.col("u"), "r_v": F.col("v")})
        for x in ("u", "v"):
            pairs = pairs.join(comp.select(F.col("node").alias(f"n_{x}"), F.col("root").alias(f"c_{x}")), F.col(x) == F.col(f"n_{x}"), "left")
        return pairs.select("u", "v", F.coalesce("c_u", "u").alias("r_u"), F.coalesce("c_v", "v").alias("r_v")).where("r_u != r_v")

    turn = F.row_number().over(Window.partitionBy("a").orderBy("bits", "b"))  # a row names two candidates a table at most
    ranked = cut(found.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v"), turn.alias("turn")))
    for lo, hi in zip((0, *TURNS), (*TURNS, None), strict=True):
        now = ranked.where(F.col("turn") > lo) if hi is None else ranked.where((F.col("turn") > lo) & (F.col("turn") <= hi))
        pairs = cut(rooted_pairs(now.select("u", "v").distinct()).select("u", "v"))
        if pairs.isEmpty():
            continue
        new = alike(pairs)
        links = cut(new if links is None else links.unionByName(new))
        comp = cut(components(links))
        new = pairs = None
        free_shuffles(docs.sparkSession)
    rooted = classes if comp is None else classes.join(comp, F.col("id") == F.col("node"), "left")
    rooted = rooted.withColumn("root", F.lit(None).cast("long") if comp is None else F.col("root")).withColumn("root", F.coalesce("root", "id"))
    rooted = rooted.select("id", "fp0", "fp1", "first", "root")
    named = rooted.join(parities(sets).withColumnRenamed("node", "s_node"), F.col("id") == F.col("s_node")).select("fp0", "fp1", "root", "n", *PARITY_COLUMNS)
    rest = other_candidates(cut(named), worded.count(), similarity, measure)
    rest = rest.join(ranked.select("u", "v").distinct(), ["u", "v"], "left_anti")
    more = cut(alike(rest))
    free_shuffles(docs.sparkSession)
    if not more.isEmpty():  # links between components: only their roots take part
        again = rooted_pairs(more).select(F.greatest("r_u", "r_v").alias("u"), F.least("r_u", "r_v").alias("v")).distinct()
        higher = components(again).select(F.col("node").alias("h_node"), F.col("root").alias("h_root"))
        rooted = rooted.join(higher, F.col("root") == F.col("h_node"), "left").withColumn("root", F.coalesce("h_root", "root"))
    rooted = cut(rooted.select(F.col("fp0").alias("c_fp0"), F.col("fp1").alias("c_fp1"), "first", "root"))
    heads = cut(rooted.groupBy("root").agg(F.min("first").alias("head")).withColumnRenamed("root", "r"))
    by_class = cut(rooted.join(heads, F.col("root") == F.col("r")).select("c_fp0", "c_fp1", F.col("head.doc_id").alias("head_id"), F.col("head.th").alias("head_th")))
    distinct = rows.distinct()
    return distinct.join(by_class, (F.col("fp0") == F.col("c_fp0")) & (F.col("fp1") == F.col("c_fp1"))).select("doc_id", "th", "head_id", "head_th")


def keep_one(docs: DataFrame, shingle: int = 5, similarity: float = 0.8, measure: str = "cosine") -> DataFrame:
    """One row of docs for each group of group_similar: its first; of rows equal in doc_id and text one. All columns stay."""
    grouped = group_similar(docs, shingle, similarity, measure)
    h_id, h_th, th = fresh(docs, "__id", "__th", "__text_hash")
    first = grouped.where(F.col("doc_id").eqNullSafe(F.col("head_id")) & (F.col("th") == F.col("head_th"))).select(F.col("head_id").alias(h_id), F.col("head_th").alias(h_th))
    first = cut(first)
    free_shuffles(docs.sparkSession)
    rows = docs.withColumn(th, F.xxhash64("text"))
    kept = rows.join(first, F.col("doc_id").eqNullSafe(F.col(h_id)) & (F.col(th) == F.col(h_th)), "left_semi")
    return kept.dropDuplicates(["doc_id", th]).select(*columns_of(docs))
