"""Numpy kernel of a sparse two-layer net: what runs inside a task of plan B.

Instances go through as flat arrays; pairs (instance, active neuron) live here only and never become rows.
"""

from __future__ import annotations

import tempfile
from collections.abc import Iterator
from dataclasses import dataclass, field, replace
from itertools import pairwise

import numpy as np

from bucketnet.functions.seeds import h32_of


@dataclass(frozen=True)
class NetConf:
    """dims features, hidden units, labels; how the output layer is sampled; how weights move.

    strategy: union, vanilla, topk, threshold, intersect (hash tables over the labels' weight vectors), dense (all
    labels), static (a random sample shared by a batch), exact_topk (the beta largest of all), dropout.
    """

    dims: int
    hidden: int
    labels: int
    strategy: str = "topk"
    k: int = 6
    tables: int = 20
    beta: int = 50
    threshold: int = 2
    family: str = "simhash"  # or wta, dwta, minhash: k symbols of m values a table
    m: int = 4
    cap: int | None = None
    policy: str = "reservoir"
    force_labels: bool = True
    correct: bool = False
    weighted: bool = False
    dropout: float = 0.5
    rate: float = 3e-3
    batch: int = 128
    optimizer: str = "adam"
    lazy: bool = True
    refresh: str = "decay"
    n0: float = 50
    decay: float = 0.1
    incremental: bool = True
    propagate: str = "before"
    seed: int = 11

    def legacy(self) -> NetConf:
        """Adaptive dropout as it was before: unbounded buckets, new tables each step, full hashing."""
        return replace(self, cap=None, refresh="every", incremental=False)


MAPPED = 32 << 20  # bytes of an array from which on it is kept in a file


def room(shape: tuple[int, ...], dtype: type) -> np.ndarray:
    """Zeros; a large array is mapped from a file without a name in the task's own folder, which ends with the array: the system holds as much of it in memory as there is room for."""
    if np.prod(shape, dtype=np.int64) * np.dtype(dtype).itemsize < MAPPED:
        return np.zeros(shape, dtype)
    with tempfile.TemporaryFile() as f:
        return np.asarray(np.memmap(f, dtype, "w+", shape=shape))


@dataclass
class Snapshot:
    """Weights and Adam moments."""

    w_in: np.ndarray
    w_out: np.ndarray
    moments: dict[str, np.ndarray] = field(default_factory=dict)
    step: int = 0

    @classmethod
    def start(cls, conf: NetConf) -> Snapshot:
        rng = np.random.default_rng(conf.seed)
        both = []
        for n in (conf.dims, conf.labels):
            both.append(w := room((n, conf.hidden), np.float32))
            for i in range(0, n, 16_384):  # drawn in parts, the same numbers
                w[i : i + 16_384] = rng.normal(0, 1 / np.sqrt(conf.hidden), w[i : i + 16_384].shape)
        return cls(*both).with_moments()

    def with_moments(self) -> Snapshot:
        for name in ("w_in", "w_out"):
            for m in ("m", "v"):
                if f"{name}.{m}" not in self.moments:
                    w = getattr(self, name)
                    self.moments[f"{name}.{m}"] = room(w.shape, w.dtype)
        return self

    @staticmethod
    def bytes_of(conf: NetConf) -> int:
        """The size of a configuration's snapshot, before it is made."""
        return 12 * conf.hidden * (conf.dims + conf.labels)

    def copy(self) -> Snapshot:
        return Snapshot(self.w_in.copy(), self.w_out.copy(), {k: v.copy() for k, v in self.moments.items()}, self.step)

    @property
    def size(self) -> int:
        return self.w_in.nbytes + self.w_out.nbytes + sum(m.nbytes for m in self.moments.values())


class Functions:
    """The hash functions of a configuration over dense vectors, for a whole batch at once: codes, one a table."""

    CHUNK = 4096

    def __init__(self, conf: NetConf):
        self.conf = conf
        if conf.family not in ("simhash", "wta", "dwta", "minhash"):
            raise ValueError(f"no such family: {conf.family}")
        rng = np.random.default_rng(h32_of(conf.seed, "tables"))
        n = conf.k * conf.tables
        self.radix = 2 if conf.family == "simhash" else conf.m
        self.buckets = self.radix**conf.k
        if self.buckets * conf.tables >= 1 << 31:
            raise ValueError("too many buckets: lower k, m or tables")
        if conf.family == "simhash":
            self.directions = rng.choice([-1.0, 0.0, 1.0], size=(conf.hidden, n), p=[1 / 3, 1 / 3, 1 / 3]).astype(np.float32)
        elif conf.family == "minhash":
            self.ranks = np.argsort(rng.random((n, conf.hidden)), axis=1).astype(np.int32)
        else:  # permutations cut into bins of m coordinates
            per = max(1, conf.hidden // conf.m)
            orders = [rng.permutation(conf.hidden)[: per * conf.m].reshape(per, -1) for _ in range(-(-n // per))]
            self.bins = np.concatenate(orders)[:n]
            self.unit = np.array([next(u for u in range(h32_of(conf.seed, "unit", f) % n, 2 * n + 2) if np.gcd(u, n) == 1) for f in range(n)])

    def symbols(self, x: np.ndarray) -> np.ndarray:
        c = self.conf
        if c.family == "minhash":  # the set: the places of a quarter of the coordinates, the largest ones
            t = max(1, c.hidden // 4)
            member = np.zeros(x.shape, dtype=bool)
            np.put_along_axis(member, np.argsort(-x, axis=1, kind="stable")[:, :t], True, axis=1)
            out = np.empty((len(x), len(self.ranks)), dtype=np.int64)
            for f, r in enumerate(self.ranks):
                out[:, f] = np.where(member, r, c.hidden).argmin(axis=1) % c.m
            return out
        seen = x[:, self.bins]
        out = seen.argmax(axis=2)
        if c.family == "dwta":  # a bin of zeros borrows from the first other one in its own order of all bins
            n = out.shape[1]
            empty, own = ~seen.any(axis=2), out.copy()
            i, f = np.nonzero(empty & ~empty.all(axis=1)[:, None])
            turn = 1
            inverse = np.array([pow(int(u), -1, n) if n > 1 else 0 for u in self.unit])
            while len(i):
                b = (f + turn * inverse[f]) % n
                hit = ~empty[i, b]
                out[i[hit], f[hit]] = own[i[hit], b[hit]]
                i, f, turn = i[~hit], f[~hit], turn + 1
        return out

    def of_projections(self, projections: np.ndarray) -> np.ndarray:
        bits = np.ascontiguousarray(projections >= 0).reshape(-1, self.conf.k)
        return (bits.astype(np.float64) @ (2.0 ** np.arange(self.conf.k))).astype(np.int64).reshape(-1, self.conf.tables)  # exact: k is less than 31

    def __call__(self, x: np.ndarray, rows: np.ndarray | None = None) -> np.ndarray:
        """Codes of x, or of those rows of it."""
        n, weight = len(x) if rows is None else len(rows), self.radix ** np.arange(self.conf.k)
        out = np.empty((n, self.conf.tables), dtype=np.int32)
        for i in range(0, n, self.CHUNK):
            part = x[i : i + self.CHUNK] if rows is None else x[rows[i : i + self.CHUNK]]
            out[i : i + self.CHUNK] = self.of_projections(part @ self.directions) if self.conf.family == "simhash" else self.symbols(part).reshape(-1, self.conf.tables, self.conf.k) @ weight
        return out


class Tables:
    """Hash tables over weight vectors, kept over a whole run: a refresh moves only entries whose code has changed.

    An entry's word is its bucket above and its rank below: with a cap a bucket holds its first cap entries, by a hash of (entry,
    insertion) for the reservoir, by the last insertion for FIFO, where a moved entry is inserted anew. Words stand by (table, label);
    each table has every label once, so tables are sorted and moved one at a time.
    """

    MEMO = 64 << 20  # bytes of projections that are kept to be moved by changes; more are made anew from the weights

    def __init__(self, conf: NetConf, w: np.ndarray, code: np.ndarray | None = None):
        self.conf, self.functions = conf, Functions(conf)
        memo = conf.incremental and conf.family == "simhash" and code is None and 4 * len(w) * conf.k * conf.tables <= self.MEMO
        self.seen = w.copy() if memo else None
        self.projections = w @ self.functions.directions if memo else None
        if code is None:
            self.code = room((len(w), conf.tables), np.int32)
            for i in range(0, len(w), Functions.CHUNK):
                at = slice(i, i + Functions.CHUNK)
                self.code[at] = self.functions.of_projections(self.projections[at]) if memo else self.functions(w[at])
        else:
            self.code = code
        self.moved = self.hashed = self.insertion = 0
        shape = (conf.tables, len(self.code))
        self.words, self.sorted, self.starts = room(shape, np.uint64), room(shape, np.int32), room(shape, np.int32)
        self._fill()

    @property
    def nbytes(self) -> int:
        return sum(x.nbytes for x in (self.code, self.words, self.sorted, self.starts, self.seen, self.projections) if x is not None)

    @property
    def entry(self) -> np.ndarray:
        return self.words.ravel()

    @property
    def order(self) -> np.ndarray:
        return (self.sorted + np.arange(self.conf.tables)[:, None] * self.words.shape[1]).ravel()

    def _words(self, label: np.ndarray, table: int) -> np.ndarray:
        key = (self.code[label, table].astype(np.int64) + table * self.functions.buckets).astype(np.uint64) << np.uint64(32)
        if self.conf.cap is not None and self.conf.policy == "reservoir":
            h = (label * self.conf.tables + table).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(h32_of(self.conf.seed, "priority", self.insertion))
            h = (h ^ (h >> np.uint64(31))) * np.uint64(0x94D049BB133111EB)
            return key | (h >> np.uint64(32))
        return key | (np.uint64(2**32 - 1) - np.uint64(self.insertion * len(self.code)) - label.astype(np.uint64))  # the last insertion first

    def _fill(self) -> None:
        every = np.arange(len(self.code))
        for table, words in enumerate(self.words):
            words[:] = self._words(every, table)
            self.sorted[table] = np.argsort(words, kind="stable")
        self._bound()

    def _bound(self, changed: np.ndarray | None = None) -> None:
        """The buckets' keys and labels, after those tables (all, if none are named) were sorted."""
        for table in range(self.conf.tables) if changed is None else changed:
            self.starts[table] = self.words[table][self.sorted[table]] >> np.uint64(32)
        self.keys, self.ids = self.starts.ravel(), self.sorted.ravel()
        if self.conf.cap is not None:
            near = [np.arange(len(keys)) - np.searchsorted(keys, keys) < self.conf.cap for keys in self.starts]
            self.keys, self.ids = (np.concatenate([x[kept] for x, kept in zip(of, near, strict=True)]) for of in (self.starts, self.sorted))

    def refresh(self, w: np.ndarray, touched: np.ndarray) -> None:
        """Touched labels get new codes, from the old projections plus those of the change or from scratch; entries with another code move."""
        if len(touched) == 0:
            return
        if self.seen is not None:
            change = w[touched] - self.seen[touched]
            live = np.flatnonzero(np.any(change != 0, axis=0))
            self.projections[touched] += change[:, live] @ self.functions.directions[live]
            self.seen[touched] = w[touched]
            self.hashed += len(touched) * len(live) * self.functions.directions.shape[1]
            new = self.functions.of_projections(self.projections[touched])
        elif self.conf.incremental:
            new = self.functions(w, touched)
            self.hashed += len(touched) * w.shape[1] * self.conf.k * self.conf.tables
        else:
            touched, new = np.arange(len(w)), self.functions(w)
            self.hashed += w.size * self.conf.k * self.conf.tables
        self.insertion += 1
        again = (self.insertion + 1) * len(self.code) >= 2**32  # numbers begin again, in order of label
        changed = []
        for table in range(self.conf.tables):
            at = np.flatnonzero(new[:, table] != self.code[touched, table])
            if len(at) == 0:
                continue
            changed.append(table)
            self.moved += len(at)
            label, words = touched[at], self.words[table]
            self.code[label, table] = new[at, table]
            if again:
                continue
            words[label] = self._words(label, table)
            gone = np.zeros(len(words), dtype=bool)
            gone[label] = True
            rest = self.sorted[table][~gone[self.sorted[table]]]
            label = label[np.argsort(words[label], kind="stable")]
            self.sorted[table] = np.insert(rest, np.searchsorted(words[rest], words[label]), label)
        if not changed:
            self.insertion -= 1
        elif again:
            self.insertion = 0
            self._fill()
        else:
            self._bound(changed)

    def pairs(self, hidden: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(instance, table, label) of all probed bucket entries."""
        c = self.conf
        key = (self.functions(hidden) + np.arange(c.tables, dtype=self.keys.dtype) * self.functions.buckets).ravel().astype(self.keys.dtype)
        lo = np.searchsorted(self.keys, key)
        n = np.searchsorted(self.keys, key + 1) - lo
        total = int(n.sum())
        at = np.repeat(lo - np.cumsum(n) + n, n) + np.arange(total)
        cell = np.repeat(np.arange(key.size), n)
        return cell // c.tables, cell % c.tables, self.ids[at].astype(np.int64)


def _drawn(conf: NetConf, rng: np.random.Generator, weights: np.ndarray | None) -> tuple[np.ndarray, np.ndarray | None]:
    """The labels of a static sample, and the expected count of each label's draw if it is corrected."""
    n, incl = conf.labels, None
    p = None if not conf.weighted or weights is None else weights / weights.sum()
    drawn = np.sort(rng.choice(n, size=min(conf.beta, n), replace=False, p=p))
    if conf.correct:
        incl = np.minimum(1.0, conf.beta * (np.full(n, 1 / n) if p is None else p))
        outside = np.ones(n, dtype=bool)
        outside[drawn] = False
        incl[outside] = 1.0
    return drawn, incl


BLOCKS = ("static", "dropout")  # strategies whose pairs fill much of (instances, labels)


def choose_block(conf: NetConf, b: int, label_of: tuple[np.ndarray, np.ndarray], step: int, weights: np.ndarray | None) -> tuple[np.ndarray | slice, np.ndarray, np.ndarray | None]:
    """The pairs that choose gives in training by a strategy of BLOCKS, as labels (a slice: all) and a mask (instance, place in labels)."""
    rng = np.random.default_rng((conf.seed, step))
    if conf.strategy == "dropout":
        labels, incl, mask, place = slice(None), None, rng.random((b, conf.labels)) >= conf.dropout, label_of[1]
    else:
        drawn, incl = _drawn(conf, rng, weights)
        labels = np.union1d(drawn, label_of[1]) if conf.force_labels else drawn
        mask, place = np.zeros((b, len(labels)), dtype=bool), np.searchsorted(labels, label_of[1])
        mask[:, np.searchsorted(labels, drawn)] = True
    if conf.force_labels:
        mask[label_of[0], place] = True
    return labels, mask, incl


def choose(conf: NetConf, tables: Tables | None, hidden: np.ndarray, w: np.ndarray, label_of: tuple[np.ndarray, np.ndarray], step: int, weights: np.ndarray | None, train: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray | None]:
    """Active (instance, label) pairs in order of instance, and the expected count of each label's draw if it is corrected."""
    b, n = len(hidden), conf.labels
    rng = np.random.default_rng((conf.seed, step))
    incl = None
    if conf.strategy == "dense":
        return np.repeat(np.arange(b), n), np.tile(np.arange(n), b), None
    if conf.strategy == "exact_topk":
        best = np.argpartition(-(hidden @ w.T), min(conf.beta, n - 1), axis=1)[:, : conf.beta]
        inst, lab = np.repeat(np.arange(b), best.shape[1]), best.ravel()
    elif conf.strategy == "dropout":
        inst, lab = np.nonzero(rng.random((b, n)) >= conf.dropout)
    elif conf.strategy == "static":
        drawn, incl = _drawn(conf, rng, weights)
        inst, lab = np.repeat(np.arange(b), len(drawn)), np.tile(drawn, b)
    else:
        i, t, x = tables.pairs(hidden)
        if conf.strategy == "vanilla":
            turn = np.argsort(np.argsort(rng.random((b, conf.tables)), axis=1), axis=1)[i, t]
            order = np.lexsort((turn, x, i))
            i, x, turn = i[order], x[order], turn[order]
            first = np.concatenate([[True], (i[1:] != i[:-1]) | (x[1:] != x[:-1])]) if len(i) else np.zeros(0, bool)
            i, x, turn = i[first], x[first], turn[first]
            per = np.zeros((b, conf.tables + 1), dtype=np.int64)
            np.add.at(per, (i, turn + 1), 1)
            keep = np.cumsum(per, axis=1)[i, turn] < conf.beta
            inst, lab = i[keep], x[keep]
        else:
            key, count = np.unique(i * n + x, return_counts=True)
            inst, lab = key // n, key % n
            if conf.strategy == "threshold":
                keep = count >= conf.threshold
            elif conf.strategy == "intersect":
                keep = count == conf.tables
            elif conf.strategy == "topk":
                order = np.lexsort((rng.random(len(key)), -count, inst))
                begin = np.searchsorted(inst[order], inst[order])
                keep = np.zeros(len(key), dtype=bool)
                keep[order[np.arange(len(key)) - begin < conf.beta]] = True
            else:
                keep = np.ones(len(key), dtype=bool)
            inst, lab = inst[keep], lab[keep]
    if train and conf.force_labels:
        inst, lab = np.concatenate([inst, label_of[0]]), np.concatenate([lab, label_of[1]])
    key = np.unique(inst * n + lab)
    return key // n, key % n, incl


LOGITS = 1 << 20  # logits of a batch that are looked at together
GATHERED = 4 << 20  # numbers of a layer's rows that are looked at together


def spans(offsets: np.ndarray, most: int) -> Iterator[tuple[int, int]]:
    """Ranges of segments that have at most so many entries together (or are one segment)."""
    lo, n = 0, len(offsets) - 1
    while lo < n:
        hi = max(lo + 1, int(np.searchsorted(offsets, offsets[lo] + most, side="right")) - 1)
        yield lo, hi
        lo = hi


def _sum_scaled(rows: np.ndarray, owner: np.ndarray, vals: np.ndarray, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """_sum_rows of rows[owner] * vals, which is never there as a whole."""
    order = np.argsort(keys, kind="stable")
    k = keys[order]
    at = np.flatnonzero(np.diff(k, prepend=-1))
    ends, out = np.append(at, len(k)), np.empty((len(at), rows.shape[1]), np.result_type(rows, vals))
    for lo, hi in spans(ends, GATHERED // rows.shape[1]):
        o = order[ends[lo] : ends[hi]]
        out[lo:hi] = np.add.reduceat(rows[owner[o]] * vals[o][:, None], at[lo:hi] - at[lo], axis=0)
    return k[at], out


def _sum_rows(rows: np.ndarray, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sums of rows of equal key, and the keys."""
    order = np.argsort(keys, kind="stable")
    k = keys[order]
    at = np.flatnonzero(np.diff(k, prepend=-1))
    return k[at], _sum_runs(rows, order, at)


def _sum_runs(rows: np.ndarray, order: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Sums of rows[order] from each place of at to the next, in that order: all first rows, then all second ones, ... (most runs are short)."""
    size = np.diff(np.append(at, len(order)))
    out = rows[order[at]]
    more, turn = np.flatnonzero(size > 1), 1
    while len(more):
        out[more] += rows[order[at[more] + turn]]
        turn += 1
        more = more[size[more] > turn]
    return out


def descend(conf: NetConf, step: int, w: np.ndarray, m: np.ndarray, v: np.ndarray, rows: np.ndarray, g: np.ndarray) -> None:
    """SGD or Adam: rows of w and its moments move by their gradients, in place; step counts from 1."""
    if conf.optimizer == "sgd":
        w[rows] -= conf.rate * g
        return
    if not conf.lazy:
        full = np.zeros_like(w)
        full[rows] = g
        rows, g = slice(None), full
    elif len(rows) == len(w):  # all rows, once each
        rows = slice(None)
    for i in range(0, len(g), 2048):  # a part at a time, which a processor's cache holds
        part, d = slice(i, i + 2048) if isinstance(rows, slice) else rows[i : i + 2048], g[i : i + 2048]
        new_m, new_v = 0.9 * m[part] + 0.1 * d, 0.999 * v[part] + 0.001 * d * d
        m[part], v[part] = new_m, new_v
        w[part] -= conf.rate * (new_m / (1 - 0.9**step)) / (np.sqrt(new_v / (1 - 0.999**step)) + 1e-8)


HASHED = ("union", "vanilla", "topk", "threshold", "intersect")


class Trainer:
    """One learner: forward, backward, update. Its tables are its own, kept by the calendar, or given, and then whoever gave them keeps them."""

    def __init__(self, conf: NetConf, snapshot: Snapshot, label_weights: np.ndarray | None = None, tables: Tables | None = None):
        from bucketnet.operators.index import Refresh

        self.conf, self.at, self.weights = conf, snapshot, label_weights
        self.tables = tables if tables is not None else Tables(conf, snapshot.w_out) if conf.strategy in HASHED else None
        self.clock = Refresh(conf.refresh, conf.n0, conf.decay) if tables is None else None
        self.touched = np.zeros(conf.labels, dtype=bool)
        self.active = self.instances = 0
        self.refreshes: list[dict] = []
        self.pairs_used: tuple | None = None
        self.rows_touched: dict[str, np.ndarray] = {}

    def hidden(self, feats: np.ndarray, vals: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        out = np.zeros((len(offsets) - 1, self.conf.hidden), dtype=np.float32)
        for lo, hi in spans(offsets, GATHERED // self.conf.hidden):
            a, b = offsets[lo], offsets[hi]
            has = np.flatnonzero(np.diff(offsets[lo : hi + 1]))
            if len(has):
                out[lo + has] = np.add.reduceat(self.at.w_in[feats[a:b]] * vals[a:b, None], offsets[lo + has] - a, axis=0)
        return np.maximum(out, 0)

    def gradients(self, feats, vals, offsets, labels, label_offsets, pairs: tuple | None = None) -> tuple[dict[str, tuple[np.ndarray, np.ndarray]], float]:
        """{layer: (rows, gradient)} of the mean loss of the batch over touched rows, and that loss. pairs: the active set of an earlier call, taken again and not counted."""
        conf, b = self.conf, len(offsets) - 1
        h = self.hidden(feats, vals, offsets)
        own = np.repeat(np.arange(b), np.diff(label_offsets)), labels
        w = self.at.w_out
        share = 1.0 / np.maximum(np.diff(label_offsets), 1)
        if conf.strategy == "dense":
            if pairs is None:
                self.active += b * conf.labels
                self.instances += b
            self.pairs_used = ()
            back, g_out, loss = self._dense(h, w, own, share[own[0]])
            back *= h > 0
            rows_out = np.arange(conf.labels)
        elif conf.strategy in BLOCKS:
            if pairs is None:
                pairs = choose_block(conf, b, own, self.at.step, self.weights)
                self.active += int(pairs[1].sum())
                self.instances += b
            cols, mask, incl = self.pairs_used = pairs
            ids, w = np.arange(conf.labels)[cols], w[cols]
            if len(ids) == 0 or not mask.any():
                return {}, 0.0
            z = h @ w.T
            if incl is not None:
                z -= np.log(incl[ids]).astype(np.float32)
            z[~mask] = -np.inf
            top = z.max(axis=1, keepdims=True)
            z -= np.where(np.isfinite(top), top, 0)
            p = np.exp(z, out=z)
            p /= np.maximum(p.sum(axis=1, keepdims=True), 1e-30)
            place = np.minimum(np.searchsorted(ids, own[1]), len(ids) - 1)
            there = (ids[place] == own[1]) & mask[own[0], place]
            mine = own[0][there], place[there]
            y = share[own[0][there]]
            loss = -(y * np.log(p[mine] + 1e-30)).sum() / b
            p[mine] -= y
            p /= b
            back = (p @ w) * (h > 0)
            met = mask.any(axis=0)
            rows_out, g_out = ids[met], (p.T @ h)[met]
        else:
            if pairs is None:
                pairs = choose(conf, self.tables, h, w, own, self.at.step, self.weights, True)
                self.active += len(pairs[0])
                self.instances += b
            inst, lab, incl = self.pairs_used = pairs
            z = np.einsum("pd,pd->p", w[lab], h[inst])
            if incl is not None:
                z = z - np.log(incl[lab])
            at = np.flatnonzero(np.diff(inst, prepend=-1))
            if len(at) == 0:
                return {}, 0.0
            size = np.diff(np.append(at, len(inst)))
            z = np.exp(z - np.repeat(np.maximum.reduceat(z, at), size))
            p = z / np.repeat(np.add.reduceat(z, at), size)
            key = inst * conf.labels + lab
            mine = np.searchsorted(key, own[0] * conf.labels + own[1])
            there = (mine < len(key)) & (key[np.minimum(mine, len(key) - 1)] == own[0] * conf.labels + own[1])
            mine = mine[there]
            y = share[own[0][there]]
            loss = -(y * np.log(p[mine] + 1e-30)).sum() / b
            p[mine] -= y
            p = (p / b).astype(np.float32)
            rows_out, g_out = _sum_rows(p[:, None] * h[inst], lab)
            back = np.zeros_like(h)
            for i, lo, n in zip(inst[at], at, size, strict=True):
                back[i] = p[lo : lo + n] @ w[lab[lo : lo + n]]
            back *= h > 0
        owner = np.repeat(np.arange(b), np.diff(offsets))
        rows_in, g_in = _sum_scaled(back, owner, vals, feats)
        return {"w_out": (rows_out, g_out), "w_in": (rows_in, g_in)}, float(loss)

    def _dense(self, h: np.ndarray, w: np.ndarray, own: tuple[np.ndarray, np.ndarray], y: np.ndarray) -> tuple[np.ndarray, np.ndarray, float]:
        """Errors of the hidden units, gradient of the output layer and mean loss of a softmax over all labels; labels go by in blocks, whose logits are made twice."""
        b, n, most = len(h), len(w), max(1, LOGITS // max(1, len(h)))
        ends = [*range(0, n, most), n]
        top, total = np.full((b, 1), -np.inf, np.float32), np.zeros((b, 1), np.float32)
        for lo, hi in pairwise(ends) if n > most else ():
            z = h @ w[lo:hi].T
            old, top = top, np.maximum(top, z.max(axis=1, keepdims=True))
            z -= top
            total = total * np.exp(old - top) + np.exp(z, out=z).sum(axis=1, keepdims=True)
        back, g, loss = np.zeros_like(h), room((n, h.shape[1]), np.float32), 0.0
        order = np.argsort(own[1], kind="stable")
        inst, lab, y = own[0][order], own[1][order], y[order]
        for lo, hi in pairwise(ends):
            p = h @ w[lo:hi].T
            p -= p.max(axis=1, keepdims=True) if n <= most else top
            np.exp(p, out=p)
            p /= p.sum(axis=1, keepdims=True) if n <= most else total
            x, z = np.searchsorted(lab, (lo, hi))
            mine = inst[x:z], lab[x:z] - lo
            loss -= (y[x:z] * np.log(p[mine] + 1e-30)).sum() / b
            p[mine] -= y[x:z]
            p /= b
            back += p @ w[lo:hi]
            np.matmul(p.T, h, out=g[lo:hi])
        return back, g, loss

    def apply(self, grads: dict[str, tuple[np.ndarray, np.ndarray]]) -> None:
        conf, s = self.conf, self.at
        s.step += 1
        for name, (rows, g) in grads.items():
            descend(conf, s.step, getattr(s, name), s.moments[f"{name}.m"], s.moments[f"{name}.v"], rows, g)
        if self.tables is not None and self.clock is not None and "w_out" in grads:
            self.touched[grads["w_out"][0]] = True
            if self.clock.fires(s.step):
                moved, hashed = self.tables.moved, self.tables.hashed
                self.tables.refresh(s.w_out, np.flatnonzero(self.touched))
                self.refreshes.append({"iteration": s.step, "touched": int(self.touched.sum()), "moved": self.tables.moved - moved, "hash_operations": self.tables.hashed - hashed})
                self.touched[:] = False

    def step(self, feats, vals, offsets, labels, label_offsets) -> float:
        """One batch; its touched rows by layer stay in rows_touched. propagate after: the output layer moves before errors go through it, over the same active set."""
        grads, loss = self.gradients(feats, vals, offsets, labels, label_offsets)
        if self.conf.propagate == "after" and grads:
            self.apply({"w_out": grads["w_out"]})
            again, _ = self.gradients(feats, vals, offsets, labels, label_offsets, self.pairs_used)
            self.at.step -= 1
            self.apply({"w_in": again["w_in"]})
        else:
            self.apply(grads)
        self.rows_touched = {name: r for name, (r, _) in grads.items()}
        return loss

    def hits(self, feats, vals, offsets, labels, label_offsets) -> int:
        """How many instances have one of their own labels as the best of all (of equal logits the smallest label is the best).

        Labels go by in blocks, and an instance is left out once another label has beaten its own.
        """
        h, w = self.hidden(feats, vals, offsets), self.at.w_out
        inst = np.repeat(np.arange(len(h)), np.diff(label_offsets))
        z = np.einsum("pd,pd->p", w[labels], h[inst])
        order = np.lexsort((labels, -z, inst))
        first = order[np.flatnonzero(np.diff(inst[order], prepend=-1))]
        live, best, mine = inst[first], z[first], labels[first]
        order = np.argsort(labels, kind="stable")
        by_label, own = labels[order], inst[order]
        lo, size = 0, 256
        while lo < len(w) and len(live):
            hi = min(len(w), lo + size)
            z = h[live] @ w[lo:hi].T
            a, c = np.searchsorted(by_label, (lo, hi))
            row = np.minimum(np.searchsorted(live, own[a:c]), len(live) - 1)
            here = live[row] == own[a:c]
            z[row[here], by_label[a:c][here] - lo] = -np.inf
            at = z.argmax(axis=1)
            top = z[np.arange(len(live)), at]
            stay = (top < best) | ((top == best) & (at + lo > mine))
            live, best, mine = live[stay], best[stay], mine[stay]
            lo, size = hi, min(4096, 4 * size)
        return len(live)

    def predict(self, feats, vals, offsets, k: int, sampled: bool = False) -> tuple[np.ndarray, np.ndarray]:
        """The k best labels of each instance and their logits; sampled: among active labels alone (-1 where there are fewer)."""
        h = self.hidden(feats, vals, offsets)
        b = len(h)
        if sampled and self.tables is not None:  # the retrieved pairs alone are ranked
            none = np.zeros(0, dtype=np.int64)
            inst, lab, _ = choose(self.conf, self.tables, h, self.at.w_out, (none, none), 0, None, False)
            z = np.einsum("pd,pd->p", self.at.w_out[lab], h[inst])
            order = np.lexsort((lab, -z, inst))
            inst, lab, z = inst[order], lab[order], z[order]
            rank = np.arange(len(inst)) - np.searchsorted(inst, inst)
            top, value = np.full((b, k), -1, dtype=np.int64), np.full((b, k), -np.inf, dtype=np.float32)
            near = rank < k
            top[inst[near], rank[near]], value[inst[near], rank[near]] = lab[near], z[near]
            return top, value
        z = h @ self.at.w_out.T
        k = min(k, z.shape[1])
        top = np.argpartition(-z, k - 1, axis=1)[:, :k]
        value = np.take_along_axis(z, top, axis=1)
        order = np.argsort(-value, axis=1, kind="stable")
        return np.take_along_axis(top, order, axis=1), np.take_along_axis(value, order, axis=1)
