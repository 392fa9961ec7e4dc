from dataclasses import replace

import numpy as np
import pytest

from bucketnet.plans.kernel import Functions, NetConf, Snapshot, Tables, Trainer, choose, choose_block

CONF = NetConf(30, 6, 12, strategy="dense", rate=0.01, batch=8)


def batch(seed=0, b=5, dims=30, labels=12):
    rng = np.random.default_rng(seed)
    n = rng.integers(1, 6, b)
    off = np.concatenate([[0], np.cumsum(n)])
    feats = np.concatenate([rng.choice(dims, k, replace=False) for k in n])
    vals = rng.random(len(feats)).astype(np.float32)
    return feats, vals, off, rng.integers(0, labels, b), np.arange(b + 1)


def loss_of(conf, snap, data):
    return Trainer(conf, snap).gradients(*data)[1]


def test_gradient_by_differences():
    snap, data = Snapshot.start(CONF), batch()
    snap.w_in, snap.w_out = snap.w_in.astype(np.float64), snap.w_out.astype(np.float64)
    grads, _ = Trainer(CONF, snap).gradients(*data)
    for name in ("w_in", "w_out"):
        rows, g = grads[name]
        for i in range(0, len(rows), 3):
            for j in range(0, 6, 2):
                up, down = snap.copy(), snap.copy()
                getattr(up, name)[rows[i], j] += 1e-3
                getattr(down, name)[rows[i], j] -= 1e-3
                d = (loss_of(CONF, up, data) - loss_of(CONF, down, data)) / 2e-3
                assert abs(d - g[i, j]) < 2e-3


@pytest.mark.parametrize("change", [{"strategy": "static", "beta": 12}, {"strategy": "exact_topk", "beta": 12}, {"strategy": "topk", "k": 1, "tables": 40, "beta": 12}, {"strategy": "static", "beta": 12, "correct": True}])
def test_all_active_is_dense(change):
    """With every label active, the sparse step is the dense one."""
    data = batch(1)
    dense, _ = Trainer(CONF, Snapshot.start(CONF)).gradients(*data)
    conf = replace(CONF, **change)
    sparse, _ = Trainer(conf, Snapshot.start(conf)).gradients(*data)
    if change["strategy"] == "topk":
        assert len(sparse["w_out"][0]) >= 11
        return
    for name in dense:
        full = np.zeros_like(getattr(Snapshot.start(CONF), name))
        full[sparse[name][0]] = sparse[name][1]
        want = np.zeros_like(full)
        want[dense[name][0]] = dense[name][1]
        assert np.allclose(full, want, atol=1e-5)


def test_strategies_against_plain_loops():
    rng = np.random.default_rng(2)
    w, h = rng.normal(size=(200, 8)).astype(np.float32), rng.normal(size=(20, 8)).astype(np.float32)
    none = np.zeros(0, np.int64)
    conf = NetConf(1, 8, 200, strategy="union", k=3, tables=5, beta=15, threshold=2)
    t = Tables(conf, w)
    cw, ch = t.code, t.functions(h)
    freq = (cw[None] == ch[:, None]).sum(axis=2)
    pairs = lambda s: set(zip(*[x.tolist() for x in choose(replace(conf, strategy=s), t, h, w, (none, none), 3, None, False)[:2]], strict=True))
    assert pairs("union") == set(zip(*np.nonzero(freq > 0), strict=True))
    assert pairs("threshold") == set(zip(*np.nonzero(freq >= 2), strict=True))
    assert pairs("intersect") == set(zip(*np.nonzero(freq == 5), strict=True))
    top = pairs("topk")
    for i in range(20):
        mine = [j for a, j in top if a == i]
        have = (freq[i] > 0).sum()
        assert len(mine) == min(15, have)
        if mine:
            assert min(freq[i, mine]) >= np.sort(freq[i])[::-1][min(15, have) - 1]
    for i in range(20):
        n = sum(a == i for a, _ in pairs("vanilla"))
        assert n >= min(15, (freq[i] > 0).sum())


def test_refresh_touched_only_is_complete():
    rng = np.random.default_rng(3)
    w = rng.normal(size=(50, 8)).astype(np.float32)
    conf = NetConf(1, 8, 50, k=3, tables=4)
    t = Tables(conf, w.copy())
    w2 = w.copy()
    w2[[3, 7]] += rng.normal(size=(2, 8)).astype(np.float32)
    t.refresh(w2, np.array([3, 7]))
    fresh = Tables(conf, w2)
    assert (t.code == fresh.code).mean() > 0.99
    assert set(zip(t.keys.tolist(), t.ids.tolist(), strict=True)) == {(int(t.code[i, j]) + j * 8, i) for i in range(50) for j in range(4)}
    before = t.moved
    t.refresh(w2, np.arange(50))
    assert t.moved == before


@pytest.mark.parametrize("family", ["simhash", "wta", "dwta", "minhash"])
@pytest.mark.parametrize("change", [{}, {"cap": 5, "policy": "reservoir"}, {"cap": 5, "policy": "fifo"}, {"incremental": False}])
def test_moved_tables_are_new_tables(family, change):
    """After any refreshes entries stand where a sort of all of them would put them."""
    rng = np.random.default_rng(5)
    w = rng.normal(size=(80, 16)).astype(np.float32)
    conf = NetConf(1, 16, 80, k=2, tables=3, family=family, **change)
    t = Tables(conf, w.copy())
    for _ in range(6):
        touched = np.unique(rng.integers(0, 80, 20))
        w[touched] += rng.normal(0, 0.6, (len(touched), 16)).astype(np.float32)
        t.refresh(w, touched)
        entry, keys, ids = t.entry.copy(), t.keys.copy(), t.ids.copy()
        order = np.argsort(entry, kind="stable")
        assert (entry[t.order] == entry[order]).all()
        t._bound()
        assert (t.keys == keys).all() and (t.ids == ids).all()
        assert (t.code == t.functions(w)).mean() > 0.99
    assert t.moved > 0
    if "cap" in change:
        assert np.unique(t.keys, return_counts=True)[1].max() <= 5


def test_last_inserted_stay_in_a_fifo_bucket():
    conf = NetConf(1, 4, 10, k=1, tables=1, cap=3, policy="fifo")
    w = np.ones((10, 4), dtype=np.float32)
    t = Tables(conf, w.copy())
    assert sorted(t.ids.tolist()) == [7, 8, 9]
    there = w.copy()
    there[2] *= -1
    t.refresh(there, np.array([2]))
    t.refresh(w, np.array([2]))  # back again: the last to come
    assert 2 in t.ids.tolist() or t.moved == 0


def test_dwta_borrows_from_filled_bins():
    conf = NetConf(1, 64, 5, k=2, tables=8, family="dwta", m=4)
    f = Functions(conf)
    x = np.zeros((3, 64), dtype=np.float32)
    x[0, :5], x[1, 7] = [3, 1, 2, 5, 4], 1
    s = f.symbols(x)
    for i in (0, 1):
        seen = x[i][f.bins]
        filled = {b for b in range(16) if seen[b].any()}
        for b in range(16):
            src = b if b in filled else min(filled, key=lambda y, b=b: (y - b) * int(f.unit[b]) % 16) if filled else None
            assert src is None or s[i, b] == seen[src].argmax()
    assert (s[2] == 0).all()


def test_sampled_inference_ranks_retrieved_pairs():
    conf = replace(CONF, strategy="union", k=2, tables=4)
    tr = Trainer(conf, Snapshot.start(conf))
    data = batch(3)
    top, value = tr.predict(*data[:3], 4, True)
    h = tr.hidden(*data[:3])
    none = np.zeros(0, np.int64)
    inst, lab, _ = choose(conf, tr.tables, h, tr.at.w_out, (none, none), 0, None, False)
    for i in range(len(h)):
        mine = sorted(lab[inst == i].tolist(), key=lambda x: -float(tr.at.w_out[x] @ h[i]))[:4]
        assert top[i][top[i] >= 0].tolist() == mine


def test_propagate_after_uses_one_active_set():
    conf = replace(CONF, strategy="vanilla", k=2, tables=3, beta=4, propagate="after", refresh="every")
    tr = Trainer(conf, Snapshot.start(conf))
    tr.step(*batch(2))
    assert tr.instances == 5 and tr.at.step == 1


@pytest.mark.parametrize("policy", ["reservoir", "fifo"])
def test_buckets_are_bounded(policy):
    conf = NetConf(1, 4, 100, k=1, tables=3, cap=7, policy=policy)
    t = Tables(conf, np.ones((100, 4), dtype=np.float32))
    assert np.unique(t.keys, return_counts=True)[1].max() == 7
    if policy == "fifo":
        assert set(t.ids.tolist()) == set(range(93, 100))


def test_lazy_adam_leaves_untouched_rows():
    conf = replace(CONF, strategy="static", beta=2, force_labels=False)
    snap = Snapshot.start(conf)
    before = snap.w_out.copy()
    tr = Trainer(conf, snap)
    tr.step(*batch(4))
    moved = np.flatnonzero((snap.w_out != before).any(axis=1))
    assert len(moved) <= 2
    dense = Trainer(replace(conf, lazy=False), Snapshot.start(conf))
    dense.at.moments["w_out.m"] += 1.0
    before = dense.at.w_out.copy()
    dense.step(*batch(4))
    assert (dense.at.w_out != before).any(axis=1).all()


@pytest.mark.parametrize("change", [{"propagate": "after"}, {"optimizer": "sgd"}, {"strategy": "dropout"}, {"strategy": "vanilla", "k": 2, "tables": 3, "beta": 4}])
def test_options_run(change):
    conf = replace(CONF, **change)
    tr = Trainer(conf, Snapshot.start(conf))
    assert np.isfinite([tr.step(*batch(i)) for i in range(5)]).all()
    assert conf.legacy().refresh == "every"


def test_loss_falls():
    tr = Trainer(replace(CONF, rate=0.05), Snapshot.start(CONF))
    data = batch(5)
    losses = [tr.step(*data) for _ in range(60)]
    assert losses[-1] < losses[0] / 3


@pytest.mark.parametrize("change", [
    {"strategy": "static", "beta": 7}, {"strategy": "static", "beta": 7, "weighted": True, "correct": True}, {"strategy": "static", "beta": 5, "force_labels": False},
    {"strategy": "dropout"}, {"strategy": "dropout", "dropout": 0.95, "force_labels": False},
])
def test_a_block_is_the_pairs_of_its_strategy(change):
    """Static sampling and dropout as a masked product: the sets of choose, none of which becomes a pair with its own row."""
    conf = NetConf(50, 6, 40, k=2, tables=4, batch=8, **change)
    rng = np.random.default_rng(3)
    own = np.repeat(np.arange(8), 2), rng.integers(0, 40, 16)
    weights = rng.integers(1, 9, 40).astype(float)
    w = rng.normal(size=(40, 6)).astype(np.float32)
    inst, lab, incl = choose(conf, None, np.zeros((8, 6), np.float32), w, own, 4, weights, True)
    cols, mask, again = choose_block(conf, 8, own, 4, weights)
    i, at = np.nonzero(mask)
    assert np.array_equal(inst, i) and np.array_equal(lab, np.arange(40)[cols][at])
    assert (incl is None and again is None) or np.array_equal(incl, again)


def test_hits_are_those_of_all_logits():
    rng = np.random.default_rng(1)
    conf = NetConf(30, 4, 3000, strategy="dense")
    tr = Trainer(conf, Snapshot.start(conf))
    tr.at.w_out[2000] = tr.at.w_out[5]  # two best labels: the smaller counts
    off = np.arange(0, 601, 3)
    feats, vals = rng.integers(0, 30, 600), rng.random(600).astype(np.float32)
    vals[:30] = 0  # no hidden unit lives: all logits are equal
    h = tr.hidden(feats, vals, off)
    z = h @ tr.at.w_out.T
    best = z.argmax(axis=1)
    own = np.where(np.arange(200) % 3 == 0, best, rng.integers(0, 3000, 200))
    own[:2], own[3] = 0, 2999
    labels, lab_off = np.stack([own, (own + 7) % 3000], axis=1).ravel(), np.arange(0, 401, 2)
    want = sum(b in (a, (a + 7) % 3000) for a, b in zip(own, best, strict=True))
    assert tr.hits(feats, vals, off, labels, lab_off) == want
    assert tr.hits(feats[:0], vals[:0], np.zeros(1, np.int64), labels[:0], np.zeros(1, np.int64)) == 0


def test_long_instances_are_gathered_in_blocks(monkeypatch):
    """Hidden sums and input gradients are the same by blocks, and a block bounds what is held, however long the instances are."""
    import tracemalloc

    from bucketnet.plans import kernel

    rng = np.random.default_rng(4)
    conf = NetConf(2000, 16, 4, strategy="dense")
    n = np.array([0, 1500, 3, 0, 2000, *[400] * 200, 0])
    off = np.concatenate([[0], np.cumsum(n)])
    feats = np.concatenate([np.sort(rng.choice(2000, k, replace=False)) for k in n])
    vals, labels = rng.random(len(feats)).astype(np.float32), rng.integers(0, 4, len(n))
    got = []
    for most in (1 << 30, 16 * 2500, 16):
        monkeypatch.setattr(kernel, "GATHERED", most)
        t = Trainer(conf, Snapshot.start(conf))
        tracemalloc.start()
        h = t.hidden(feats, vals, off)
        peak = tracemalloc.get_traced_memory()[1]
        tracemalloc.stop()
        rows, g = t.gradients(feats, vals, off, labels, np.arange(len(n) + 1))[0]["w_in"]
        got.append((h, rows, g))
        assert (peak < 2**20) == (most < 1 << 30)
    for x in got[1:]:
        assert all(np.array_equal(a, b) for a, b in zip(x, got[0], strict=True))
    plain = np.stack([(Snapshot.start(conf).w_in[feats[a:b]] * vals[a:b, None]).sum(axis=0) for a, b in zip(off, off[1:], strict=False)])
    assert np.allclose(got[0][0], np.maximum(plain, 0), atol=1e-3)


def test_a_large_net_is_kept_in_files():
    """Weights, moments and tables of many labels are mapped; what is made beside them is small, and the codes are those of the whole product."""
    import tracemalloc

    conf = NetConf(64, 16, 200_000, strategy="topk", k=12, tables=20, n0=1, beta=50)
    rng = np.random.default_rng(conf.seed)
    whole = [rng.normal(0, 0.25, (n, 16)).astype(np.float32) for n in (64, 200_000)]
    projections = whole[1] @ Functions(conf).directions
    tracemalloc.start()
    try:
        tr = Trainer(replace(conf, batch=8), Snapshot.start(conf))
        peak = tracemalloc.get_traced_memory()[1]
    finally:
        tracemalloc.stop()
    assert peak < 160 << 20  # the projections alone are 192 MB, their bits as numbers were 384 MB
    assert np.array_equal(tr.at.w_in, whole[0]) and np.array_equal(tr.at.w_out, whole[1])
    assert (tr.tables.code == ((projections >= 0).reshape(-1, 20, 12) @ (1 << np.arange(12)))).mean() > 0.9999


def test_dense_blocks_are_the_whole_softmax(monkeypatch):
    """Blocks of labels give the gradients and the loss of all labels at once, and no product is larger than a block's."""
    from bucketnet.plans import kernel

    conf = replace(CONF, strategy="dense")
    data, got = batch(7), []
    for most in (1 << 20, 12):
        monkeypatch.setattr(kernel, "LOGITS", most)
        grads, loss = Trainer(conf, Snapshot.start(conf)).gradients(*data)
        got.append((loss, *[x for name in ("w_out", "w_in") for x in grads[name]]))
    for a, b in zip(*got, strict=True):
        assert np.allclose(a, b, atol=1e-6)


def test_codes_from_scratch_are_those_of_kept_projections(monkeypatch):
    """Tables too large to keep their projections hash touched labels anew, with the same codes."""
    rng = np.random.default_rng(3)
    w = rng.normal(size=(60, 8)).astype(np.float32)
    conf = NetConf(1, 8, 60, k=3, tables=4)
    kept = Tables(conf, w.copy())
    monkeypatch.setattr(Tables, "MEMO", 0)
    anew = Tables(conf, w.copy())
    assert anew.projections is None and kept.projections is not None
    for _ in range(4):
        touched = np.unique(rng.integers(0, 60, 20))
        w[touched] += rng.normal(0, 0.5, (len(touched), 8)).astype(np.float32)
        for t in (kept, anew):
            t.refresh(w, touched)
        assert np.array_equal(kept.code, anew.code) and np.array_equal(kept.entry, anew.entry) and kept.moved == anew.moved
