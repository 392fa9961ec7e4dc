import numpy as np
import pytest

from bucketnet.plans.deep import DeepNet, LayerConf


def data(n=300, dims=40, labels=6, seed=0):
    rng = np.random.default_rng(seed)
    y = rng.integers(0, labels, n)
    x = (rng.random((n, dims)) < 0.1).astype(np.float32)
    x[np.arange(n), y] += 2
    return x, y


def test_gradient_by_differences():
    net = DeepNet(10, [LayerConf(7), LayerConf(5), LayerConf(4)], dtype=np.float64)
    x, y = data(6, 10, 4)
    x = x.astype(np.float64)
    grads, _ = net.gradients(x, y)
    for i, (rows, g) in enumerate(grads):
        for a in range(0, len(rows), 2):
            for b in range(0, g.shape[1], 3):
                loss = []
                for s in (1e-5, -1e-5):
                    net.w[i][rows[a], b] += s
                    loss.append(net.gradients(x, y)[1])
                    net.w[i][rows[a], b] -= s
                assert abs((loss[0] - loss[1]) / 2e-5 - g[a, b]) < 1e-5


@pytest.mark.parametrize("hashed", [(False, False, False), (False, True, True), (True, True, True), (False, False, True)])
def test_any_subset_of_layers_can_be_hashed(hashed):
    layers = [LayerConf(n, h, k=2, tables=8, beta=b) for n, h, b in zip((32, 24, 6), hashed, (16, 12, 4), strict=True)]
    net = DeepNet(40, layers, rate=1e-2)
    x, y = data()
    for i in range(150):
        pick = np.random.default_rng(i).choice(len(x), 64, replace=False)
        net.step(x[pick], y[pick])
    assert (net.predict(x) == y).mean() > 0.8


def test_inactive_units_are_not_touched():
    net = DeepNet(40, [LayerConf(30), LayerConf(50, True, k=3, tables=4, beta=5)], rate=1e-2)
    x, y = data(labels=30, n=4)
    before = net.w[1].copy()
    active = set(net.forward(x, (np.arange(4), y))[1][-1][1].tolist())
    net.step(x, y)
    assert set(np.flatnonzero((net.w[1] != before).any(axis=1)).tolist()) <= active
