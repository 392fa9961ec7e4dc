"""Nets of any depth, each layer hashed or not: an inactive unit is 0, is not computed and gets no update.

Used like kernel.Trainer inside a task. A hashed layer has tables over its units' weight vectors; what it is given is
hashed with the same directions, the sparse input by its non-zeros alone.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from bucketnet.operators.index import Refresh
from bucketnet.plans.kernel import NetConf, Tables, _sum_rows, choose


@dataclass(frozen=True)
class LayerConf:
    """size units; hashed: which of them are active is asked of tables."""

    size: int
    hashed: bool = False
    strategy: str = "topk"
    k: int = 4
    tables: int = 10
    beta: int = 32


class DeepNet:
    """layers: hidden ones, and the output last. Weights of layer i are units x inputs."""

    def __init__(self, dims: int, layers: list[LayerConf], rate: float = 3e-3, seed: int = 11, n0: float = 50, decay: float = 0.1, dtype=np.float32):
        rng = np.random.default_rng(seed)
        sizes = [dims, *[x.size for x in layers]]
        self.layers, self.rate, self.step_no = layers, rate, 0
        self.w = [rng.normal(0, 1 / np.sqrt(layers[0].size if i == 0 else sizes[i]), (sizes[i + 1], sizes[i])).astype(dtype) for i in range(len(layers))]
        self.m, self.v = ([np.zeros_like(w) for w in self.w] for _ in range(2))
        self.confs = [NetConf(1, sizes[i], x.size, strategy=x.strategy, k=x.k, tables=x.tables, beta=x.beta, seed=seed + i) for i, x in enumerate(layers)]
        self.tables = [Tables(c, w) if x.hashed else None for c, w, x in zip(self.confs, self.w, layers, strict=True)]
        self.clock = Refresh("decay", n0, decay)
        self.touched = [np.zeros(x.size, dtype=bool) for x in layers]

    def _active(self, i: int, x: np.ndarray, own: tuple[np.ndarray, np.ndarray] | None) -> tuple[np.ndarray, np.ndarray]:
        """(instance, unit) pairs of layer i."""
        none = np.zeros(0, dtype=np.int64)
        if self.tables[i] is None:
            n = self.layers[i].size
            return np.repeat(np.arange(len(x)), n), np.tile(np.arange(n), len(x))
        inst, unit, _ = choose(self.confs[i], self.tables[i], x, self.w[i], own or (none, none), self.step_no, None, own is not None)
        return inst, unit

    def forward(self, x: np.ndarray, own: tuple[np.ndarray, np.ndarray] | None) -> tuple[list[np.ndarray], list[tuple[np.ndarray, np.ndarray]], np.ndarray]:
        """Inputs of each layer, active pairs of each layer, and the output's values at its pairs. x: a batch of inputs, rows of dims."""
        inputs, pairs = [], []
        for i in range(len(self.w)):
            inst, unit = self._active(i, x, own if i == len(self.w) - 1 else None)
            inputs.append(x)
            pairs.append((inst, unit))
            z = np.einsum("pd,pd->p", self.w[i][unit], x[inst])
            if i == len(self.w) - 1:
                return inputs, pairs, z
            x = np.zeros((len(x), self.layers[i].size), dtype=x.dtype)
            x[inst, unit] = np.maximum(z, 0)
        raise AssertionError

    def gradients(self, x: np.ndarray, labels: np.ndarray) -> tuple[list[tuple[np.ndarray, np.ndarray]], float]:
        """(units, gradient) of each layer over touched units, and the mean loss; a label per instance."""
        b = len(x)
        inputs, pairs, z = self.forward(x, (np.arange(b), labels))
        inst, unit = pairs[-1]
        at = np.flatnonzero(np.diff(inst, prepend=-1))
        size = np.diff(np.append(at, len(inst)))
        p = np.exp(z - np.repeat(np.maximum.reduceat(z, at), size))
        p = p / np.repeat(np.add.reduceat(p, at), size)
        mine = unit == labels[inst]
        loss = float(-np.log(p[mine] + 1e-30).sum() / b)
        delta = (p - mine) / b
        grads: list = [None] * len(self.w)
        for i in range(len(self.w) - 1, -1, -1):
            inst, unit = pairs[i]
            grads[i] = _sum_rows(delta[:, None] * inputs[i][inst], unit)
            if i:  # messages to active units below
                back = np.zeros_like(inputs[i])
                np.add.at(back, inst, delta[:, None] * self.w[i][unit])
                below, units = pairs[i - 1]
                delta = np.where(inputs[i][below, units] > 0, back[below, units], 0)
        return grads, loss

    def step(self, x: np.ndarray, labels: np.ndarray) -> float:
        grads, loss = self.gradients(x, labels)
        self.step_no += 1
        for i, (rows, g) in enumerate(grads):
            m, v = self.m[i], self.v[i]
            m[rows] = 0.9 * m[rows] + 0.1 * g
            v[rows] = 0.999 * v[rows] + 0.001 * g * g
            self.w[i][rows] -= self.rate * (m[rows] / (1 - 0.9**self.step_no)) / (np.sqrt(v[rows] / (1 - 0.999**self.step_no)) + 1e-8)
            self.touched[i][rows] = True
        if self.clock.fires(self.step_no):
            for i, t in enumerate(self.tables):
                if t is not None:
                    t.refresh(self.w[i], np.flatnonzero(self.touched[i]))
                self.touched[i][:] = False
        return loss

    def predict(self, x: np.ndarray) -> np.ndarray:
        """The best label of each instance over all units of all layers."""
        for i, w in enumerate(self.w):
            z = x @ w.T
            x = np.maximum(z, 0) if i < len(self.w) - 1 else z
        return x.argmax(axis=1)
