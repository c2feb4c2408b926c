"""The value network in numpy: a ReLU perceptron with the three losses and Adam."""

from __future__ import annotations

from typing import NamedTuple

import numpy as np


class Batch(NamedTuple):
    """n-step transitions. ret: discounted rewards of the steps taken; steps: how many; done: no state follows;
    mask2: actions valid in the later state; mask: in the earlier one; demo: rows to imitate; weight: importance."""

    state: np.ndarray
    action: np.ndarray
    ret: np.ndarray
    steps: np.ndarray
    state2: np.ndarray
    done: np.ndarray
    mask: np.ndarray
    mask2: np.ndarray
    demo: np.ndarray
    weight: np.ndarray


class QNet:
    def __init__(self, sizes: tuple[int, ...], seed: int = 42):
        rng = np.random.default_rng(seed)
        self.params: list[np.ndarray] = []
        for a, b in zip(sizes[:-1], sizes[1:], strict=True):
            self.params += [rng.normal(0, np.sqrt(2 / a), (a, b)).astype(np.float32), np.zeros(b, np.float32)]
        self.moments = [(np.zeros_like(p), np.zeros_like(p)) for p in self.params]
        self.time = 0

    def forward(self, x: np.ndarray, keep: list | None = None) -> np.ndarray:
        x = np.atleast_2d(x)
        last = len(self.params) // 2 - 1
        for k in range(last + 1):
            if keep is not None:
                keep.append(x)
            x = x @ self.params[2 * k] + self.params[2 * k + 1]
            if k < last:
                x = np.maximum(x, 0)
        return x

    def backward(self, kept: list[np.ndarray], grad: np.ndarray) -> list[np.ndarray]:
        out: list[np.ndarray] = []
        for k in range(len(kept) - 1, -1, -1):
            out[:0] = [kept[k].T @ grad, grad.sum(axis=0)]
            if k:
                grad = (grad @ self.params[2 * k].T) * (kept[k] > 0)
        return out

    def copy_from(self, other: QNet) -> None:
        self.params = [p.copy() for p in other.params]

    def adam(self, grads: list[np.ndarray], rate: float, clip: float) -> None:
        norm = np.sqrt(sum(float((g * g).sum()) for g in grads))
        scale = min(1.0, clip / (norm + 1e-12))
        self.time += 1
        for k, g in enumerate(grads):
            m, v = self.moments[k]
            m += 0.1 * (g * scale - m)
            v += 0.001 * ((g * scale) ** 2 - v)
            self.params[k] -= rate * (m / (1 - 0.9**self.time)) / (np.sqrt(v / (1 - 0.999**self.time)) + 1e-8)

    def save(self, path: str) -> None:
        np.savez(path, *self.params)

    @staticmethod
    def load(path: str) -> QNet:
        net = QNet((1, 1))
        with np.load(path) as f:
            net.params = [f[k] for k in f.files]
        net.moments = [(np.zeros_like(p), np.zeros_like(p)) for p in net.params]
        return net


def _best(q: np.ndarray, mask: np.ndarray) -> np.ndarray:
    return np.where(mask, q, -np.inf).argmax(axis=1)


def td_targets(batch: Batch, online: QNet, target: QNet, discount: float, bootstrap: str = "max_target", discount_bootstrap: bool = True) -> np.ndarray:
    """Rewards of the steps taken plus the value of the state after them."""
    later = target.forward(batch.state2)
    chooser = online.forward(batch.state2) if bootstrap == "double" else later
    value = later[np.arange(len(later)), _best(chooser, batch.mask2)]
    factor = discount**batch.steps if discount_bootstrap else 1.0
    alive = ~batch.done & batch.mask2.any(axis=1)
    return batch.ret + np.where(alive, factor * np.where(alive, value, 0), 0)


def td_loss(q: np.ndarray, batch: Batch, targets: np.ndarray) -> tuple[float, np.ndarray, np.ndarray]:
    """(weighted mean squared error, gradient by q, errors)."""
    rows = np.arange(len(q))
    error = q[rows, batch.action] - targets
    grad = np.zeros_like(q)
    grad[rows, batch.action] = 2 * batch.weight * error / len(q)
    return float((batch.weight * error**2).mean()), grad, error


def margin_loss(q: np.ndarray, batch: Batch, margin: float) -> tuple[float, np.ndarray]:
    """Zero where the imitated action leads every other valid one by the margin; demo rows only."""
    rows = np.arange(len(q))
    lifted = np.where(batch.mask, q + margin, -np.inf)
    lifted[rows, batch.action] = q[rows, batch.action]
    top = lifted.argmax(axis=1)
    loss = np.where(batch.demo, lifted[rows, top] - q[rows, batch.action], 0)
    grad = np.zeros_like(q)
    on = batch.demo & (top != batch.action)
    np.add.at(grad, (rows[on], top[on]), 1 / len(q))
    np.add.at(grad, (rows[on], batch.action[on]), -1 / len(q))
    return float(loss.mean()), grad


def l2(params: list[np.ndarray]) -> float:
    return float(sum((p.astype(np.float64) ** 2).sum() for p in params))


def learn(online: QNet, target: QNet, batch: Batch, cfg) -> tuple[dict[str, float], np.ndarray]:
    """One update; returns the losses and the errors that refresh priorities."""
    kept: list[np.ndarray] = []
    q = online.forward(batch.state, kept)
    targets = td_targets(batch, online, target, cfg.discount, cfg.bootstrap, cfg.discount_bootstrap)
    td, g1, error = td_loss(q, batch, targets)
    mg, g2 = margin_loss(q, batch, cfg.margin)
    a, b, c = cfg.lambdas
    grads = online.backward(kept, (a * g1 + b * g2).astype(np.float32))
    grads = [g + 2 * c * p for g, p in zip(grads, online.params, strict=True)]
    reg = l2(online.params)
    online.adam(grads, cfg.rate, cfg.clip)
    return {"td": td, "margin": mg, "l2": reg, "total": a * td + b * mg + c * reg}, error


def tabular_update(q: dict, state, action: int, reward: float, state2, valid2: list[int], alpha: float, discount: float) -> float:
    """Q-learning on a table keyed by (state, action); the reference learner for toy grids."""
    future = max((q.get((state2, a), 0.0) for a in valid2), default=0.0)
    old = q.get((state, action), 0.0)
    q[state, action] = old + alpha * (reward + discount * future - old)
    return q[state, action]
