"""Pair classifiers in numpy: the twin network and the families it is compared with."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np


def he_normal(rng: np.random.Generator, n_in: int, n_out: int) -> np.ndarray:
    return rng.standard_normal((n_in, n_out)) * np.sqrt(2.0 / n_in)


@dataclass
class Network:
    """Rectified layers under a logistic unit.

    With ``twin`` the layers of ``trunk`` run on each half of the input with the same weights and their
    outputs are laid end to end; otherwise they run on the whole input.  ``comparator`` follows.
    """

    inputs: int = 24
    trunk: tuple[int, ...] = (200, 200, 200, 200)
    comparator: tuple[int, ...] = (200, 100, 50, 25)
    twin: bool = True
    dropout: float = 0.2
    seed: int = 1
    weights: list[tuple[np.ndarray, np.ndarray]] = field(default_factory=list)

    def __post_init__(self) -> None:
        if not self.weights:
            rng = np.random.default_rng(self.seed)
            self.weights = [(he_normal(rng, a, b), np.zeros(b)) for a, b in self.shapes()]

    def shapes(self) -> list[tuple[int, int]]:
        width, out = self.inputs if self.twin else 2 * self.inputs, []
        for w in self.trunk:
            out.append((width, w))
            width = w
        width = 2 * width if self.twin else width
        for w in (*self.comparator, 1):
            out.append((width, w))
            width = w
        return out

    def count_params(self) -> int:
        return sum(a * b + b for a, b in self.shapes())

    def forward(self, x: np.ndarray, masks: dict[int, np.ndarray] | None = None) -> tuple[np.ndarray, list[np.ndarray]]:
        """Probabilities and the inputs of every layer."""
        seen, n = [], len(self.trunk)
        h = np.concatenate([x[:, : self.inputs], x[:, self.inputs :]]) if self.twin else x
        for i, (w, b) in enumerate(self.weights):
            if i == n and self.twin:
                h = np.concatenate([h[: len(x)], h[len(x) :]], axis=1)
            seen.append(h)
            h = h @ w + b
            if i < len(self.weights) - 1:
                h = np.maximum(h, 0)
                if masks and i in masks:
                    h = h * masks[i]
        return 1 / (1 + np.exp(-np.clip(h[:, 0], -60, 60))), seen

    def draw_masks(self, rows: int, rng: np.random.Generator) -> dict[int, np.ndarray]:
        """Inverted dropout on every other hidden layer."""
        out = {}
        for i, (_, width) in enumerate(self.shapes()[:-1]):
            if self.dropout and i % 2:
                n = 2 * rows if self.twin and i < len(self.trunk) else rows
                out[i] = (rng.random((n, width)) >= self.dropout) / (1 - self.dropout)
        return out

    def gradients(self, x: np.ndarray, y: np.ndarray, masks: dict[int, np.ndarray] | None = None) -> tuple[float, list[tuple[np.ndarray, np.ndarray]]]:
        p, seen = self.forward(x, masks)
        d = ((p - y) / len(x))[:, None]
        out: list[tuple[np.ndarray, np.ndarray]] = []
        for i in range(len(self.weights) - 1, -1, -1):
            w, _ = self.weights[i]
            out.append((seen[i].T @ d, d.sum(axis=0)))
            if i == 0:
                break
            d = d @ w.T
            if i == len(self.trunk) and self.twin:
                d = np.concatenate([d[:, : d.shape[1] // 2], d[:, d.shape[1] // 2 :]])
                above = np.concatenate([seen[i][:, : seen[i].shape[1] // 2], seen[i][:, seen[i].shape[1] // 2 :]])
            else:
                above = seen[i]
            d = d * (above > 0)
            if masks and i - 1 in masks:
                d = d * masks[i - 1]
        return cross_entropy(p, y), out[::-1]

    def predict(self, x: np.ndarray, symmetry: str = "concat") -> np.ndarray:
        if self.twin and len(x):
            return self._twin(x, symmetry)
        p = self.forward(x)[0]
        if symmetry == "average":
            p = (p + self.forward(np.concatenate([x[:, self.inputs :], x[:, : self.inputs]], axis=1))[0]) / 2
        return p

    def _twin(self, x: np.ndarray, symmetry: str) -> np.ndarray:
        """What ``forward`` says, with each distinct half of the rows taken through the trunk, and through its part of the
        first layer after it, once for all its pairs and both orders."""
        n, k = len(self.trunk), len(x)
        halves = np.ascontiguousarray(np.concatenate([x[:, : self.inputs], x[:, self.inputs :]]))
        _, one, at = np.unique(halves.view(f"V{halves.itemsize * halves.shape[1]}").ravel(), return_index=True, return_inverse=True)
        h = halves[one]
        for w, b in self.weights[:n]:
            h = np.maximum(h @ w + b, 0)
        first, bias = self.weights[n]
        left, right = h @ first[: h.shape[1]], h @ first[h.shape[1] :]

        def rest(i: np.ndarray, j: np.ndarray) -> np.ndarray:
            z = left[i] + right[j] + bias
            for w, b in self.weights[n + 1 :]:
                z = np.maximum(z, 0) @ w + b
            return 1 / (1 + np.exp(-np.clip(z[:, 0], -60, 60)))

        p = rest(at[:k], at[k:])
        return (p + rest(at[k:], at[:k])) / 2 if symmetry == "average" else p


@dataclass
class Scaled:
    """A network with the scaling it was trained under, for rows of raw metrics: logarithm, then z-scores."""

    net: Network
    mean: list[float]
    std: list[float]

    def predict(self, x: np.ndarray, symmetry: str = "concat") -> np.ndarray:
        m, s = np.array([*self.mean, *self.mean]), np.array([v or 1.0 for v in (*self.std, *self.std)])
        return self.net.predict((np.log1p(x) - m) / s, symmetry)


def cross_entropy(p: np.ndarray, y: np.ndarray) -> float:
    p = np.clip(p, 1e-12, 1 - 1e-12)
    return float(-(y * np.log(p) + (1 - y) * np.log(1 - p)).mean())


def asymmetry(net: Network, x: np.ndarray) -> float:
    """Largest change of the score when the two halves swap."""
    swapped = np.concatenate([x[:, net.inputs :], x[:, : net.inputs]], axis=1)
    return float(np.abs(net.predict(x) - net.predict(swapped)).max(initial=0))


def logistic(inputs: int = 24, seed: int = 1) -> Network:
    return Network(inputs, (), (), twin=False, dropout=0, seed=seed)


def shallow(inputs: int = 24, width: int | None = None, seed: int = 1) -> Network:
    """One hidden layer, by default with about as many parameters as the twin network."""
    target = Network(inputs).count_params()
    return Network(inputs, (width or round((target - 1) / (2 * inputs + 2)),), (), twin=False, dropout=0, seed=seed)


def plain(inputs: int = 24, reading: str = "wide", seed: int = 1) -> Network:
    """Deep network without twins: trunk widths doubled (wide) or as in one twin (narrow)."""
    return Network(inputs, ({"wide": 400, "narrow": 200}[reading],) * 4, (200, 100, 50, 25), twin=False, seed=seed)


def siamese(inputs: int = 24, seed: int = 1) -> Network:
    return Network(inputs, seed=seed)


def fit(net: Network, x: np.ndarray, y: np.ndarray, valid: tuple[np.ndarray, np.ndarray] | None = None, lr: float = 1e-4, decay: float = 0.97, batch: int = 1000, epochs: int = 50, patience: int = 2, seed: int = 7, augment: bool = False) -> list[dict]:
    """Mini-batch SGD; the rate falls by 3 % an epoch; stops after ``patience`` epochs without a better
    validation loss.  Returns the log of the epochs.  ``augment`` trains on both orders of a pair."""
    if augment:
        x, y = np.concatenate([x, np.concatenate([x[:, net.inputs :], x[:, : net.inputs]], axis=1)]), np.concatenate([y, y])
    rng, log, best, bad = np.random.default_rng(seed), [], np.inf, 0
    for epoch in range(epochs):
        order = rng.permutation(len(x))
        for at in range(0, len(x), batch):
            pick = order[at : at + batch]
            _, grads = net.gradients(x[pick], y[pick], net.draw_masks(len(pick), rng))
            net.weights = [(w - lr * gw, b - lr * gb) for (w, b), (gw, gb) in zip(net.weights, grads, strict=True)]
        p = net.predict(x)
        row = {"epoch": epoch, "lr": lr, "train_loss": cross_entropy(p, y), "train_acc": float(((p > 0.5) == y).mean())}
        if valid is not None:
            q = net.predict(valid[0])
            row |= {"valid_loss": cross_entropy(q, valid[1]), "valid_acc": float(((q > 0.5) == valid[1]).mean())}
            bad = 0 if row["valid_loss"] < best else bad + 1
            best = min(best, row["valid_loss"])
        log.append(row)
        lr *= decay
        if valid is not None and bad >= patience:
            break
    return log
