"""A perceptron with two hidden layers and sigmoid outputs, in numpy: forward pass, soft focal loss, masked gradients, Adam."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

EPS = 1e-7


@dataclass(frozen=True)
class TrainConfig:
    hidden: tuple[int, int] = (512, 256)
    dropout: float = 0.2
    batch: int = 16
    rate: float = 1e-3
    decay: float = 1e-3
    alpha: float = 0.9
    gamma: float = 2.0
    epochs: int = 100
    patience: int = 10
    folds: int = 5
    loss: str = "focal"


def sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def focal(p: np.ndarray, y: np.ndarray, alpha: float, gamma: float) -> np.ndarray:
    p = np.clip(p, EPS, 1 - EPS)
    return alpha * y * (1 - p) ** gamma * -np.log(p) + (1 - alpha) * (1 - y) * p**gamma * -np.log(1 - p)


def bce(p: np.ndarray, y: np.ndarray) -> np.ndarray:
    p = np.clip(p, EPS, 1 - EPS)
    return -(y * np.log(p) + (1 - y) * np.log(1 - p))


def focal_slope(p: np.ndarray, y: np.ndarray, alpha: float, gamma: float) -> np.ndarray:
    """Derivative of the focal loss by the logit."""
    p = np.clip(p, EPS, 1 - EPS)
    up = gamma * p * (1 - p) ** gamma * np.log(p) - (1 - p) ** (gamma + 1)
    down = p ** (gamma + 1) - gamma * p**gamma * (1 - p) * np.log(1 - p)
    return alpha * y * up + (1 - alpha) * (1 - y) * down


def masked_mean(loss: np.ndarray, mask: np.ndarray) -> float:
    """Mean over a row's own cells, then over rows."""
    return float(((loss * mask).sum(1) / mask.sum(1)).mean())


class Adam:
    """Updates parameters in place; the decay is added to the gradient."""

    def __init__(self, config: TrainConfig):
        self.config, self.n, self.m, self.v = config, 0, None, None

    def step(self, params: list[np.ndarray], slopes: list[np.ndarray]) -> None:
        if self.m is None:
            self.m, self.v = [np.zeros_like(a) for a in params], [np.zeros_like(a) for a in params]
        self.n += 1
        for m, v, param, g in zip(self.m, self.v, params, slopes, strict=True):
            g = g + self.config.decay * param
            m += 0.1 * (g - m)
            v += 0.001 * (g * g - v)
            param -= self.config.rate * (m / (1 - 0.9**self.n)) / (np.sqrt(v / (1 - 0.999**self.n)) + 1e-8)


class Mlp:
    def __init__(self, dims: tuple[int, ...], seed: int = 0):
        rng = np.random.default_rng(seed)
        self.w = [rng.standard_normal((a, b)) * np.sqrt(2 / a) for a, b in zip(dims, dims[1:], strict=False)]
        self.b = [np.zeros(b) for b in dims[1:]]

    def forward(self, x: np.ndarray, cols: slice | np.ndarray = slice(None), drop: float = 0.0, rng=None) -> tuple[np.ndarray, list]:
        """(probabilities of the outputs ``cols``, what the backward pass needs). The head is cut before it is multiplied."""
        kept, h = [], x
        for w, b in zip(self.w[:-1], self.b[:-1], strict=True):
            z = h @ w + b
            a = np.maximum(z, 0)
            m = (rng.random(a.shape) >= drop) / (1 - drop) if drop and rng is not None else None
            kept.append((h, z, m))
            h = a * m if m is not None else a
        kept.append((h, None, None))
        return sigmoid(h @ self.w[-1][:, cols] + self.b[-1][cols]), kept

    def backward(self, slope: np.ndarray, kept: list) -> tuple[list[np.ndarray], list[np.ndarray]]:
        """Gradients given the loss's derivative by the output logits."""
        dw, db, delta = [None] * len(self.w), [None] * len(self.w), slope
        for k in range(len(self.w) - 1, -1, -1):
            dw[k], db[k] = kept[k][0].T @ delta, delta.sum(0)
            if k:
                delta = delta @ self.w[k].T
                _, z, m = kept[k - 1]
                delta = delta * (z > 0) * (m if m is not None else 1)
        return dw, db

    def gradients(self, x, y, mask, config: TrainConfig, rng=None):
        p, kept = self.forward(x, drop=config.dropout if rng is not None else 0.0, rng=rng)
        slope = focal_slope(p, y, config.alpha, config.gamma) if config.loss == "focal" else np.clip(p, EPS, 1 - EPS) - y
        return self.backward(slope * mask / mask.sum(1, keepdims=True) / len(x), kept)

    def loss(self, x, y, mask, config: TrainConfig) -> float:
        p = self.forward(x)[0]
        return masked_mean(focal(p, y, config.alpha, config.gamma) if config.loss == "focal" else bce(p, y), mask)

    def fit(self, x, y, mask, config: TrainConfig, seed: int = 0, held: tuple | None = None) -> Mlp:
        rng, adam = np.random.default_rng(seed), Adam(config)
        best, waited, saved = np.inf, 0, None
        for _ in range(config.epochs):
            order = rng.permutation(len(x))
            for i in range(0, len(x), config.batch):
                at = order[i : i + config.batch]
                dw, db = self.gradients(x[at], y[at], mask[at], config, rng)
                adam.step(self.w + self.b, dw + db)
            if held is not None:
                now = self.loss(*held, config)
                if now < best - 1e-5:
                    best, waited, saved = now, 0, ([a.copy() for a in self.w], [a.copy() for a in self.b])
                elif (waited := waited + 1) >= config.patience:
                    break
        if saved is not None:
            self.w, self.b = saved
        return self

    def to_bytes(self) -> bytes:
        return np.concatenate([a.ravel() for a in self.w + self.b]).astype("<f4").tobytes()

    @classmethod
    def from_bytes(cls, dims: tuple[int, ...], data: bytes) -> Mlp:
        out, flat, at = cls(dims), np.frombuffer(data, "<f4").astype(float), 0
        for group in (out.w, out.b):
            for k, a in enumerate(group):
                group[k] = flat[at : at + a.size].reshape(a.shape)
                at += a.size
        return out
