"""Mixture-density component: the distribution of a number given a category.

Data: column 0 the category's code, column 1 the number scaled to [-1, 1].
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np

from .losses import logit_gap, soft_cross_entropy, softmax
from .tensor import Tensor, exp, log, log_softmax, log_sum_exp, relu, square
from .training import Params

FLOOR = 1e-3
_HALF_LOG_2PI = 0.5 * np.log(2 * np.pi)


@dataclass(frozen=True)
class MixtureDensity:
    categories: int
    components: int = 10
    hidden: int = 64
    temperature: float = 2.0
    name: str = "mdn"

    def initial(self, rng: np.random.Generator) -> Params:
        h, k = self.hidden, self.components
        w = lambda a, b: rng.normal(0, np.sqrt(2 / a), (a, b))
        bias = np.concatenate([np.zeros(k), np.linspace(-0.9, 0.9, k), np.full(k, np.log(0.2))])
        return {"w1": w(self.categories, h), "b1": np.zeros(h), "w2": w(h, h), "b2": np.zeros(h), "w3": w(h, 3 * k) * 0.1, "b3": bias}

    def noise(self, rng: np.random.Generator, n: int) -> None:
        return None

    def heads(self, p: dict[str, Tensor], codes: np.ndarray) -> tuple[Tensor, Tensor, Tensor]:
        """Weight logits, means and deviations for each row."""
        x = Tensor(np.eye(self.categories)[np.clip(codes.astype(int), 0, self.categories - 1)])
        h = relu(relu(x @ p["w1"] + p["b1"]) @ p["w2"] + p["b2"])
        z, k = h @ p["w3"] + p["b3"], self.components
        return z[:, :k], z[:, k : 2 * k], exp(z[:, 2 * k :]) + FLOOR

    def _row_loss(self, p: dict[str, Tensor], data: np.ndarray) -> Tensor:
        w, m, s = self.heads(p, data[:, 0])
        y = data[:, 1:2]
        parts = log_softmax(w) - square((m - y) / s) * 0.5 - log(s) - _HALF_LOG_2PI
        return -log_sum_exp(parts)

    def loss(self, p: dict[str, Tensor], data: np.ndarray, noise=None) -> Tensor:
        return self._row_loss(p, data).mean()

    def row_loss(self, params: Params, data: np.ndarray) -> np.ndarray:
        return self._row_loss({k: Tensor(v) for k, v in params.items()}, data).value

    def imitation(self, p: dict[str, Tensor], teacher: Params, data: np.ndarray, noise=None) -> Tensor:
        """Tempered cross-entropy of the weights plus squared gaps of means and of deviations."""
        tw, tm, ts = (t.value for t in self.heads({k: Tensor(v) for k, v in teacher.items()}, data[:, 0]))
        w, m, s = self.heads(p, data[:, 0])
        return soft_cross_entropy(tw, w, self.temperature) + logit_gap(tm, m) + logit_gap(ts, s)

    def counted(self, data: np.ndarray, likely: np.ndarray, like: np.ndarray, teacher: Params | None = None) -> Callable[[dict[str, Tensor]], Tensor]:
        """The objective with ``likely`` as the weight of each row's loss and ``like`` as that of its imitation."""
        t, each = self.temperature, like[:, None]
        told = None if teacher is None or not like.any() else [x.value for x in self.heads({k: Tensor(v) for k, v in teacher.items()}, data[:, 0])]

        def value(p: dict[str, Tensor]) -> Tensor:
            out = (self._row_loss(p, data) * likely).sum()
            if told is None:
                return out
            w, m, s = self.heads(p, data[:, 0])
            soft = (log_softmax(w * (1 / t)) * (softmax(told[0], t) * each)).sum()
            return out - soft + (square(m - told[1]) * each).sum() + (square(s - told[2]) * each).sum()

        return value

    def table(self, params: Params) -> list[tuple[int, list[float], list[float], list[float]]]:
        """(category, omega, mu, sigma): the whole model, since its input is finite."""
        w, m, s = (t.value for t in self.heads({k: Tensor(v) for k, v in params.items()}, np.arange(self.categories)))
        w = np.exp(w - w.max(1, keepdims=True))
        w /= w.sum(1, keepdims=True)
        return [(i, w[i].tolist(), m[i].tolist(), s[i].tolist()) for i in range(self.categories)]

    def density(self, params: Params, category: int, y: np.ndarray) -> np.ndarray:
        data = np.column_stack([np.full(len(y), category), y])
        return np.exp(-self.row_loss(params, data))
