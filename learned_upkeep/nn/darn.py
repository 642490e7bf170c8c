"""Autoregressive component: the joint distribution of codes as a chain of conditionals by a masked network."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from functools import cached_property

import numpy as np

from .losses import soft_cross_entropy, softmax
from .tensor import Tensor, cross_entropy, log_softmax, masked_linear, relu
from .training import Params


@dataclass(frozen=True)
class MaskedAutoregressive:
    sizes: tuple[int, ...]
    hidden: int = 64
    temperature: float = 2.0
    reduction: str = "mean"
    name: str = "darn"

    @cached_property
    def starts(self) -> list[int]:
        return [0, *np.cumsum(self.sizes).tolist()]

    @cached_property
    def masks(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Unit degrees: an input of column i reaches units of degree above i, and those reach columns from their degree on."""
        m = len(self.sizes)
        column = np.repeat(np.arange(m), self.sizes)
        degree = np.arange(self.hidden) % max(1, m - 1) + 1
        return (column[:, None] < degree[None, :]) * 1.0, (degree[:, None] <= degree[None, :]) * 1.0, (degree[:, None] <= column[None, :]) * 1.0

    def initial(self, rng: np.random.Generator) -> Params:
        d, h = sum(self.sizes), self.hidden
        w = lambda a, b: rng.normal(0, np.sqrt(2 / a), (a, b))
        return {"w1": w(d, h) * np.sqrt(d / len(self.sizes) / 2), "b1": np.zeros(h), "w2": w(h, h), "b2": np.zeros(h), "w3": w(h, d) * 0.1, "b3": np.zeros(d)}

    def noise(self, rng: np.random.Generator, n: int) -> None:
        return None

    def encode(self, data: np.ndarray) -> np.ndarray:
        x = np.zeros((len(data), sum(self.sizes)))
        for i, k in enumerate(self.sizes):
            x[np.arange(len(data)), self.starts[i] + np.clip(data[:, i].astype(int), 0, k - 1)] = 1
        return x

    def logits(self, p: dict[str, Tensor], x: np.ndarray) -> Tensor:
        a, b, c = self.masks
        h = relu(masked_linear(relu(masked_linear(Tensor(x), p["w1"], p["b1"], a)), p["w2"], p["b2"], b))
        return masked_linear(h, p["w3"], p["b3"], c)

    def _row_loss(self, p: dict[str, Tensor], data: np.ndarray) -> Tensor:
        x = self.encode(data)
        z, out = self.logits(p, x), None
        for i in range(len(self.sizes)):
            a, b = self.starts[i], self.starts[i + 1]
            part = -(log_softmax(z[:, a:b]) * x[:, a:b]).sum(1)
            out = part if out is None else out + part
        return out

    def loss(self, p: dict[str, Tensor], data: np.ndarray, noise=None) -> Tensor:
        return self._row_loss(p, data).mean()

    def row_loss(self, params: Params, data: np.ndarray) -> np.ndarray:
        return self._row_loss({k: Tensor(v) for k, v in params.items()}, data).value

    def imitation(self, p: dict[str, Tensor], teacher: Params, data: np.ndarray, noise=None) -> Tensor:
        """Tempered cross-entropy of each conditional; ``reduction`` says whether columns are averaged or summed."""
        x = self.encode(data)
        t = self.logits({k: Tensor(v) for k, v in teacher.items()}, x).value
        z, out = self.logits(p, x), Tensor(0.0)
        for a, b in zip(self.starts, self.starts[1:], strict=False):
            out = out + soft_cross_entropy(t[:, a:b], z[:, a:b], self.temperature)
        return out * (1 / len(self.sizes)) if self.reduction == "mean" else out

    def counted(self, data: np.ndarray, likely: np.ndarray, like: np.ndarray, teacher: Params | None = None) -> Callable[[dict[str, Tensor]], Tensor]:
        """The objective with ``likely`` as the weight of each row's loss and ``like`` as that of its imitation, in one pass of the network."""
        x, t = self.encode(data), self.temperature
        target, soft = x * likely[:, None], None
        if teacher is not None and like.any():
            z = self.logits({k: Tensor(v) for k, v in teacher.items()}, x).value
            soft = np.hstack([softmax(z[:, a:b], t) for a, b in zip(self.starts, self.starts[1:], strict=False)]) * like[:, None]
            soft = soft / len(self.sizes) if self.reduction == "mean" else soft
            if t == 1:
                target, soft = target + soft, None

        def value(p: dict[str, Tensor]) -> Tensor:
            z = self.logits(p, x)
            out = cross_entropy(z, target, self.starts)
            return out if soft is None else out + cross_entropy(z * (1 / t), soft, self.starts)

        return value

    def conditional(self, params: Params, x: np.ndarray, i: int) -> np.ndarray:
        """Probabilities of column i given the one-hot columns before it."""
        z = self.logits({k: Tensor(v) for k, v in params.items()}, x).value[:, self.starts[i] : self.starts[i + 1]]
        e = np.exp(z - z.max(1, keepdims=True))
        return e / e.sum(1, keepdims=True)

    def box_mass(self, params: Params, lo: np.ndarray, hi: np.ndarray, paths: int, rng: np.random.Generator) -> float:
        """Probability of lo <= codes <= hi by progressive sampling: codes are drawn inside the box, column by column,
        and the masses of the box in each conditional multiply to an unbiased weight."""
        if (lo > hi).any():
            return 0.0
        x, weight = np.zeros((paths, sum(self.sizes))), np.ones(paths)
        last = max((i for i, k in enumerate(self.sizes) if lo[i] > 0 or hi[i] < k - 1), default=-1)
        for i in range(last + 1):  # columns after the last predicate integrate to 1
            p = self.conditional(params, x, i)
            p[:, : lo[i]] = 0
            p[:, hi[i] + 1 :] = 0
            mass = p.sum(1)
            weight *= mass
            c = np.cumsum(p, 1)
            pick = (c < (rng.random(paths) * mass)[:, None]).sum(1).clip(lo[i], hi[i])
            x[np.arange(paths), self.starts[i] + pick] = 1
        return float(weight.mean())

    def cell_mass(self, params: Params, cells: np.ndarray) -> np.ndarray:
        return np.exp(-self.row_loss(params, cells))
