"""Variational autoencoder over codes: a Gaussian latent, and a softmax for each column in the decoder."""

from __future__ import annotations

from dataclasses import dataclass
from functools import cached_property

import numpy as np

from .losses import logit_gap
from .tensor import Tensor, exp, log_softmax, relu, square
from .training import Params


def _mixed(h: np.ndarray) -> np.ndarray:
    """Odd multipliers and shifts that spread 64 bits."""
    h = (h + np.uint64(0x9E3779B97F4A7C15)) * np.uint64(0xD6E8FEB86659FD93)
    h = (h ^ (h >> np.uint64(32))) * np.uint64(0xC2B2AE3D27D4EB4F)
    return h ^ (h >> np.uint64(29))


@dataclass(frozen=True)
class TabularVae:
    sizes: tuple[int, ...]
    latent: int = 8
    hidden: int = 64
    decoder_only: bool = False
    name: str = "vae"

    @cached_property
    def starts(self) -> list[int]:
        return [0, *np.cumsum(self.sizes).tolist()]

    def initial(self, rng: np.random.Generator) -> Params:
        d, h, z = sum(self.sizes), self.hidden, self.latent
        w = lambda a, b: rng.normal(0, np.sqrt(2 / a), (a, b))
        encoder = {"ew1": w(d, h) * np.sqrt(d / len(self.sizes)), "eb1": np.zeros(h), "ew2": w(h, 2 * z) * 0.3, "eb2": np.zeros(2 * z)}
        return encoder | {"dw1": w(z, h), "db1": np.zeros(h), "dw2": w(h, d) * 0.3, "db2": np.zeros(d)}

    def noise(self, rng: np.random.Generator, n: int) -> np.ndarray:
        return rng.normal(size=(n, self.latent))

    def encode(self, data: np.ndarray) -> np.ndarray:
        x = np.zeros((len(data), sum(self.sizes)))
        for i, k in enumerate(self.sizes):
            x[np.arange(len(data)), self.starts[i] + np.clip(data[:, i].astype(int), 0, k - 1)] = 1
        return x

    def encoder(self, p: dict[str, Tensor], x: np.ndarray) -> tuple[Tensor, Tensor]:
        h = relu(Tensor(x) @ p["ew1"] + p["eb1"]) @ p["ew2"] + p["eb2"]
        return h[:, : self.latent], h[:, self.latent :]

    def decoder(self, p: dict[str, Tensor], z: Tensor) -> Tensor:
        return relu(z @ p["dw1"] + p["db1"]) @ p["dw2"] + p["db2"]

    def _row_loss(self, p: dict[str, Tensor], data: np.ndarray, noise: np.ndarray) -> Tensor:
        x = self.encode(data)
        mean, logvar = self.encoder(p, x)
        out = self.decoder(p, mean + exp(logvar * 0.5) * noise)
        total = (exp(logvar) + square(mean) - logvar - 1.0).sum(1) * 0.5
        for a, b in zip(self.starts, self.starts[1:], strict=False):
            total = total - (log_softmax(out[:, a:b]) * x[:, a:b]).sum(1)
        return total

    def loss(self, p: dict[str, Tensor], data: np.ndarray, noise: np.ndarray | None = None) -> Tensor:
        p = self._frozen(p)
        return self._row_loss(p, data, np.zeros((len(data), self.latent)) if noise is None else noise).mean()

    def row_loss(self, params: Params, data: np.ndarray) -> np.ndarray:
        """Noise depends on a row's content only, so a row has one loss however the data are partitioned."""
        return self._row_loss({k: Tensor(v) for k, v in params.items()}, data, self.noise_of(data)).value

    def noise_of(self, data: np.ndarray) -> np.ndarray:
        """Normal numbers from a hash of each row's codes and the latent's number: no generator, no state."""
        h = np.zeros(len(data), "uint64")
        for c in data.astype("int64").astype("uint64").T:
            h = _mixed(h ^ c)
        keys = _mixed(h[:, None] ^ np.arange(1, 2 * self.latent + 1, dtype="uint64"))
        u = ((keys >> np.uint64(11)).astype("float64") + 0.5) / 2.0**53
        return np.sqrt(-2 * np.log(u[:, : self.latent])) * np.cos(2 * np.pi * u[:, self.latent :])

    def imitation(self, p: dict[str, Tensor], teacher: Params, data: np.ndarray, noise: np.ndarray | None = None) -> Tensor:
        """Half the squared gaps of encoder outputs plus half those of decoder outputs, teacher and student under the same noise."""
        p = self._frozen(p)
        x, t = self.encode(data), {k: Tensor(v) for k, v in teacher.items()}
        noise = np.zeros((len(data), self.latent)) if noise is None else noise
        tm, tv = self.encoder(t, x)
        sm, sv = self.encoder(p, x)
        t_out = self.decoder(t, tm + exp(tv * 0.5) * noise).value
        s_out = self.decoder(p, sm + exp(sv * 0.5) * noise)
        decoded = logit_gap(t_out, s_out)
        if self.decoder_only:
            return decoded * 0.5
        return (logit_gap(tm.value, sm) + logit_gap(tv.value, sv) + decoded) * 0.5

    def _frozen(self, p: dict[str, Tensor]) -> dict[str, Tensor]:
        """With ``decoder_only`` the encoder's weights get no gradient."""
        return {k: Tensor(v.value) if k[0] == "e" else v for k, v in p.items()} if self.decoder_only else p

    def sample(self, params: Params, n: int, rng: np.random.Generator) -> np.ndarray:
        """Codes of ``n`` synthetic rows: a latent from the prior, then a draw from each column's softmax."""
        out = self.decoder({k: Tensor(v) for k, v in params.items()}, Tensor(rng.normal(size=(n, self.latent)))).value
        cols = []
        for a, b in zip(self.starts, self.starts[1:], strict=False):
            e = np.exp(out[:, a:b] - out[:, a:b].max(1, keepdims=True))
            c = np.cumsum(e / e.sum(1, keepdims=True), 1)
            cols.append((c < rng.random((n, 1))).sum(1).clip(0, b - a - 1))
        return np.column_stack(cols)
