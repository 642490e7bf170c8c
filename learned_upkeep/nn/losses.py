"""Imitation losses between a teacher (plain arrays) and a student (tensors), averaged over rows."""

from __future__ import annotations

import numpy as np

from .tensor import Tensor, log_softmax, square


def softmax(z: np.ndarray, temperature: float = 1.0) -> np.ndarray:
    z = z / temperature
    e = np.exp(z - z.max(-1, keepdims=True))
    return e / e.sum(-1, keepdims=True)


def soft_cross_entropy(teacher: np.ndarray, student: Tensor, temperature: float) -> Tensor:
    """Row means of the tempered cross-entropy over the last axis of logits."""
    p = softmax(teacher, temperature)
    return -(log_softmax(student * (1 / temperature)) * p).sum() * (1 / len(teacher))


def logit_gap(teacher: np.ndarray, student: Tensor) -> Tensor:
    """Row means of the summed squared differences."""
    return square(student - teacher).sum() * (1 / len(teacher))
