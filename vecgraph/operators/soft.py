"""Soft codes: codeword probabilities, perturbed by Gumbel noise that doesn't depend on partitioning."""

from __future__ import annotations

import numpy as np


def log_softmax(x: np.ndarray) -> np.ndarray:
    top = x.max(-1, keepdims=True)
    return x - top - np.log(np.exp(x - top).sum(-1, keepdims=True))


def assign_prob(y: np.ndarray, book: np.ndarray, temperature: float = 1.0, sign: str = "nearest") -> np.ndarray:
    """Probability of every codeword for chunks y: the nearest is likeliest. sign="as_printed" turns that around (tests only)."""
    d = ((y[:, None, :] - book[None]) ** 2).sum(-1) / temperature
    return np.exp(log_softmax(-d if sign == "nearest" else d))


def gumbel(u: np.ndarray) -> np.ndarray:
    return -np.log(-np.log(u))


def soft_code(prob: np.ndarray, noise: np.ndarray, temperature: float = 1.0) -> np.ndarray:
    return np.exp(log_softmax((np.log(prob) + noise) / temperature))
