"""The small set of bulk tensor primitives that every operator is lowered to, over numpy arrays."""

from __future__ import annotations

import numpy as np


def sigmoid(x: np.ndarray) -> np.ndarray:
    """Logistic function that never overflows: the exponent is always of a negative number."""
    e = np.exp(-np.abs(x))
    return np.where(x >= 0, 1.0, e) / (1.0 + e)


def logsumexp(x: np.ndarray) -> np.ndarray:
    top = x.max(axis=1, keepdims=True)
    return top + np.log(np.exp(x - top).sum(axis=1, keepdims=True))


def softmax(x: np.ndarray) -> np.ndarray:
    return np.exp(x - logsumexp(x))


def argmax(x: np.ndarray) -> np.ndarray:
    """Index of the largest value, ties to the lowest index."""
    return x.argmax(axis=1)


def relu(x: np.ndarray) -> np.ndarray:
    return np.maximum(x, 0.0)


ACTIVATIONS = {"relu": relu, "tanh": np.tanh, "logistic": sigmoid, "identity": lambda x: x}


def squared_distances(x: np.ndarray, s: np.ndarray) -> np.ndarray:
    """All squared distances from norms and one product; cancellation is clamped at 0."""
    return np.maximum((x * x).sum(1)[:, None] + (s * s).sum(1)[None, :] - 2.0 * (x @ s.T), 0.0)


def squared_distances_naive(x: np.ndarray, s: np.ndarray, budget: int = 64 << 20) -> np.ndarray:
    """The same by an n x m x d difference tensor, in row chunks under a byte budget."""
    step = max(1, budget // max(1, 8 * s.size))
    return np.concatenate([((x[k : k + step, None, :] - s[None]) ** 2).sum(-1) for k in range(0, max(1, len(x)), step)])


def interactions_outer(x: np.ndarray) -> np.ndarray:
    """Squares first, then pair products in row-major upper-triangle order: one outer product and one gather."""
    d = x.shape[1]
    a, b = np.triu_indices(d, 1)
    flat = (x[:, :, None] * x[:, None, :]).reshape(len(x), d * d)
    return flat[:, np.concatenate([np.arange(d) * (d + 1), a * d + b])]


def interactions_pairwise(x: np.ndarray) -> np.ndarray:
    """The same, one gather and product for each pair."""
    d = x.shape[1]
    parts = [x[:, i] * x[:, i] for i in range(d)] + [x[:, i] * x[:, j] for i in range(d) for j in range(i + 1, d)]
    return np.stack(parts, 1)


def fixed_bytes(values: list[str | None], width: int) -> np.ndarray:
    """Strings as rows of ``width`` bytes, zero-padded; a null is all 255, which is no UTF-8."""
    out = np.zeros((len(values), width), np.uint8)
    for k, v in enumerate(values):
        raw = b"\xff" * width if v is None else v.encode()[:width]
        out[k, : len(raw)] = np.frombuffer(raw, np.uint8)
    return out


#: Primitive calls of the idioms, for d inputs.
def calls_pairwise(d: int) -> int:
    return d * d + d + 1


CALLS_OUTER = 2
