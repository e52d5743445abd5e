"""Relation operators and similarities on matrices (rows are vectors), with their gradients.

The first axis, or axes, of X are rows; parameters belong to one relation. ``backward`` gives the
gradients of X and of the parameters from the gradient of the output.
"""

from __future__ import annotations

import numpy as np


def parameters(op: str, d: int) -> np.ndarray | None:
    """The parameters with which an operator leaves vectors as they are (or, for correlation, nearly)."""
    if op == "identity":
        return None
    if op == "translation":
        return np.zeros(d, np.float32)
    if op == "diagonal":
        return np.ones(d, np.float32)
    if op == "linear":
        return np.eye(d, dtype=np.float32)
    if op == "complex_diagonal":
        return np.concatenate([np.ones(d // 2), np.zeros(d - d // 2)]).astype(np.float32)
    if op == "circular_correlation":
        return np.eye(1, d, dtype=np.float32)[0]
    raise ValueError(op)


def _halves(x):
    h = x.shape[-1] // 2
    return x[..., :h], x[..., h:]


def forward(op: str, x: np.ndarray, theta: np.ndarray | None) -> np.ndarray:
    if op == "identity":
        return x
    if op == "translation":
        return x + theta
    if op == "diagonal":
        return x * theta
    if op == "linear":
        return x @ theta.T
    if op == "complex_diagonal":
        (xr, xi), (tr, ti) = _halves(x), _halves(theta)
        return np.concatenate([xr * tr - xi * ti, xr * ti + xi * tr], -1)
    if op == "circular_correlation":
        return x @ _circulant(theta).T if len(theta) <= CIRCULANT else _correlate(theta, x)
    raise ValueError(op)


#: Up to so many dimensions a correlation with one vector is a product with its circulant matrix; that is faster than three transforms.
CIRCULANT = 256


def _circulant(theta):
    """The matrix whose product with x is the correlation: row k has theta_i at column i + k."""
    n = len(theta)
    return theta[(np.arange(n)[None, :] - np.arange(n)[:, None]) % n]


def _correlate(theta, x):
    n = x.shape[-1]
    return np.fft.irfft(np.conj(np.fft.rfft(theta)) * np.fft.rfft(x), n).astype(x.dtype)


def _convolve(a, b):
    n = b.shape[-1]
    return np.fft.irfft(np.fft.rfft(a) * np.fft.rfft(b), n).astype(b.dtype)


def _rows(a):
    return a.reshape(-1, a.shape[-1])


def backward(op: str, x: np.ndarray, theta: np.ndarray | None, dy: np.ndarray) -> tuple[np.ndarray, np.ndarray | None]:
    if op == "identity":
        return dy, None
    if op == "translation":
        return dy, _rows(dy).sum(0)
    if op == "diagonal":
        return dy * theta, _rows(dy * x).sum(0)
    if op == "linear":
        return dy @ theta, _rows(dy).T @ _rows(x)
    if op == "complex_diagonal":
        (xr, xi), (tr, ti), (gr, gi) = _halves(x), _halves(theta), _halves(dy)
        dx = np.concatenate([gr * tr + gi * ti, gi * tr - gr * ti], -1)
        dt = np.concatenate([gr * xr + gi * xi, gi * xr - gr * xi], -1)
        return dx, _rows(dt).sum(0)
    if op == "circular_correlation":
        # y_k = sum_i theta_i x_(i+k): its adjoints are a convolution and a correlation
        if len(theta) <= CIRCULANT:
            n = len(theta)
            both = _rows(dy).T @ _rows(x)  # (k, j) adds to the parameter j - k
            at = np.arange(n)
            return dy @ _circulant(theta), both[at[None, :], (at[:, None] + at[None, :]) % n].sum(1)
        return _convolve(theta, dy), _rows(_correlate(dy, x)).sum(0)
    raise ValueError(op)


def normalise(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Unit rows and their former sizes; zero rows stay zero."""
    size = np.sqrt(np.einsum("...i,...i->...", x, x))[..., None]
    return x * _inverse(size), size


def normalise_back(unit: np.ndarray, size: np.ndarray, dy: np.ndarray) -> np.ndarray:
    return (dy - unit * np.einsum("...i,...i->...", unit, dy)[..., None]) * _inverse(size)


def _inverse(size: np.ndarray) -> np.ndarray:
    return np.divide(1, size, out=np.zeros_like(size), where=size > 0)


def pair_scores(sim: str, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Similarity of corresponding rows (complex products of stacked halves are plain dot products)."""
    if sim == "cos":
        a, b = normalise(a)[0], normalise(b)[0]
    return (a * b).sum(-1)
