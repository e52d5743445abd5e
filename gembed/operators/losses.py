"""Losses over one positive and its negatives, and their gradients by score.

pos: (..., rows), neg: (..., rows, J), live: same shape as neg, false where a negative does not count,
weight: (..., rows). The hinge is max(0, margin - positive + negative), so that a step raises true
edges above corrupted ones.
"""

from __future__ import annotations

import numpy as np


def softplus(x):
    return np.maximum(x, 0) + np.log1p(np.exp(-np.abs(x)))


def sigmoid(x):
    e = np.exp(-np.abs(x))
    return np.where(x >= 0, 1, e) / (1 + e)


def ranking(pos, neg, live, weight, margin=0.1):
    return masked("ranking", pos, neg, live, weight, margin)


def logistic(pos, neg, live, weight, margin=0.0):
    return masked("logistic", pos, neg, live, weight, margin)


def softmax(pos, neg, live, weight, margin=0.0):
    return masked("softmax", pos, neg, live, weight, margin)


def masked(name, pos, neg, live, weight, margin):
    return OVER[name](pos, np.where(live, neg, -np.inf).astype(neg.dtype, copy=False), np.count_nonzero(live, -1), weight, margin)


def _ranking(pos, neg, alive, weight, margin):
    neg += (margin - pos)[..., None].astype(neg.dtype)
    gn = (neg > 0) * weight[..., None]
    np.maximum(neg, 0, out=neg)
    return float((neg.sum(-1) * weight).sum()), -gn.sum(-1), gn


def _logistic(pos, neg, alive, weight, margin):
    each = weight / np.maximum(alive, 1).astype(neg.dtype)
    e = np.exp(-np.abs(neg))
    over = (np.maximum(neg, 0) + np.log1p(e)).sum(-1)
    loss = (weight * softplus(-pos)).sum() + (each * over).sum()
    gn = np.where(neg >= 0, 1, e).astype(neg.dtype, copy=False)
    e += 1
    gn /= e
    gn *= each[..., None]
    return float(loss), -weight * sigmoid(-pos), gn


def _softmax(pos, neg, alive, weight, margin):
    top = np.maximum(pos, neg.max(-1, initial=-np.inf))
    neg -= top[..., None]
    np.exp(neg, out=neg)
    ep = np.exp(pos - top)
    total = ep + neg.sum(-1)
    loss = (weight * (np.log(total) - (pos - top))).sum()
    neg *= (weight / total)[..., None]
    return float(loss), weight * (ep / total - 1), neg


LOSSES = {"ranking": ranking, "logistic": logistic, "softmax": softmax}
#: The same on scores that are minus infinity where a negative does not count, and the number of others in each row; ``neg`` is overwritten.
OVER = {"ranking": _ranking, "logistic": _logistic, "softmax": _softmax}
