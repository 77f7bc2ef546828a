"""Linear-chain conditional random field over batches of sentences of one length."""

from __future__ import annotations

import numpy as np


def logsumexp(x: np.ndarray, axis: int) -> np.ndarray:
    top = x.max(axis=axis, keepdims=True)
    return (top + np.log(np.exp(x - top).sum(axis=axis, keepdims=True))).squeeze(axis)


def path_score(e: np.ndarray, y: np.ndarray, trans: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """Scores of tag paths; ``e`` is batch x length x tags."""
    b, n, _ = e.shape
    at = np.arange(b)
    s = start[y[:, 0]] + end[y[:, -1]]
    for t in range(n):
        s = s + e[at, t, y[:, t]]
        if t:
            s = s + trans[y[:, t - 1], y[:, t]]
    return s


def forward(e: np.ndarray, trans: np.ndarray, start: np.ndarray) -> np.ndarray:
    """Log sums over all paths that end in a tag at a place."""
    a = np.empty_like(e)
    a[:, 0] = start + e[:, 0]
    for t in range(1, e.shape[1]):
        a[:, t] = logsumexp(a[:, t - 1, :, None] + trans[None], 1) + e[:, t]
    return a


def backward(e: np.ndarray, trans: np.ndarray, end: np.ndarray) -> np.ndarray:
    b = np.empty_like(e)
    b[:, -1] = end
    for t in range(e.shape[1] - 2, -1, -1):
        b[:, t] = logsumexp(trans[None] + (e[:, t + 1] + b[:, t + 1])[:, None, :], 2)
    return b


def log_partition(e: np.ndarray, trans: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    return logsumexp(forward(e, trans, start)[:, -1] + end, 1)


def nll_grad(e: np.ndarray, y: np.ndarray, trans: np.ndarray, start: np.ndarray, end: np.ndarray, weight: np.ndarray | None = None) -> tuple[float, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Summed negative log-likelihood, each sentence by its ``weight`` (else 1), and its gradients by emissions, transitions, start and end: expected less observed counts."""
    n_b, n, k = e.shape
    w = np.ones(n_b) if weight is None else weight
    a, b = forward(e, trans, start), backward(e, trans, end)
    z = logsumexp(a[:, -1] + end, 1)
    d_e = (np.exp(a + b - z[:, None, None]) - np.eye(k)[y]) * w[:, None, None]
    g_trans = np.zeros_like(trans)
    for t in range(1, n):
        pair = a[:, t - 1, :, None] + trans[None] + (e[:, t] + b[:, t])[:, None, :] - z[:, None, None]
        g_trans += (np.exp(pair) * w[:, None, None]).sum(0)
        np.subtract.at(g_trans, (y[:, t - 1], y[:, t]), w)
    loss = float((w * (z - path_score(e, y, trans, start, end))).sum())
    return loss, d_e, g_trans, d_e[:, 0].sum(0), d_e[:, -1].sum(0)


def viterbi(e: np.ndarray, trans: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """Best paths; ties to the smaller tag."""
    b, n, k = e.shape
    s, back = start + e[:, 0], np.zeros((b, n, k), np.int64)
    for t in range(1, n):
        step = s[:, :, None] + trans[None]
        back[:, t] = step.argmax(1)
        s = step.max(1) + e[:, t]
    out = np.empty((b, n), np.int64)
    out[:, -1] = (s + end).argmax(1)
    for t in range(n - 1, 0, -1):
        out[:, t - 1] = back[np.arange(b), t, out[:, t]]
    return out
