"""Taggers in numpy: shared two-way recurrent encoder, optional attention, a dense layer and a CRF for each task.

The plain and the attention tagger have one task (entity tags); the joint tagger has two (entity tags, value-type
tags), whose losses are added by weight.
"""

from __future__ import annotations

from collections.abc import Mapping
from dataclasses import dataclass, field

import numpy as np

from reportgraph.functions.vectors import VectorFiles
from reportgraph.tagger import crf


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 0.5 * (1 + np.tanh(0.5 * x))


def lstm(x: np.ndarray, wx: np.ndarray, wh: np.ndarray, bias: np.ndarray) -> tuple[np.ndarray, list]:
    """States of batch x length x dim inputs, and what the way back needs."""
    b, n, _ = x.shape
    h_dim = wh.shape[0]
    h, c, out, tape = np.zeros((b, h_dim)), np.zeros((b, h_dim)), np.empty((b, n, h_dim)), []
    # What the inputs add is one product for all places; laid out by place.
    from_x = (x.transpose(1, 0, 2).reshape(n * b, -1) @ wx + bias).reshape(n, b, -1)
    for t in range(n):
        g = from_x[t] + h @ wh
        gates = sigmoid(g[:, : 3 * h_dim])
        i, f, o, u = gates[:, :h_dim], gates[:, h_dim : 2 * h_dim], gates[:, 2 * h_dim :], np.tanh(g[:, 3 * h_dim :])
        c_new = f * c + i * u
        tc = np.tanh(c_new)
        tape.append((h, c, i, f, o, u, tc))
        h, c = o * tc, c_new
        out[:, t] = h
    return out, tape


def lstm_back(x: np.ndarray, wx: np.ndarray, wh: np.ndarray, tape: list, d_out: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    b, n, _ = x.shape
    b, n, _ = x.shape
    h_dim = wh.shape[0]
    dgs = np.empty((n, b, 4 * h_dim))
    dh, dc = np.zeros((b, h_dim)), np.zeros((b, h_dim))
    for t in range(n - 1, -1, -1):
        h, c, i, f, o, u, tc = tape[t]
        dh = dh + d_out[:, t]
        dc = dc + dh * o * (1 - tc**2)
        dg = dgs[t]
        dg[:, :h_dim] = dc * u * i * (1 - i)
        dg[:, h_dim : 2 * h_dim] = dc * c * f * (1 - f)
        dg[:, 2 * h_dim : 3 * h_dim] = dh * tc * o * (1 - o)
        dg[:, 3 * h_dim :] = dc * i * (1 - u**2)
        dh, dc = dg @ wh.T, dc * f
    # The weights' gradients are one product each over all places.
    dg = dgs.reshape(n * b, -1)
    return x.transpose(1, 0, 2).reshape(n * b, -1).T @ dg, np.concatenate([step[0] for step in tape]).T @ dg, dg.sum(0)


def attention(h: np.ndarray, u: np.ndarray, mode: str = "reweight") -> tuple[np.ndarray, np.ndarray]:
    """``(result, shares)``: a score for each place, its softmax over places, and either the states weighted place by
    place (tanh of length times share times state) or 'pooled' to one vector for the sentence."""
    s = h @ u
    a = np.exp(s - s.max(1, keepdims=True))
    a = a / a.sum(1, keepdims=True)
    if mode == "pooled":
        return np.tanh((a[:, :, None] * h).sum(1)), a
    return np.tanh(h.shape[1] * a[:, :, None] * h), a


def attention_back(h: np.ndarray, u: np.ndarray, a: np.ndarray, r: np.ndarray, d_r: np.ndarray, mode: str = "reweight") -> tuple[np.ndarray, np.ndarray]:
    d_in = (d_r * (1 - r**2))[:, None, :] if mode == "pooled" else d_r * (1 - r**2) * h.shape[1]
    d_h = d_in * a[:, :, None]
    d_a = (d_in * h).sum(2)
    d_s = a * (d_a - (a * d_a).sum(1, keepdims=True))
    return d_h + d_s[:, :, None] * u, np.einsum("bn,bnh->h", d_s, h)


@dataclass
class Tagger:
    """``tags`` holds the tag names of each task; ``loss_weights`` the weight of each task's loss."""

    dim: int
    hidden: int
    tags: tuple[tuple[str, ...], ...]
    use_attention: bool = True
    loss_weights: tuple[float, ...] = (1.0,)
    seed: int = 7
    weights: dict[str, np.ndarray] = field(default_factory=dict)
    #: Trained word vectors; words that they lack have vectors of their spelling.
    vectors: Mapping[str, np.ndarray] | VectorFiles | None = None

    def __post_init__(self):
        if self.weights:
            return
        rng = np.random.default_rng(self.seed)
        w, h = self.weights, self.hidden
        for way in ("fwd", "bwd"):
            w[f"{way}_wx"] = rng.normal(0, 1 / np.sqrt(self.dim), (self.dim, 4 * h))
            w[f"{way}_wh"] = rng.normal(0, 1 / np.sqrt(h), (h, 4 * h))
            w[f"{way}_b"] = np.concatenate([np.zeros(h), np.ones(h), np.zeros(2 * h)])
        for k, tags in enumerate(self.tags):
            n = len(tags)
            w[f"att{k}"] = rng.normal(0, 0.1, 2 * h)
            w[f"dense{k}"], w[f"bias{k}"] = rng.normal(0, 1 / np.sqrt(2 * h), (2 * h, n)), np.zeros(n)
            w[f"trans{k}"], w[f"start{k}"], w[f"end{k}"] = np.zeros((n, n)), np.zeros(n), np.zeros(n)

    def encode(self, x: np.ndarray) -> tuple[np.ndarray, list, list]:
        w = self.weights
        f, tf = lstm(x, w["fwd_wx"], w["fwd_wh"], w["fwd_b"])
        b, tb = lstm(x[:, ::-1], w["bwd_wx"], w["bwd_wh"], w["bwd_b"])
        return np.concatenate([f, b[:, ::-1]], 2), tf, tb

    def emissions(self, h: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray | None]:
        r, a = attention(h, self.weights[f"att{k}"]) if self.use_attention else (h, None)
        return r @ self.weights[f"dense{k}"] + self.weights[f"bias{k}"], r, a

    def loss_grad(self, x: np.ndarray, ys: list[np.ndarray], counts: np.ndarray | None = None) -> tuple[float, dict[str, np.ndarray]]:
        """Weighted mean loss of a batch, in which a sentence stands for ``counts`` equal ones, and the gradient of each weight."""
        w, g = self.weights, {}
        share = np.full(len(x), 1 / len(x)) if counts is None else counts / counts.sum()
        h, tf, tb = self.encode(x)
        d_h, total = np.zeros_like(h), 0.0
        for k, y in enumerate(ys):
            part = self.loss_weights[k]
            e, r, a = self.emissions(h, k)
            loss, d_e, g_t, g_s, g_e = crf.nll_grad(e, y, w[f"trans{k}"], w[f"start{k}"], w[f"end{k}"], share)
            total += part * loss
            d_e = part * d_e
            g[f"trans{k}"], g[f"start{k}"], g[f"end{k}"] = part * g_t, part * g_s, part * g_e
            g[f"dense{k}"], g[f"bias{k}"] = np.einsum("bnh,bnk->hk", r, d_e), d_e.sum((0, 1))
            d_r = d_e @ w[f"dense{k}"].T
            if self.use_attention:
                d_r, g[f"att{k}"] = attention_back(h, w[f"att{k}"], a, r, d_r)
            d_h += d_r
        n = self.hidden
        g["fwd_wx"], g["fwd_wh"], g["fwd_b"] = lstm_back(x, w["fwd_wx"], w["fwd_wh"], tf, d_h[:, :, :n])
        g["bwd_wx"], g["bwd_wh"], g["bwd_b"] = lstm_back(x[:, ::-1], w["bwd_wx"], w["bwd_wh"], tb, d_h[:, ::-1, n:])
        return total, g

    def decode(self, x: np.ndarray, k: int = 0) -> np.ndarray:
        w = self.weights
        e, _, _ = self.emissions(self.encode(x)[0], k)
        return crf.viterbi(e, w[f"trans{k}"], w[f"start{k}"], w[f"end{k}"])


def plain_tagger(dim: int, hidden: int, entity_tags: tuple[str, ...], **kw) -> Tagger:
    return Tagger(dim, hidden, (entity_tags,), use_attention=False, **kw)


def attention_tagger(dim: int, hidden: int, entity_tags: tuple[str, ...], **kw) -> Tagger:
    return Tagger(dim, hidden, (entity_tags,), **kw)


def joint_tagger(dim: int, hidden: int, entity_tags: tuple[str, ...], type_tags: tuple[str, ...], loss_weights: tuple[float, float] = (1.0, 0.5), **kw) -> Tagger:
    return Tagger(dim, hidden, (entity_tags, type_tags), loss_weights=loss_weights, **kw)


class Adam:
    def __init__(self, rate: float = 0.01):
        self.rate, self.t, self.m, self.v = rate, 0, {}, {}

    def step(self, weights: dict[str, np.ndarray], grads: dict[str, np.ndarray]) -> None:
        self.t += 1
        size = np.sqrt(sum(float((g**2).sum()) for g in grads.values()))
        clip = min(1.0, 5.0 / max(size, 1e-9))
        for k, g in grads.items():
            g = g * clip
            m = self.m[k] = 0.9 * self.m.get(k, 0.0) + 0.1 * g
            v = self.v[k] = 0.999 * self.v.get(k, 0.0) + 0.001 * g * g
            weights[k] = weights[k] - self.rate * (m / (1 - 0.9**self.t)) / (np.sqrt(v / (1 - 0.999**self.t)) + 1e-8)
