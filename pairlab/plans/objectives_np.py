"""Objectives of the log-linear policy and their gradients, for a batch of queries at once.

A batch has x (queries x candidates x features) and live (which candidates exist).  The policy is
pi(o | q) = softmax(x . w); a response is one decision, so its mean token log-probability is log pi.  Each function returns
the sum of the objective over its rows, the sum of its gradient by w, and the number of rows."""

from __future__ import annotations

import numpy as np

Result = tuple[float, np.ndarray, int]


def log_probs(x: np.ndarray, live: np.ndarray, w: np.ndarray) -> np.ndarray:
    z = np.where(live, x @ w, -np.inf)
    top = z.max(1, keepdims=True)
    return z - top - np.log(np.exp(z - top).sum(1, keepdims=True))


def centred(x: np.ndarray, live: np.ndarray, lp: np.ndarray) -> np.ndarray:
    """Gradient of log pi of each candidate: its features less their mean under the policy."""
    p = np.where(live, np.exp(lp), 0.0)
    return x - np.einsum("qk,qkd->qd", p, x)[:, None]


def log_sigmoid(z: np.ndarray) -> np.ndarray:
    return np.where(z >= 0, -np.log1p(np.exp(-np.abs(z))), z - np.log1p(np.exp(-np.abs(z))))


def sigmoid(z: np.ndarray) -> np.ndarray:
    return np.exp(log_sigmoid(z))


def sft(x: np.ndarray, live: np.ndarray, w: np.ndarray, chosen: np.ndarray) -> Result:
    """Mean over a query's chosen responses; a row is a query with one or more."""
    lp = log_probs(x, live, w)
    n = chosen.sum(1)
    rows = n > 0
    share = np.where(chosen, 1.0, 0.0)[rows] / n[rows, None]
    value = np.where(chosen, lp, 0.0)[rows] * share
    return float(value.sum()), np.einsum("qk,qkd->d", share, centred(x, live, lp)[rows]), int(rows.sum())


def zipped(ok: np.ndarray, live: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Query, place of the chosen and of the rejected one: the i-th right answer with the i-th wrong one."""
    out = []
    for good, bad in zip(ok & live, ~ok & live):
        out.append(min(good.sum(), bad.sum()))
    n = np.array(out, np.int64)
    rank = lambda m: np.where(m, np.cumsum(m, 1) - 1, 1 << 30)
    g, b = rank(ok & live) < n[:, None], rank(~ok & live) < n[:, None]
    return np.repeat(np.arange(len(n)), n), np.nonzero(g)[1], np.nonzero(b)[1]


def dpo(x, live, w, ref: np.ndarray, pairs, beta: float) -> Result:
    q, c, r = pairs
    lp, lr = log_probs(x, live, w), log_probs(x, live, ref)
    z = beta * ((lp[q, c] - lr[q, c]) - (lp[q, r] - lr[q, r]))
    # the policy's mean features cancel
    return float(log_sigmoid(z).sum()), ((beta * sigmoid(-z))[:, None] * (x[q, c] - x[q, r])).sum(0), len(q)


def orpo(x, live, w, pairs, beta: float) -> Result:
    q, c, r = pairs
    lp = log_probs(x, live, w)
    g = centred(x, live, lp)
    rest = lambda m: np.maximum(-np.expm1(m), 1e-300)  # noqa: E731  1 - pi
    odds = lambda m: m - np.log(rest(m))
    z = odds(lp[q, c]) - odds(lp[q, r])
    pull = (beta * sigmoid(-z))[:, None] * (g[q, c] / rest(lp[q, c])[:, None] - g[q, r] / rest(lp[q, r])[:, None])
    return float((lp[q, c] + beta * log_sigmoid(z)).sum()), (g[q, c] + pull).sum(0), len(q)


def group_relative(x, live, w, old: np.ndarray, ref: np.ndarray, drawn: np.ndarray, reward: np.ndarray, clip: float = 0.2, beta: float = 0.0) -> Result:
    """drawn: queries x group places of candidates (-1: none), reward: queries x candidates. A group of equal rewards has advantage 0."""
    there = drawn >= 0
    at = np.where(there, drawn, 0)
    take = lambda v: np.take_along_axis(v, at, 1)
    n = np.maximum(there.sum(1, keepdims=True), 1)
    r = np.where(there, take(reward), 0.0)
    mean = r.sum(1, keepdims=True) / n
    std = np.sqrt((np.where(there, r - mean, 0.0) ** 2).sum(1, keepdims=True) / n)
    dead = np.where(there, r, np.inf).min(1, keepdims=True) >= np.where(there, r, -np.inf).max(1, keepdims=True)
    a = np.where(there & ~dead, (r - mean) / np.where(dead, 1.0, std), 0.0)
    lp, lo, lr = (log_probs(x, live, v) for v in (w, old, ref))
    ratio = np.exp(take(lp) - take(lo))
    free, held = ratio * a, np.clip(ratio, 1 - clip, 1 + clip) * a
    d = take(lp) - take(lr)
    value = np.where(there, np.minimum(free, held) - beta * (np.exp(-d) - 1 + d), 0.0)
    pull = np.where(there, np.where(free <= held, free, 0.0) - beta * (1 - np.exp(-d)), 0.0) / n
    g = np.take_along_axis(centred(x, live, lp), at[:, :, None], 1)
    return float((value / n).sum()), np.einsum("qk,qkd->d", pull, g), len(x)


def uniforms(query: np.ndarray, k: int, seed: int) -> np.ndarray:
    """queries x k numbers in [0, 1) by a hash of query, place and seed, the same wherever a query lies."""
    with np.errstate(over="ignore"):
        h = query.astype(np.int64).view(np.uint64)[:, None] * np.uint64(0x9E3779B97F4A7C15) + np.arange(1, k + 1, dtype=np.uint64) * np.uint64(0xBF58476D1CE4E5B9) + np.uint64(seed) * np.uint64(0x94D049BB133111EB)
        for m in (0xFF51AFD7ED558CCD, 0xC4CEB9FE1A85EC53):
            h = (h ^ (h >> np.uint64(33))) * np.uint64(m)
        h ^= h >> np.uint64(33)
    return (h >> np.uint64(11)).astype(float) / 2.0**53


def draw(lp: np.ndarray, live: np.ndarray, query: np.ndarray, k: int, seed: int) -> np.ndarray:
    """queries x k places of candidates drawn from the policy, with replacement."""
    upto = np.cumsum(np.where(live, np.exp(lp), 0.0), 1)
    last = live.shape[1] - 1 - np.argmax(live[:, ::-1], 1)
    return np.minimum((uniforms(query, k, seed)[:, :, None] >= upto[:, None]).sum(2), last[:, None])
