"""The numpy twins of the array expressions: same operations in the same order."""

from __future__ import annotations

import numpy as np


def distances(x: np.ndarray, w: np.ndarray) -> np.ndarray:
    """Samples x prototypes."""
    out = np.zeros((len(x), len(w)))
    for j in range(x.shape[1]):
        d = x[:, j, None] - w[None, :, j]
        out += d * d
    return out


#: Prototypes from which on ``nearest`` screens, and the scores of a block of samples, which stay in cache.
SCREEN_FROM, SCREEN_BLOCK = 24, 2**20


def nearest(x: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Each sample's nearest prototype (the lowest of equally near ones) and its squared distance: those of ``distances``, bit for bit.

    Many prototypes are screened by a matrix product in single precision. Where another prototype comes within its error, and
    where a value is not finite, the sample is measured against all.
    """
    n, dims = x.shape
    if len(w) < SCREEN_FROM:
        d2 = distances(x, w)
        near = d2.argmin(axis=1)
        return near, d2[np.arange(n), near]
    near, middle = np.empty(n, np.intp), w.mean(axis=0)
    rows = max(1, SCREEN_BLOCK // len(w))
    with np.errstate(over="ignore", invalid="ignore"):
        at = w - middle
        half = 0.5 * (at * at).sum(axis=1)
        right = np.ascontiguousarray(np.concatenate([-at, half[:, None]], axis=1).T.astype(np.float32))
        span, reach = np.sqrt(2 * half.max()), np.abs(w).max()
        for a in range(0, n, rows):
            own = x[a : a + rows]
            of, line = own - middle, np.arange(len(own))
            score = np.concatenate([of, np.ones((len(of), 1))], axis=1).astype(np.float32) @ right  # half the squared distance, less half the sample's own square
            found = score.argmin(axis=1)
            least = score[line, found].astype(np.float64)
            score[line, found] = np.inf
            slack = (dims + 8) * 2.0**-23 * (np.sqrt((of * of).sum(axis=1)) + span) ** 2 + dims * 2.0**-48 * (np.abs(own).max(axis=1) + reach) ** 2
            close = np.flatnonzero(~(score.min(axis=1) > least + slack))
            if len(close):
                found[close] = distances(own[close], w).argmin(axis=1)
            near[a : a + rows] = found
        d2 = np.zeros(n)
        for j in range(dims):
            d = x[:, j] - w[near, j]
            d2 += d * d
    return near, d2


def in_order(terms: np.ndarray, axis: int = -1) -> np.ndarray:
    """Sums along an axis, added from left to right."""
    return np.add.accumulate(terms, axis=axis).take(-1, axis=axis) if terms.shape[axis] else terms.sum(axis=axis)


def gradient(x: np.ndarray, w: np.ndarray, reduce: str = "mean", normalise: str = "batch", loss: str = "prototypes") -> np.ndarray:
    """Sum over the samples, in order; over the batch, the cluster, or not divided.

    Of prototypes: prototype minus sample. Of losses with a target, which ends each sample: residual times sample.
    """
    if loss != "prototypes":
        of = residuals(x, w, loss)[:, None] * x[:, :-1]
        g = in_order(of, axis=0)[None]
        return g / len(x) if reduce == "mean" else g
    near, _ = nearest(x, w)
    off = w[near] - x
    g = np.stack([np.bincount(near, weights=off[:, j], minlength=len(w)) for j in range(x.shape[1])], axis=1)
    if normalise == "cluster":
        return g / np.maximum(np.bincount(near, minlength=len(w)), 1)[:, None]
    return g / len(x) if reduce == "mean" else g


def residuals(x: np.ndarray, w: np.ndarray, loss: str) -> np.ndarray:
    score = in_order(x[:, :-1] * w[0])
    return (score if loss == "squares" else 1.0 / (1.0 + np.exp(-score))) - x[:, -1]


def flat_sqdist(a: np.ndarray, b: np.ndarray) -> float:
    d = (a - b).ravel()
    return float(in_order(d * d)) if d.size else 0.0


def accepts(w: np.ndarray, g: np.ndarray, eps: float, e: np.ndarray, have: np.ndarray) -> bool:
    """The window over the blocks that the message has."""
    return flat_sqdist((w - eps * g)[have], e[have]) < flat_sqdist(w[have], e[have])


def step(w: np.ndarray, g: np.ndarray, mail: list[tuple[np.ndarray, np.ndarray]], eps: float, window: bool = True, scope: str = "message", empty: str = "null") -> tuple[np.ndarray, int]:
    """The modified step and how many messages counted. ``mail``: states and the blocks each has."""
    total, count, good = w.copy(), np.ones(len(w)), 0
    for e, have in mail:
        if empty == "zero_norm" and not e[have].any() or scope == "state" and not have.all():
            continue
        if window and scope == "block":
            have = np.asarray([h and flat_sqdist(w[i] - eps * g[i], e[i]) < flat_sqdist(w[i], e[i]) for i, h in enumerate(have)])
        elif window and not accepts(w, g, eps, e, have):
            continue
        if have.any():
            total[have] += e[have]
            count[have] += 1
            good += 1
    return (w - total / count[:, None]) + g, good


def apply(w: np.ndarray, g: np.ndarray, modified: np.ndarray, eps: float, gain: str = "eps") -> np.ndarray:
    return w - eps * modified if gain == "eps" else w - ((modified - g) + eps * g)


def losses(x: np.ndarray, w: np.ndarray, loss: str = "prototypes") -> np.ndarray:
    """Each sample's loss: half the squared distance to the nearest prototype, half the squared residual, or the log-loss."""
    if loss == "prototypes":
        return 0.5 * nearest(x, w)[1]
    if loss == "squares":
        return 0.5 * residuals(x, w, loss) ** 2
    score = in_order(x[:, :-1] * w[0])
    return np.logaddexp(0.0, score) - x[:, -1] * score


def loss(x: np.ndarray, w: np.ndarray, kind: str = "prototypes") -> float:
    return float(losses(x, w, kind).mean())


def alone(x: np.ndarray, w: np.ndarray, eps: float, seen=None) -> np.ndarray:
    """Workers that step alone on one sample at a time: ``x`` steps x workers x dims, ``w`` workers x k x dims."""
    w, line = w.copy(), np.arange(w.shape[0])
    for t in range(len(x)):
        d = x[t][:, None] - w
        near = in_order(d * d).argmin(axis=1)
        own = w[line, near]
        w[line, near] = own - eps * (own - x[t])
        if seen is not None and seen(t, w):
            break
    return w
