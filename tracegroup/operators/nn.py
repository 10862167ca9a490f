"""Recurrent encoders with exact gradients, in NumPy.

All arrays are batch x time x size with lengths; what stands behind a row's length never counts. Both
directions of a layer see only true steps: the backward one runs over each row reversed in its own length.
"""

from __future__ import annotations

import numpy as np

Arrays = dict[str, np.ndarray]
POOLS = ("all", "avg", "max", "hidden")


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 0.5 * (1 + np.tanh(0.5 * x))


def softplus(x: np.ndarray) -> np.ndarray:
    return np.maximum(x, 0) + np.log1p(np.exp(-np.abs(x)))


def reversed_rows(x: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Each row's first `length` steps in reverse order; its own inverse."""
    t = np.arange(x.shape[1])[None, :]
    at = np.where(t < lengths[:, None], lengths[:, None] - 1 - t, t)
    return x[np.arange(len(x))[:, None], at]


class Lstm:
    """One direction. Parameters under `name` in a shared dictionary: w ((inputs + size) x 4 size) and b."""

    def __init__(self, params: Arrays, name: str, inputs: int, size: int, rng: np.random.Generator | None = None):
        self.name, self.size, self.params = name, size, params
        if rng is not None:
            params[f"{name}.w"] = rng.normal(0, 1 / np.sqrt(inputs + size), (inputs + size, 4 * size))
            params[f"{name}.b"] = np.concatenate([np.zeros(size), np.ones(size), np.zeros(2 * size)])

    def forward(self, x: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray, tuple]:
        w, b, n = self.params[f"{self.name}.w"], self.params[f"{self.name}.b"], self.size
        batch, steps, inputs = x.shape
        h, c = np.zeros((batch, n), x.dtype), np.zeros((batch, n), x.dtype)
        out = np.zeros((batch, steps, n), x.dtype)
        saved = []
        given = x @ w[:inputs] + b
        for t in range(steps):
            live = (t < lengths)[:, None]
            z = given[:, t] + h @ w[inputs:]
            i, f, o, g = sigmoid(z[:, :n]), sigmoid(z[:, n : 2 * n]), sigmoid(z[:, 2 * n : 3 * n]), np.tanh(z[:, 3 * n :])
            c_new = f * c + i * g
            tc = np.tanh(c_new)
            saved.append((h, c, i, f, o, g, tc, live))
            h, c = np.where(live, o * tc, h), np.where(live, c_new, c)
            out[:, t] = np.where(live, h, 0)
        return out, h, (x, saved)

    def backward(self, d_out: np.ndarray, d_last: np.ndarray, cache: tuple, grads: Arrays) -> np.ndarray:
        x, saved = cache
        w, n = self.params[f"{self.name}.w"], self.size
        inputs = x.shape[2]
        dx = np.zeros_like(x)
        dw, db = np.zeros_like(w), np.zeros(4 * n, w.dtype)
        dh, dc = d_last.copy(), np.zeros_like(d_last)
        for t in reversed(range(x.shape[1])):
            h, c, i, f, o, g, tc, live = saved[t]
            dh_t = np.where(live, dh + d_out[:, t], 0)
            do = dh_t * tc
            dct = np.where(live, dc, 0) + dh_t * o * (1 - tc * tc)
            dz = np.concatenate([dct * g * i * (1 - i), dct * c * f * (1 - f), do * o * (1 - o), dct * i * (1 - g * g)], 1)
            dw[:inputs] += x[:, t].T @ dz
            dw[inputs:] += h.T @ dz
            db += dz.sum(0)
            dx[:, t] = dz @ w[:inputs].T
            dh = np.where(live, dz @ w[inputs:].T, dh)
            dc = np.where(live, dct * f, dc)
        grads[f"{self.name}.w"] = grads.get(f"{self.name}.w", 0) + dw
        grads[f"{self.name}.b"] = grads.get(f"{self.name}.b", 0) + db
        return dx


def pooled(out: np.ndarray, last: np.ndarray, lengths: np.ndarray, pool: str) -> tuple[np.ndarray, tuple]:
    """Step outputs and last state as one vector: mean, greatest value per place, last state, or all three side by side. Empty rows give zeros."""
    live = np.arange(out.shape[1])[None, :, None] < lengths[:, None, None]
    n = np.maximum(lengths, 1)[:, None]
    mean = np.where(live, out, 0).sum(1) / n
    shut = np.where(live, out, -np.inf)
    at = shut.argmax(1) if out.shape[1] else np.zeros(last.shape, int)
    top = np.where(lengths[:, None] > 0, np.take_along_axis(out, at[:, None, :], 1)[:, 0] if out.shape[1] else 0, 0)
    vec = {"avg": mean, "max": top, "hidden": last}[pool] if pool != "all" else np.concatenate([mean, top, last], 1)
    return vec, (out.shape, live, n, at, lengths, pool)


def pooled_back(d: np.ndarray, cache: tuple) -> tuple[np.ndarray, np.ndarray]:
    shape, live, n, at, lengths, pool = cache
    d_out, size = np.zeros(shape, d.dtype), shape[2]
    d_last = np.zeros((shape[0], size), d.dtype)
    parts = {"avg": d, "max": d, "hidden": d} if pool != "all" else {"avg": d[:, :size], "max": d[:, size : 2 * size], "hidden": d[:, 2 * size :]}
    if pool in ("all", "avg"):
        d_out += np.where(live, (parts["avg"] / n)[:, None, :], 0)
    if pool in ("all", "max") and shape[1]:
        add = np.where(lengths[:, None] > 0, parts["max"], 0)
        np.add.at(d_out, (np.arange(shape[0])[:, None], at, np.arange(size)[None, :]), add)
    if pool in ("all", "hidden"):
        d_last += parts["hidden"]
    return d_out, d_last


class BiLstm:
    """Both directions side by side, and a pool."""

    def __init__(self, params: Arrays, name: str, inputs: int, size: int, pool: str = "all", rng: np.random.Generator | None = None):
        self.ahead, self.back = Lstm(params, f"{name}.ahead", inputs, size, rng), Lstm(params, f"{name}.back", inputs, size, rng)
        self.size, self.pool = size, pool
        self.width = 6 * size if pool == "all" else 2 * size

    def forward(self, x: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, tuple]:
        a, ha, ca = self.ahead.forward(x, lengths)
        b, hb, cb = self.back.forward(reversed_rows(x, lengths), lengths)
        vec, cp = pooled(np.concatenate([a, reversed_rows(b, lengths)], 2), np.concatenate([ha, hb], 1), lengths, self.pool)
        return vec, (ca, cb, cp, lengths)

    def backward(self, d: np.ndarray, cache: tuple, grads: Arrays) -> np.ndarray:
        ca, cb, cp, lengths = cache
        d_out, d_last = pooled_back(d, cp)
        n = self.size
        dx = self.ahead.backward(d_out[:, :, :n], d_last[:, :n], ca, grads)
        return dx + reversed_rows(self.back.backward(reversed_rows(d_out[:, :, n:], lengths), d_last[:, n:], cb, grads), lengths)


class Mlp:
    """One hidden layer with a ramp, one number out."""

    def __init__(self, params: Arrays, name: str, inputs: int, hidden: int, rng: np.random.Generator | None = None):
        self.name, self.params = name, params
        if rng is not None:
            params[f"{name}.w1"] = rng.normal(0, np.sqrt(2 / inputs), (inputs, hidden))
            params[f"{name}.b1"] = np.zeros(hidden)
            params[f"{name}.w2"] = rng.normal(0, np.sqrt(1 / hidden), (hidden, 1))
            params[f"{name}.b2"] = np.zeros(1)

    def forward(self, x: np.ndarray) -> tuple[np.ndarray, tuple]:
        p, k = self.params, self.name
        h = np.maximum(x @ p[f"{k}.w1"] + p[f"{k}.b1"], 0)
        return (h @ p[f"{k}.w2"] + p[f"{k}.b2"])[:, 0], (x, h)

    def backward(self, d: np.ndarray, cache: tuple, grads: Arrays) -> np.ndarray:
        x, h = cache
        p, k = self.params, self.name
        dh = (d[:, None] @ p[f"{k}.w2"].T) * (h > 0)
        for key, g in (("w2", h.T @ d[:, None]), ("b2", d.sum(keepdims=True)), ("w1", x.T @ dh), ("b1", dh.sum(0))):
            grads[f"{k}.{key}"] = grads.get(f"{k}.{key}", 0) + g
        return dh @ p[f"{k}.w1"].T


class Adam:
    def __init__(self, params: Arrays, rate: float = 1e-3):
        self.params, self.rate, self.t = params, rate, 0
        self.m = {k: np.zeros_like(v) for k, v in params.items()}
        self.v = {k: np.zeros_like(v) for k, v in params.items()}

    def step(self, grads: Arrays) -> None:
        self.t += 1
        for k, g in grads.items():
            self.m[k] = 0.9 * self.m[k] + 0.1 * g
            self.v[k] = 0.999 * self.v[k] + 0.001 * g * g
            self.params[k] -= (self.rate * (self.m[k] / (1 - 0.9**self.t)) / (np.sqrt(self.v[k] / (1 - 0.999**self.t)) + 1e-8)).astype(self.params[k].dtype)
