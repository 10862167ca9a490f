"""Models of traces: tokens to frame vectors to trace vectors, and a pairwise scorer that marks shared frames.

Weights are one dictionary of arrays, saved as .npz and broadcast to tasks. A batch encodes each distinct
frame once, whatever its number of occurrences.
"""

from __future__ import annotations

import hashlib
import io
from dataclasses import asdict, dataclass

import numpy as np

from tracegroup.operators.nn import Arrays, BiLstm, Mlp


@dataclass(frozen=True)
class EncoderConfig:
    """frame_encoder: bilstm or mean (average of token vectors). Traces and frames are read whole unless most_frames or most_tokens is given."""

    vocab: int = 10_000
    token: int = 32
    frame: int = 32
    trace: int = 64
    pool: str = "all"
    frame_encoder: str = "bilstm"
    most_frames: int | None = None
    most_tokens: int | None = None
    seed: int = 11


#: A frame [OWN, x, y] has a fixed vector of its own, drawn from x and y.
OWN = -1
#: Steps, padding included, that a network runs over at a time (a longer row is taken alone).
CELLS = 1 << 14


def padded(rows: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Rows of ids as one array with lengths."""
    lengths = np.array([len(r) for r in rows], np.int64)
    out = np.zeros((len(rows), max(1, int(lengths.max(initial=0)))), np.int64)
    for i, r in enumerate(rows):
        out[i, : lengths[i]] = r
    return out, lengths


def by_length(rows: list, most: int = CELLS) -> list[np.ndarray]:
    """Places of rows of like length, in groups that padded have at most `most` cells."""
    lengths = np.array([max(1, len(r)) for r in rows], np.int64)
    order = np.argsort(lengths, kind="stable")
    out, start = [], 0
    for end in range(1, len(order) + 1):
        if end == len(order) or (end + 1 - start) * lengths[order[end]] > most:
            out.append(order[start:end])
            start = end
    return out


class TraceEncoder:
    """Traces as lists of frames, frames as arrays of token ids."""

    def __init__(self, config: EncoderConfig, params: Arrays | None = None, name: str = "e"):
        self.config, self.name = config, name
        self.params: Arrays = {} if params is None else params
        rng = None if f"{name}.tokens" in self.params else np.random.default_rng(config.seed)
        if rng is not None:
            self.params[f"{name}.tokens"] = rng.normal(0, 0.3, (config.vocab, config.token))
        self.frames = BiLstm(self.params, f"{name}.frame", config.token, config.frame, "all", rng) if config.frame_encoder == "bilstm" else None
        self.frame_width = self.frames.width if self.frames else config.token
        self.traces = BiLstm(self.params, f"{name}.trace", self.frame_width, config.trace, config.pool, rng)
        self.width = self.traces.width

    def _frame_vectors(self, frames: list[np.ndarray], keep: bool) -> tuple[np.ndarray, list]:
        out, caches = np.zeros((len(frames), self.frame_width)), []
        own = np.array([len(f) > 0 and f[0] == OWN for f in frames])
        for i in np.flatnonzero(own):
            out[i] = np.random.default_rng([self.config.seed, *frames[i].astype(np.uint32)]).normal(0, 0.3, self.frame_width)
        rest = np.flatnonzero(~own)
        for at in by_length([frames[i] for i in rest]):
            at = rest[at]
            ids, lengths = padded([frames[i] for i in at])
            x = self.params[f"{self.name}.tokens"][ids]
            if self.frames:
                vec, cache = self.frames.forward(x, lengths)
            else:
                live = np.arange(ids.shape[1])[None, :, None] < lengths[:, None, None]
                vec, cache = np.where(live, x, 0).sum(1) / np.maximum(lengths, 1)[:, None], live
            out[at] = vec
            if keep:
                caches.append((at, ids, lengths, cache))
        return out, caches

    def forward(self, traces: list[list[bytes]], marks: list[np.ndarray] | None = None, marker: np.ndarray | None = None, keep: bool = True) -> tuple[np.ndarray, tuple]:
        """Vectors of traces whose frames are token ids as bytes of int32. marks: per trace, which frames get the marker added.

        keep=False leaves out what backward needs, so that memory is that of CELLS steps.
        """
        traces = [t[: self.config.most_frames] for t in traces]
        index = {f: i for i, f in enumerate(dict.fromkeys(f for t in traces for f in t))}
        vec, frame_caches = self._frame_vectors([np.frombuffer(f, np.int32)[: self.config.most_tokens] for f in index] or [np.zeros(0, np.int32)], keep)
        out, caches = np.zeros((len(traces), self.width)), []
        for at in by_length(traces):
            ids, lengths = padded([np.array([index[f] for f in traces[i]], np.int64) for i in at])
            x = vec[ids]
            flags = None
            if marks is not None:
                flags = np.zeros(ids.shape, bool)
                for k, i in enumerate(at):
                    flags[k, : lengths[k]] = marks[i][: lengths[k]]
                x = x + flags[:, :, None] * marker
            out[at], cache = self.traces.forward(x, lengths)
            if keep:
                caches.append((at, ids, lengths, flags, cache))
        return out, (frame_caches, vec.shape, caches)

    def backward(self, d: np.ndarray, cache: tuple, grads: Arrays) -> np.ndarray:
        """Adds gradients; gives that of the marker."""
        frame_caches, shape, caches = cache
        dvec, dmarker = np.zeros(shape), np.zeros(shape[1])
        for at, ids, lengths, flags, inner in caches:
            dx = self.traces.backward(d[at], inner, grads)
            live = np.arange(ids.shape[1])[None, :] < lengths[:, None]
            np.add.at(dvec, ids[live], dx[live])
            if flags is not None:
                dmarker += dx[flags].sum(0)
        g = grads.setdefault(f"{self.name}.tokens", np.zeros_like(self.params[f"{self.name}.tokens"]))
        for at, ids, lengths, inner in frame_caches:
            if self.frames:
                dt = self.frames.backward(dvec[at], inner, grads)
            else:
                dt = np.where(inner, (dvec[at] / np.maximum(lengths, 1)[:, None])[:, None, :], 0)
            real = np.arange(ids.shape[1])[None, :] < lengths[:, None]
            np.add.at(g, ids[real], dt[real])
        return dmarker


def shared_marks(query: list[bytes], candidate: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Which frames of each trace also stand in the other; every occurrence counts."""
    q, c = set(query), set(candidate)
    return np.array([f in c for f in query], bool), np.array([f in q for f in candidate], bool)


class CrossEncoder:
    """Scores a (query, candidate) pair: both encoded with the marker on shared frames, side by side, into a small network. The query comes first."""

    def __init__(self, config: EncoderConfig, params: Arrays | None = None, use_marker: bool = True):
        self.params: Arrays = {} if params is None else params
        fresh = "r.marker" not in self.params
        self.encoder = TraceEncoder(config, self.params, "r")
        rng = np.random.default_rng(config.seed + 1) if fresh else None
        if fresh:
            self.params["r.marker"] = rng.normal(0, 0.3, self.encoder.frame_width)
        self.use_marker = use_marker
        self.head = Mlp(self.params, "r.head", 2 * self.encoder.width, max(2, self.encoder.width // 3), rng)

    def forward(self, pairs: list[tuple[list[bytes], list[bytes]]], keep: bool = True) -> tuple[np.ndarray, tuple]:
        marks = [shared_marks(q, c) for q, c in pairs]
        if not self.use_marker:
            marks = [(np.zeros_like(a), np.zeros_like(b)) for a, b in marks]
        v = self.params["r.marker"]
        both, cache = self.encoder.forward([q for q, _ in pairs] + [c for _, c in pairs], [a for a, _ in marks] + [b for _, b in marks], v, keep)
        n = len(pairs)
        score, head = self.head.forward(np.concatenate([both[:n], both[n:]], 1))
        return score, (n, cache, head)

    def backward(self, d: np.ndarray, cache: tuple, grads: Arrays) -> None:
        n, inner, head = cache
        dx = self.head.backward(d, head, grads)
        w = dx.shape[1] // 2
        dv = self.encoder.backward(np.concatenate([dx[:, :w], dx[:, w:]]), inner, grads)
        grads["r.marker"] = grads.get("r.marker", 0) + (dv if self.use_marker else 0 * dv)


def unit(x: np.ndarray) -> np.ndarray:
    """Rows of length 1; zero rows stay."""
    n = np.linalg.norm(x, axis=1, keepdims=True)
    return x / np.where(n > 0, n, 1)


def unit_back(x: np.ndarray, d: np.ndarray) -> np.ndarray:
    n = np.linalg.norm(x, axis=1, keepdims=True)
    n = np.where(n > 0, n, 1)
    u = x / n
    return (d - u * (d * u).sum(1, keepdims=True)) / n


def dump(params: Arrays) -> bytes:
    out = io.BytesIO()
    np.savez(out, **params)
    return out.getvalue()


def restore(raw: bytes) -> Arrays:
    with np.load(io.BytesIO(raw)) as z:
        return {k: z[k] for k in z.files}


def model_hash(config: EncoderConfig, params: Arrays) -> str:
    """Names the weights, to be stored beside the vectors they gave."""
    h = hashlib.sha256(repr(sorted(asdict(config).items())).encode())
    for k in sorted(params):
        h.update(k.encode() + params[k].tobytes())
    return h.hexdigest()[:16]
