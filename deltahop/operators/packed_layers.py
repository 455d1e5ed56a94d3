"""Layers and gradients of one packed batch in numpy, for Arrow grouped maps and local tests.

A layer is a class with forward(batch, h) -> (out, saved) and backward(batch, saved, grad) -> (grad of h, grads of its weights).
`batch` is the sample as the layer sees it, that is trimmed by the layers before.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

from deltahop.operators.packing import Packed, segment_sum


def _spread(batch: Packed) -> np.ndarray:
    """Output row of each entry of the neighbour lists."""
    return np.repeat(np.arange(len(batch.nbr_starts)), batch.lengths())


def _scatter(rows: np.ndarray, values: np.ndarray, n: int) -> np.ndarray:
    """(n, width) sums of the values of each row; column by column, which takes a fraction of np.add.at's time."""
    return np.stack([np.bincount(rows, c, n) for c in np.ascontiguousarray(values.T)], 1)


def _activate(x: np.ndarray, kind: str) -> np.ndarray:
    return np.maximum(x, 0) if kind == "relu" else np.tanh(x) if kind == "tanh" else x


def _slope(x: np.ndarray, y: np.ndarray, kind: str) -> np.ndarray:
    return (x > 0).astype(x.dtype) if kind == "relu" else 1 - y * y if kind == "tanh" else np.ones_like(x)


@dataclass
class AddLayer:
    weights: dict[str, np.ndarray] = field(default_factory=dict)

    def forward(self, batch: Packed, h: np.ndarray):
        return h[batch.outputs] + segment_sum(h[batch.input_rows], batch.nbr_starts), h.shape

    def backward(self, batch: Packed, saved, grad: np.ndarray):
        back = _scatter(batch.input_rows, grad[_spread(batch)], saved[0])
        back[batch.outputs] += grad
        return back, {}


@dataclass
class SageLayer:
    """act(self W_self + mean W_nbr + b)"""

    weights: dict[str, np.ndarray]
    activation: str = "relu"

    @classmethod
    def random(cls, d: int, out: int, rng: np.random.Generator, activation: str = "relu") -> SageLayer:
        scale = np.sqrt(1.0 / d)
        return cls({"self": rng.normal(0, scale, (d, out)), "nbr": rng.normal(0, scale, (d, out)), "bias": np.zeros(out)}, activation)

    def forward(self, batch: Packed, h: np.ndarray):
        n = np.maximum(batch.lengths(), 1)[:, None]
        own, mean = h[batch.outputs], segment_sum(h[batch.input_rows], batch.nbr_starts) / n
        x = own @ self.weights["self"] + mean @ self.weights["nbr"] + self.weights["bias"]
        y = _activate(x, self.activation)
        return y, (h.shape, own, mean, n, x, y)

    def backward(self, batch: Packed, saved, grad: np.ndarray):
        shape, own, mean, n, x, y = saved
        g = grad * _slope(x, y, self.activation)
        to_nbr = (g @ self.weights["nbr"].T) / n
        back = _scatter(batch.input_rows, to_nbr[_spread(batch)], shape[0])
        back[batch.outputs] += g @ self.weights["self"].T
        return back, {"self": own.T @ g, "nbr": mean.T @ g, "bias": g.sum(0)}


@dataclass
class GatLayer:
    """Attention over the neighbours and the vertex itself; `heads` heads are concatenated."""

    weights: dict[str, np.ndarray]
    heads: int = 1
    slope: float = 0.2
    activation: str = "none"

    @classmethod
    def random(cls, d: int, out: int, rng: np.random.Generator, heads: int = 1, activation: str = "none") -> GatLayer:
        w = {}
        for k in range(heads):
            w |= {f"w{k}": rng.normal(0, np.sqrt(1.0 / d), (d, out // heads)), f"s{k}": rng.normal(0, 0.3, out // heads), f"n{k}": rng.normal(0, 0.3, out // heads)}
        return cls(w, heads, activation=activation)

    def _lists(self, batch: Packed, rows: int):
        """Neighbour entries with the vertex itself put before each list."""
        n = len(batch.nbr_starts)
        own = np.arange(rows - n, rows)
        starts = batch.nbr_starts + np.arange(n)
        sizes = batch.lengths() + 1
        src = np.empty(len(batch.input_rows) + n, np.int64)
        first = np.zeros(len(src), bool)
        first[starts] = True
        src[first], src[~first] = own, batch.input_rows
        return own, src, np.repeat(np.arange(n), sizes), starts

    def forward(self, batch: Packed, h: np.ndarray):
        own, src, row, starts = self._lists(batch, len(h))
        outs, saved = [], []
        for k in range(self.heads):
            z = h @ self.weights[f"w{k}"]
            pre = (z @ self.weights[f"s{k}"])[own][row] + (z @ self.weights[f"n{k}"])[src]
            e = np.where(pre > 0, pre, self.slope * pre)
            x = np.exp(e - np.maximum.reduceat(e, starts)[row]) if len(e) else e
            alpha = x / segment_sum(x, starts)[row]
            outs.append(segment_sum(alpha[:, None] * z[src], starts))
            saved.append((z, pre, alpha))
        x = np.concatenate(outs, 1)
        y = _activate(x, self.activation)
        return y, (h, own, src, row, starts, saved, x, y)

    def backward(self, batch: Packed, saved, grad: np.ndarray):
        h, own, src, row, starts, heads, x, y = saved
        g_all = grad * _slope(x, y, self.activation)
        back, grads = np.zeros_like(h), {}
        width = g_all.shape[1] // self.heads
        for k, (z, pre, alpha) in enumerate(heads):
            g = g_all[:, k * width : (k + 1) * width]
            dz = _scatter(src, alpha[:, None] * g[row], len(z))
            da = (g[row] * z[src]).sum(1)
            de = alpha * (da - segment_sum(alpha * da, starts)[row])
            de = np.where(pre > 0, de, self.slope * de)
            s, n = self.weights[f"s{k}"], self.weights[f"n{k}"]
            per_row = segment_sum(de, starts)
            dz[own] += per_row[:, None] * s
            dz += np.bincount(src, de, len(z))[:, None] * n
            grads |= {f"s{k}": z[own].T @ per_row, f"n{k}": z[src].T @ de, f"w{k}": h.T @ dz}
            back += dz @ self.weights[f"w{k}"].T
        return back, grads


def run_forward(batch: Packed, h0: np.ndarray, layers: list):
    """(vectors of the targets, saved states): the batch is trimmed after every layer."""
    h, saved = h0, []
    for i, layer in enumerate(layers):
        h, state = layer.forward(batch, h)
        saved.append((batch, state))
        if i + 1 < len(layers):
            batch = batch.trimmed()
    return h, saved


def run_backward(layers: list, saved, grad: np.ndarray):
    """(grad of h0, grads per layer)."""
    grads = [None] * len(layers)
    for i in range(len(layers) - 1, -1, -1):
        batch, state = saved[i]
        grad, grads[i] = layers[i].backward(batch, state, grad)
    return grad, grads


def softmax_head(h: np.ndarray, w: np.ndarray, b: np.ndarray, labels: np.ndarray):
    """(mean loss, logits, grad of h, grads of w and b)."""
    logits = h @ w + b
    p = np.exp(logits - logits.max(1, keepdims=True))
    p /= p.sum(1, keepdims=True)
    n = len(labels)
    loss = -np.log(np.maximum(p[np.arange(n), labels], 1e-300)).mean()
    d = p.copy()
    d[np.arange(n), labels] -= 1
    d /= n
    return loss, logits, d @ w.T, h.T @ d, d.sum(0)


def distmult_head(h: np.ndarray, src: np.ndarray, rel: np.ndarray, dst: np.ndarray, neg: np.ndarray, r: np.ndarray):
    """Softmax loss of true destinations among shared negatives. src, dst, neg: rows of h; rel: rows of r.

    Returns (mean loss, grad of h, grad of r, positive scores, negative scores).
    """
    q = h[src] * r[rel]
    pos, other = (q * h[dst]).sum(1), q @ h[neg].T
    same = dst[:, None] == neg[None]
    other = np.where(same, -np.inf, other)
    scores = np.concatenate([pos[:, None], other], 1)
    top = scores.max(1, keepdims=True)
    p = np.exp(scores - top)
    z = p.sum(1, keepdims=True)
    loss = (np.log(z[:, 0]) + top[:, 0] - pos).mean()
    d = p / z
    d[:, 0] -= 1
    d /= len(src)
    gh, gr = np.zeros_like(h), np.zeros_like(r)
    gq = d[:, :1] * h[dst] + d[:, 1:] @ h[neg]
    np.add.at(gh, dst, d[:, :1] * q)
    np.add.at(gh, neg, d[:, 1:].T @ q)
    np.add.at(gh, src, gq * r[rel])
    np.add.at(gr, rel, gq * h[src])
    return loss, gh, gr, pos, other
