"""A convolutional text classifier in numpy: embeddings, several filter widths, max pooling, softmax.

Sequences of ids lie one after another in one array, each followed by at least
``max(widths) - 1`` zeros; id 0 embeds to zero, so no filter sees two sequences.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


@dataclass
class ConvNet:
    emb: np.ndarray  # (ids, dims); row 0 is zero
    filters: dict[int, np.ndarray]  # width -> (width, dims, filters)
    bias: np.ndarray
    dense: np.ndarray
    top: np.ndarray

    @classmethod
    def fresh(cls, ids: int, classes: int, dims: int, n_filters: int, widths: tuple[int, ...], seed: int = 7) -> "ConvNet":
        rng = np.random.default_rng(seed)
        emb = rng.normal(0, 0.3, (ids, dims)).astype(np.float32)
        emb[0] = 0
        filters = {w: rng.normal(0, 1 / np.sqrt(w * dims), (w, dims, n_filters)).astype(np.float32) for w in widths}
        total = n_filters * len(widths)
        return cls(emb, filters, np.zeros(total, np.float32), rng.normal(0, 0.3, (total, classes)).astype(np.float32), np.zeros(classes, np.float32))

    @property
    def pad(self) -> int:
        return max(self.filters) - 1

    def _params(self) -> list[np.ndarray]:
        return [self.emb, *self.filters.values(), self.bias, self.dense, self.top]

    def _pooled(self, ids: np.ndarray, starts: np.ndarray, where: bool):
        x = self.emb[ids]
        best, at = [], []
        ends = np.append(starts[1:], len(ids) - self.pad)
        for w, f in self.filters.items():
            n = len(ids) - w + 1
            c = x[:n] @ f[0]
            for o in range(1, w):
                c += x[o : o + n] @ f[o]
            if where:
                p = np.stack([s + c[s:e].argmax(0) for s, e in zip(starts, np.minimum(ends, n))])
                best.append(c[p, np.arange(c.shape[1])])
                at.append(p)
            else:
                best.append(np.maximum.reduceat(c, starts))
        return np.concatenate(best, 1), at

    def fit(self, seqs: list[np.ndarray], labels: np.ndarray, weights: np.ndarray, epochs: int, batch: int = 64, rate: float = 0.01, decay: float = 1e-5, seed: int = 11) -> None:
        """Adam on the weighted cross entropy; the gradient runs through the pooled positions only."""
        rng = np.random.default_rng(seed)
        params = self._params()
        m, v = [np.zeros_like(p) for p in params], [np.zeros_like(p) for p in params]
        step, zeros = 0, np.zeros(self.pad, np.int32)
        for epoch in range(epochs):
            order = rng.permutation(len(seqs))
            for lo in range(0, len(order), batch):
                idx = order[lo : lo + batch]
                parts, starts, at = [], [], 0
                for i in idx:
                    starts.append(at)
                    parts += [seqs[i] if len(seqs[i]) else np.zeros(1, np.int32), zeros]
                    at += max(1, len(seqs[i])) + self.pad
                ids, starts = np.concatenate(parts), np.array(starts)
                best, where = self._pooled(ids, starts, True)
                h = np.maximum(best + self.bias, 0)
                z = h @ self.dense + self.top
                p = np.exp(z - z.max(1, keepdims=True))
                p /= p.sum(1, keepdims=True)
                p[np.arange(len(idx)), labels[idx]] -= 1
                p *= (weights[idx] / len(idx))[:, None]
                dh = (p @ self.dense.T) * (h > 0)
                grads = [np.zeros_like(self.emb), *[np.zeros_like(f) for f in self.filters.values()], dh.sum(0), h.T @ p, p.sum(0)]
                col = 0
                for k, (w, f) in enumerate(self.filters.items()):
                    n = f.shape[2]
                    d, pos = dh[:, col : col + n], where[k]
                    for o in range(w):
                        i = ids[pos + o]
                        grads[1 + k][o] += np.einsum("bfd,bf->df", self.emb[i], d)
                        np.add.at(grads[0], i.ravel(), (d[:, :, None] * f[o].T[None]).reshape(-1, f.shape[1]))
                    col += n
                grads[0][0] = 0
                step += 1
                lr = rate * (1 - 0.9 * (epoch / max(1, epochs)))
                for q, g, a, b in zip(params, grads, m, v):
                    if q is not self.emb:
                        g = g + decay * q
                    a += 0.1 * (g - a)
                    b += 0.001 * (g * g - b)
                    q -= lr * (a / (1 - 0.9**step)) / (np.sqrt(b / (1 - 0.999**step)) + 1e-8)
                self.emb[0] = 0

    def tables(self) -> dict[int, list[np.ndarray]]:
        """For each width and offset the filters' responses to every id: a convolution is then a sum of looked-up rows."""
        return {w: [np.ascontiguousarray(self.emb @ f[o]) for o in range(w)] for w, f in self.filters.items()}

    def logits(self, best: np.ndarray) -> np.ndarray:
        return np.maximum(best + self.bias, 0) @ self.dense + self.top


def softmax(z: np.ndarray) -> np.ndarray:
    p = np.exp(z - z.max(-1, keepdims=True))
    return p / p.sum(-1, keepdims=True)
