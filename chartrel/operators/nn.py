"""A small convolutional network in numpy: three rounds of convolution and pooling, then dense layers; one head per relation function."""

from __future__ import annotations

import numpy as np

CLASSES = ("increasing", "decreasing", "neutral")
SIDE = 32
#: Filters of the three rounds, width of the dense layer.
FILTERS, DENSE = (8, 16, 24), 48


def shrink(mask: np.ndarray, side: int = SIDE) -> np.ndarray:
    """A mask's bounding box as a side x side image of ink shares."""
    ys, xs = np.nonzero(mask)
    if not len(ys):
        return np.zeros((side, side), np.float32)
    y0, x0 = ys.min(), xs.min()
    cy = ((ys - y0) * side // max(1, ys.max() - y0 + 1)).astype(int)
    cx = ((xs - x0) * side // max(1, xs.max() - x0 + 1)).astype(int)
    out = np.zeros((side, side), np.float32)
    np.add.at(out, (cy, cx), 1)
    return np.minimum(out, 1)


def _columns(x: np.ndarray) -> np.ndarray:
    """3 x 3 neighbourhoods of an N x H x W x C array, zero beyond the edge."""
    n, h, w, c = x.shape
    p = np.pad(x, ((0, 0), (1, 1), (1, 1), (0, 0)))
    return np.concatenate([p[:, i : i + h, j : j + w] for i in range(3) for j in range(3)], axis=3)


class Cnn:
    """Weights and the passes through them."""

    def __init__(self, heads: int = 1, seed: int = 0, weights: dict[str, np.ndarray] | None = None):
        self.heads = heads
        if weights is not None:
            self.w = weights
            return
        rng, self.w, c = np.random.default_rng(seed), {}, 1
        for k, f in enumerate(FILTERS):
            self.w[f"k{k}"] = (rng.normal(size=(9 * c, f)) * np.sqrt(2 / (9 * c))).astype(np.float32)
            self.w[f"b{k}"] = np.zeros(f, np.float32)
            c = f
        flat = c * (SIDE // 8) ** 2
        self.w["d"] = (rng.normal(size=(flat, DENSE)) * np.sqrt(2 / flat)).astype(np.float32)
        self.w["db"] = np.zeros(DENSE, np.float32)
        self.w["o"] = (rng.normal(size=(DENSE, 3 * heads)) * 0.1).astype(np.float32)
        self.w["ob"] = np.zeros(3 * heads, np.float32)

    def forward(self, x: np.ndarray, keep: bool = False):
        """Probabilities N x heads x 3 of N x SIDE x SIDE images, and what the way back needs."""
        tape, a = [], x[..., None].astype(np.float32)
        for k in range(3):
            col = _columns(a)
            z = col @ self.w[f"k{k}"] + self.w[f"b{k}"]
            r = np.maximum(z, 0)
            n, h, w, c = r.shape
            blocks = r.reshape(n, h // 2, 2, w // 2, 2, c).transpose(0, 1, 3, 5, 2, 4).reshape(n, h // 2, w // 2, c, 4)
            at = blocks.argmax(axis=-1)
            a = np.take_along_axis(blocks, at[..., None], axis=-1)[..., 0]
            if keep:
                tape.append((col, z, at))
        f = a.reshape(len(a), -1)
        hidden = np.maximum(f @ self.w["d"] + self.w["db"], 0)
        out = (hidden @ self.w["o"] + self.w["ob"]).reshape(len(x), self.heads, 3)
        e = np.exp(out - out.max(axis=2, keepdims=True))
        return e / e.sum(axis=2, keepdims=True), (tape, a.shape, f, hidden)

    def gradient(self, x: np.ndarray, y: np.ndarray) -> tuple[dict[str, np.ndarray], float]:
        """Summed gradients and loss for labels N x heads (-1: no label)."""
        p, (tape, shape, f, hidden) = self.forward(x, keep=True)
        known = (y >= 0)[..., None]
        d = (p - np.eye(3, dtype=np.float32)[np.maximum(y, 0)]) * known
        loss = -float(np.log(np.maximum(np.take_along_axis(p, np.maximum(y, 0)[..., None], 2), 1e-9))[known].sum())
        d = d.reshape(len(x), -1)
        g = {"o": hidden.T @ d, "ob": d.sum(axis=0)}
        dh = (d @ self.w["o"].T) * (hidden > 0)
        g["d"], g["db"] = f.T @ dh, dh.sum(axis=0)
        da = (dh @ self.w["d"].T).reshape(shape)
        for k in (2, 1, 0):
            col, z, at = tape[k]
            n, h, w, c = z.shape
            up = np.zeros((n, h // 2, w // 2, c, 4), np.float32)
            np.put_along_axis(up, at[..., None], da[..., None], axis=-1)
            dz = up.reshape(n, h // 2, w // 2, c, 2, 2).transpose(0, 1, 4, 2, 5, 3).reshape(n, h, w, c) * (z > 0)
            g[f"k{k}"] = col.reshape(-1, col.shape[-1]).T @ dz.reshape(-1, c)
            g[f"b{k}"] = dz.sum(axis=(0, 1, 2))
            if k:
                dc = dz @ self.w[f"k{k}"].T
                cin = dc.shape[-1] // 9
                p_ = np.zeros((n, h + 2, w + 2, cin), np.float32)
                for m in range(9):
                    i, j = divmod(m, 3)
                    p_[:, i : i + h, j : j + w] += dc[..., m * cin : (m + 1) * cin]
                da = p_[:, 1:-1, 1:-1]
        return g, loss


class Adam:
    def __init__(self, rate: float = 2e-3):
        self.rate, self.t, self.m = rate, 0, {}

    def step(self, w: dict[str, np.ndarray], g: dict[str, np.ndarray]) -> None:
        self.t += 1
        for k, v in g.items():
            a, b = self.m.setdefault(k, (np.zeros_like(w[k]), np.zeros_like(w[k])))
            a += 0.1 * (v - a)
            b += 0.001 * (v * v - b)
            w[k] -= (self.rate * (a / (1 - 0.9**self.t)) / (np.sqrt(b / (1 - 0.999**self.t)) + 1e-8)).astype(np.float32)


def fit(x: np.ndarray, y: np.ndarray, model: Cnn | None = None, epochs: int = 30, batch: int = 32, seed: int = 0, rate: float = 2e-3, check: tuple[np.ndarray, np.ndarray] | None = None) -> Cnn:
    """Training on the driver, for the hundreds of images that suffice; a given model is fine-tuned from its weights.

    With images and classes to ``check``, the weights of the epoch that does best on them are kept and their score is ``validation``.
    """
    model = Cnn(y.shape[1], seed) if model is None else Cnn(model.heads, weights={k: v.copy() for k, v in model.w.items()})
    rng, adam, best = np.random.default_rng(seed), Adam(rate), None
    for _ in range(epochs):
        for part in np.array_split(rng.permutation(len(x)), max(1, len(x) // batch)):
            g, _ = model.gradient(x[part], y[part])
            adam.step(model.w, {k: v / len(part) for k, v in g.items()})
        if check is not None and len(check[0]):
            score = float((model.forward(check[0])[0].argmax(axis=2) == check[1]).mean())
            if best is None or score > best[0]:
                best = score, {k: v.copy() for k, v in model.w.items()}
    if best:
        model.validation, model.w = best
    return model
