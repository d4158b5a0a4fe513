"""Small networks in numpy for the tasks that judge vectors: classes, numbers, links.

Hidden layers are sigmoid (classes) or ReLU (numbers). The link network puts source and target through a layer each,
subtracts, and goes on with another layer. Training is Adam with Nesterov momentum on mini-batches with dropout and an
L2 penalty; a tenth of the training rows is held back, and training stops when its loss has not fallen for `patience`
epochs; the best weights are kept. Widths, rates and penalties that have no published value are defaults of our own.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


@dataclass(frozen=True)
class Settings:
    hidden: tuple[int, ...] = (600,)
    dropout: float = 0.2
    l2: float = 1e-4
    rate: float = 2e-3
    batch: int = 64
    patience: int = 50
    max_epochs: int = 200
    val_share: float = 0.1
    seed: int = 1


BINARY, CATEGORIES, REGRESSION, LINK = Settings((600,)), Settings((600, 300)), Settings((300, 300, 150, 150), rate=1e-3), Settings((300, 150))


def _sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -40, 40)))


class Net:
    """kind: binary, categories, regression or link (inputs are source and target side by side)."""

    def __init__(self, kind: str, n_in: int, n_out: int, s: Settings):
        self.kind, self.s = kind, s
        rng = np.random.default_rng(s.seed)
        sizes = [n_in, *s.hidden, n_out]
        if kind == "link":
            half = n_in // 2
            sizes = [half, *s.hidden, 1]
        init = lambda a, b: rng.normal(0, np.sqrt((2.0 if kind == "regression" else 1.0) / a), (a, b))
        self.w = [init(a, b) for a, b in zip(sizes, sizes[1:])] + ([init(sizes[0], sizes[1])] if kind == "link" else [])
        self.b = [np.zeros(w.shape[1]) for w in self.w]

    def forward(self, x: np.ndarray, rng: np.random.Generator | None = None):
        """Output and what the backward pass needs; dropout only with a generator."""
        act = (lambda z: np.maximum(z, 0)) if self.kind == "regression" else _sigmoid
        layers, masks, n = [], [], len(self.w) - (self.kind == "link")
        if self.kind == "link":
            half = x.shape[1] // 2
            a, c = act(x[:, :half] @ self.w[0] + self.b[0]), act(x[:, half:] @ self.w[-1] + self.b[-1])
            layers, h, first = [(x, a, c)], a - c, 1
        else:
            layers, h, first = [], x, 0
        for i in range(first, n):
            if i and rng is not None and self.s.dropout:
                m = (rng.random(h.shape) >= self.s.dropout) / (1 - self.s.dropout)
                h = h * m
            else:
                m = None
            masks.append(m)
            z = h @ self.w[i] + self.b[i]
            layers.append((h, z))
            h = z if i == n - 1 else act(z)
        return h, layers, masks

    def output(self, x: np.ndarray) -> np.ndarray:
        z = self.forward(x)[0]
        if self.kind in ("binary", "link"):
            return _sigmoid(z)
        if self.kind == "categories":
            e = np.exp(z - z.max(axis=1, keepdims=True))
            return e / e.sum(axis=1, keepdims=True)
        return z

    def loss(self, x: np.ndarray, y: np.ndarray) -> float:
        p = self.output(x)
        if self.kind == "regression":
            return float(np.abs(p[:, 0] - y).mean())
        if self.kind == "categories":
            return float(-np.log(p[np.arange(len(y)), y.astype(int)] + 1e-12).mean())
        return float(-(y * np.log(p[:, 0] + 1e-12) + (1 - y) * np.log(1 - p[:, 0] + 1e-12)).mean())

    def gradients(self, x: np.ndarray, y: np.ndarray, rng=None) -> tuple[list[np.ndarray], list[np.ndarray]]:
        z, layers, masks = self.forward(x, rng)
        if self.kind == "regression":
            d = np.sign(z[:, 0] - y)[:, None] / len(y)
        elif self.kind == "categories":
            e = np.exp(z - z.max(axis=1, keepdims=True))
            d = e / e.sum(axis=1, keepdims=True)
            d[np.arange(len(y)), y.astype(int)] -= 1
            d /= len(y)
        else:
            d = (_sigmoid(z[:, 0]) - y)[:, None] / len(y)
        gw, gb = [np.zeros_like(w) for w in self.w], [np.zeros_like(b) for b in self.b]
        first = 1 if self.kind == "link" else 0
        n = len(self.w) - first
        for i in range(n - 1, first - 1, -1):
            h, _ = layers[i] if not first else layers[i - first + 1]
            gw[i], gb[i] = h.T @ d, d.sum(axis=0)
            d = d @ self.w[i].T
            m = masks[i - first]
            if m is not None:
                d = d * m
            if i > first:
                before = layers[i - 1][1] if not first else layers[i - first][1]
                d = d * ((before > 0) if self.kind == "regression" else _sigmoid(before) * (1 - _sigmoid(before)))
        if first:
            x0, a, c = layers[0]
            half = x0.shape[1] // 2
            da, dc = d * a * (1 - a), -d * c * (1 - c)
            gw[0], gb[0], gw[-1], gb[-1] = x0[:, :half].T @ da, da.sum(axis=0), x0[:, half:].T @ dc, dc.sum(axis=0)
        return [g + 2 * self.s.l2 * w for g, w in zip(gw, self.w)], gb


def train(kind: str, x: np.ndarray, y: np.ndarray, settings: Settings, n_out: int = 1) -> Net:
    rng = np.random.default_rng(settings.seed)
    order = rng.permutation(len(x))
    held = order[: max(1, int(settings.val_share * len(x)))]
    rows = order[len(held) :] if len(order) > len(held) else held
    net = Net(kind, x.shape[1], n_out, settings)
    params = net.w + net.b
    m, v = [np.zeros_like(p) for p in params], [np.zeros_like(p) for p in params]
    best, kept, since, t = np.inf, [p.copy() for p in params], 0, 0
    for _ in range(settings.max_epochs):
        shuffled = rng.permutation(rows)
        for start in range(0, len(shuffled), settings.batch):
            part = shuffled[start : start + settings.batch]
            gw, gb = net.gradients(x[part], y[part], rng)
            t += 1
            for p, g, a, b in zip(params, gw + gb, m, v):
                a += 0.1 * (g - a)
                b += 0.001 * (g * g - b)
                look = 0.9 * a / (1 - 0.9 ** (t + 1)) + 0.1 * g / (1 - 0.9**t)
                p -= settings.rate * look / (np.sqrt(b / (1 - 0.999**t)) + 1e-8)
        now = net.loss(x[held], y[held])
        if now < best - 1e-6:
            best, kept, since = now, [p.copy() for p in params], 0
        else:
            since += 1
            if since > settings.patience:
                break
    for p, k in zip(params, kept):
        p[...] = k
    return net


class Recurrent:
    """A small recurrent encoder (one tanh layer over character ids, mean state to classes), trained by Adam.

    A text is read whole, in windows of `length` characters, the last of which ends where the text ends; its state is the
    mean of its windows'. A shorter text is one window, padded before its start.
    """

    def __init__(self, classes: int, width: int = 24, vocabulary: int = 64, length: int = 60, seed: int = 1):
        rng = np.random.default_rng(seed)
        self.length, self.vocabulary = length, vocabulary
        self.p = {"e": rng.normal(0, 0.3, (vocabulary, width)), "u": np.eye(width) * 0.8 + rng.normal(0, 0.05, (width, width)), "o": rng.normal(0, 0.2, (width, classes)), "c": np.zeros(classes)}

    def ids(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Windows x length ids, and the number of each window's text."""
        parts, owner = [], []
        for i, t in enumerate(map(str.lower, texts)):
            starts = [*range(0, max(len(t) - self.length, 0), self.length), max(len(t) - self.length, 0)]
            parts += [t[k : k + self.length] for k in starts]
            owner += [i] * len(starts)
        out = np.zeros((len(parts), self.length), dtype=int)
        for i, t in enumerate(parts):
            codes = [1 + ord(ch) % (self.vocabulary - 1) for ch in t]
            out[i, self.length - len(codes) :] = codes
        return out, np.array(owner, dtype=int)

    def states(self, x: np.ndarray) -> list[np.ndarray]:
        h, out = np.zeros((len(x), self.p["u"].shape[0])), []
        for t in range(self.length):
            h = np.tanh(self.p["e"][x[:, t]] + h @ self.p["u"])
            out.append(h)
        return out

    def predict(self, texts: list[str]) -> np.ndarray:
        out = []
        for i in range(0, len(texts), 64):
            some = texts[i : i + 64]
            x, owner = self.ids(some)
            h = np.zeros((len(some), self.p["u"].shape[0]))
            for k in range(0, len(x), 2048):
                np.add.at(h, owner[k : k + 2048], np.mean(self.states(x[k : k + 2048]), axis=0))
            h /= np.bincount(owner, minlength=len(some))[:, None]
            out.append((h @ self.p["o"] + self.p["c"]).argmax(axis=1))
        return np.concatenate(out) if out else np.zeros(0, int)

    def fit(self, texts: list[str], y: np.ndarray, epochs: int = 12, rate: float = 5e-3, seed: int = 1) -> Recurrent:
        rng, (x, owner) = np.random.default_rng(seed), self.ids(texts)
        begins = np.searchsorted(owner, np.arange(len(texts) + 1))
        m, v, t = {k: np.zeros_like(w) for k, w in self.p.items()}, {k: np.zeros_like(w) for k, w in self.p.items()}, 0
        for _ in range(epochs):
            for part in np.array_split(rng.permutation(len(texts)), max(1, len(texts) // 32)):
                many = begins[part + 1] - begins[part]
                windows, of = np.concatenate([np.arange(begins[i], begins[i + 1]) for i in part]), np.repeat(np.arange(len(part)), many)
                hs = self.states(x[windows])
                mean = np.add.reduceat(np.mean(hs, axis=0), np.cumsum(many) - many) / many[:, None]
                z = mean @ self.p["o"] + self.p["c"]
                d = np.exp(z - z.max(axis=1, keepdims=True))
                d /= d.sum(axis=1, keepdims=True)
                d[np.arange(len(part)), y[part]] -= 1
                d /= len(part)
                g = {k: np.zeros_like(w) for k, w in self.p.items()}
                g["o"], g["c"], each, back = mean.T @ d, d.sum(axis=0), (d @ self.p["o"].T / (self.length * many[:, None]))[of], 0
                for s in range(self.length - 1, -1, -1):
                    dz = (each + back) * (1 - hs[s] ** 2)
                    np.add.at(g["e"], x[windows, s], dz)
                    if s:
                        g["u"] += hs[s - 1].T @ dz
                    back = dz @ self.p["u"].T
                t += 1
                for k in self.p:
                    gk = np.clip(g[k], -1, 1)
                    m[k] = 0.9 * m[k] + 0.1 * gk
                    v[k] = 0.999 * v[k] + 0.001 * gk * gk
                    self.p[k] -= rate * (m[k] / (1 - 0.9**t)) / (np.sqrt(v[k] / (1 - 0.999**t)) + 1e-8)
        return self
