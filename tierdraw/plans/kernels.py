"""Message compressors on one numpy vector, for sweeps of many small training runs; the same methods as the DataFrame operators, with draws from a generator."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np

Rng = np.random.Generator
Compressor = Callable[[np.ndarray, Rng], tuple[np.ndarray, int]]


def uncompressed(w: np.ndarray, rng: Rng) -> tuple[np.ndarray, int]:
    return w, 64 * len(w)


def top_k(k: int) -> Compressor:
    def f(w, rng):
        out = np.zeros_like(w)
        at = np.argpartition(-np.abs(w), min(k, len(w)) - 1)[:k]
        out[at] = w[at]
        return out, 64 * k

    return f


def rand_k(k: int) -> Compressor:
    def f(w, rng):
        out = np.zeros_like(w)
        at = rng.choice(len(w), k, replace=False)
        out[at] = w[at] * (len(w) / k)
        return out, 64 * k

    return f


def segment_tier(s: int) -> Compressor:
    """A segment of s coordinates in order of magnitude, drawn in proportion to its norm."""

    def f(w, rng):
        order = np.argsort(-np.abs(w), kind="stable")
        starts = np.arange(0, len(w), s)
        delta = np.sqrt(np.add.reduceat(w[order] ** 2, starts))
        out = np.zeros_like(w)
        if delta.sum() == 0:
            return out, 64 * s
        q = delta / delta.sum()
        l = rng.choice(len(q), p=q)
        at = order[starts[l] : starts[l] + s]
        out[at] = w[at] / q[l]
        return out, 64 * len(at)

    return f


def fixed_tier(w: np.ndarray, rng: Rng) -> tuple[np.ndarray, int]:
    """One bit of the fixed-point ladder, drawn with geometric probabilities."""
    d, top = len(w), np.abs(w).max(initial=0.0)
    if top == 0:
        return np.zeros_like(w), 2 * d + 70
    l = min(int(np.floor(-np.log2(1 - rng.random() * (1 - 2.0**-63)))) + 1, 63)
    y = np.abs(w) / top
    bit = np.where(y >= 1, 1.0, np.floor(y * 2.0**l) % 2)
    return np.sign(w) * top * bit * (1 - 2.0**-63), 2 * d + 70


def fixed_bits(bits: int) -> Compressor:
    def f(w, rng):
        top = np.abs(w).max(initial=0.0)
        y = np.minimum(np.abs(w) / (top or 1.0), 1 - 2.0**-bits)
        return np.sign(w) * top * np.floor(y * 2**bits) / 2**bits, (1 + bits) * len(w) + 64

    return f


def quantize(steps: int, bits: int) -> Compressor:
    def f(w, rng):
        norm = np.sqrt(w @ w)
        z = steps * np.abs(w) / (norm or 1.0)
        return norm * np.sign(w) * (np.floor(z) + (rng.random(len(w)) < z - np.floor(z))) / steps, bits * len(w) + 64

    return f


def grid(w: np.ndarray, level: int) -> np.ndarray:
    c = np.abs(w).max(initial=0.0)
    if c == 0:
        return np.zeros_like(w)
    delta, edge = 2 * c / (2**level - 1), 2 ** (level - 1) - 1
    return delta * np.clip(np.rint(w / delta), -edge, edge)


def round_to_grid(level: int) -> Compressor:
    return lambda w, rng: (grid(w, level), level * len(w) + 64)


def grid_tier(depth: int) -> Compressor:
    """A drawn difference of the rounding ladder, in proportion to its norm."""

    def f(w, rng):
        values = [np.zeros_like(w), *[grid(w, l) for l in range(1, depth)], w]
        parts = np.diff(np.stack(values), axis=0)
        delta = np.sqrt((parts**2).sum(axis=1))
        if delta.sum() == 0:
            return np.zeros_like(w), 64
        q = delta / delta.sum()
        l = rng.choice(depth, p=q)
        return parts[l] / q[l], 64 * len(w) if l == depth - 1 else (l + 2) * len(w) + 64 + (depth - 1).bit_length()

    return f


class Feedback:
    """EF21 with momentum over a top-k compressor; one per worker."""

    def __init__(self, k: int, beta: float = 0.1) -> None:
        self.c, self.beta, self.m = top_k(k), beta, None

    def __call__(self, w: np.ndarray, rng: Rng) -> tuple[np.ndarray, int]:
        if self.m is None:
            self.m, self.g = w.copy(), w.copy()
            return self.g, 64 * len(w)
        self.m = (1 - self.beta) * self.m + self.beta * w
        sent, bits = self.c(self.m - self.g, rng)
        self.g = self.g + sent
        return self.g, bits


def make(method: str, n: int, k_frac: float) -> Callable[[], Compressor]:
    """A factory of one worker's compressor."""
    k = max(1, int(round(k_frac * n)))
    return {
        "uncompressed": lambda: uncompressed, "topk": lambda: top_k(k), "randk": lambda: rand_k(k), "ef21m": lambda: Feedback(k), "tier_segment": lambda: segment_tier(k),
        "tier_fixed": lambda: fixed_tier, "fixed_2bit": lambda: fixed_bits(1), "qsgd_2bit": lambda: quantize(1, 2), "tier_rtn": lambda: grid_tier(8), **{f"rtn_{l}": (lambda l=l: round_to_grid(l)) for l in (2, 4, 8, 16)},
    }[method]


# losses: gradient and mean loss of a batch, and class scores -----------------------------------------


def softmax_scores(x: np.ndarray, a: np.ndarray, classes: int) -> np.ndarray:
    return a @ x.reshape(classes, -1).T


def softmax_grad(x: np.ndarray, a: np.ndarray, y: np.ndarray, classes: int) -> np.ndarray:
    z = softmax_scores(x, a, classes)
    p = np.exp(z - z.max(axis=1, keepdims=True))
    p /= p.sum(axis=1, keepdims=True)
    p[np.arange(len(y)), y] -= 1
    return (p.T @ a / len(y)).ravel()


HIDDEN = 256


def mlp_parts(x: np.ndarray, d: int, classes: int) -> tuple[np.ndarray, np.ndarray]:
    cut = HIDDEN * d
    return x[:cut].reshape(HIDDEN, d), x[cut:].reshape(classes, HIDDEN + 1)


def mlp_scores(x: np.ndarray, a: np.ndarray, classes: int) -> np.ndarray:
    w1, w2 = mlp_parts(x, a.shape[1], classes)
    h = np.tanh(a @ w1.T)
    return h @ w2[:, :-1].T + w2[:, -1]


def mlp_grad(x: np.ndarray, a: np.ndarray, y: np.ndarray, classes: int) -> np.ndarray:
    w1, w2 = mlp_parts(x, a.shape[1], classes)
    h = np.tanh(a @ w1.T)
    z = h @ w2[:, :-1].T + w2[:, -1]
    p = np.exp(z - z.max(axis=1, keepdims=True))
    p /= p.sum(axis=1, keepdims=True)
    p[np.arange(len(y)), y] -= 1
    p /= len(y)
    g1 = ((p @ w2[:, :-1]) * (1 - h * h)).T @ a
    return np.concatenate([g1.ravel(), np.concatenate([p.T @ h, p.sum(axis=0)[:, None]], axis=1).ravel()])


def judged(x: np.ndarray, a: np.ndarray, y: np.ndarray, classes: int, model: str) -> tuple[np.ndarray, np.ndarray]:
    """Loss of each row, infinite where a score is not finite, and whether its class is found."""
    z = (mlp_scores if model == "mlp" else softmax_scores)(x, a, classes)
    with np.errstate(invalid="ignore", over="ignore"):
        shift = z - z.max(axis=1, keepdims=True)
        loss = np.log(np.exp(shift).sum(axis=1)) - shift[np.arange(len(z)), y]
    return np.where(np.isfinite(z).all(axis=1), loss, np.inf), z.argmax(axis=1) == y


def train(data: dict, method: str, k_frac: float, m: int, batch: int, seed: int, eta: float, steps: int, every: int = 5, models: list | None = None) -> list[tuple]:
    """One run: (step, bits_cum, loss, acc, grad_norm2) every few steps. ``data``: a, y, ta, ty, classes, model ('softmax' or 'mlp'). ``models`` receives the models of these steps."""
    rng = np.random.default_rng(seed)
    a, y, classes = data["a"], data["y"], data["classes"]
    grad = mlp_grad if data["model"] == "mlp" else softmax_grad
    n = HIDDEN * a.shape[1] + classes * (HIDDEN + 1) if data["model"] == "mlp" else classes * a.shape[1]
    x = rng.normal(0, 0.1, n) if data["model"] == "mlp" else np.zeros(n)
    factory = make(method, n, k_frac)
    workers = [factory() for _ in range(m)]
    shard = np.arange(len(y)) % m
    own = [np.flatnonzero(shard == i) if (shard == i).any() else np.arange(len(y)) for i in range(m)]
    out, bits = [], 0
    for step in range(1, steps + 1):
        mean, plain = np.zeros(n), np.zeros(n)
        for i, c in enumerate(workers):
            at = rng.choice(own[i], batch)
            g = grad(x, a[at], y[at], classes)
            sent, b = c(g, rng)
            mean += sent / m
            plain += g / m
            bits += b
        x = x - eta * mean
        if step % every == 0 or step == steps:
            losses, hits = judged(x, data["ta"], data["ty"], classes, data["model"])
            out.append((step, bits, float(losses.mean()) if np.isfinite(losses).all() else float("inf"), float(hits.mean()), float(plain @ plain)))
            if models is not None:
                models.append(x)
    return out
