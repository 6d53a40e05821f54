"""Array arithmetic of blocks, attention, losses, wavelets, optimizers and schedules."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def total(a: Column) -> Column:
    return F.aggregate(a, F.lit(0.0), lambda s, x: s + x)


def dot(a: Column, b: Column) -> Column:
    return total(F.zip_with(a, b, lambda x, y: x * y))


def bind(values: dict[str, Column], body) -> Column:
    """``body`` of values that are worked out once for a row; inside a function over an array, an expression would
    be worked out again for each element."""
    one = F.array(F.struct(*(v.alias(k) for k, v in values.items())))
    return F.get(F.transform(one, body), F.lit(0))


def rms_norm(x: Column, eps: float = 1e-6) -> Column:
    return bind({"x": x}, lambda a: bind({"x": a["x"], "r": F.sqrt(dot(a["x"], a["x"]) / F.size(a["x"]) + eps)}, lambda t: F.transform(t["x"], lambda v: v / t["r"])))


def layer_norm(x: Column, eps: float = 1e-6) -> Column:
    spread = lambda a: F.sqrt(total(F.transform(a["x"], lambda v: (v - a["m"]) * (v - a["m"]))) / F.size(a["x"]) + eps)
    centred = lambda a: bind({"x": a["x"], "m": a["m"], "s": spread(a)}, lambda t: F.transform(t["x"], lambda v: (v - t["m"]) / t["s"]))
    return bind({"x": x}, lambda y: bind({"x": y["x"], "m": total(y["x"]) / F.size(y["x"])}, centred))


def progressive_norm(x: Column, layer: int) -> Column:
    """RMS norm damped with depth; layers count from one."""
    return F.transform(rms_norm(x), lambda v: v / math.sqrt(layer))


def gated_residual(x: Column, r: Column, gate: Column) -> Column:
    g = F.tanh(gate)
    return F.zip_with(x, r, lambda a, b: a + g * b)


def norm_scale(x: Column, scale: Column) -> Column:
    return F.transform(layer_norm(x), lambda v: v * (1 + scale))


# --- attention (numpy kernels of one sample) ---


def softmax(x: np.ndarray) -> np.ndarray:
    e = np.exp(x - x.max(axis=-1, keepdims=True))
    return e / e.sum(axis=-1, keepdims=True)


def gqa(q: np.ndarray, k: np.ndarray, v: np.ndarray) -> np.ndarray:
    """Query heads [Hq,S,d] share key and value heads [Hkv,T,d] in equal groups."""
    rep = len(q) // len(k)
    k, v = np.repeat(k, rep, axis=0), np.repeat(v, rep, axis=0)
    return softmax(q @ k.transpose(0, 2, 1) / math.sqrt(q.shape[-1])) @ v


def joint(img: np.ndarray, txt: np.ndarray, mode: str = "joint") -> np.ndarray:
    """Image tokens attend to image and text in one call; ``separate`` adds two calls; ``both`` lets text
    attend as well."""
    every = np.concatenate([img, txt])
    one = lambda q, kv: softmax(q @ kv.T / math.sqrt(q.shape[-1])) @ kv
    if mode == "joint":
        return one(img, every)
    return one(img, img) + one(img, txt) if mode == "separate" else one(every, every)


def rotary(x: np.ndarray, pos: np.ndarray, axes: tuple[int, ...], base: float = 10_000.0) -> np.ndarray:
    """Rotate pairs of dimensions by positions on several axes; ``axes`` are dimensions per axis."""
    out, at = x.astype(np.float64).copy(), 0
    for a, d in enumerate(axes):
        f = base ** (-np.arange(0, d, 2) / d)
        ang = pos[:, a : a + 1] * f
        u, w = x[:, at : at + d : 2], x[:, at + 1 : at + d : 2]
        out[:, at : at + d : 2], out[:, at + 1 : at + d : 2] = u * np.cos(ang) - w * np.sin(ang), u * np.sin(ang) + w * np.cos(ang)
        at += d
    return out


# --- flow ---


def interpolate(x0: Column, eps: Column, t: Column) -> Column:
    return F.zip_with(x0, eps, lambda a, b: (1 - t) * a + t * b)


def velocity(x0: Column, eps: Column) -> Column:
    return F.zip_with(x0, eps, lambda a, b: a - b)


def reconstruct(v: Column, eps: Column) -> Column:
    return F.zip_with(v, eps, lambda a, b: a + b)


def mse(a: Column, b: Column) -> Column:
    d = F.zip_with(a, b, lambda x, y: (x - y) * (x - y))
    return total(d) / F.size(d)


#: Image tokens and the shift that goes with them.
SHIFT_POINTS = ((256, 0.5), (4096, 1.15))


def mu(tokens: Column) -> Column:
    (n0, m0), (n1, m1) = SHIFT_POINTS
    return m0 + (tokens - n0) * ((m1 - m0) / (n1 - n0))


def logistic(x: Column) -> Column:
    return 1 / (1 + F.exp(-x))


def shift_t(t: Column, m: Column, sigma: float = 1.0) -> Column:
    return F.exp(m) / (F.exp(m) + F.pow(1 / t - 1, F.lit(sigma)))


def integrate(z1: np.ndarray, cond, uncond, steps: int = 50, guidance: float = 8.0) -> np.ndarray:
    """Straight-path integration from noise to data with guided velocity."""
    z, dt = z1.copy(), 1.0 / steps
    for i in range(steps):
        t = 1.0 - i * dt
        u = uncond(z, t)
        z = z + dt * (u + guidance * (cond(z, t) - u))
    return z


# --- wavelet ---


def haar(grid: Column, side: int = 8) -> dict[str, Column]:
    """Four half-size bands of one orthonormal Haar step."""
    signs = {"ll": (1, 1, 1, 1), "lh": (1, 1, -1, -1), "hl": (1, -1, 1, -1), "hh": (1, -1, -1, 1)}
    out = {}
    for k, s in signs.items():
        out[k] = F.array(*(sum((F.get(grid, F.lit((r + i // 2) * side + c + i % 2)) * float(s[i]) for i in range(4)), F.lit(0.0)) / 2 for r in range(0, side, 2) for c in range(0, side, 2)))
    return out


def wavelet_loss(a: Column, b: Column, high: float = 1.0) -> Column:
    x, y = haar(a), haar(b)
    return mse(x["ll"], y["ll"]) + high * sum((mse(x[k], y[k]) for k in ("lh", "hl", "hh")), F.lit(0.0))


# --- router regularizers ---


def log_sum_exp(logits: Column) -> Column:
    m = F.array_max(logits)
    return m + F.log(total(F.transform(logits, lambda v: F.exp(v - m))))


def ortho_loss(w: np.ndarray) -> tuple[float, float]:
    """Off-diagonal and diagonal part of the squared distance of the column Gram matrix from identity."""
    n = w / np.linalg.norm(w, axis=0, keepdims=True)
    g = n.T @ n - np.eye(w.shape[1])
    return float((g**2).sum() - (np.diag(g) ** 2).sum()) / w.shape[1] ** 2, float((np.diag(g) ** 2).sum()) / w.shape[1] ** 2


def ortho_step(w: np.ndarray, rate: float = 1e-7) -> np.ndarray:
    """One direct step against the gradient of the loss through the normalisation."""
    size = np.linalg.norm(w, axis=0, keepdims=True)
    n = w / size
    g = 4 * n @ (n.T @ n - np.eye(w.shape[1])) / w.shape[1] ** 2
    return w - rate * (g - n * (n * g).sum(axis=0, keepdims=True)) / size


def balance_loss(fraction: np.ndarray, probability: np.ndarray) -> float:
    return float(len(fraction) * (fraction * probability).sum())


# --- optimizers and schedules ---


def newton_schulz(g: np.ndarray, steps: int = 10) -> np.ndarray:
    """Nearest semi-orthogonal matrix by cubic iteration."""
    x = g / (np.linalg.norm(g) + 1e-12)
    flip = x.shape[0] > x.shape[1]
    x = x.T if flip else x
    for _ in range(steps):
        x = 1.5 * x - 0.5 * x @ x.T @ x
    return x.T if flip else x


def rms_scale(shape: tuple[int, int]) -> float:
    return 0.2 * math.sqrt(max(shape))


def ortho_momentum_step(w, g, buf, lr=1e-4, beta=0.95, decay=0.01):
    buf = beta * buf + g
    return w * (1 - lr * decay) - lr * rms_scale(w.shape) * newton_schulz(g + beta * buf, 30), buf


def adamw_step(w, g, m, v, t, lr=1e-4, b1=0.9, b2=0.95, decay=0.01, eps=1e-8):
    m, v = b1 * m + (1 - b1) * g, b2 * v + (1 - b2) * g * g
    return w * (1 - lr * decay) - lr * (m / (1 - b1**t)) / (np.sqrt(v / (1 - b2**t)) + eps), m, v


def group_of(name: Column, rank: Column) -> Column:
    """Parameter groups: matrices, router and embeddings, vectors."""
    return F.when(name.rlike("router|embed|modulation|head"), "adamw_decay").when(rank >= 2, "orthogonalised").otherwise("adamw_plain")


def hold_lr(step: Column, peak: float = 1e-4, warm: int = 1000) -> Column:
    return peak * F.least(F.lit(1.0), step / warm)


def stable_decay_lr(step: Column, last: int, peak: float = 1e-4, warm: int = 1000, share: float = 0.1) -> Column:
    start = last * (1 - share)
    return F.when(step < warm, peak * step / warm).when(step < start, F.lit(peak)).otherwise(peak * F.greatest(F.lit(0.0), (last - step) / (last - start)))


def geometric_weights(k: int, beta: float) -> list[float]:
    return [beta**k if j == 0 else (1 - beta) * beta ** (k - j) for j in range(k + 1)]


def implied_decay(c: list[float]) -> list[float]:
    """Multipliers of the updates that a weighted merge stands for: sums of the weights from each on."""
    return [sum(c[m:]) for m in range(len(c))]


def merge_weights(scheme: str, n: int, beta: float = 0.9) -> list[float]:
    """Weights of the last ``n`` checkpoints, oldest first. ``printed``: 1 - sqrt(j/n) with j from the
    oldest; ``derived``: differences of the decay profile 1 - sqrt(j/n), which weigh the newest least only
    where the profile falls slowly."""
    if scheme == "mean":
        raw = [1.0] * n
    elif scheme == "geometric":
        raw = [beta ** (n - 1 - j) for j in range(n)]
    elif scheme == "printed":
        raw = [1 - math.sqrt(j / n) for j in range(n)]
    elif scheme == "derived":
        raw = [math.sqrt((j + 1) / n) - math.sqrt(j / n) for j in range(n)]
    else:
        raw = [0.0] * (n - 1) + [1.0]
    return [r / sum(raw) for r in raw]


def timestep_embedding(t: Column, dims: int, base: float = 10_000.0) -> Column:
    """Cosines then sines of 1000 t over falling frequencies."""
    half = dims // 2
    rate = lambda i: 1000 * t * F.pow(F.lit(base), -(i % half) / half)
    return F.transform(F.sequence(F.lit(0), F.lit(dims - 1)), lambda i: F.when(i < half, F.cos(rate(i))).otherwise(F.sin(rate(i))))


def modulation(emb: np.ndarray, w1: np.ndarray, w2: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Scale and gate of one layer: two linear layers with a SiLU between; zero w2 is the identity."""
    h = emb @ w1
    scale, gate = np.split((h / (1 + np.exp(-h))) @ w2, 2, axis=-1)
    return 1 + scale, np.tanh(gate)


def truncated_normal(key: Column, sigma: float, seed: int, bound: float = 2.0, tries: int = 8) -> Column:
    """A normal draw by hash of the key, drawn again while beyond ``bound`` sigmas; after ``tries`` draws (one in
    10^10) the bound itself."""
    unit = lambda *salt: (F.pmod(F.xxhash64(key, F.lit(seed), *salt), F.lit(1 << 52)) + 1) / float((1 << 52) + 1)
    draws = [F.sqrt(-2 * F.log(unit(F.lit(2 * k)))) * F.cos(2 * np.pi * unit(F.lit(2 * k + 1))) for k in range(tries)]
    return sigma * F.coalesce(*[F.when(F.abs(z) <= bound, z) for z in draws], F.lit(bound))
