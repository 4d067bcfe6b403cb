"""Small sine-activated networks in numpy: layout, initial values, forward, backward, Adam."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


@dataclass(frozen=True)
class NetSpec:
    """`depth` sine layers of `hidden` units and a linear output; inputs are 3 coordinates and a latent code."""

    hidden: int = 24
    depth: int = 3
    omega: float = 30.0
    latent_dim: int = 4
    coords: int = 3

    @property
    def layers(self) -> list[tuple[int, int]]:
        sizes = [self.coords + self.latent_dim] + [self.hidden] * self.depth + [1]
        return list(zip(sizes, sizes[1:]))

    @property
    def parameters(self) -> int:
        return sum(a * b + b for a, b in self.layers)

    def layout(self) -> list[tuple[int, str, int, int]]:
        """(layer, kind, row, col) of every place in the flat parameter vector."""
        out = []
        for layer, (a, b) in enumerate(self.layers):
            out += [(layer, "w", i, j) for i in range(a) for j in range(b)] + [(layer, "b", 0, j) for j in range(b)]
        return out

    def split(self, theta: np.ndarray) -> list[tuple[np.ndarray, np.ndarray]]:
        out, at = [], 0
        for a, b in self.layers:
            out.append((theta[at : at + a * b].reshape(a, b), theta[at + a * b : at + a * b + b]))
            at += a * b + b
        return out


def parameters_for_width(width: int, depth: int, inputs: int = 4) -> int:
    """Parameters of a plain coordinate network of `depth` sine layers."""
    return inputs * width + width + (depth - 1) * (width * width + width) + width + 1


def width_for_bytes(budget: float, depth: int, inputs: int = 4, bytes_each: int = 4) -> int:
    """The widest network whose parameters fit the budget (closed form of the quadratic in the width)."""
    n = budget / bytes_each
    a, b, c = depth - 1, inputs + 1 + depth - 1 + 1, 1 - n
    w = (n - 1) / b if a == 0 else (-b + np.sqrt(b * b - 4 * a * c)) / (2 * a)
    return max(1, int(w))


def init_params(spec: NetSpec, scale: int, net_id: int, seed: int = 0) -> np.ndarray:
    """First layer uniform in 1/fan_in, others in sqrt(6/fan_in)/omega: the same on every retry."""
    rng = np.random.default_rng([seed, scale, net_id])
    parts = []
    for layer, (a, b) in enumerate(spec.layers):
        bound = 1 / a if layer == 0 else np.sqrt(6 / a) / spec.omega
        parts += [rng.uniform(-bound, bound, a * b), rng.uniform(-bound, bound, b)]
    return np.concatenate(parts)


def init_latent(spec: NetSpec, scale: int, block_id: int, seed: int = 0) -> np.ndarray:
    return np.random.default_rng([seed + 1, scale, block_id]).normal(0, 0.1, spec.latent_dim)


def local_coordinates(bx: int, by: int, bz: int) -> np.ndarray:
    """Row-major voxel places of a block in [-1, 1]^3."""
    axis = lambda n: np.linspace(-1, 1, n) if n > 1 else np.zeros(1)
    g = np.meshgrid(axis(bx), axis(by), axis(bz), indexing="ij")
    return np.stack([a.ravel() for a in g], axis=1)


def forward(spec: NetSpec, theta: np.ndarray, x: np.ndarray, keep: list | None = None) -> np.ndarray:
    h = x
    for w, b in spec.split(theta)[:-1]:
        a = spec.omega * (h @ w + b)
        if keep is not None:
            keep.append((h, a))
        h = np.sin(a)
    w, b = spec.split(theta)[-1]
    if keep is not None:
        keep.append((h, None))
    return (h @ w + b)[:, 0]


def backward(spec: NetSpec, theta: np.ndarray, kept: list, d_out: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Gradients by parameter and by input, from the gradient by output."""
    parts, out = spec.split(theta), []
    d = d_out[:, None]
    for layer in range(len(parts) - 1, -1, -1):
        h, a = kept[layer]
        if a is not None:
            d = d * np.cos(a) * spec.omega
        out.append(np.concatenate([(h.T @ d).ravel(), d.sum(axis=0)]))
        d = d @ parts[layer][0].T
    return np.concatenate(out[::-1]), d


class Adam:
    """Adam with weight decay added to the gradient (or, decoupled, to the step)."""

    def __init__(self, size: int, beta1: float = 0.9, beta2: float = 0.999, eps: float = 1e-8, decay: float = 2e-5, decoupled: bool = False):
        self.m, self.v, self.t = np.zeros(size), np.zeros(size), 0
        self.beta1, self.beta2, self.eps, self.decay, self.decoupled = beta1, beta2, eps, decay, decoupled

    def step(self, x: np.ndarray, g: np.ndarray, rate: float) -> np.ndarray:
        self.t += 1
        if self.decay and not self.decoupled:
            g = g + self.decay * x
        self.m = self.beta1 * self.m + (1 - self.beta1) * g
        self.v = self.beta2 * self.v + (1 - self.beta2) * g * g
        move = rate * (self.m / (1 - self.beta1**self.t)) / (np.sqrt(self.v / (1 - self.beta2**self.t)) + self.eps)
        return x - move - (rate * self.decay * x if self.decoupled else 0)


def net_inputs(coords: np.ndarray, latents: np.ndarray) -> np.ndarray:
    """Every block's coordinates with its latent code beside them."""
    nb, b = len(latents), len(coords)
    return np.concatenate([np.tile(coords, (nb, 1)), np.repeat(latents, b, axis=0)], axis=1)


def loss_and_gradient(spec: NetSpec, theta: np.ndarray, latents: np.ndarray, coords: np.ndarray, values: np.ndarray, loss: str = "mse") -> tuple[float, np.ndarray, np.ndarray]:
    """Mean over blocks of the block's mean squared error (or of its norm), with gradients by parameters and latents."""
    nb, b = values.shape
    kept: list = []
    out = forward(spec, theta, net_inputs(coords, latents), kept).reshape(nb, b)
    e = out - values
    if loss == "mse":
        total, d = float(np.mean(e * e)), 2 * e / e.size
    else:
        norm = np.sqrt((e * e).sum(axis=1, keepdims=True)) + 1e-12
        total, d = float(norm.mean()), e / norm / nb
    g, dx = backward(spec, theta, kept, d.ravel())
    return total, g, dx[:, spec.coords :].reshape(nb, b, -1).sum(axis=1)


def fit_net(spec: NetSpec, theta: np.ndarray, latents: np.ndarray, coords: np.ndarray, values: np.ndarray, epochs: int, rate: float, alive: np.ndarray | None = None, loss: str = "mse", chunk: int = 4096) -> tuple[np.ndarray, np.ndarray, float]:
    """Trains one net on its blocks; all voxels are seen in every epoch, whole blocks at a time. Pruned parameters stay 0."""
    adam_t, adam_l = Adam(len(theta)), Adam(latents.size, decay=0.0)
    per = max(1, chunk // max(1, len(coords)))
    last = np.inf
    for _ in range(epochs):
        total = 0.0
        for i in range(0, len(values), per):
            part = slice(i, i + per)
            here, g, gl = loss_and_gradient(spec, theta, latents[part], coords, values[part], loss)
            full = np.zeros_like(latents)
            full[part] = gl
            theta = adam_t.step(theta, g if alive is None else g * alive, rate)
            if alive is not None:
                theta = theta * alive
            if spec.latent_dim:
                latents = adam_l.step(latents.ravel(), full.ravel(), rate).reshape(latents.shape)
            total += here * len(values[part])
        last = total / len(values)
    return theta, latents, last
