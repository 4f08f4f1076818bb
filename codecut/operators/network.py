"""Small encoders in numpy: parameters are one flat vector, layers are plain descriptions."""

from __future__ import annotations

import json
import math
from dataclasses import dataclass

import numpy as np


@dataclass(frozen=True)
class EncoderSpec:
    """dim inputs to ``bits`` outputs. layers: ("dense", in, out, relu?) or ("conv", in channels, out channels, kernel, pool)."""

    dim: int
    bits: int
    layers: tuple[tuple, ...]

    @property
    def n_params(self) -> int:
        return sum(int(np.prod(s)) for s in self.shapes())

    def shapes(self) -> list[tuple[int, ...]]:
        out: list[tuple[int, ...]] = []
        for layer in self.layers:
            out += [(layer[1], layer[2]), (layer[2],)] if layer[0] == "dense" else [(layer[2], layer[1], layer[3]), (layer[2],)]
        return out

    def to_json(self) -> str:
        return json.dumps([self.dim, self.bits, self.layers])

    @staticmethod
    def from_json(text: str) -> "EncoderSpec":
        dim, bits, layers = json.loads(text)
        return EncoderSpec(dim, bits, tuple(tuple(x) for x in layers))


def dense_encoder(dim: int, bits: int, hidden: tuple[int, ...] | None = None) -> EncoderSpec:
    """Two hidden layers as wide as the input (or as given), rectified, and a linear output."""
    widths = [dim, *((dim, dim) if hidden is None else hidden)]
    layers = [("dense", a, b, True) for a, b in zip(widths, widths[1:])]
    return EncoderSpec(dim, bits, (*layers, ("dense", widths[-1], bits, False)))


def conv_encoder(dim: int, bits: int, channels: tuple[int, ...] = (4, 4), kernel: int = 5, pool: int = 2) -> EncoderSpec:
    """Convolution, rectification and max pooling along the vector, twice, and one linear map."""
    size, before, layers = dim, 1, []
    for c in channels:
        layers.append(("conv", before, c, kernel, pool))
        size, before = (size - kernel + 1) // pool, c
        if size < 1:
            raise ValueError(f"{dim} components are too few for kernel {kernel} and pool {pool}")
    return EncoderSpec(dim, bits, (*layers, ("dense", size * before, bits, False)))


def linear_encoder(dim: int, bits: int) -> EncoderSpec:
    return EncoderSpec(dim, bits, (("dense", dim, bits, False),))


def init_params(spec: EncoderSpec, seed: int = 0) -> np.ndarray:
    """Seeded normal weights scaled by fan-in; zero biases."""
    rng = np.random.default_rng(seed)
    out = []
    for shape in spec.shapes():
        if len(shape) == 1:
            out.append(np.zeros(shape))
        else:
            fan = shape[0] if len(shape) == 2 else shape[1] * shape[2]
            out.append(rng.normal(0, math.sqrt(2 / fan), shape).ravel())
    return np.concatenate(out)


def split_params(spec: EncoderSpec, params: np.ndarray) -> list[np.ndarray]:
    out, at = [], 0
    for shape in spec.shapes():
        n = int(np.prod(shape))
        out.append(params[at : at + n].reshape(shape))
        at += n
    return out


def _run(spec: EncoderSpec, params: np.ndarray, x: np.ndarray):
    """Output before the head, and what the way back needs."""
    parts, kept = split_params(spec, params), []
    for i, layer in enumerate(spec.layers):
        w, b = parts[2 * i], parts[2 * i + 1]
        if layer[0] == "dense":
            flat = x.reshape(len(x), -1)
            y = flat @ w + b
            kept.append((flat, y, x.shape))
            x = np.maximum(y, 0) if layer[3] else y
        else:
            _, _, c_out, k, pool = layer
            x = x.reshape(len(x), layer[1], -1)
            views = np.lib.stride_tricks.sliding_window_view(x, k, axis=2)  # n, in, places, k
            y = np.einsum("nipk,oik->nop", views, w, optimize=True) + b[:, None]
            m = y.shape[2] // pool
            tiles = np.maximum(y[:, :, : m * pool], 0).reshape(len(x), c_out, m, pool)
            best = tiles.argmax(3)
            kept.append((views, y, best, x.shape))
            x = np.take_along_axis(tiles, best[..., None], 3)[..., 0]
    return x, kept


def forward(spec: EncoderSpec, params: np.ndarray, x: np.ndarray, head: str = "tanh") -> np.ndarray:
    """(n, bits): outputs in (-1, 1) with head tanh, -1 and +1 with head sign (sign of 0 is +1)."""
    z, _ = _run(spec, params, np.asarray(x, float))
    return np.tanh(z) if head == "tanh" else np.where(z >= 0, 1.0, -1.0)


def backward(spec: EncoderSpec, params: np.ndarray, x: np.ndarray, output_grad) -> tuple[np.ndarray, object]:
    """Gradient of the parameters; output_grad maps tanh outputs to (their gradient, anything)."""
    z, kept = _run(spec, params, np.asarray(x, float))
    h = np.tanh(z)
    g, extra = output_grad(h)
    g = g * (1 - h * h)
    parts, grads = split_params(spec, params), []
    for i in range(len(spec.layers) - 1, -1, -1):
        layer, w = spec.layers[i], parts[2 * i]
        if layer[0] == "dense":
            flat, y, shape = kept[i]
            if layer[3]:
                g = g * (y > 0)
            grads.append(((flat.T @ g).ravel(), g.sum(0)))
            g = (g @ w.T).reshape(shape)
        else:
            views, y, best, shape = kept[i]
            _, _, c_out, k, pool = layer
            m = best.shape[2]
            g = g.reshape(len(y), c_out, m)
            tiles = np.zeros((len(y), c_out, m, pool))
            np.put_along_axis(tiles, best[..., None], g[..., None], 3)
            gy = np.zeros_like(y)
            gy[:, :, : m * pool] = tiles.reshape(len(y), c_out, m * pool)
            gy *= y > 0
            grads.append((np.einsum("nop,nipk->oik", gy, views, optimize=True).ravel(), gy.sum((0, 2))))
            gx = np.zeros(shape)
            for j in range(k):
                gx[:, :, j : j + y.shape[2]] += np.einsum("nop,oi->nip", gy, w[:, :, j], optimize=True)
            g = gx
    return np.concatenate([np.concatenate(p) for p in reversed(grads)]), extra
