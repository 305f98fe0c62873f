"""Losses and their gradients on arrays: the kernels that run on Arrow batches. Weights are lists of (out, in+1) matrices,
the last column being the bias; the x of a batch comes without a bias column."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np


@dataclass(frozen=True)
class NetSpec:
    """inputs, then the number of outputs of each layer. loss: xent_softmax, xent_relu_mlp, mse_softmax, mse_linear or xent_logistic.

    softmax_form 'reference' gives the softmax an additional class of score 0 in its denominator.
    """

    inputs: int
    outputs: tuple[int, ...]
    loss: str = "xent_softmax"
    softmax_form: str = "standard"
    shapes: tuple[tuple[int, int], ...] = field(init=False, default=())

    def __post_init__(self):
        if self.loss not in ("xent_softmax", "xent_relu_mlp", "mse_softmax", "mse_linear", "xent_logistic"):
            raise ValueError(f"unknown loss {self.loss}")
        if len(self.outputs) > 1 and self.loss != "xent_relu_mlp":
            raise ValueError("hidden layers need the loss xent_relu_mlp")
        ins = (self.inputs, *self.outputs[:-1])
        object.__setattr__(self, "shapes", tuple((o, i + 1) for o, i in zip(self.outputs, ins)))

    @property
    def parameters(self) -> int:
        return sum(a * b for a, b in self.shapes)

    def zeros(self) -> list[np.ndarray]:
        return [np.zeros(s) for s in self.shapes]

    def start(self, seed: int = 0) -> list[np.ndarray]:
        """Zeros for one layer (convex), scaled normal weights for a network."""
        if len(self.outputs) == 1:
            return self.zeros()
        rng = np.random.default_rng(seed)
        return [rng.standard_normal(s) * np.sqrt(2.0 / s[1]) * ([1.0] * (s[1] - 1) + [0.0]) for s in self.shapes]


def with_bias(x: np.ndarray) -> np.ndarray:
    return np.hstack([x, np.ones((len(x), 1))])


def softmax(scores: np.ndarray, form: str = "standard") -> np.ndarray:
    top = scores.max(axis=1, keepdims=True)
    if form == "reference":
        top = np.maximum(top, 0)
    e = np.exp(scores - top)
    return e / (e.sum(axis=1, keepdims=True) + (np.exp(-top) if form == "reference" else 0))


def forward(spec: NetSpec, weights: list[np.ndarray], x: np.ndarray) -> tuple[list[np.ndarray], np.ndarray]:
    """Inputs of every layer (with bias) and the last layer's scores."""
    seen, z = [], x
    for at, w in enumerate(weights):
        zb = with_bias(z)
        seen.append(zb)
        z = zb @ w.T
        if at < len(weights) - 1:
            z = np.maximum(z, 0)
    return seen, z


def losses(spec: NetSpec, weights: list[np.ndarray], x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Loss and whether the prediction is wrong, for every row."""
    _, s = forward(spec, weights, x)
    if spec.loss == "mse_linear":
        e = s[:, 0] - y
        return 0.5 * e * e, np.zeros(len(y))
    if spec.loss == "xent_logistic":
        z = s[:, 0]
        return np.logaddexp(0, z) - y * z, ((z > 0) != (y > 0.5)).astype(float)
    p = softmax(s, spec.softmax_form)
    at = np.arange(len(y)), y.astype(int)
    wrong = (p.argmax(axis=1) != y).astype(float)
    if spec.loss == "mse_softmax":
        hot = np.zeros_like(p)
        hot[at] = 1
        return 0.5 * ((p - hot) ** 2).sum(axis=1), wrong
    return -np.log(np.maximum(p[at], 1e-300)), wrong


def gradients(spec: NetSpec, weights: list[np.ndarray], x: np.ndarray, y: np.ndarray) -> list[np.ndarray]:
    """Summed gradient of the rows, one matrix per layer."""
    seen, s = forward(spec, weights, x)
    if spec.loss == "mse_linear":
        delta = s - y[:, None]
    elif spec.loss == "xent_logistic":
        delta = 1 / (1 + np.exp(-np.clip(s, -700, 700))) - y[:, None]
    else:
        p = softmax(s, spec.softmax_form)
        hot = np.zeros_like(p)
        hot[np.arange(len(y)), y.astype(int)] = 1
        delta = p - hot
        if spec.loss == "mse_softmax":
            delta = p * (delta - (p * delta).sum(axis=1, keepdims=True))
    out = []
    for at in range(len(weights) - 1, -1, -1):
        out.append(delta.T @ seen[at])
        if at:
            delta = (delta @ weights[at][:, :-1]) * (seen[at][:, :-1] > 0)
    return out[::-1]


@dataclass(frozen=True)
class NestedLayout:
    """Groups of output units cut by repeated splitting: the layer q steps before the output into cuts^(q+1) of them.
    t counts the groups of all layers; each is padded to the largest."""

    spec: NetSpec
    cuts: int

    @property
    def groups(self) -> list[int]:
        return [self.cuts ** (len(self.spec.shapes) - at) for at in range(len(self.spec.shapes))]

    @property
    def t(self) -> int:
        return sum(self.groups)

    @property
    def per_layer(self) -> list[int]:
        return [-(-o // n) * i for (o, i), n in zip(self.spec.shapes, self.groups)]

    @property
    def block(self) -> int:
        return max(self.per_layer)

    @property
    def numbers(self) -> int:
        """Numbers of a message: a group of every layer, without padding to the largest."""
        return sum(self.per_layer)

    def split(self, grads: list[np.ndarray]) -> np.ndarray:
        out, first = np.zeros((self.t, self.block)), 0
        for g, n, size in zip(grads, self.groups, self.per_layer):
            flat = np.zeros(n * size)
            flat[: g.size] = g.ravel()
            out[first : first + n, :size] = flat.reshape(n, size)
            first += n
        return out

    def merge(self, blocks: np.ndarray) -> list[np.ndarray]:
        out, first = [], 0
        for (o, i), n, size in zip(self.spec.shapes, self.groups, self.per_layer):
            out.append(np.ascontiguousarray(blocks[first : first + n, :size]).ravel()[: o * i].reshape(o, i))
            first += n
        return out


@dataclass(frozen=True)
class GroupLayout:
    """How the parameters of a network fall into t groups of equal, padded size: groups of output units of each layer,
    or (axis 'input') groups of one output's weights."""

    spec: NetSpec
    t: int
    axis: str = "output"

    @property
    def per_layer(self) -> list[int]:
        """Padded numbers in one group of each layer."""
        if self.axis == "input":
            return [-(-o * i // self.t) for o, i in self.spec.shapes]
        return [-(-o // self.t) * i for o, i in self.spec.shapes]

    @property
    def block(self) -> int:
        """Numbers in one group over all layers: the length of a message."""
        return sum(self.per_layer)

    @property
    def numbers(self) -> int:
        return self.block

    def split(self, grads: list[np.ndarray]) -> np.ndarray:
        """t x block, with zeros for padding."""
        parts = []
        for g, size in zip(grads, self.per_layer):
            flat = np.zeros(size * self.t)
            flat[: g.size] = g.ravel()
            parts.append(flat.reshape(self.t, size))
        return np.hstack(parts)

    def merge(self, blocks: np.ndarray) -> list[np.ndarray]:
        """The matrices of t x block numbers; padding is dropped."""
        out, at = [], 0
        for shape, size in zip(self.spec.shapes, self.per_layer):
            flat = np.ascontiguousarray(blocks[:, at : at + size]).ravel()
            out.append(flat[: shape[0] * shape[1]].reshape(shape))
            at += size
        return out
