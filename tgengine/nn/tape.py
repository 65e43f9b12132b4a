"""A small reverse-mode differentiation tape over numpy arrays."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np


class Var:
    def __init__(self, value: np.ndarray, parents: tuple = (), back: Callable | None = None):
        self.value, self.parents, self.back, self.grad = np.asarray(value, dtype=np.float64), parents, back, None

    def __add__(self, o: "Var") -> "Var":
        return Var(self.value + o.value, (self, o), lambda g: (_fit(g, self.value.shape), _fit(g, o.value.shape)))

    def __mul__(self, o: "Var") -> "Var":
        return Var(self.value * o.value, (self, o), lambda g: (_fit(g * o.value, self.value.shape), _fit(g * self.value, o.value.shape)))

    def __matmul__(self, o: "Var") -> "Var":
        return Var(self.value @ o.value, (self, o), lambda g: (g @ o.value.T, self.value.T @ g))

    def one_minus(self) -> "Var":
        return Var(1 - self.value, (self,), lambda g: (-g,))


def _fit(g: np.ndarray, shape: tuple) -> np.ndarray:
    while g.ndim > len(shape):
        g = g.sum(axis=0)
    for i, n in enumerate(shape):
        if n == 1 and g.shape[i] != 1:
            g = g.sum(axis=i, keepdims=True)
    return g


def sigmoid(x: Var) -> Var:
    s = 1 / (1 + np.exp(-np.clip(x.value, -60, 60)))
    return Var(s, (x,), lambda g: (g * s * (1 - s),))


def tanh(x: Var) -> Var:
    s = np.tanh(x.value)
    return Var(s, (x,), lambda g: (g * (1 - s * s),))


def relu(x: Var) -> Var:
    return Var(np.maximum(x.value, 0), (x,), lambda g: (g * (x.value > 0),))


def beside(a: Var, b: Var) -> Var:
    n = a.value.shape[1]
    return Var(np.hstack([a.value, b.value]), (a, b), lambda g: (g[:, :n], g[:, n:]))


def spread(to: np.ndarray, x: np.ndarray, rows: int) -> np.ndarray:
    """Sums of the rows of x by their place in `to`."""
    if not len(to):
        return np.zeros((rows, x.shape[1]))
    return np.column_stack([np.bincount(to, x[:, k], rows) for k in range(x.shape[1])])


class Graph:
    """One snapshot's edges among local nodes; weighted sums over in-edges, scaled by target."""

    def __init__(self, src: np.ndarray, dst: np.ndarray, w: np.ndarray, nodes: int, norm: np.ndarray | None = None):
        self.src, self.dst, self.w, self.nodes, self.edges = src, dst, w, nodes, len(src)
        self.norm = np.ones(nodes) if norm is None else norm
        self.passes, self.messages = 0, 0

    def gather(self, x: np.ndarray, forward: bool = True) -> np.ndarray:
        if forward:
            return spread(self.dst, x[self.src] * self.w[:, None], self.nodes) * self.norm[:, None]
        return spread(self.src, (x * self.norm[:, None])[self.dst] * self.w[:, None], self.nodes)

    def count(self, messages: int) -> None:
        self.passes += 1
        self.messages += messages

    def sum(self, x: Var) -> Var:
        self.count(self.edges)
        return Var(self.gather(x.value), (x,), lambda g: (self.gather(g, False),))

    def raw(self, x: np.ndarray, pick: np.ndarray | None = None) -> np.ndarray:
        """Unscaled sums of the messages of all edges, or of the picked ones."""
        src, dst, w = (self.src, self.dst, self.w) if pick is None else (self.src[pick], self.dst[pick], self.w[pick])
        return spread(dst, x[src] * w[:, None], self.nodes)

    def moved(self, before: "Graph", x_before: np.ndarray, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Which edges of `before` are in the minus set and which of this graph in the plus set."""
        changed = (x_before != x).any(axis=1)
        a, b = before.src * self.nodes + before.dst, self.src * self.nodes + self.dst
        return ~np.isin(a, b) | changed[before.src], ~np.isin(b, a) | changed[self.src]

    def attend(self, score: Var, x: Var) -> Var:
        """Sums of x over in-edges, weighted by the softmax of the edges' scores (a column) at each target."""
        self.count(len(self.src))
        top = np.full(self.nodes, -np.inf)
        np.maximum.at(top, self.dst, score.value[:, 0])
        e = np.exp(score.value[:, 0] - top[self.dst])
        p = e / np.bincount(self.dst, e, self.nodes)[self.dst]
        out = np.zeros((self.nodes, x.value.shape[1]))
        np.add.at(out, self.dst, x.value[self.src] * p[:, None])

        def back(g: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
            each = (g[self.dst] * x.value[self.src]).sum(axis=1)
            mean = np.bincount(self.dst, each * p, self.nodes)[self.dst]
            dx = np.zeros_like(x.value)
            np.add.at(dx, self.src, g[self.dst] * p[:, None])
            return (p * (each - mean))[:, None], dx

        return Var(out, (score, x), back)


def take(x: Var, rows: np.ndarray) -> Var:
    def back(g: np.ndarray) -> tuple[np.ndarray]:
        out = np.zeros_like(x.value)
        np.add.at(out, rows, g)
        return (out,)

    return Var(x.value[rows], (x,), back)


def leaky(x: Var, slope: float = 0.2) -> Var:
    k = np.where(x.value > 0, 1.0, slope)
    return Var(x.value * k, (x,), lambda g: (g * k,))


def dot(x: Var, y: np.ndarray) -> Var:
    """Sum of products with a constant."""
    return Var((x.value * y).sum(), (x,), lambda g: (g * y,))


def share_abs(x: Var, y: np.ndarray, rows: np.ndarray, cells: int) -> Var:
    """Absolute errors of some rows, as a share of `cells`."""
    d = np.zeros_like(x.value)
    d[rows] = x.value[rows] - y
    return Var(np.abs(d).sum() / cells, (x,), lambda g: (g * np.sign(d) / cells,))


def mean_abs(x: Var, y: np.ndarray) -> Var:
    d = x.value - y
    return Var(np.abs(d).mean(), (x,), lambda g: (g * np.sign(d) / d.size,))


def total(items: list[Var]) -> Var:
    return Var(sum(i.value for i in items), tuple(items), lambda g: tuple(g for _ in items))


def backward(loss: Var) -> None:
    order, seen = [], set()
    stack = [(loss, False)]
    while stack:
        v, done = stack.pop()
        if done:
            order.append(v)
        elif id(v) not in seen:
            seen.add(id(v))
            stack.append((v, True))
            stack += [(p, False) for p in v.parents]
    for v in order:
        v.grad = np.zeros_like(v.value)
    loss.grad = np.ones_like(loss.value)
    for v in reversed(order):
        if v.back:
            for p, g in zip(v.parents, v.back(v.grad)):
                p.grad = p.grad + g
