"""Graph and temporal layers over the tape, each a small set of weights and a function of a snapshot."""

from __future__ import annotations

import numpy as np

from .tape import Graph, Var, leaky, relu, take

Weights = dict[str, np.ndarray]


def _matrix(r: np.random.Generator, rows: int, cols: int) -> np.ndarray:
    return r.normal(0, 1 / np.sqrt(rows), (rows, cols))


class GraphConv:
    """relu(A x W + b); `norm`: messages divided by the root of out- times in-degree; `loop`: each node hears itself too."""

    def __init__(self, width: int, hidden: int, norm: bool = False, loop: bool = False, seed: int = 7):
        self.norm, self.loop = norm, loop
        self.w = {"conv": _matrix(np.random.default_rng(seed), width, hidden), "conv.b": np.zeros((1, hidden))}

    def prepared(self, g: Graph) -> Graph:
        src, dst, w = g.src, g.dst, g.w
        if self.loop:
            own = np.arange(g.nodes)
            src, dst, w = np.r_[src, own], np.r_[dst, own], np.r_[w, np.ones(g.nodes)]
        if self.norm:
            out, into = np.bincount(src, minlength=g.nodes), np.bincount(dst, minlength=g.nodes)
            w = w / np.sqrt(out[src] * into[dst])
        return Graph(src, dst, w, g.nodes, None if self.norm else g.norm)

    def __call__(self, g: Graph, x: Var, p: dict[str, Var]) -> Var:
        return relu(self.prepared(g).sum(x) @ p["conv"] + p["conv.b"])


class GraphAttention:
    """Softmax over in-edges of leaky(a . W x_source + b . W x_target). The scores depend on weights: after an update every target is gathered anew; between updates `kept` serves unchanged snapshots."""

    def __init__(self, width: int, hidden: int, seed: int = 7):
        r = np.random.default_rng(seed)
        self.w = {"att": _matrix(r, width, hidden), "att.src": _matrix(r, hidden, 1), "att.dst": _matrix(r, hidden, 1)}
        self.version, self.kept = 0, {}

    def updated(self) -> None:
        self.version += 1
        self.kept.clear()

    def __call__(self, g: Graph, x: Var, p: dict[str, Var]) -> Var:
        z = x @ p["att"]
        return g.attend(leaky(take(z @ p["att.src"], g.src) + take(z @ p["att.dst"], g.dst)), z)

    def infer(self, t: int, graphs: dict[int, Graph], feats: dict[int, np.ndarray], w: Weights) -> np.ndarray:
        """Values at snapshot t with fixed weights: only targets whose in-edges or sources changed since t-1 are gathered anew."""
        g, x = graphs[t], feats[t]
        key, before = (self.version, t), (self.version, t - 1)
        if key in self.kept:
            return self.kept[key]
        p = {k: Var(v) for k, v in w.items()}
        if before in self.kept:
            minus, plus = g.moved(graphs[t - 1], feats[t - 1], x)
            own = (feats[t - 1] != x).any(axis=1)  # a target's own features are part of its scores
            hit = np.zeros(g.nodes, dtype=bool)
            hit[graphs[t - 1].dst[minus]] = hit[g.dst[plus]] = True
            at = (hit | own)[g.dst]
            part = Graph(g.src[at], g.dst[at], g.w[at], g.nodes)
            value = np.where((hit | own)[:, None], self(part, Var(x), p).value, self.kept[before])
            g.count(int(at.sum()))
        else:
            value = self(g, Var(x), p).value
        self.kept[key] = value
        return value


class TemporalAttention:
    """Attention over a node's own states of past steps, in place of a recurrent cell: the last state asks, all answer."""

    def __init__(self, width: int, hidden: int, seed: int = 7):
        r = np.random.default_rng(seed)
        self.w = {k: _matrix(r, width, hidden) for k in ("ask", "key", "val")}

    def __call__(self, steps: list[Var], p: dict[str, Var]) -> Var:
        n, length = steps[0].value.shape[0], len(steps)
        # the steps of a node are sources of edges to the node
        g = Graph(np.arange(n * length), np.tile(np.arange(n), length), np.ones(n * length), n * length)
        rows = _stack(steps)
        ask, key = take(steps[-1] @ p["ask"], np.tile(np.arange(n), length)), rows @ p["key"]
        scores = (ask * key) @ Var(np.full((key.value.shape[1], 1), 1 / np.sqrt(key.value.shape[1])))
        return take(g.attend(scores, rows @ p["val"]), np.arange(n))


def _stack(steps: list[Var]) -> Var:
    n = steps[0].value.shape[0]
    return Var(np.vstack([s.value for s in steps]), tuple(steps), lambda g: tuple(g[i * n : (i + 1) * n] for i in range(len(steps))))


class StaticGnn:
    """Embedding of the present snapshot only: two graph layers, no recurrence (the contrast case)."""

    def __init__(self, width: int, hidden: int, seed: int = 7):
        a, b = GraphConv(width, hidden, loop=True, seed=seed), GraphConv(hidden, hidden, loop=True, seed=seed + 1)
        self.first, self.second = a, b
        self.w = {f"{i}.{k}": v for i, layer in enumerate((a, b)) for k, v in layer.w.items()}

    def __call__(self, g: Graph, x: Var, p: dict[str, Var]) -> Var:
        part = lambda i: {k[2:]: v for k, v in p.items() if k.startswith(f"{i}.")}
        return self.second(g, self.first(g, x, part(0)), part(1))


