"""Stacked and integrated graph-recurrent models.

Since aggregation is linear, A(XW) = (AX)W: one aggregate of an operand serves all gates. Aggregates of layer-1 inputs
depend on the snapshot alone; the global store keeps them across sequences and between decoder and encoder, and they are
moved from the kept aggregate of the snapshot before by the two delta sets. The local store holds the operands' aggregates of one cell.
"""

from __future__ import annotations

from collections import Counter

import numpy as np

from ..operators.cache import GlobalStore, LocalStore, imminence
from ..plans.reuse import ALL, MODELS, Flags
from .tape import Graph, Var, backward, beside, dot, mean_abs, relu, share_abs, sigmoid, tanh, total

Weights = dict[str, np.ndarray]
State = list[tuple[Var, Var]]


def init(name: str, width: int, hidden: int, seed: int = 7) -> Weights:
    m, r, w = MODELS[name], np.random.default_rng(seed), {}
    parts = ("enc", "dec") if m.decoder else ("enc",)
    for part in parts:
        for layer in range(m.layers):
            k = width if layer == 0 else hidden
            if m.kind == "stacked":
                w[f"{part}{layer}.conv"] = r.normal(0, 1 / np.sqrt(k), (k, hidden))
                k = hidden + (k if name == "stk_skip_lstm" else 0)
            for g in range(m.gates):
                w[f"{part}{layer}.x{g}"] = r.normal(0, 1 / np.sqrt(k), (k, hidden))
                w[f"{part}{layer}.h{g}"] = r.normal(0, 1 / np.sqrt(hidden), (hidden, hidden))
                w[f"{part}{layer}.b{g}"] = np.zeros((1, hidden))
    w["head"] = r.normal(0, 1 / np.sqrt(hidden), (hidden, width))
    w["head.b"] = np.zeros((1, width))
    return w


def _lstm(xs: list[Var], hs: list[Var], c: Var, p: dict[str, Var], at: str) -> tuple[Var, Var]:
    z = [xs[g] @ p[f"{at}.x{g}"] + hs[g] @ p[f"{at}.h{g}"] + p[f"{at}.b{g}"] for g in range(4)]
    c = sigmoid(z[1]) * c + sigmoid(z[0]) * tanh(z[3])
    return sigmoid(z[2]) * tanh(c), c


def _gru(xs: list[Var], hs: list[Var], h: Var, p: dict[str, Var], at: str, g: Graph | None = None) -> Var:
    """The reset follows aggregation and projection, so that all three gates share the hidden aggregate; with `g` it comes before, at the price of one more aggregate."""
    z = sigmoid(xs[0] @ p[f"{at}.x0"] + hs[0] @ p[f"{at}.h0"] + p[f"{at}.b0"])
    r = sigmoid(xs[1] @ p[f"{at}.x1"] + hs[1] @ p[f"{at}.h1"] + p[f"{at}.b1"])
    back = r * (hs[2] @ p[f"{at}.h2"]) if g is None else g.sum(r * h) @ p[f"{at}.h2"]
    n = tanh(xs[2] @ p[f"{at}.x2"] + back + p[f"{at}.b2"])
    return z.one_minus() * h + z * n


class Sample:
    """What one task holds: graphs and features by snapshot, the rows that are predicted, and the stores.

    `feats` are the raw values (whole numbers stay exact in sums and deltas); `scale` divides them where they are used.
    """

    def __init__(self, graphs: dict[int, Graph], feats: dict[int, np.ndarray], targets: np.ndarray | None = None, scale: np.ndarray | float = 1.0, capacity: int | None = None, policy: str = "lookahead", reset: str = "after"):
        self.graphs, self.feats, self.scale, self.reset = graphs, feats, scale, reset
        self.targets = np.arange(next(iter(feats.values())).shape[0]) if targets is None else targets
        self.global_store, self.local_store = GlobalStore(capacity, policy), LocalStore()
        self.future: Counter = Counter()
        self.waits: dict[str, float] = {"enc": 0.0, "dec": 0.0}

    def x(self, t: int) -> np.ndarray:
        return self.feats[t] / self.scale

    def expect(self, name: str, sequences: list[list[int]], flags: Flags, stride: int = 1) -> None:
        """Counts the reads of every input aggregate that the sequences are going to make."""
        m = MODELS[name]
        self.future = Counter()
        for q, times in enumerate(sequences):
            for part in ("enc", "dec") if m.decoder else ("enc",):
                for t in times:
                    for gate in range(1 if flags.gates or m.kind == "stacked" else m.gates):
                        self.future[_key(flags, q, part, gate, t + (part == "dec"))] += 1
        length = len(sequences[0]) if sequences else 1
        self.waits = {part: imminence(part, length, stride) for part in ("enc", "dec")}

    def passes(self) -> int:
        return sum(g.passes for g in self.graphs.values())

    def messages(self) -> int:
        return sum(g.messages for g in self.graphs.values())


def _key(flags: Flags, q: int, part: str, gate: int, t: int) -> tuple:
    """Identity of an input aggregate: shared over gates, over sequences, over parts, or not."""
    return (0 if flags.gates else gate, None if flags.sequences else q, None if flags.teacher else part, t)


def _input_sums(s: Sample, key: tuple, flags: Flags, threshold: float = 0.5) -> np.ndarray:
    """Unscaled neighbour sums of the raw features: from the kept sums of the snapshot before and the deltas, or from scratch."""
    t = key[-1]
    g = s.graphs[t]
    before = s.global_store.peek((*key[:-1], t - 1)) if flags.incremental else None
    if before is not None:
        minus, plus = g.moved(s.graphs[t - 1], s.feats[t - 1], s.feats[t])
        n = int(minus.sum() + plus.sum())
        if n <= threshold * g.edges:
            g.count(n)
            return before - s.graphs[t - 1].raw(s.feats[t - 1], minus) + g.raw(s.feats[t], plus)
    g.count(g.edges)
    return g.raw(s.feats[t])


def _first_input(s: Sample, q: int, part: str, t: int, flags: Flags, gate: int, last: bool) -> Var:
    """Scaled neighbour sums of layer 1's input, through the global store."""
    key = _key(flags, q, part, gate, t)
    if s.future[key]:
        s.future[key] -= 1
    kept = flags.sequences or flags.teacher or flags.incremental
    make = lambda: _input_sums(s, key, flags)
    wait = s.waits[part] if last else 0.0
    sums = s.global_store.get(key, s.future[key], wait, make, flags.incremental) if kept else make()
    return Var(sums * s.graphs[t].norm[:, None] / s.scale)


def step(name: str, s: Sample, q: int, part: str, t: int, x: Var | None, state: State, p: dict[str, Var], flags: Flags) -> State:
    """All layers of one snapshot. `x` None: the true features, whose aggregates the global store keeps."""
    m, g, own = MODELS[name], s.graphs[t], x is None
    out: State = []
    value = Var(s.x(t)) if own else x
    for layer in range(m.layers):
        h, c = state[layer]
        at = f"{part}{layer}"
        stored = own and layer == 0
        s.local_store.open()

        def operand(kind: str, gate: int, stored: bool = stored, value: Var = value, h: Var = h) -> Var:
            last = gate == m.gates - 1 or flags.gates
            make = (lambda: _first_input(s, q, part, t, flags, gate, last)) if stored and kind == "x" else (lambda: g.sum(value if kind == "x" else h))
            return s.local_store.get(kind, make) if flags.gates else make()

        if m.kind == "stacked":
            u = relu((_first_input(s, q, part, t, flags, 0, True) if stored else g.sum(value)) @ p[f"{at}.conv"])
            u = beside(u, value) if name == "stk_skip_lstm" else u
            h, c = _lstm([u] * 4, [h] * 4, c, p, at)
        else:
            ax, ah = ([operand(k, i) for i in range(m.gates)] for k in "xh")
            if m.gates == 4:
                h, c = _lstm(ax, ah, c, p, at)
            else:
                h = _gru(ax, ah, h, p, at, g if s.reset == "before" else None)
        out.append((h, c))
        value = h
    return out


def start(name: str, nodes: int, hidden: int) -> State:
    return [(Var(np.zeros((nodes, hidden))), Var(np.zeros((nodes, hidden)))) for _ in range(MODELS[name].layers)]


def head(h: Var, p: dict[str, Var]) -> Var:
    return h @ p["head"] + p["head.b"]


def forward(name: str, s: Sample, times: list[int], w: Weights, hidden: int, flags: Flags = ALL, teacher_forcing: bool = True, q: int = 0, p: dict[str, Var] | None = None) -> tuple[list[Var], dict[str, Var]]:
    """Predictions for the snapshots that follow: of the last encoder step, or of every decoder step. Sequences may differ in length.

    The decoder reads the snapshot after each encoder step; without forcing, its own last prediction."""
    m, p = MODELS[name], p or {k: Var(v) for k, v in w.items()}
    if not s.future:
        s.expect(name, [times], flags)
        q = 0
    state = start(name, next(iter(s.feats.values())).shape[0], hidden)
    for t in times:
        state = step(name, s, q, "enc", t, None, state, p, flags)
    if not m.decoder:
        return [head(state[-1][0], p)], p
    out: list[Var] = []
    for i, t in enumerate(times):
        x = None if teacher_forcing or i == 0 else out[-1]
        state = step(name, s, q, "dec", t + 1, x, state, p, flags)
        out.append(head(state[-1][0], p))
    return out, p


def targets(name: str, times: list[int]) -> list[int]:
    return [t + 2 for t in times] if MODELS[name].decoder else [times[-1] + 1]


def error(y: Var, s: Sample, t: int, cells: int | None = None) -> Var:
    truth = s.x(t)
    if len(s.targets) == len(truth) and cells is None:
        return mean_abs(y, truth)
    return share_abs(y, truth[s.targets], s.targets, cells or max(1, len(s.targets) * truth.shape[1]))


def loss_and_grads(name: str, s: Sample, times: list[int], w: Weights, hidden: int, flags: Flags = ALL, q: int = 0) -> tuple[float, Weights]:
    out, p = forward(name, s, times, w, hidden, flags, q=q)
    ends = targets(name, times)
    loss = total([error(o, s, t) for o, t in zip(out, ends)])
    backward(loss)
    return float(loss.value) / len(ends), {k: v.grad / len(ends) if v.grad is not None else np.zeros_like(v.value) for k, v in p.items()}


# pieces of a sample that a machine holds of it where snapshots or nodes are spread


def conv_piece(name: str, layer: int, g: Graph, x: np.ndarray, w: Weights, up: np.ndarray | None = None) -> tuple[np.ndarray, Weights]:
    """The graph layer of one snapshot; with the gradient of its output, the gradients of its input and weights."""
    key = f"enc{layer}.conv"
    xv, p = Var(x), Var(w[key])
    u = relu(g.sum(xv) @ p)
    u = beside(u, xv) if name == "stk_skip_lstm" else u
    if up is None:
        return u.value, {}
    backward(dot(u, up))
    return xv.grad, {key: p.grad}


def cell_piece(layer: int, us: list[np.ndarray], w: Weights, hidden: int, up: list[np.ndarray] | None = None, truth: tuple | None = None) -> tuple[list[np.ndarray], Weights, float]:
    """The recurrent layer of some nodes over a whole sequence. `truth`: (values, rows, cells) that the last state predicts.

    Returns the states, or with a gradient or a truth the inputs' gradients, the weights' gradients and the loss."""
    names = [k for k in w if k.startswith(f"enc{layer}.") and not k.endswith("conv")] + (["head", "head.b"] if truth else [])
    p = {k: Var(w[k]) for k in names}
    ins = [Var(u) for u in us]
    h = c = Var(np.zeros((us[0].shape[0], hidden)))
    outs = []
    for u in ins:
        h, c = _lstm([u] * 4, [h] * 4, c, p, f"enc{layer}")
        outs.append(h)
    if up is None and truth is None:
        return [o.value for o in outs], {}, 0.0
    parts = [dot(o, u) for o, u in zip(outs, up)] if up is not None else []
    loss = share_abs(head(h, p), *truth) if truth else None
    backward(total([*parts, *([loss] if truth else [])]))
    return [i.grad for i in ins], {k: v.grad for k, v in p.items()}, float(loss.value) if truth else 0.0


def run_piece(name: str, s: Sample, part: str, times: list[int], w: Weights, state: list[tuple[np.ndarray, np.ndarray]], flags: Flags, up: list[tuple[np.ndarray, np.ndarray]] | None = None, cells: int = 1, learn: bool = True) -> tuple[list[tuple[np.ndarray, np.ndarray]], Weights, float]:
    """Neighbouring snapshots of an integrated model on one machine: the state handed over comes in and goes out.

    With `up`, the gradient of the state that went out, the result is that of the state that came in, and of the weights."""
    p = {k: Var(v) for k, v in w.items()}
    came = [(Var(h), Var(c)) for h, c in state]
    now: State = came
    errors = []
    for t in times:
        now = step(name, s, 0, part, t, None, now, p, flags)
        if part == "dec":
            errors.append(error(head(now[-1][0], p), s, t + 1, cells))
    loss = float(sum(e.value for e in errors))
    if up is None:
        return [(h.value, c.value) for h, c in now], {}, loss
    backward(total([*errors, *[dot(v, u) for pair, ups in zip(now, up) for v, u in zip(pair, ups)]]))
    zero = lambda v: v.grad if v.grad is not None else np.zeros_like(v.value)
    return [(zero(h), zero(c)) for h, c in came], {k: v.grad for k, v in p.items() if v.grad is not None}, loss


class Adam:
    def __init__(self, w: Weights, rate: float = 1e-3):
        self.rate, self.t = rate, 0
        self.m, self.v = {k: np.zeros_like(x) for k, x in w.items()}, {k: np.zeros_like(x) for k, x in w.items()}

    def step(self, w: Weights, g: Weights) -> None:
        self.t += 1
        for k in w:
            self.m[k] = 0.9 * self.m[k] + 0.1 * g[k]
            self.v[k] = 0.999 * self.v[k] + 0.001 * g[k] ** 2
            w[k] = w[k] - self.rate * (self.m[k] / (1 - 0.9**self.t)) / (np.sqrt(self.v[k] / (1 - 0.999**self.t)) + 1e-8)


class Network:
    """A model by its parts, ready to predict and to be differentiated."""

    def __init__(self, name: str, width: int, hidden: int, teacher_forcing: bool = True, seed: int = 7):
        self.name, self.hidden, self.teacher_forcing, self.weights = name, hidden, teacher_forcing, init(name, width, hidden, seed)

    def predict(self, s: Sample, times: list[int], flags: Flags = ALL) -> list[np.ndarray]:
        return [y.value for y in forward(self.name, s, times, self.weights, self.hidden, flags, self.teacher_forcing)[0]]

    def learn(self, s: Sample, times: list[int], flags: Flags = ALL) -> tuple[float, Weights]:
        return loss_and_grads(self.name, s, times, self.weights, self.hidden, flags)


def stack_pairs(width: int, hidden: int, conv: str = "conv") -> Network:
    """Two pairs of a graph layer and a recurrent cell, one on the other."""
    return Network(f"stk_{conv}_lstm", width, hidden)


def stack_seq2seq(width: int, hidden: int, cell: str = "lstm", teacher_forcing: bool = True) -> Network:
    """Encoder and decoder of two layers each, graph layers inside the cells."""
    return Network(f"int_conv_{cell}", width, hidden, teacher_forcing)
