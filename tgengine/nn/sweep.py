"""Whole sequences over graphs of any number of edges, in little memory.

A task's snapshots lie in a file of its own and are read in pieces; so are the states and aggregates between forward and backward.
In memory are a few vectors per node and one cell of `ROWS` nodes. Counters, stores and results are those of `models.forward`.
"""

from __future__ import annotations

import os
import tempfile
import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from ..operators.cache import LocalStore
from ..plans.reuse import MODELS, Flags
from .cells import Cell
from .models import Sample, Weights, _first_input, targets
from .tape import Graph, Var, spread

Pair = tuple[np.ndarray, np.ndarray | None]

#: Nodes of one cell that are differentiated at a time (so few that a product stays on one thread and in the cache), edges that are read at a time, and those of them that are summed at a time.
ROWS, EDGES, SUMMED = 1 << 10, 1 << 18, 1 << 15


def squeeze(x: np.ndarray) -> bytes:
    """Numbers with their first bytes together, then their second ones and so on, compressed."""
    return zlib.compress(np.ascontiguousarray(x.view(np.uint8).reshape(len(x), -1).T), 1) if len(x) else b""


def widen(data: bytes, dtype: str) -> np.ndarray:
    """What `squeeze` was given."""
    if not len(data):
        return np.zeros(0, dtype)
    planes = np.frombuffer(zlib.decompress(data), np.uint8).reshape(np.dtype(dtype).itemsize, -1)
    return np.ascontiguousarray(planes.T).view(dtype).ravel()


def put_edges(src: np.ndarray, dst: np.ndarray) -> bytes:
    """Edges in the order of their targets, whose steps are kept, beside the sources."""
    order = np.lexsort((src, dst))
    return squeeze(np.r_[src[order], np.diff(dst[order], prepend=0)].astype("<i8"))


def edge_ends(src: bytes, dst: bytes | None) -> Pair:
    """Sources and targets of a row: plain ones in `src` and `dst`, or `put_edges`' in `src` alone."""
    if dst is not None:
        return np.frombuffer(src, "<i8"), np.frombuffer(dst, "<i8")
    both = widen(src, "<i8")
    return both[: len(both) // 2], np.cumsum(both[len(both) // 2 :])


def put_features(a: np.ndarray, b: np.ndarray, x: np.ndarray) -> Pair:
    """Nodes, and beside them their values, last of which whether they are targets."""
    return squeeze(a.astype("<i8")), squeeze(np.column_stack([x, b]).astype("<f8").ravel())


def features(src: bytes, dst: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """What `put_features` was given."""
    a = widen(src, "<i8")
    x = widen(dst, "<f8").reshape(len(a), -1)
    return a, x[:, -1] == 1, x[:, :-1]


class Shelf:
    """Arrays in an unnamed file of the task: `put` gives the place from which `take` reads."""

    def __init__(self):
        self.file, self.end = tempfile.TemporaryFile(), 0

    def put(self, x: np.ndarray) -> tuple:
        data, at = memoryview(np.ascontiguousarray(x)).cast("B") if x.size else b"", self.end
        self.end += len(data)
        done = 0
        while done < len(data):
            done += os.pwrite(self.file.fileno(), data[done:], at + done)
        return at, x.shape, x.dtype

    def take(self, place: tuple, lo: int = 0, hi: int | None = None) -> np.ndarray:
        """The array, or its rows from lo to hi."""
        at, shape, dtype = place
        hi = shape[0] if hi is None else min(hi, shape[0])
        row = dtype.itemsize * int(np.prod(shape[1:]))
        out = np.empty((hi - lo, *shape[1:]), dtype)
        view, done = memoryview(out).cast("B") if out.size else b"", 0
        while done < len(view):
            done += os.preadv(self.file.fileno(), [view[done:]], at + lo * row + done)
        return out

    def clear(self) -> None:
        self.file.truncate(0)
        self.end = 0

    def close(self) -> None:
        self.file.close()


class ShelvedGraph(Graph):
    """A snapshot of the edges dst * nodes + src (`code`), sorted by target, then source; all weights are one."""

    def __init__(self, shelf: Shelf, code: np.ndarray, nodes: int):
        code.sort()
        self.shelf, self.nodes, self.edges = shelf, nodes, len(code)
        self.norm = 1 / np.maximum(1, np.bincount(code // nodes, minlength=nodes))
        self.places = shelf.put((code % nodes).astype(np.int32)), shelf.put((code // nodes).astype(np.int32))
        self.passes = self.messages = 0

    @property
    def src(self) -> np.ndarray:
        return self.shelf.take(self.places[0])

    @property
    def dst(self) -> np.ndarray:
        return self.shelf.take(self.places[1])

    def pieces(self) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        for lo in range(0, self.edges, EDGES):
            yield tuple(self.shelf.take(x, lo, lo + EDGES).astype(np.intp) for x in self.places)

    def gather(self, x: np.ndarray, forward: bool = True) -> np.ndarray:
        if forward:
            return self.raw(x) * self.norm[:, None]
        out = np.zeros((x.shape[1], self.nodes))
        columns = np.ascontiguousarray((x * self.norm[:, None]).T)
        room = np.empty(EDGES)
        for src, dst in self.pieces():
            for o, c in zip(out, columns):
                o += np.bincount(src, np.take(c, dst, out=room[: len(dst)], mode="clip"), self.nodes)
        return np.ascontiguousarray(out.T)

    def raw(self, x: np.ndarray, pick: np.ndarray | None = None) -> np.ndarray:
        if pick is not None:
            return spread(self.dst[pick], x[self.src[pick]], self.nodes)
        out = np.zeros((x.shape[1], self.nodes))
        columns = np.ascontiguousarray(x.T)  # a column of few bytes is read at random faster than rows
        room = np.empty(SUMMED)  # the same few bytes for all messages
        for read in self.pieces():
            for at in range(0, len(read[0]), SUMMED):
                src, dst = (v[at : at + SUMMED] for v in read)
                lo, hi = dst[0], dst[-1] + 1  # sorted: a piece touches neighbouring targets
                dst = dst - lo
                for o, c in zip(out, columns):
                    o[lo:hi] += np.bincount(dst, np.take(c, src, out=room[: len(src)], mode="clip"), hi - lo)
        return np.ascontiguousarray(out.T)

    def moved(self, before: Graph, x_before: np.ndarray, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        changed = (x_before != x).any(axis=1)
        here, there = ((g.src, g.dst.astype(np.int64)) for g in (self, before))
        a, b = there[1] * self.nodes + there[0], here[1] * self.nodes + here[0]
        return ~_within(a, b) | changed[there[0]], ~_within(b, a) | changed[here[0]]


def _within(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Which of a are in b; both sorted, without repeats."""
    if not len(b):
        return np.zeros(len(a), dtype=bool)
    return b[np.minimum(np.searchsorted(b, a), len(b) - 1)] == a


def slices(batches: Iterator[pa.RecordBatch], keys: list[str]) -> Iterator[tuple[tuple, pa.RecordBatch]]:
    """Batches cut where the keys change."""
    for rb in batches:
        if not rb.num_rows:
            continue
        cols = [rb.column(k).to_numpy(zero_copy_only=False) for k in keys]
        cuts = np.flatnonzero(np.any([c[1:] != c[:-1] for c in cols], axis=0)) + 1
        for lo, hi in zip([0, *cuts], [*cuts, rb.num_rows]):
            yield tuple(c[lo] for c in cols), rb.slice(lo, hi - lo)


def shelved(parts: Iterator[pa.RecordBatch], lanes: tuple[str, ...], scale: np.ndarray, shelf: Shelf, capacity: int | None, policy: str) -> tuple[Sample, int]:
    """A sample and the number of its targets, from rows that hold all features first and then the edges by snapshot; one feature in a row, or many as `put_features` leaves them."""
    given: dict[int, list[tuple[np.ndarray, np.ndarray, np.ndarray]]] = {}
    n = 0
    nodes: np.ndarray | None = None
    graphs: dict[int, Graph] = {}
    feats: dict[int, np.ndarray] = {}
    wanted = np.zeros(0, dtype=np.int64)
    pending: list[np.ndarray] = []
    at: int | None = None

    def known() -> None:
        nonlocal nodes, wanted
        none = np.zeros(0, dtype=np.int64)
        nodes = np.unique(np.concatenate([none, *(a for x in given.values() for a, _, _ in x)]))
        wanted = np.searchsorted(nodes, np.unique(np.concatenate([none, *(a[b] for x in given.values() for a, b, _ in x)])))
        for k in sorted(given):
            feats[k] = np.zeros((len(nodes), len(lanes)))
            for a, _, x in given.pop(k):
                feats[k][np.searchsorted(nodes, a)] = x

    def flush() -> None:
        if pending:
            code = np.concatenate(pending)
            pending.clear()
            graphs[at] = ShelvedGraph(shelf, code, len(nodes))

    for rb in parts:
        edge = pc.equal(rb.column("kind"), "e").to_numpy(zero_copy_only=False)
        bundled = ~edge & rb.column("src").is_valid().to_numpy(zero_copy_only=False)
        if not edge.all():
            n = max(n, int(pc.max(rb.column("n").filter(pa.array(~edge))).as_py()))
        for i in np.flatnonzero(bundled):
            given.setdefault(rb.column("t")[i].as_py(), []).append(features(*(rb.column(k)[i].as_buffer() for k in ("src", "dst"))))
        if not (edge | bundled).all():
            f = rb.filter(pa.array(~(edge | bundled)))
            t, a, b = (f.column(k).to_numpy() for k in ("t", "a", "b"))
            x = np.column_stack([f.column(k).to_numpy() for k in lanes])
            for k in np.unique(t):
                mine = t == k
                given.setdefault(int(k), []).append((a[mine], b[mine] == 1, x[mine]))
        for i in np.flatnonzero(edge):
            if nodes is None:
                known()
            now = rb.column("t")[i].as_py()
            if now != at:
                flush()
                at = now
            src, dst = (rb.column(k)[i] for k in ("src", "dst"))
            src, dst = edge_ends(src.as_buffer(), dst.as_buffer() if dst.is_valid else None)
            pending.append(np.searchsorted(nodes, dst) * len(nodes) + np.searchsorted(nodes, src))
    if nodes is None:
        known()
    flush()
    none = np.zeros(0, dtype=np.int64)
    for k in feats:
        if k not in graphs:
            graphs[k] = ShelvedGraph(shelf, none.copy(), len(nodes))
    return Sample(graphs, feats, wanted, scale, capacity, policy), n


def sweep(name: str, s: Sample, q: int, times: list[int], w: Weights, hidden: int, flags: Flags, seen: Callable[[int, np.ndarray], np.ndarray | None], shelf: Shelf, learn: bool = False) -> Weights:
    """One sequence. `seen(i, y)` gets the i-th prediction of the targets and returns its gradient where there is one; with `learn` the weights' gradients come back."""
    m = MODELS[name]
    nodes = next(iter(s.feats.values())).shape[0]
    visits = [("enc", t) for t in times] + ([("dec", t + 1) for t in times] if m.decoder else [])
    first_out = len(visits) - len(targets(name, times))
    return _swept(name, s, q, visits, first_out, w, _zeros(name, nodes, hidden), flags, seen, shelf, _zeros(name, nodes, hidden) if learn else None)[1]


def piece(name: str, s: Sample, part: str, times: list[int], w: Weights, state: list[Pair], flags: Flags, shelf: Shelf, up: list[Pair] | None = None, cells: int = 1) -> tuple[list[Pair], Weights, float]:
    """`models.run_piece` of an integrated model: the state that comes in is handed on, or with `up`, the gradient of the one that went out, its own gradient."""
    loss = 0.0

    def seen(i: int, y: np.ndarray) -> np.ndarray:
        nonlocal loss
        d = y - s.x(times[i] + 1)[s.targets]
        loss += float(np.abs(d).sum() / cells)
        return np.sign(d) / cells

    came, grads = _swept(name, s, 0, [(part, t) for t in times], 0 if part == "dec" else len(times), w, state, flags, seen, shelf, up)
    return came, grads, loss


def _zeros(name: str, nodes: int, hidden: int) -> list[Pair]:
    m = MODELS[name]
    zero = lambda: np.zeros((nodes, hidden))
    return [(zero(), zero() if m.gates == 4 else None) for _ in range(m.layers)]


def _swept(name: str, s: Sample, q: int, visits: list[tuple[str, int]], first_out: int, w: Weights, state: list[Pair], flags: Flags, seen: Callable[[int, np.ndarray], np.ndarray | None], shelf: Shelf, due: list[Pair] | None) -> tuple[list[Pair], Weights]:
    """The state after the visits, of which those from `first_out` on predict; or with `due`, the gradient of that state, the gradient of the state before them and of the weights."""
    m, learn = MODELS[name], due is not None
    assert s.reset == "after"
    nodes, hidden, skip = *state[0][0].shape, name == "stk_skip_lstm"
    zero = lambda: np.zeros((nodes, hidden))
    state = list(state)
    kept: list[list[tuple]] = []
    cells = {at: Cell(name, at, w) for at in {f"{part}{layer}" for part, _ in visits for layer in range(m.layers)}}
    grads: Weights = {}
    shelf.clear()
    for i, (part, t) in enumerate(visits):
        g, held = s.graphs[t], []
        value = s.x(t)
        for layer in range(m.layers):
            h, c = state[layer]
            s.local_store.open()

            def operand(kind: str, gate: int, first: bool = layer == 0, value: np.ndarray = value, h: np.ndarray = h) -> np.ndarray:
                last = gate == m.gates - 1 or flags.gates
                make = (lambda: _first_input(s, q, part, t, flags, gate, last)) if first and kind == "x" else (lambda: g.sum(Var(value if kind == "x" else h)))  # noqa: B023
                return (s.local_store.get(kind, make) if flags.gates else make()).value

            if m.kind == "stacked":
                ax, ah = (_first_input(s, q, part, t, flags, 0, True) if layer == 0 else g.sum(Var(value))).value, None
            else:
                # without reuse every gate gathers anew, the same values
                for gate in range(m.gates):
                    ax = operand("x", gate)
                for gate in range(m.gates):
                    ah = operand("h", gate)
            across = value if skip else None
            if learn:
                held.append(tuple(None if x is None else shelf.put(x) for x in (ax, ah, across, h, c)))
            new = zero(), zero() if m.gates == 4 else None
            for lo in range(0, nodes, ROWS):
                made = cells[f"{part}{layer}"].forward(*(None if x is None else x[lo : lo + ROWS] for x in (ax, ah, across, h, c)))
                for x, v in zip(new, made):
                    if v is not None:
                        x[lo : lo + ROWS] = v
            state[layer], value = new, new[0]
        if i >= first_out:
            top = state[-1][0][s.targets]
            up = seen(i - first_out, top @ w["head"] + w["head.b"])
            if learn:
                grads["head"] = grads.get("head", 0) + top.T @ up
                grads["head.b"] = grads.get("head.b", 0) + up.sum(axis=0, keepdims=True)
                held.append(shelf.put(up))
        kept.append(held)
    if due is None:
        return state, {}
    del state, value
    due = list(due)
    for i in range(len(visits) - 1, -1, -1):
        part, t = visits[i]
        g = s.graphs[t]
        if i >= first_out:
            due[-1][0][s.targets] += shelf.take(kept[i][m.layers]) @ w["head"].T
        for layer in range(m.layers - 1, -1, -1):
            ins = kept[i][layer]
            back = [None if x is None else np.zeros(x[1]) for x in ins]
            gh, gc = due[layer]
            for lo in range(0, nodes, ROWS):
                vs = tuple(None if x is None else shelf.take(x, lo, lo + ROWS) for x in ins)
                found = cells[f"{part}{layer}"].backward(vs, gh[lo : lo + ROWS], None if gc is None else gc[lo : lo + ROWS])
                for x, v in zip(back, found):
                    if v is not None:
                        x[lo : lo + ROWS] = v
            gax, gah, across, gh, gc = back
            if gah is not None:
                gh += g.gather(gah, False)
            if layer:
                due[layer - 1][0][:] += g.gather(gax, False)
                if across is not None:
                    due[layer - 1][0][:] += across
            due[layer] = gh, gc
    for cell in cells.values():
        grads |= cell.weights()
    return due, grads
