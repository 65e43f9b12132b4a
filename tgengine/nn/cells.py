"""The recurrent cells of `models`, on arrays and differentiated by hand, for the nodes of a piece.

Nodes lie side by side, so that a gate is a run of whole rows; all gates of an operand are one product, and tanh(x) is 2 sigmoid(2x) - 1.
"""

from __future__ import annotations

import numpy as np

from ..plans.reuse import MODELS

Ins = tuple[np.ndarray | None, ...]


def _sigmoid(z: np.ndarray) -> np.ndarray:
    """In place."""
    np.clip(z, -60, 60, out=z)
    np.negative(z, out=z)
    np.exp(z, out=z)
    z += 1
    return np.divide(1, z, out=z)


def _tanh(z: np.ndarray) -> np.ndarray:
    """In place."""
    z *= 2
    _sigmoid(z)
    z *= 2
    z -= 1
    return z


class Cell:
    """The cell `at` (part and layer) with its weights. Operands: aggregated input, aggregated state, the value beside the graph layer's output, state h and c; those that a model has not are None."""

    def __init__(self, name: str, at: str, w: dict[str, np.ndarray]):
        self.at, self.gates = at, MODELS[name].gates
        self.conv = w[f"{at}.conv"] if MODELS[name].kind == "stacked" else None
        self.x, self.h, self.b = (np.ascontiguousarray(np.hstack([w[f"{at}.{k}{g}"] for g in range(self.gates)]).T) for k in "xhb")
        self.hidden = len(self.b) // self.gates
        self.grads = [np.zeros_like(v) for v in (self.x, self.h, self.b)] + ([np.zeros_like(self.conv)] if self.conv is not None else [])

    def _ins(self, ax: np.ndarray, ah: np.ndarray | None, across: np.ndarray | None, h: np.ndarray, c: np.ndarray | None) -> Ins:
        """Operands with the nodes side by side: of the gates' two products, and the state."""
        t = [None if v is None else np.ascontiguousarray(v.T) for v in (ax, ah, across, h, c)]
        if self.conv is None:
            return t[0], t[1], t[3], t[4]
        u = np.maximum(self.conv.T @ t[0], 0)
        return u if across is None else np.vstack([u, t[2]]), t[3], t[3], t[4]

    def _lstm(self, x: np.ndarray, hs: np.ndarray, c: np.ndarray) -> Ins:
        k = self.hidden
        z = self.x @ x
        z += self.h @ hs
        z += self.b
        _sigmoid(z[: 3 * k])
        _tanh(z[3 * k :])
        c = z[k : 2 * k] * c
        c += z[:k] * z[3 * k :]
        return z, c, _tanh(c.copy())

    def _gru(self, x: np.ndarray, hs: np.ndarray) -> Ins:
        k = self.hidden
        z = self.x @ x
        z += self.b
        back = self.h @ hs
        z[: 2 * k] += back[: 2 * k]
        _sigmoid(z[: 2 * k])
        z[2 * k :] += z[k : 2 * k] * back[2 * k :]
        _tanh(z[2 * k :])
        return z, back[2 * k :]

    def forward(self, *ins: np.ndarray | None) -> tuple[np.ndarray, np.ndarray | None]:
        x, hs, h, c = self._ins(*ins)
        k = self.hidden
        if self.gates == 4:
            z, c, top = self._lstm(x, hs, c)
            return (z[2 * k : 3 * k] * top).T, c.T
        z, _ = self._gru(x, hs)
        return (h + z[:k] * (z[2 * k :] - h)).T, None

    def backward(self, ins: Ins, gh: np.ndarray, gc: np.ndarray | None) -> list[np.ndarray | None]:
        """Gradients of the operands; those of the weights are added to `grads`."""
        x, hs, h, c = self._ins(*ins)
        k, up = self.hidden, np.ascontiguousarray(gh.T)
        if self.gates == 4:
            z, _, top = self._lstm(x, hs, c)
            i, f, o, g = (z[j * k : (j + 1) * k] for j in range(4))
            d = np.empty_like(z)
            down = gc.T + up * o * (1 - top * top)
            np.multiply(down, g, out=d[:k])
            np.multiply(down, c, out=d[k : 2 * k])
            np.multiply(up, top, out=d[2 * k : 3 * k])
            np.multiply(down, i, out=d[3 * k :])
            d[: 3 * k] *= z[: 3 * k] * (1 - z[: 3 * k])
            d[3 * k :] *= 1 - g * g
            d_back, dh, dc = d, None, down * f
        else:
            z, back = self._gru(x, hs)
            u, r, n = (z[j * k : (j + 1) * k] for j in range(3))
            d = np.empty_like(z)
            np.multiply(up, (n - h) * u * (1 - u), out=d[:k])
            np.multiply(up, u * (1 - n * n), out=d[2 * k :])
            np.multiply(d[2 * k :], back * r * (1 - r), out=d[k : 2 * k])
            d_back = d.copy()
            d_back[2 * k :] *= r
            dh, dc = up * (1 - u), None
        dx, dhs = self.x.T @ d, self.h.T @ d_back
        for whole, one in zip(self.grads, (d @ x.T, d_back @ hs.T, d.sum(axis=1, keepdims=True))):
            whole += one
        side = None
        if self.conv is not None:
            width = self.conv.shape[1]
            side = dx[width:] if ins[2] is not None else None
            du = dx[:width] * (x[:width] > 0)
            self.grads[3] += ins[0].T @ du.T
            dx, dhs, dh = self.conv @ du, None, dhs if dh is None else dhs + dh
        return [None if v is None else v.T for v in (dx, dhs, side, dh, dc)]

    def weights(self) -> dict[str, np.ndarray]:
        """Gradients by the weights' names."""
        k = self.hidden
        out = {f"{self.at}.{name}{g}": v[g * k : (g + 1) * k].T for name, v in zip("xhb", self.grads) for g in range(self.gates)}
        return out | ({f"{self.at}.conv": self.grads[3]} if self.conv is not None else {})
