"""Which aggregations a model repeats, and which reuse removes; choices made before a plan is built."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class Flags:
    incremental: bool = True
    gates: bool = True
    sequences: bool = True
    teacher: bool = True


NONE = Flags(False, False, False, False)
ALL = Flags()


@dataclass(frozen=True)
class ModelShape:
    """kind: 'stacked' (graph layer, then cell) or 'integrated' (graph layers inside the cell's gates)."""

    name: str
    kind: str
    gates: int
    layers: int = 2

    @property
    def decoder(self) -> bool:
        return self.kind == "integrated"


MODELS = {m.name: m for m in (ModelShape("stk_conv_lstm", "stacked", 4), ModelShape("stk_skip_lstm", "stacked", 4), ModelShape("int_conv_lstm", "integrated", 4), ModelShape("int_conv_gru", "integrated", 3))}
#: Settings of the published experiments.
DEFAULTS = {"hidden": 64, "length": 8, "stride": 1, "batch": 10_000, "fanouts": (25, 10), "pairs": 2, "layers": 2, "threshold": 0.5, "order": "seq_first"}


def applicable(model: ModelShape) -> list[dict]:
    """Per layer and operand ('input', 'hidden'): which reuse can apply. Across gates: integrated cells, every layer; across sequences and from decoder to encoder: inputs of layer 1 only."""
    rows = []
    for layer in range(1, model.layers + 1):
        for operand in ("input", "hidden") if model.kind == "integrated" else ("input",):
            first = layer == 1 and operand == "input"
            rows.append({"model": model.name, "layer": layer, "operand": operand, "gates": model.kind == "integrated", "sequences": first, "teacher": first and model.decoder, "incremental": first})
    return rows


def passes(model: ModelShape, gates: bool) -> dict[str, int]:
    """Graph passes of one cell step per layer: by operand."""
    if model.kind == "stacked":
        return {"input": 1, "hidden": 0}
    k = 1 if gates else model.gates
    return {"input": k, "hidden": k}


def project_first(width_in: int, width_out: int, consumers: int) -> bool:
    """Projecting before aggregation narrows the shuffle only for a single narrower consumer; several gates share one aggregate."""
    return consumers == 1 and width_out < width_in


def scratch_or_delta(change_ratio: float, threshold: float = DEFAULTS["threshold"]) -> str:
    return "scratch" if change_ratio > threshold else "delta"
