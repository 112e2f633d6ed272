"""Size and work of a network, from its shape alone."""

from __future__ import annotations

import numpy as np

from .features import Template
from .model import Network
from .quantize import CodedNetwork

#: Eight matrix products a cell and step.
LSTM_PRODUCTS = 8


def dense_params(h0, hidden: int, classes: int):
    """Parameters of the hidden layer and the output; ``h0`` may be a column."""
    return h0 * hidden + hidden + hidden * classes + classes


def params(template: Template, hidden: int, classes: int) -> int:
    return sum(g.vocab * g.dim for g in template.groups) + dense_params(template.h0, hidden, classes)


def flops(h0: int, hidden: int, classes: int, count_bias: bool = False) -> int:
    """One forward pass given h0: two per dense weight; logits counted, non-linearities and normalisation not."""
    return 2 * h0 * hidden + 2 * hidden * classes + (hidden + classes if count_bias else 0)


def size_bytes(template: Template, hidden: int, classes: int, bits: int = 32, scale_bytes: int = 0, resources: int = 0) -> float:
    """Embeddings of ``bits`` a number and a scale a row, the rest as 4-byte floats, and resources."""
    rows = sum(g.vocab for g in template.groups)
    dense = dense_params(template.h0, hidden, classes)
    return sum(g.vocab * g.dim for g in template.groups) * bits / 8 + rows * scale_bytes + 4 * dense + resources


def size_kb(net: Network | CodedNetwork) -> float:
    """Kilobytes of a network as it stands: codes and scales if it is kept in codes, and the bytes of its resources (maps, vocabularies)."""
    resources = int(net.resources.get("bytes", 0))
    if isinstance(net, CodedNetwork):
        scales = sum(s.size for s in net.scales) * net.scale_bytes
        return (size_bytes(net.template, len(net.c), len(net.classes), net.bits, 0, resources) + scales) / 1024
    return size_bytes(net.template, len(net.c), len(net.classes), 32, 0, resources) / 1024


def net_flops(net: Network | CodedNetwork) -> int:
    return flops(net.template.h0, len(net.c), len(net.classes))


def lstm_params(layers: int, width: int, inputs: int | None = None) -> int:
    sizes = [inputs or width] + [width] * (layers - 1)
    return sum(4 * width * (i + width + 1) for i in sizes)


def lstm_flops(layers: int, width: int, steps: int = 1, inputs: int | None = None) -> int:
    sizes = [inputs or width] + [width] * (layers - 1)
    return steps * sum(LSTM_PRODUCTS * width * (i + width) for i in sizes)


def decisions(task: str, units: int = 1, swaps: int = 0) -> float:
    """Forward passes per document, token, character or word of a sentence of ``units`` words."""
    return {"document": 1, "token": 1, "char": 1, "word": (2 * units - 1 + 2 * swaps) / units}[task]


def lstm_cell(x: np.ndarray, h: np.ndarray, c: np.ndarray, w: np.ndarray, u: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """One step of a batch: four gates, each from one product with the input and one with the state."""
    n = h.shape[1]
    gate = lambda k: x @ w[k * n : (k + 1) * n].T + h @ u[k * n : (k + 1) * n].T + b[k * n : (k + 1) * n]
    s = lambda z: 1 / (1 + np.exp(-z))
    c = s(gate(1)) * c + s(gate(0)) * np.tanh(gate(2))
    return s(gate(3)) * np.tanh(c), c
