"""Bilinear schemes: how n0 x n0 blocks multiply with q products.

A scheme gives each product's left and right combination of blocks and each
output block's combination of products. Blocks are numbered row by row.
``stages`` are shared two-operand steps that save additions.
"""

from __future__ import annotations

import itertools
import math
from dataclasses import dataclass, field

import numpy as np


@dataclass(frozen=True)
class Stages:
    """Named sums: each step is (name, ((coefficient, operand), ...)); outputs name the results.

    Operands are block numbers as strings, or names of earlier steps.
    """

    steps: tuple[tuple[str, tuple[tuple[int, str], ...]], ...]
    outputs: tuple[str, ...]

    def table(self, inputs: int) -> np.ndarray:
        """Plain coefficients, one row per output."""
        known = {str(k): np.eye(inputs, dtype=int)[k] for k in range(inputs)}
        for name, terms in self.steps:
            known[name] = sum(c * known[x] for c, x in terms)
        return np.array([known[x] for x in self.outputs])

    @property
    def additions(self) -> int:
        return sum(len(terms) - 1 for _, terms in self.steps)


def plain_stages(table: np.ndarray) -> Stages:
    """Stages without sharing, from plain coefficients."""
    steps, outputs = [], []
    for k, row in enumerate(table):
        terms = tuple((int(c), str(x)) for x, c in enumerate(row) if c)
        if len(terms) == 1 and terms[0][0] == 1:
            outputs.append(terms[0][1])
        else:
            steps.append((f"o{k}", terms))
            outputs.append(f"o{k}")
    return Stages(tuple(steps), tuple(outputs))


@dataclass(frozen=True)
class Scheme:
    name: str
    n0: int
    q: int
    left: Stages
    right: Stages
    out: Stages
    tables: tuple = field(init=False, compare=False, hash=False, repr=False)

    def __post_init__(self):
        blocks = self.n0**2
        object.__setattr__(self, "tables", (self.left.table(blocks), self.right.table(blocks), self.out.table(self.q)))

    @property
    def additions(self) -> int:
        return self.left.additions + self.right.additions + self.out.additions

    @property
    def omega(self) -> float:
        """Exponent of the arithmetic."""
        return math.log(self.q, self.n0)

    def validate(self) -> bool:
        """The n0**6 product identities: left x right x out is matrix multiplication."""
        u, v, w = self.tables
        got = np.einsum("ra,rb,cr->abc", u, v, w)
        n, want = self.n0, np.zeros_like(got)
        for i, k, j in itertools.product(range(n), repeat=3):
            want[i * n + k, k * n + j, i * n + j] = 1
        return bool((got == want).all())

    def growth(self) -> int:
        """Largest factor by which one level can raise the magnitude of a product sum."""
        u, v, w = (np.abs(t) for t in self.tables)
        return int((w @ (u.sum(1) * v.sum(1))).max())


def _sum(*terms):
    return tuple((c, str(x)) for c, x in terms)


# The two seven-product schemes, blocks 0..3 = 11, 12, 21, 22.
_S18 = Scheme(
    "s7a18", 2, 7,
    Stages((("l0", _sum((1, 0), (1, 3))), ("l1", _sum((1, 2), (1, 3))), ("l4", _sum((1, 0), (1, 1))), ("l5", _sum((1, 2), (-1, 0))), ("l6", _sum((1, 1), (-1, 3)))), ("l0", "l1", "0", "3", "l4", "l5", "l6")),
    Stages((("r0", _sum((1, 0), (1, 3))), ("r2", _sum((1, 1), (-1, 3))), ("r3", _sum((1, 2), (-1, 0))), ("r5", _sum((1, 0), (1, 1))), ("r6", _sum((1, 2), (1, 3)))), ("r0", "0", "r2", "r3", "3", "r5", "r6")),
    Stages((("c11", _sum((1, 0), (1, 3), (-1, 4), (1, 6))), ("c12", _sum((1, 2), (1, 4))), ("c21", _sum((1, 1), (1, 3))), ("c22", _sum((1, 0), (-1, 1), (1, 2), (1, 5)))), ("c11", "c12", "c21", "c22")),
)
_S15 = Scheme(
    "s7a15", 2, 7,
    Stages((("x1", _sum((1, 2), (1, 3))), ("x2", _sum((1, "x1"), (-1, 0))), ("x3", _sum((1, 1), (-1, "x2"))), ("x4", _sum((1, 0), (-1, 2)))), ("0", "1", "x3", "3", "x1", "x2", "x4")),
    Stages((("y1", _sum((1, 1), (-1, 0))), ("y2", _sum((1, 3), (-1, "y1"))), ("y3", _sum((1, "y2"), (-1, 2))), ("y4", _sum((1, 3), (-1, 1)))), ("0", "2", "3", "y3", "y1", "y2", "y4")),
    Stages((("u", _sum((1, 0), (1, 5))), ("v", _sum((1, "u"), (1, 6))), ("w", _sum((1, "u"), (1, 4))), ("c11", _sum((1, 0), (1, 1))), ("c12", _sum((1, "w"), (1, 2))), ("c21", _sum((1, "v"), (-1, 3))), ("c22", _sum((1, "v"), (1, 4)))), ("c11", "c12", "c21", "c22")),
)


def classical(n0: int) -> Scheme:
    """The n0**3 products of the definition."""
    cells = list(itertools.product(range(n0), repeat=3))
    u = np.array([[int(x == i * n0 + k) for x in range(n0**2)] for i, k, j in cells])
    v = np.array([[int(x == k * n0 + j) for x in range(n0**2)] for i, k, j in cells])
    w = np.array([[int(i * n0 + j == c) for i, k, j in cells] for c in range(n0**2)])
    return Scheme(f"c{n0**3}", n0, n0**3, plain_stages(u), plain_stages(v), plain_stages(w))


def compose(a: Scheme, b: Scheme) -> Scheme:
    """The scheme that applies ``b`` inside ``a``: (n0 n0') blocks a side, q q' products.

    Used to fuse levels: one step of the composed scheme replaces two.
    """
    n, m = a.n0, b.n0
    order = [((i // m) * n + (j // m)) * m * m + (i % m) * m + (j % m) for i in range(n * m) for j in range(n * m)]

    def inputs(s, t):
        return np.kron(s, t)[:, order]

    (ua, va, wa), (ub, vb, wb) = a.tables, b.tables
    out = np.kron(wa, wb)[order, :]
    return Scheme(f"{a.name}x{b.name}", n * m, a.q * b.q, plain_stages(inputs(ua, ub)), plain_stages(inputs(va, vb)), plain_stages(out))


SCHEMES = {s.name: s for s in (_S18, _S15, classical(2))}
SCHEMES["tensor4"] = compose(_S15, _S15)


def scheme_of(name) -> Scheme:
    """A scheme by name; a scheme given is validated and passed through."""
    if isinstance(name, Scheme):
        if not name.validate():
            raise ValueError(f"{name.name} doesn't multiply matrices")
        return name
    return SCHEMES[name]
