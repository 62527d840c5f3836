"""Lazy matrix expressions: products by small factors are fused before any table is built."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from ..matrix import RowFrame
from ..operators import gram as _gram
from ..operators.thin import scale_columns, times_small


class Expr:
    def times(self, w: np.ndarray) -> Expr:
        return Times(self, np.asarray(w, float))

    def scaled(self, d: np.ndarray) -> Expr:
        return Scale(self, np.asarray(d, float))

    def rows(self) -> RowFrame:
        return lower(optimise(self))

    def gram(self) -> np.ndarray:
        """(E)*(E), with factors pulled out of the scan: (A W)*(A W) = W* (A*A) W."""
        e = optimise(self)
        if isinstance(e, Times) and isinstance(e.of, Source):
            return e.w.T @ _gram.gram_matrix(e.of.frame) @ e.w
        return _gram.gram_matrix(lower(e))

    def explain(self) -> str:
        return f"{self}\n-> {optimise(self)}"


@dataclass
class Source(Expr):
    frame: RowFrame

    def __str__(self):
        return f"rows[{self.frame.n}]"


@dataclass
class Times(Expr):
    of: Expr
    w: np.ndarray

    def __str__(self):
        return f"({self.of} * {self.w.shape[0]}x{self.w.shape[1]})"


@dataclass
class Scale(Expr):
    of: Expr
    d: np.ndarray

    def __str__(self):
        return f"({self.of} * diag[{len(self.d)}])"


def optimise(e: Expr) -> Expr:
    """Neighbouring factors become one; a scaling next to a factor goes into it.

    Inverses of ill-conditioned triangles must not be multiplied together; they are solved row by row and never stand here.
    """
    if isinstance(e, Source):
        return e
    of = optimise(e.of)
    if isinstance(e, Times):
        if isinstance(of, Times):
            return Times(of.of, of.w @ e.w)
        if isinstance(of, Scale):
            return Times(of.of, of.d[:, None] * e.w)
        return Times(of, e.w)
    if isinstance(of, Times):
        return Times(of.of, of.w * e.d)
    if isinstance(of, Scale):
        return Scale(of.of, of.d * e.d)
    return Scale(of, e.d)


def lower(e: Expr) -> RowFrame:
    if isinstance(e, Source):
        return e.frame
    if isinstance(e, Times):
        return times_small(lower(e.of), e.w)
    return scale_columns(lower(e.of), e.d)
