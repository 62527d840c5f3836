"""Random orthogonal mixing of the columns of a matrix, applied to its rows.

A round multiplies by points of the unit circle, Fourier-transforms and permutes; neighbouring reals are the
real and imaginary parts.  An odd width gets one zero column, which leaves again on the way back.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np


@dataclass(frozen=True)
class MixingPlan:
    n: int
    kind: str = "fourier"
    phases: tuple = ()
    orders: tuple = ()
    dense: np.ndarray | None = None

    @property
    def width(self) -> int:
        """Columns after mixing."""
        return self.n + self.n % 2 if self.kind == "fourier" else self.n

    @staticmethod
    def build(n: int, seed: int = 0, rounds: int | str = 2, kind: str = "fourier") -> MixingPlan:
        """kind: "fourier", "gaussian" (the orthogonal factor of a Gaussian matrix, for small n) or "none"; rounds: a number or "log"."""
        rng = np.random.default_rng(seed)
        if kind == "none":
            return MixingPlan(n, kind)
        if kind == "gaussian":
            q, r = np.linalg.qr(rng.standard_normal((n, n)))
            return MixingPlan(n, kind, dense=q * np.sign(np.diag(r)))
        half = (n + 1) // 2
        count = max(1, int(np.ceil(np.log2(max(n, 2))))) if rounds == "log" else int(rounds)
        phases = tuple(np.exp(2j * np.pi * rng.random(half)) for _ in range(count))
        return MixingPlan(n, kind, phases, tuple(rng.permutation(half) for _ in range(count)))

    def forward(self, x: np.ndarray) -> np.ndarray:
        """Rows of x mixed: (b, n) to (b, width)."""
        if self.kind == "none":
            return x
        if self.kind == "gaussian":
            return x @ self.dense.T
        if self.n % 2:
            x = np.concatenate((x, np.zeros((len(x), 1))), axis=1)
        z = np.ascontiguousarray(x).view(np.complex128)
        for phase, order in zip(self.phases, self.orders, strict=True):
            z = np.fft.fft(z * phase, axis=1, norm="ortho")[:, order]
        return np.ascontiguousarray(z).view(np.float64)

    def inverse(self, x: np.ndarray) -> np.ndarray:
        """Undoes forward(): (b, width) to (b, n)."""
        if self.kind == "none":
            return x
        if self.kind == "gaussian":
            return x @ self.dense
        z = np.ascontiguousarray(x).view(np.complex128)
        for phase, order in zip(self.phases[::-1], self.orders[::-1], strict=True):
            back = np.empty_like(z)
            back[:, order] = z
            z = np.fft.ifft(back, axis=1, norm="ortho") * phase.conj()
        return np.ascontiguousarray(z).view(np.float64)[:, : self.n]
