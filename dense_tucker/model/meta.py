"""Sizes of a tensor, its core and the number of workers: all that planning needs."""

from __future__ import annotations

import warnings
from dataclasses import dataclass
from fractions import Fraction
from math import prod


class NoValidGrid(ValueError):
    """No grid of the asked number of blocks fits the core."""


@dataclass(frozen=True)
class TensorMeta:
    """L: lengths of the tensor, K: lengths of its core; modes are numbered from 0 inside."""

    L: tuple[int, ...]
    K: tuple[int, ...]
    name: str = ""

    def __post_init__(self):
        object.__setattr__(self, "L", tuple(int(x) for x in self.L))
        object.__setattr__(self, "K", tuple(int(x) for x in self.K))
        if len(self.L) != len(self.K) or not self.L:
            raise ValueError("L and K must have the same length, one at least")
        if any(not 1 <= k <= n for k, n in zip(self.K, self.L, strict=True)):
            raise ValueError(f"need 1 <= K <= L, have L={self.L} K={self.K}")

    @property
    def n(self) -> int:
        return len(self.L)

    def cardinality(self) -> int:
        return prod(self.L)

    def core_size(self) -> int:
        return prod(self.K)

    def fiber_count(self, mode: int) -> int:
        return self.cardinality() // self.L[mode]

    def h(self, mode: int) -> Fraction:
        """Compression factor of a mode."""
        return Fraction(self.K[mode], self.L[mode])

    def size_after(self, modes: int) -> int:
        """Cardinality once the modes of a bit mask are multiplied."""
        return prod(self.K[i] if modes >> i & 1 else self.L[i] for i in range(self.n))

    def shape_after(self, modes: int) -> tuple[int, ...]:
        return tuple(self.K[i] if modes >> i & 1 else self.L[i] for i in range(self.n))

    def compression_rate(self, with_factors: bool = False) -> float:
        stored = self.core_size() + (sum(a * b for a, b in zip(self.L, self.K, strict=True)) if with_factors else 0)
        return self.cardinality() / stored

    def validate(self) -> list[str]:
        """Warnings about ranks that the other modes' core cannot fill (planning stays allowed)."""
        notes = [f"mode {i + 1}: K={k} exceeds the product of the other core lengths" for i, k in enumerate(self.K) if k > self.core_size() // k]
        for note in notes:
            warnings.warn(note, stacklevel=2)
        return notes

    @classmethod
    def from_dataframe(cls, df, modes: list[str], ratio: float = 2.0, name: str = "") -> TensorMeta:
        """L from distinct counts of the mode columns, K = ceil(L / ratio)."""
        from pyspark.sql import functions as F

        L = df.agg(*[F.count_distinct(m) for m in modes]).first()
        return cls(tuple(L), tuple(-(-int(n * 1000) // int(ratio * 1000)) for n in L), name)


#: Published sizes of the tensors that the experiments name.
NAMED = {
    "HCCI": TensorMeta((672, 672, 627, 16), (279, 279, 153, 14), "HCCI"),
    "TJLR": TensorMeta((460, 700, 360, 16, 4), (306, 232, 239, 16, 4), "TJLR"),
    "SP": TensorMeta((500, 500, 500, 11, 10), (81, 129, 127, 7, 6), "SP"),
    "least_gain": TensorMeta((400, 400, 20, 20, 20), (320, 40, 10, 10, 10), "least_gain"),
    "greatest_gain": TensorMeta((400, 100, 100, 50, 20), (80, 80, 10, 40, 10), "greatest_gain"),
}
