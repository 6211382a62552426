"""Core and factors of a decomposition, with Parquet storage."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from .meta import TensorMeta


@dataclass
class Decomposition:
    meta: TensorMeta
    core: np.ndarray
    factors: list[np.ndarray]
    error: float | None = None
    sweeps: int = 0
    energies: dict[int, np.ndarray] = field(default_factory=dict)  # eigenvalues by mode

    def reconstruct(self) -> np.ndarray:
        out = self.core
        for m, f in enumerate(self.factors):
            out = np.moveaxis(np.tensordot(f, out, (1, m)), 0, m)
        return out

    def factor_frame(self, spark: SparkSession) -> DataFrame:
        rows = [(m + 1, i, [float(x) for x in r]) for m, f in enumerate(self.factors) for i, r in enumerate(f)]
        return spark.createDataFrame(rows, "mode int, row int, vec array<double>")

    def core_frame(self, spark: SparkSession) -> DataFrame:
        from ..operators.cells import from_array

        return from_array(spark, self.core)

    def mode_scores(self, spark: SparkSession, mode: int) -> DataFrame:
        """Rows of a factor as component scores of the mode's indices, with each component's share of energy."""
        f = self.factors[mode]
        values = self.energies.get(mode)
        share = values[: f.shape[1]] / max(values.sum(), 1e-300) if values is not None else np.full(f.shape[1], np.nan)
        rows = [(i, c + 1, float(f[i, c]), float(share[c])) for i in range(f.shape[0]) for c in range(f.shape[1])]
        return spark.createDataFrame(rows, "idx int, component int, score double, energy_share double")

    def save(self, spark: SparkSession, path: str) -> None:
        self.core_frame(spark).write.parquet(f"{path}/core")
        self.factor_frame(spark).write.parquet(f"{path}/factors")
        error = float("nan") if self.error is None else float(self.error)
        spark.createDataFrame([(list(self.meta.L), list(self.meta.K), self.meta.name, error, self.sweeps)], "L array<bigint>, K array<bigint>, name string, error double, sweeps int").write.parquet(f"{path}/meta")

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> Decomposition:
        m = spark.read.parquet(f"{path}/meta").first()
        meta = TensorMeta(tuple(m["L"]), tuple(m["K"]), m["name"])
        core = np.zeros(meta.K)
        for r in spark.read.parquet(f"{path}/core").collect():
            core[tuple(r[:-1])] = r[-1]
        factors = [np.zeros((n, k)) for n, k in zip(meta.L, meta.K, strict=True)]
        for r in spark.read.parquet(f"{path}/factors").collect():
            factors[r["mode"] - 1][r["row"]] = r["vec"]
        return cls(meta, core, factors, None if np.isnan(m["error"]) else m["error"], m["sweeps"])
