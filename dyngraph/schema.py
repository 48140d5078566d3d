"""Table shapes of the engine and the objects that carry them."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

EDGES = T.StructType([T.StructField(c, T.LongType()) for c in ("t", "src", "dst")] + [T.StructField("w", T.DoubleType())])
VERTICES = T.StructType([T.StructField("v", T.LongType())])
RUNS = "src long, dst long, t_from long, t_to long, w double"


def assert_schema(df: DataFrame, expected: T.StructType) -> DataFrame:
    """df, or an error that names the columns whose name or type differs."""
    have, want = [(f.name, f.dataType) for f in df.schema], [(f.name, f.dataType) for f in expected]
    if have != want:
        raise TypeError(f"expected {want}, got {have}")
    return df


@dataclass(frozen=True)
class DynamicGraph:
    """Snapshots 1..T over one vertex set: edges (t, src, dst, w), vertices (v)."""

    edges: DataFrame
    vertices: DataFrame
    T: int

    def with_edges(self, edges: DataFrame) -> DynamicGraph:
        return replace(self, edges=edges)

    @property
    def spark(self):
        return self.edges.sparkSession


@dataclass(frozen=True)
class FeatureTensor:
    """One row (t, v, x0, x1, ...) for every vertex in every snapshot."""

    df: DataFrame
    width: int
    name: str = "x"

    @property
    def cols(self) -> list[str]:
        return [f"{self.name}{i}" for i in range(self.width)]

    @property
    def keys(self) -> list[str]:
        """The columns that name a frame; with home, the key by which frames are laid out."""
        return [*(["home"] if "home" in self.df.columns else []), "t", "v"]

    def renamed(self, name: str) -> FeatureTensor:
        return FeatureTensor(self.df.select(*self.keys, *[F.col(a).alias(f"{name}{i}") for i, a in enumerate(self.cols)]), self.width, name)

    def keep(self, condition: Column) -> FeatureTensor:
        return replace(self, df=self.df.where(condition))


@dataclass
class Config:
    """Widths and windows of a model and of its training. Windows, blocks and optimiser are ours: nothing fixes them."""

    hidden: int = 6
    classes: int = 2
    layers: int = 2
    window: int = 3
    life: int = 3
    blocks: int = 4
    rate: float = 0.1
    optimizer: str = "sgd"
    precompute: bool = True
    layout: str = "snapshot"
    transfer: str = "full"
    processors: int = 4
    seed: int = 7
    extra: dict = field(default_factory=dict)


def fixed_weights(rows: int, cols: int, k: int = 0) -> np.ndarray:
    """Weights by formula, the same in SQL: ((3 i + 5 j + k) mod 7 - 3) / 10."""
    i, j = np.ogrid[:rows, :cols]
    return ((3 * i + 5 * j + k) % 7 - 3) / 10.0
