"""Parameters of the method, its baselines and its evaluation."""

from __future__ import annotations

import math
from dataclasses import asdict, dataclass, replace

from pyspark.sql import DataFrame, SparkSession


def default_bins(n: int) -> int:
    """Number of bins for n vertices: the whole part of ln n, one at least."""
    return max(1, math.floor(math.log(n))) if n > 1 else 1


def check_bins(k: int, n: int, allow_over_bound: bool = False) -> int:
    """k if it leaves no bin empty and keeps to the bound ln n; otherwise an error."""
    if k < 1 or k > max(n, 1):
        raise ValueError(f"{k} bins do not suit {n} vertices")
    if k > default_bins(n) and not allow_over_bound:
        raise ValueError(f"{k} bins exceed the bound {default_bins(n)} for {n} vertices")
    return k


@dataclass(frozen=True)
class WalkConfig:
    """Walk length, walks per vertex, jump probability, noise, window, dimension; None switches a noise off.

    eps_degree scales the Laplace noise of degree vectors, eps_walk the substitution law of emitted vertices. tree names
    the way of the server: 'hybrid', 'average', 'single' and 'complete' are exact, with all pairs, and refuse graphs beyond
    the exact limit; 'bisect' works by blocks at any size. outside is what a block law does with the mass it bounds outside
    the block: 'drop' it, or draw from all vertices with it ('uniform').
    """

    length: int = 40
    per_vertex: int = 80
    jump: float = 0.2
    eps_degree: float | None = 2.0
    eps_walk: float | None = 2.0
    sensitivity: float = 1.0
    bins: int | None = None
    bin_sizes: str = "equal"
    rounding: str = "round"
    near: str = "leaves"
    jump_emits: str = "target"
    charge_final_jump: bool = True
    score_scale: float = 1.0
    calibrated: float | None = None
    window: int = 10
    dim: int = 128
    tree: str = "hybrid"
    block: int = 1024
    outside: str = "drop"
    row_cap: int | None = None
    one_sided: bool = False
    band: int | None = None
    perturb_rows: bool = False
    exact_two_hop: bool = False
    seed: str = "1"
    rng: str = "md5"

    def with_(self, **changes) -> WalkConfig:
        return replace(self, **changes)

    def as_frame(self, spark: SparkSession) -> DataFrame:
        """One row of name and value for each parameter."""
        rows = [(k, None if v is None else str(v)) for k, v in asdict(self).items()]
        return spark.createDataFrame(rows, "name string, value string")
