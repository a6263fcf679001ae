"""Spectral clustering through landmarks: exact on a hash sample of bounded size, every item then
takes the group of its nearest landmark."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from trajkit.operators import lloyd as L
from trajkit.operators.graphcut import normalized_cut

MAX_LANDMARKS = 3000


def landmark_spectral(z: DataFrame, cols: list[str], k: int, landmarks: int = 300, sigma: float | None = None, seed: str = "0") -> DataFrame:
    """item_id, class."""
    if landmarks > MAX_LANDMARKS:
        raise ValueError(f"at most {MAX_LANDMARKS} landmarks: the cut's cost is cubic in them")
    x = L.seeds(z, cols, landmarks, seed)
    d = np.sqrt(((x[:, None] - x[None]) ** 2).sum(2))
    sigma = sigma or float(np.median(d[d > 0])) / 2
    w = np.exp(-(d**2) / (2 * sigma**2))
    np.fill_diagonal(w, 0)
    groups = normalized_cut(w, k)
    near = L._assign_arrow(z.select("item_id", *cols), cols, x)
    return near.select("item_id", F.element_at(F.array(*[F.lit(int(g)) for g in groups]), F.col("label") + 1).alias("class"))
