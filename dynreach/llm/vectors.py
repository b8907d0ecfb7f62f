"""What the vector operators share: which vectors take part, and rotations."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from dynreach.llm.common import seeded


def usable(column: str) -> Column:
    """Not null, not empty, no null or non-finite component, not all zero."""
    sound = F.forall(column, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    return F.coalesce(F.col(column).isNotNull() & sound & F.exists(column, lambda x: x != 0), F.lit(False))


def rotation(d: int, seed: int) -> np.ndarray:
    """A uniform random orthogonal matrix."""
    q, r = np.linalg.qr(seeded(seed * 1_000_003 + d).standard_normal((d, d)))
    return q * np.sign(np.diag(r))
