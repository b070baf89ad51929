"""Bounds on the rank of page matrices, and the rank that is there."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame


def recurrence_bound(terms: int, degree: int) -> int:
    """Order of a sum of ``terms`` products of exponential, cosine and a
    polynomial of at most ``degree``."""
    return terms * (degree + 1) * (degree + 2)


def stacked_bound(shared: int, order: int) -> int:
    """Rank of the stacked matrix of series that mix ``shared`` recurrences."""
    return shared * order


def second_moment_bound(shared: int, order: int, shared2: int, order2: int) -> int:
    return (shared * order) ** 2 + shared2 * order2


def numeric_rank(pages: DataFrame, column: str = "vals", tolerance: float = 1e-6) -> int:
    """Singular values above the tolerance, from one cohort's Gram matrix."""
    from pagecast.operators.factor import gram_rows

    rows = gram_rows(pages, 1 << 40).where("moment = " + ("1" if column == "vals" else "2")).collect()
    g = sum(np.frombuffer(r["g"]) for r in rows)
    w = round(len(g) ** 0.5)
    s = np.sqrt(np.maximum(np.linalg.eigvalsh(g.reshape(w, w))[::-1], 0))
    return int(np.count_nonzero(s > tolerance * s[0])) if s[0] > 0 else 0
