"""Root finding and quadrature as column expressions, so thousands of queries are solved in parallel without a UDF."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def solve_decreasing(f: Callable[[Column], Column], lo: Column, hi: Column, steps: int = 60) -> Column:
    """The root of a decreasing function between lo and hi, by a fixed number of bisections."""

    def halve(s: Column, _: Column) -> Column:
        mid = (s["lo"] + s["hi"]) / 2
        above = f(mid) > 0
        return F.struct(F.when(above, mid).otherwise(s["lo"]).alias("lo"), F.when(above, s["hi"]).otherwise(mid).alias("hi"))

    start = F.struct(lo.cast("double").alias("lo"), hi.cast("double").alias("hi"))
    return F.aggregate(F.sequence(F.lit(1), F.lit(steps)), start, halve, lambda s: (s["lo"] + s["hi"]) / 2)


def reciprocal_sum(x: Column, shifts: Column) -> Column:
    """The sum of 1 / (x - s) over an array of shifts."""
    return F.aggregate(shifts, F.lit(0.0), lambda a, s: a + 1.0 / (x - s))


def unit_nodes(n: int = 64) -> list[tuple[float, float]]:
    """Nodes and weights of Gauss-Legendre quadrature on (0, 1)."""
    x, w = np.polynomial.legendre.leggauss(n)
    return [(float((a + 1) / 2), float(b / 2)) for a, b in zip(x, w, strict=True)]


def integrate_unit(f: Callable[[Column], Column], n: int = 64) -> Column:
    """The integral of f over (0, 1)."""
    nodes = F.array(*[F.struct(F.lit(z).alias("z"), F.lit(w).alias("w")) for z, w in unit_nodes(n)])
    return F.aggregate(nodes, F.lit(0.0), lambda a, t: a + t["w"] * f(t["z"]))
