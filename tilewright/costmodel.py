"""What a tile join costs: the closed model, the realised work, and advice drawn from both."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .measures import products, quality
from .plans.layout import Layout, payload_of
from .plans.methods import PLANS

#: Payloads of the sweep as shares of the dataset.
FRACTIONS = (0.00001, 0.00005, 0.0001, 0.0002, 0.0005, 0.001, 0.002, 0.005, 0.01, 0.05)


def join_cost(r: float, s: float, k: float, alpha: float, beta: float) -> float:
    """Comparisons in k even tiles of which a share alpha is replicas, and beta per input object."""
    return (1 + alpha) ** 2 * r * s / k + beta * (r + s)


def join_cost_column(r, s, k, alpha, beta):
    """The same as a column expression."""
    grown = 1 + F.col(alpha)
    return grown * grown * F.col(r) * F.col(s) / F.col(k) + F.lit(beta) * (F.col(r) + F.col(s))


def uniform_alpha(side: float, k: float) -> float:
    """Replica share of square objects of a side on the unit square, in sqrt(k) x sqrt(k) tiles."""
    return (1 + side * math.sqrt(k)) ** 2 - 1


def uniform_optimum(side: float) -> tuple[float, float]:
    """The number of tiles that minimises the comparisons of uniform squares, and its alpha."""
    k = 1 / side**2
    return k, uniform_alpha(side, k)


def realised(r: DataFrame, s: DataFrame, layout: Layout, beta: float = 0.0) -> DataFrame:
    """Sum and maximum of the tiles' products, and the sum with beta per routed object."""
    p = products(r, s, layout)
    return p.agg(F.sum("work").alias("work"), F.max("work").alias("largest"), (F.sum("work") + beta * F.sum(F.col("r_n") + F.col("s_n"))).alias("cost"))


def sweep(r: DataFrame, s: DataFrame, method: str, fractions=FRACTIONS, beta: float = 2.0, least: int = 10, **opts) -> list[dict]:
    """Model and realised cost per payload share; payloads under `least` objects are left out."""
    from .plans.methods import plan_joint

    nr, ns = r.count(), s.count()
    both = r.select("id", "xmin", "ymin", "xmax", "ymax").unionByName(s.select("id", "xmin", "ymin", "xmax", "ymax"))
    out = []
    for f in fractions:
        b = payload_of(f, nr + ns)
        if b < least:
            continue
        layout = plan_joint(r, s, method, b, **opts)
        q = quality(both, layout).first()
        cost = realised(r, s, layout, beta).first()
        out.append({"method": method, "fraction": f, "payload": b, "k": layout.count, "alpha": q["lambda"], "model": join_cost(nr, ns, layout.count, q["lambda"], beta), "work": cost["work"], "largest": cost["largest"]})
    return out


def advise_payload(r: DataFrame, s: DataFrame, method: str, fractions=FRACTIONS, beta: float = 2.0, ratio: float | None = None, seed: int = 1, **opts) -> dict:
    """The row of least model cost, measured on a sample of both sides if a ratio is given."""
    from .plans.sampling import sample_boxes

    if ratio:
        r, s = sample_boxes(r, ratio, seed), sample_boxes(s, ratio, seed)
    rows = sweep(r, s, method, fractions, beta, least=1 if ratio else 10, **opts)
    return min(rows, key=lambda row: row["model"])


def advise_method(layout_seconds: dict[str, float], join_seconds: dict[str, float], queries: int) -> str:
    """The method of least total time for so many joins over one layout."""
    return min(join_seconds, key=lambda m: layout_seconds[m] + queries * join_seconds[m])


def makespan(tile_costs: list[float], workers: int) -> float:
    """Time of the longest worker when the largest tiles are given out first."""
    import heapq

    loads = [0.0] * max(1, workers)
    heapq.heapify(loads)
    for c in sorted(tile_costs, reverse=True):
        heapq.heapreplace(loads, loads[0] + c)
    return max(loads)


__all__ = ["FRACTIONS", "PLANS", "advise_method", "advise_payload", "join_cost", "join_cost_column", "makespan", "realised", "sweep", "uniform_alpha", "uniform_optimum"]
