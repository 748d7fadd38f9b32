"""Boxes and polygons as well-known text."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

NUMBER = r"(-?\d+(?:\.\d+)?(?:[eE][-+]?\d+)?)"


def diamond_wkt(boxes: DataFrame, name: str = "geom") -> DataFrame:
    """boxes with the diamond inscribed in each as polygon text."""
    cx, cy = (F.col("xmin") + F.col("xmax")) / 2, (F.col("ymin") + F.col("ymax")) / 2
    spots = ((F.col("xmin"), cy), (cx, F.col("ymin")), (F.col("xmax"), cy), (cx, F.col("ymax")), (F.col("xmin"), cy))
    text = F.concat_ws(", ", *(F.format_string("%.1f %.1f", x, y) for x, y in spots))
    return boxes.withColumn(name, F.concat(F.lit("POLYGON (("), text, F.lit("))")))


def geometry_type(name: str = "geom"):
    return F.upper(F.trim(F.regexp_extract(name, r"^\s*([A-Za-z]+)", 1)))


def boxes_of_wkt(rows: DataFrame, name: str = "geom") -> DataFrame:
    """rows with the bounding box of their geometry text; null text gives a null box."""
    numbers = F.transform(F.regexp_extract_all(name, F.lit(NUMBER), F.lit(1)), lambda v: v.cast("double"))
    xs, ys = F.filter(numbers, lambda v, i: i % 2 == 0), F.filter(numbers, lambda v, i: i % 2 == 1)
    return rows.withColumns({"xmin": F.array_min(xs), "ymin": F.array_min(ys), "xmax": F.array_max(xs), "ymax": F.array_max(ys)})


def _ring(text: str) -> np.ndarray:
    inner = text[text.index("((") + 2 : text.index("))")].split("), (")[0]
    return np.array([[float(v) for v in p.split()] for p in inner.split(",")])


def _side(a: np.ndarray, b: np.ndarray, p: np.ndarray) -> np.ndarray:
    return np.sign((b[..., 0] - a[..., 0]) * (p[..., 1] - a[..., 1]) - (b[..., 1] - a[..., 1]) * (p[..., 0] - a[..., 0]))


def _inside(p: np.ndarray, ring: np.ndarray) -> np.ndarray:
    """Whether points (n, 2) lie in the rings (n, k, 2) of the same places."""
    a, b, p = ring[:, :-1], ring[:, 1:], p[:, None]
    cross = (a[..., 1] > p[..., 1]) != (b[..., 1] > p[..., 1])
    with np.errstate(divide="ignore", invalid="ignore"):
        x = a[..., 0] + (p[..., 1] - a[..., 1]) * (b[..., 0] - a[..., 0]) / (b[..., 1] - a[..., 1])
    return (cross & (p[..., 0] < x)).sum(axis=1) % 2 == 1


def pairs_meet(u: np.ndarray, v: np.ndarray) -> np.ndarray:
    """rings_meet() of many pairs: rings (n, p, 2) with rings (n, q, 2)."""
    a, b = u[:, :-1, None], u[:, 1:, None]
    c, d = v[:, None, :-1], v[:, None, 1:]
    s1, s2, s3, s4 = _side(a, b, c), _side(a, b, d), _side(c, d, a), _side(c, d, b)
    spans = (np.maximum(np.minimum(a, b), np.minimum(c, d)) <= np.minimum(np.maximum(a, b), np.maximum(c, d))).all(axis=-1)
    return (spans & (s1 * s2 <= 0) & (s3 * s4 <= 0)).any(axis=(1, 2)) | _inside(u[:, 0], v) | _inside(v[:, 0], u)


def rings_meet(u: np.ndarray, v: np.ndarray) -> bool:
    """Two polygons without holes share a point: an edge pair crosses or touches, or one holds the other."""
    return bool(pairs_meet(u[None], v[None])[0])


#: Pairs of polygons that are tested at once.
AT_ONCE = 1 << 14


def polygons_meet(x: pa.Table, y: pa.Table, i: np.ndarray, j: np.ndarray, name: str = "geom") -> np.ndarray:
    """Of which pairs (row i of x, row j of y) the polygon texts share a point: each text is read once."""
    ok = np.zeros(len(i), bool)
    by_size = []
    for t, at in ((x, i), (y, j)):
        rings, used = {}, np.unique(at)
        size, place = np.zeros(len(t), np.int64), np.zeros(len(t), np.int64)
        texts = t.column(name).take(pa.array(used)).to_pylist()
        for row, text in zip(used.tolist(), texts):
            if text is not None:
                ring = _ring(text)
                same = rings.setdefault(len(ring), [])
                size[row], place[row] = len(ring), len(same)
                same.append(ring)
        by_size.append(({k: np.stack(v) for k, v in rings.items()}, size[at], place[at]))
    (p, p_size, p_at), (q, q_size, q_at) = by_size
    for m in p:
        for n in q:
            some = np.flatnonzero((p_size == m) & (q_size == n))
            for at in range(0, len(some), AT_ONCE):
                k = some[at : at + AT_ONCE]
                ok[k] = pairs_meet(p[m][p_at[k]], q[n][q_at[k]])
    return ok


def polygons_intersect(pairs: DataFrame, left: str = "r_geom", right: str = "s_geom") -> DataFrame:
    """pairs whose two polygon texts share a point: the refinement after a box join."""

    def test(batches):
        for batch in batches:
            x, y = (pa.table({"geom": batch.column(c)}) for c in (left, right))
            every = np.arange(batch.num_rows)
            ok = polygons_meet(x, y, every, every)
            yield batch.filter(pa.array(ok, pa.bool_()))

    return pairs.mapInArrow(test, pairs.schema)
