"""The experiments: quality, join time, layout time, parallel and sampled layouts, advice.

Each w* function returns rows as dictionaries; run `python -m tilewright.workloads NAME SF_DIR` to print
them. Sweeps take every payload fraction of the reference that gives a tile at least `LEAST` objects (one
at the full size); EXPERIMENTS.md holds the results and what they say of each claim.
"""

from __future__ import annotations

import json
import os
import subprocess
import sys
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import costmodel, measures
from .functions.geometry import BOX
from .operators import route, tilejoin
from .plans import methods, sampling, twolevel
from .plans.layout import payload_of
from .sources import fixtures

FRACTIONS = costmodel.FRACTIONS
#: Objects a tile must get for a fraction to be run.
LEAST = 10
PARALLEL = ("binary", "strip", "least_cut", "sort_tile")
RATIOS = (0.01, 0.05, 0.1, 0.25, 0.5, 1.0)
GUARD = {"binary": {"max_cross": 0.5}}


def timed(action: Callable[[], object]) -> tuple[float, object]:
    began = time.perf_counter()
    out = action()
    return time.perf_counter() - began, out


def time3(plan: Callable[[], DataFrame]) -> float:
    """Mean of three runs into a sink that keeps nothing."""
    return sum(timed(lambda: plan().write.format("noop").mode("overwrite").save())[0] for _ in range(3)) / 3


def _boxes(spark: SparkSession, d: str, name: str) -> DataFrame:
    df = fixtures.FIXTURES[name](spark, d).persist()
    df.count()
    return df


def payloads_of(n: int, fractions=FRACTIONS) -> list[tuple[float, int]]:
    """The fractions of n objects that give a tile at least LEAST of them, with the payloads."""
    return [(f, b) for f in fractions if (b := payload_of(f, n)) >= LEAST]


def _plan(boxes: DataFrame, method: str, b: int):
    return methods.PLANS[method](boxes, b, **GUARD.get(method, {}))


def w1_four_tiles(spark: SparkSession, d: str) -> list[dict]:
    boxes = fixtures.toy_four_tiles(spark)
    layout = methods.plan_fixed_grid(boxes, cells=2)
    return [r.asDict() for r in measures.payloads(route.explode_tiles(boxes, layout), layout).orderBy("tile_id").collect()]


def w2_layouts_of_32(spark: SparkSession, d: str) -> list[dict]:
    boxes = fixtures.toy_32(spark, d).persist()
    return [{"method": m, **{c: t[c] for c in ("tile_id", "xmin", "ymin", "xmax", "ymax")}} for m in methods.PLANS for t in _plan(boxes, m, 4).rows()]


def w3_equal_tiles(spark: SparkSession, d: str, cells: int = 1000) -> list[dict]:
    out = []
    for name in ("skew", "line"):
        boxes = _boxes(spark, d, name)
        q = measures.quality(boxes, methods.plan_fixed_grid(boxes, cells=cells)).first()
        out.append({"dataset": name, "cells": cells, "largest": q["largest"], "mean": q["mean"], "ratio": q["largest_to_mean"]})
    return out


def w4_w5_quality(spark: SparkSession, d: str, names=("skew", "even", "span"), fractions=FRACTIONS) -> list[dict]:
    """sigma and lambda of the six methods over payloads."""
    out = []
    for name in names:
        boxes = _boxes(spark, d, name)
        n = boxes.count()
        for f, b in payloads_of(n, fractions):
            for m in methods.PLANS:
                layout = _plan(boxes, m, b)
                q = measures.quality(boxes, layout, b).first()
                out.append({"dataset": name, "method": m, "fraction": f, "payload": b, "k": q["k"], "sigma": q["sigma"], "lambda": q["lambda"], "largest_to_mean": q["largest_to_mean"]})
    return out


def _sides(spark: SparkSession, d: str, name: str) -> tuple[DataFrame, DataFrame]:
    """The two inputs of a join: the skewed set by kind of event, others by parity of the id."""
    if name == "skew":
        boxes = fixtures.typed_skew_boxes(spark, d)
        looks = F.col("event_type").isin("view", "click")
        return boxes.filter(looks).drop("event_type").persist(), boxes.filter(~looks).drop("event_type").persist()
    return tuple(x.persist() for x in fixtures.halves(_boxes(spark, d, name)))


def w6_join_time(spark: SparkSession, d: str, fractions=FRACTIONS) -> list[dict]:
    """Join time, mean of three runs, layout not included; and the model and the real number of comparisons."""
    out = []
    for name in ("skew", "even"):
        r, s = _sides(spark, d, name)
        nr, ns = r.count(), s.count()
        for f, b in payloads_of(nr + ns, fractions):
            for m in methods.PLANS:
                layout = methods.plan_joint(r, s, m, b, **GUARD.get(m, {}))
                how = {"assign": "one_sided"} if layout.kind == "packing" else {}
                alpha = measures.quality(r.select("id", *BOX).unionByName(s.select("id", *BOX)), layout).first()["lambda"]
                done = costmodel.realised(r, s, layout).first()
                out.append({
                    "dataset": name, "method": m, "fraction": f, "payload": b, "k": layout.count, "lambda": alpha, "seconds": time3(lambda: tilejoin.join(r, s, layout, **how)),
                    "pairs": tilejoin.join(r, s, layout, **how).count(), "model": costmodel.join_cost(nr, ns, layout.count, alpha, 2.0), "work": done["work"], "largest": done["largest"],
                })
    return out


def w7_w8_layout_time(spark: SparkSession, d: str, name: str = "line", fractions=FRACTIONS) -> list[dict]:
    """Derivation of a layout from boxes in memory."""
    boxes = _boxes(spark, d, name)
    n = boxes.count()
    return [{"method": m, "fraction": f, "payload": b, "seconds": timed(lambda: _plan(boxes, m, b).tiles.count())[0]} for f, b in payloads_of(n, fractions) for m in methods.PLANS]


def _two_level_seconds(spark: SparkSession, d: str, method: str, buckets: int) -> tuple[float, list[float]]:
    """Time of a two-level layout from the table to its tiles, reading included, and of the kernel in each bucket."""
    boxes = fixtures.line_boxes(spark, d)
    n = boxes.count()
    payload = payload_of(0.001, n)
    took, layout = timed(lambda: twolevel.two_level(boxes, payload, method, coarse=-(-n // buckets), **GUARD.get(method, {})))
    return took, list(layout.params["bucket_seconds"].values())


def w9_scalability(spark: SparkSession, d: str, cores=(1, 2, 4), workers=(8, 16, 32, 50), buckets: int = 64) -> list[dict]:
    """Two-level layouts in sessions of their own on 1, 2 and 4 cores, I/O included; beyond, the longest worker
    when the buckets' own measured kernel times are given out, the longest first."""
    program = f"""
import json, sys
from pyspark.sql import SparkSession
from tilewright import workloads as w
cores, d, buckets = sys.argv[1], sys.argv[2], int(sys.argv[3])
s = SparkSession.builder.master(f"local[{{cores}}]").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.driver.memory", "4g").config("spark.sql.shuffle.partitions", "64").config("spark.sql.adaptive.coalescePartitions.enabled", "false").getOrCreate()
w._two_level_seconds(s, d, "sort_tile", 8)
print(json.dumps({{m: w._two_level_seconds(s, d, m, buckets) for m in {list(PARALLEL)!r}}}))
"""
    out = []
    for c in cores:
        here = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
        env = os.environ | {"PYTHONPATH": f"{here}:{os.environ.get('PYTHONPATH', '')}"}
        done = subprocess.run([sys.executable, "-c", program, str(c), d, str(buckets)], capture_output=True, text=True, env=env, check=True)
        for m, (took, each) in json.loads(done.stdout.strip().splitlines()[-1]).items():
            row = {"method": m, "cores": c, "seconds": took, "kernel_seconds": sum(each), "longest_bucket": max(each)}
            out.append(row | ({f"kernel_makespan_{k}": costmodel.makespan(each, k) for k in (1, *workers)} if c == cores[0] else {}))
    return out


def w9_single_bucket(spark: SparkSession, d: str) -> list[dict]:
    """The kernels over one bucket of all objects against 64 buckets, one core each."""
    out = []
    for m in PARALLEL:
        one, many = (sum(_two_level_seconds(spark, d, m, k)[1]) for k in (1, 64))
        out.append({"method": m, "one_bucket": one, "sum_of_64_buckets": many, "ratio": one / many})
    return out


def w10_fine_payload(spark: SparkSession, d: str) -> list[dict]:
    boxes = _boxes(spark, d, "line")
    n = boxes.count()
    return [{"payload": b, "seconds": timed(lambda: twolevel.two_level(boxes, b, "strip", coarse=n // 32))[0]} for b in (n // 5000 + 1, n // 1000 + 1, n // 200 + 1)]


def w11_coarse_buckets(spark: SparkSession, d: str) -> list[dict]:
    boxes = _boxes(spark, d, "even")
    n = boxes.count()
    b = payload_of(0.01, n)
    base = methods.plan_strip(boxes, b)
    out = []
    for share in (64, 16, 4, 2):
        s, layout = timed(lambda: twolevel.two_level(boxes, b, "strip", coarse=max(1, n // share)))
        out.append({"coarse": n // share, "seconds": s, **measures.layout_agreement(boxes, base, layout).first().asDict()})
    return out


def w12_sampling(spark: SparkSession, d: str, ratios=RATIOS, fractions=FRACTIONS) -> list[dict]:
    boxes = _boxes(spark, d, "skew")
    n = boxes.count()
    out = []
    for m in ("binary", "strip", "least_cut"):
        for ratio in ratios:
            for f, b in payloads_of(n, fractions):
                q = measures.quality(boxes, sampling.sampled_layout(boxes, b, m, ratio=ratio, **GUARD.get(m, {}))).first()
                out.append({"method": m, "ratio": ratio, "fraction": f, "sigma": q["sigma"], "lambda": q["lambda"], "k": q["k"]})
    return out


def w13_assignment(spark: SparkSession, d: str) -> list[dict]:
    """Replicas against repeated reads: seconds and rows that the joins read."""
    r, s = (x.persist() for x in fixtures.halves(_boxes(spark, d, "skew")))
    layout = methods.plan_joint(r, s, "strip", payload_of(0.01, r.count() + s.count()))
    per = measures.products(r, s, layout).agg(F.sum("r_n").alias("r"), F.sum("s_n").alias("s")).first()
    homes = [route.with_home(x, layout).groupBy("home_tile").agg(F.count(F.lit(1)).alias("n")) for x in (r, s)]
    reach = [route.explode_tiles(route.with_home(x, layout), layout).select("home_tile", "tile_id").distinct() for x in (r, s)]
    # Each tile with every tile that its objects, or the other side's, reach.
    met = reach[0].select("home_tile", F.col("tile_id").alias("t")).join(reach[1].select(F.col("home_tile").alias("other"), F.col("tile_id").alias("t")), "t").select("home_tile", "other").distinct()
    again = met.join(homes[0].withColumnRenamed("n", "rn"), "home_tile").join(homes[1].select(F.col("home_tile").alias("other"), F.col("n").alias("sn")), "other").agg(F.sum(F.col("rn") + F.col("sn"))).first()[0]
    rows = {"multi": per["r"] + per["s"], "single": again, "one_sided": r.count() + per["s"]}
    return [{"assign": a, "rows_read": rows[a], "seconds": time3(lambda: tilejoin.join(r, s, layout, assign=a))} for a in rows]


def rank_correlation(a: list[float], b: list[float]) -> float:
    def ranks(v):
        order = sorted(range(len(v)), key=lambda i: v[i])
        return {i: k for k, i in enumerate(order)}

    ra, rb, n = ranks(a), ranks(b), len(a)
    return 1 - 6 * sum((ra[i] - rb[i]) ** 2 for i in range(n)) / (n * (n * n - 1)) if n > 1 else 1.0


def w14_cost_model(spark: SparkSession, d: str, rows: list[dict] | None = None) -> list[dict]:
    """Model, real work and measured seconds of w6's joins, and how their ranks agree."""
    rows = rows or w6_join_time(spark, d)
    out = []
    for name in sorted({x["dataset"] for x in rows}):
        mine = [x for x in rows if x["dataset"] == name]
        pairs = {f"{a}_{b}": rank_correlation([x[a] for x in mine], [x[b] for x in mine]) for a, b in (("model", "work"), ("model", "seconds"), ("work", "seconds"), ("largest", "seconds"))}
        out.append({"dataset": name, "joins": len(mine), **pairs})
    return out


def w15_advice(spark: SparkSession, d: str, rows: list[dict] | None = None) -> list[dict]:
    """The best method per dataset and fraction: least sigma, least lambda, least join time."""
    quality = w4_w5_quality(spark, d, ("skew", "even"))
    times = {(x["dataset"], x["fraction"], x["method"]): x["seconds"] for x in rows or w6_join_time(spark, d)}
    out = []
    for name, f in sorted({(x["dataset"], x["fraction"]) for x in quality}):
        mine = [x | {"seconds": times.get((name, f, x["method"]), float("inf"))} for x in quality if (x["dataset"], x["fraction"]) == (name, f)]
        out += [{"dataset": name, "fraction": f, "criterion": c, "method": min(mine, key=lambda x: x[c])["method"]} for c in ("sigma", "lambda", "seconds")]
    return out


def w16_chooser(spark: SparkSession, d: str) -> list[dict]:
    layout = {x["method"]: x["seconds"] for x in w7_w8_layout_time(spark, d, "skew", (0.01,))}
    join = {x["method"]: x["seconds"] for x in w6_join_time(spark, d, (0.01,)) if x["dataset"] == "skew"}
    return [{"queries": q, "method": costmodel.advise_method(layout, join, q)} for q in (1, 10, 100)]


WORKLOADS = {f.__name__: f for f in (
    w1_four_tiles, w2_layouts_of_32, w3_equal_tiles, w4_w5_quality, w6_join_time, w7_w8_layout_time, w9_scalability, w9_single_bucket, w10_fine_payload,
    w11_coarse_buckets, w12_sampling, w13_assignment, w14_cost_model, w15_advice, w16_chooser,
)}


def main() -> None:
    name, d = sys.argv[1], sys.argv[2]
    spark = SparkSession.builder.getOrCreate()
    for row in WORKLOADS[name](spark, d):
        print(json.dumps(row))


if __name__ == "__main__":
    main()
