"""Learning time laws from measurements: (query_id, kind, nodes, units, n_batches, repeat, seconds)."""

from __future__ import annotations

import time
from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

MEASURED = "query_id string, kind string, nodes int, units double, n_batches int, repeat int, seconds double"
MODEL = "query_id string, b0 double, bn double, bnp double, bp double"
TERMS = {"full": ("one", "n", "n/p", "1/p"), "share": ("one", "n", "n/p")}


def per_nodes(meas: DataFrame) -> DataFrame:
    """A line through seconds over units for each query and number of nodes."""
    return meas.groupBy("query_id", "nodes").agg(F.regr_slope("seconds", "units").alias("slope"), F.regr_intercept("seconds", "units").alias("intercept"), F.regr_r2("seconds", "units").alias("r2"))


def _terms(form: str) -> list[Column]:
    n, p = F.col("units"), F.col("nodes")
    every = {"one": F.lit(1.0), "n": n, "n/p": n / p, "1/p": 1 / p}
    return [every[t].cast("double") for t in TERMS[form]]


def fit_batch_time(meas: DataFrame, form: str = "share") -> DataFrame:
    """Coefficients by least squares. One pass gathers sums of products, a row for each query; the normal equations of
    three or four terms are solved from those rows. form: full has all four terms, share leaves out 1/p."""
    terms = _terms(form)
    k = len(terms)
    products = [F.sum(terms[i] * terms[j]).alias(f"m{i}_{j}") for i in range(k) for j in range(i, k)]
    rights = [F.sum(terms[i] * F.col("seconds")).alias(f"r{i}") for i in range(k)]
    sums = meas.groupBy("query_id").agg(*products, *rights)

    def solve(frames):
        for frame in frames:
            out = []
            for row in frame.itertuples(index=False):
                r = row._asdict()
                m = np.array([[r[f"m{min(i, j)}_{max(i, j)}"] for j in range(k)] for i in range(k)])
                scale = np.sqrt(np.diag(m)) + 1e-300
                x = np.linalg.lstsq(m / np.outer(scale, scale), np.array([r[f"r{i}"] for i in range(k)]) / scale, rcond=1e-13)[0] / scale
                out.append((r["query_id"], *(list(x) + [0.0] * (4 - k))))
            yield pd.DataFrame(out, columns=["query_id", "b0", "bn", "bnp", "bp"])

    return sums.mapInPandas(solve, MODEL)


def fit_piecewise(meas: DataFrame, x: str, breaks: list[float], by: tuple[str, ...] = ("query_id",)) -> DataFrame:
    """A line for each segment between breaks, which belong to both of their segments: seg, lo, hi, slope, intercept."""
    edges = [float("-inf"), *breaks, float("inf")]
    seg = F.array(*(F.when(F.col(x).between(lo, hi), F.lit(i)) for i, (lo, hi) in enumerate(zip(edges, edges[1:], strict=False))))
    cut = meas.withColumn("seg", F.explode(F.filter(seg, lambda s: s.isNotNull())))
    fitted = cut.groupBy(*by, "seg").agg(F.regr_slope("seconds", x).alias("slope"), F.regr_intercept("seconds", x).alias("intercept"))
    pick = lambda values: F.element_at(F.array(*(F.lit(v) for v in values)), F.col("seg") + 1)
    return fitted.select(*by, "seg", pick(edges[:-1]).alias("lo"), pick(edges[1:]).alias("hi"), "slope", "intercept")


def fit_merge_time(meas: DataFrame, knots: list[float]) -> DataFrame:
    """The final merge over the number of batches, for each number of nodes."""
    return fit_piecewise(meas.filter("kind = 'merge'").withColumn("states", F.col("n_batches").cast("double")), "states", knots, ("query_id", "nodes"))


def segment_lookup(asked: DataFrame, segments: DataFrame, x: str) -> DataFrame:
    """Seconds at x by the segment that holds it (lo < x <= hi)."""
    hit = (asked["query_id"] == segments["query_id"]) & (asked[x] > segments["lo"]) & (asked[x] <= segments["hi"])
    return asked.join(segments, hit).select(asked["query_id"], x, "seg", (F.col("intercept") + F.col("slope") * F.col(x)).alias("seconds"))


def interpolate_nodes(lines: DataFrame, lo: int, hi: int, target: int) -> DataFrame:
    """The line of a size between two measured ones, by their lines' values over 1 / nodes."""
    a, b = lines.filter(F.col("nodes") == lo).alias("a"), lines.filter(F.col("nodes") == hi).alias("b")
    t = (1 / target - 1 / hi) / (1 / lo - 1 / hi)
    mix = lambda c: F.col(f"b.{c}") + (F.col(f"a.{c}") - F.col(f"b.{c}")) * F.lit(t)
    return a.join(b, F.col("a.query_id") == F.col("b.query_id")).select(F.col("a.query_id").alias("query_id"), F.lit(target).alias("nodes"), mix("slope").alias("slope"), mix("intercept").alias("intercept"))


def extrapolate_nodes(lines: DataFrame, units: float, targets: list[int]) -> DataFrame:
    """Seconds on sizes beyond the measured ones: values at the wanted units, then a constant plus a part over nodes."""
    at = lines.withColumn("seconds", F.col("intercept") + F.col("slope") * F.lit(float(units))).withColumn("inverse", 1 / F.col("nodes"))
    curve = at.groupBy("query_id").agg(F.regr_intercept("seconds", "inverse").alias("c0"), F.regr_slope("seconds", "inverse").alias("c1"))
    return curve.select("query_id", F.explode(F.array(*map(F.lit, targets))).alias("nodes"), "c0", "c1").select("query_id", "nodes", F.lit(float(units)).alias("units"), (F.col("c0") + F.col("c1") / F.col("nodes")).alias("seconds"))


def transfer_by_ratio(meas: DataFrame, base_query: str, ref_nodes: int) -> DataFrame:
    """Seconds of all queries on all sizes, from the base query on all and the others on one."""
    base = meas.filter(F.col("query_id") == base_query).select("nodes", "units", F.col("seconds").alias("base_s"))
    here = meas.filter(F.col("nodes") == ref_nodes).join(base.filter(F.col("nodes") == ref_nodes).drop("nodes"), "units")
    ratio = here.groupBy("query_id").agg(F.avg(F.col("seconds") / F.col("base_s")).alias("ratio"))
    return ratio.crossJoin(base).select("query_id", "nodes", "units", (F.col("ratio") * F.col("base_s")).alias("seconds"))


def model_error(meas: DataFrame, model: DataFrame) -> DataFrame:
    """Relative errors of a model by query and nodes, and whether all are within a quarter."""
    t = F.col("b0") + F.col("bn") * F.col("units") + (F.col("bnp") * F.col("units") + F.col("bp")) / F.col("nodes")
    off = F.abs(t - F.col("seconds")) / F.col("seconds")
    return meas.join(model, "query_id").groupBy("query_id", "nodes").agg(F.avg(off).alias("mape"), F.max(off).alias("max_ape"), (F.max(off) <= 0.25).alias("within_25"))


def calibrate(spark: SparkSession, query_id: str, job: Callable[[float], DataFrame], sizes: list[float], nodes: int, repeats: int = 2) -> DataFrame:
    """Times a query on slices of several sizes; rows of MEASURED. job: units to a frame."""
    rows = []
    for units in sizes:
        for r in range(repeats):
            began = time.perf_counter()
            job(units).write.format("noop").mode("overwrite").save()
            rows.append((query_id, "batch", nodes, float(units), 1, r, time.perf_counter() - began))
    return spark.createDataFrame(rows, MEASURED)
