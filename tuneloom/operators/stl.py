"""Seasonal-trend decomposition: local regression and its simpler relatives."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T


def loess(y, span: int, degree: int = 1, weights=None, at=None) -> np.ndarray:
    """Tricube local regression on the regular grid 0 .. n-1, evaluated at `at` (the grid by default)."""
    y = np.asarray(y, float)
    n = len(y)
    w_out = np.ones(n) if weights is None else np.asarray(weights, float)
    at = np.arange(n, dtype=float) if at is None else np.asarray(at, float)
    q = min(span, n)
    left = np.clip(np.round(at).astype(int) - (q - 1) // 2, 0, n - q)
    if q < n:  # the q nearest: move while the other side is nearer
        for _ in range(2):
            left = np.where((left > 0) & (np.abs(left - 1 - at) < np.abs(left + q - 1 - at)), left - 1, left)
            left = np.where((left + q < n) & (np.abs(left + q - at) < np.abs(left - at)), left + 1, left)
    idx = left[:, None] + np.arange(q)
    dist = np.abs(idx - at[:, None])
    h = np.maximum(dist[:, 0], dist[:, -1])
    if span > n:
        h = h * span / n
    h = np.maximum(h, 1e-12)[:, None]
    w = np.clip(1 - np.minimum(dist / (h * (1 + 1e-9)), 1) ** 3, 0, None) ** 3 * w_out[idx]
    sw = w.sum(axis=1)
    sw = np.where(sw > 0, sw, 1)
    yi = y[idx]
    ym = (w * yi).sum(axis=1) / sw
    if degree == 0:
        return ym
    xm = (w * idx).sum(axis=1) / sw
    dx = idx - xm[:, None]
    sxx = (w * dx * dx).sum(axis=1)
    sxy = (w * dx * (yi - ym[:, None])).sum(axis=1)
    line = ym + (at - xm) * np.where(sxx > 1e-12, sxy / np.where(sxx > 1e-12, sxx, 1), 0)
    if degree == 1:
        return line
    out = np.empty(len(at))
    for i in range(len(at)):
        x = idx[i] - at[i]
        v = np.stack([np.ones(q), x, x * x], axis=1) * np.sqrt(w[i])[:, None]
        out[i] = np.linalg.lstsq(v, yi[i] * np.sqrt(w[i]), rcond=None)[0][0]
    return out


def _odd(x: float) -> int:
    k = int(np.ceil(x))
    return k + 1 - k % 2


def _moving(x: np.ndarray, k: int) -> np.ndarray:
    c = np.concatenate([[0.0], np.cumsum(x)])
    return (c[k:] - c[:-k]) / k


def stl(y, period: int, s_win: int | str = 7, t_win: int | None = None, l_win: int | None = None, inner: int = 2, outer: int = 0):
    """(seasonal, trend, resid) of a regular series of at least two periods."""
    y = np.asarray(y, float)
    n, p = len(y), period
    if n < 2 * p:
        raise ValueError("fewer than two periods")
    if not np.isfinite(y).all():
        raise ValueError("values must be finite")
    width = 10 * n + 1 if s_win == "periodic" else s_win
    t_win = t_win or _odd(1.5 * p / (1 - 1.5 / width))
    l_win = l_win or _odd(p)
    trend, seasonal, robust = np.zeros(n), np.zeros(n), np.ones(n)
    for rest in range(outer, -1, -1):
        for _ in range(inner):
            detrended = y - trend
            cycle = np.empty(n + 2 * p)
            for phase in range(p):
                sub, sw = detrended[phase::p], robust[phase::p]
                m = len(sub)
                if s_win == "periodic":
                    smooth = np.full(m + 2, (sub * sw).sum() / max(sw.sum(), 1e-12))
                else:
                    smooth = loess(sub, width, 1, sw, np.arange(-1, m + 1))
                cycle[phase :: p][: m + 2] = smooth
            low = loess(_moving(_moving(_moving(cycle, p), p), 3), l_win)
            seasonal = cycle[p : p + n] - low
            trend = loess(y - seasonal, t_win, 1, robust)
        if rest:
            r = np.abs(y - seasonal - trend)
            h = 6 * np.median(r)
            robust = np.where(r < h, (1 - (r / h) ** 2) ** 2, 0) if h > 0 else np.ones(n)
    return seasonal, trend, y - seasonal - trend


def decompose_stl(points: DataFrame, keys: list[str], period: int, **how) -> DataFrame:
    """points (keys, ts, value on a regular step) with seasonal, trend, resid. One shuffle on the keys."""
    out = T.StructType(points.schema.fields + [T.StructField(c, T.DoubleType()) for c in ("seasonal", "trend", "resid")])

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("ts", kind="stable")
        s, t, r = stl(pdf["value"].to_numpy(float), period, **how)
        return pdf.assign(seasonal=s, trend=t, resid=r)

    return points.groupBy(*keys).applyInPandas(run, out)


def decompose_classical(points: DataFrame, keys: list[str], period: int, digits: int = 9) -> DataFrame:
    """Centred moving average, phase means, rest; null where the average lacks points. Windows only."""
    by_time = Window.partitionBy(*keys).orderBy("ts")
    half = period // 2
    df = points.withColumn("i", F.row_number().over(by_time) - 1).withColumn("n", F.count(F.lit(1)).over(Window.partitionBy(*keys)))
    whole = F.sum("value").over(by_time.rowsBetween(-half, half))
    if period % 2 == 0:
        whole = whole - (F.lag("value", half).over(by_time) + F.lead("value", half).over(by_time)) / 2
    inside = (F.col("i") >= half) & (F.col("i") < F.col("n") - half)
    df = df.withColumn("trend", F.when(inside, F.round(whole / period, digits)))
    phase = Window.partitionBy(*keys, "phase")
    df = df.withColumn("phase", F.col("i") % period).withColumn("raw", F.avg(F.col("value") - F.col("trend")).over(phase))
    centre = df.select(*keys, "phase", "raw").distinct().groupBy(*keys).agg(F.avg("raw").alias("centre"))
    df = df.join(centre, keys).withColumn("seasonal", F.round(F.col("raw") - F.col("centre"), digits))
    df = df.withColumn("resid", F.round(F.col("value") - F.col("seasonal") - F.col("trend"), 6))
    return df.select(*points.columns, "seasonal", "trend", "resid")


def decompose_median(points: DataFrame, keys: list[str], period: int) -> DataFrame:
    """Seasonal = median of the phase, no trend."""
    i = F.row_number().over(Window.partitionBy(*keys).orderBy("ts")) - 1
    df = points.withColumn("phase", i % period)
    med = df.groupBy(*keys, "phase").agg(F.median("value").alias("seasonal"))
    return df.join(med, [*keys, "phase"]).withColumn("trend", F.lit(0.0)).withColumn("resid", F.col("value") - F.col("seasonal")).select(*points.columns, "seasonal", "trend", "resid")


def decompose_none(points: DataFrame) -> DataFrame:
    return points.withColumn("seasonal", F.lit(0.0)).withColumn("trend", F.lit(0.0)).withColumn("resid", F.col("value"))


def loess_trend(points: DataFrame, keys: list[str], span: int) -> DataFrame:
    """Degree-1 tricube trend over the points at most `span` places off: closed-form weighted sums over one window, on the JVM."""
    by_time = Window.partitionBy(*keys).orderBy("ts")
    a = points.withColumn("i", (F.row_number().over(by_time) - 1).cast("long")).withColumn("near", F.collect_list("value").over(by_time.rowsBetween(-span, span)))
    weigh = lambda d: F.pow(1 - F.pow(F.abs(d) / F.lit(float(span + 1)), F.lit(3.0)), F.lit(3.0))
    x = lambda j: (j - F.least(F.col("i"), F.lit(span))).cast("double")
    terms = F.transform("near", lambda y, j: F.struct(weigh(x(j)).alias("w"), x(j).alias("x"), y.alias("y")))
    total = lambda f: F.aggregate("terms", F.lit(0.0), lambda s, t: s + t["w"] * f(t))
    sums = a.withColumn("terms", terms).select(
        *keys, "ts", "value", total(lambda t: F.lit(1.0)).alias("sw"), total(lambda t: t["x"]).alias("sx"), total(lambda t: t["y"]).alias("sy"), total(lambda t: t["x"] * t["x"]).alias("sxx"), total(lambda t: t["x"] * t["y"]).alias("sxy")
    )
    det = F.col("sw") * F.col("sxx") - F.col("sx") * F.col("sx")
    return sums.select(*keys, "ts", "value", F.round((F.col("sxx") * F.col("sy") - F.col("sx") * F.col("sxy")) / det, 4).alias("trend"))
