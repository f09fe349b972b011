"""Iterated robust outlier test on residuals.

Each step scores the point farthest from the median in units of the median absolute deviation, compares the score with a
critical value that depends on how many points are gone, and removes the point. Sorted once, the farthest point is always at
one of the two ends, the median moves by index, and the deviation is a selection from two rising runs, so a series costs
one sort and a logarithm for each step.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.stats import esd_critical

SCHEMA = "k int, ts timestamp, value double, resid double, score double, lambda double, direction string, is_anomaly boolean"


def default_bound(n: int) -> int:
    return max(1, int(0.02 * n))


def _kth(s: np.ndarray, lo: int, hi: int, m: float, k: int) -> float:
    """The k-th smallest (from 0) of |s[i] - m| for lo <= i < hi, s sorted."""
    mid = lo + int(np.searchsorted(s[lo:hi], m))
    left, right = mid - lo, hi - mid  # runs m - s[mid-1], ... and s[mid] - m, ..., both rising
    a, b = max(0, k + 1 - right), min(k + 1, left)
    while a < b:
        i = (a + b) // 2
        if m - s[mid - 1 - i] < s[mid + k - i] - m:
            a = i + 1
        else:
            b = i
    best = -math.inf
    if a:
        best = m - s[mid - a]
    if k + 1 - a:
        best = max(best, s[mid + k - a] - m)
    return float(best)


def _median_deviation(s, lo, hi, m):
    n = hi - lo
    if n % 2:
        return _kth(s, lo, hi, m, n // 2)
    return (_kth(s, lo, hi, m, n // 2 - 1) + _kth(s, lo, hi, m, n // 2)) / 2


def esd_steps(resid, bound: int | None = None, alpha: float = 0.05, stop: str = "first", direction: str = "both", center: str = "median", spread: str = "mad", scale: float = 1.0, zero: str = "skip"):
    """[(position, score, critical value, is_anomaly)] in order of removal; one entry for each test made."""
    x = np.asarray(resid, float)
    n = len(x)
    bound = default_bound(n) if bound is None else bound
    order = np.lexsort((np.arange(n), x))
    s = x[order]
    lo, hi, total, squares = 0, n, float(s.sum()), float((s * s).sum())
    steps = []
    for k in range(1, bound + 1):
        m = hi - lo
        if m < 1 or n - k - 1 < 1:
            break
        mid = float(s[lo + m // 2] if m % 2 else (s[lo + m // 2 - 1] + s[lo + m // 2]) / 2) if center == "median" else total / m
        if spread == "mad":
            unit = _median_deviation(s, lo, hi, mid) * scale
        elif spread == "mean_ad":
            unit = float(np.abs(s[lo:hi] - mid).mean()) * scale
        else:
            unit = math.sqrt(max(0.0, (squares - total * total / m) / max(1, m - 1)))
        low, high = mid - s[lo], s[hi - 1] - mid
        take_low = direction == "low" or (direction == "both" and low >= high)
        gap = low if take_low else high
        if unit <= 0:
            if zero == "skip":
                break
            score = math.inf if gap > 0 else 0.0
        else:
            score = max(gap, 0.0) / unit
        # of equal values the earliest goes first
        v = s[lo] if take_low else s[hi - 1]
        at = lo if take_low else int(np.searchsorted(s[lo:hi], v)) + lo
        limit = esd_critical(n, k, alpha, "both" if direction == "both" else "one")
        steps.append((int(order[at]), float(score), limit, score > limit))
        if not take_low and at != hi - 1:
            order[at : hi - 1] = order[at + 1 : hi].copy()
        lo, hi = (lo + 1, hi) if take_low else (lo, hi - 1)
        total, squares = total - v, squares - v * v
    if stop == "first":
        cut = next((i for i, t in enumerate(steps) if not t[3]), len(steps))
    else:
        cut = max((i + 1 for i, t in enumerate(steps) if t[3]), default=0)
    return [(p, c, lam, i < cut) for i, (p, c, lam, _) in enumerate(steps)]


def esd_naive(resid, bound=None, alpha=0.05, stop="first", direction="both", center="median", spread="mad", scale=1.0, zero="skip"):
    """The same, recomputed from scratch at every step; the yardstick of the tests."""
    x = [float(v) for v in resid]
    n, left, steps = len(x), list(range(len(x))), []
    for k in range(1, (default_bound(n) if bound is None else bound) + 1):
        if not left or n - k - 1 < 1:
            break
        v = np.array([x[i] for i in left])
        mid = float(np.median(v)) if center == "median" else float(v.mean())
        unit = {"mad": lambda: float(np.median(np.abs(v - mid))) * scale, "mean_ad": lambda: float(np.abs(v - mid).mean()) * scale, "std": lambda: float(v.std(ddof=1)) if len(v) > 1 else 0.0}[spread]()
        gap = {"both": np.abs(v - mid), "high": v - mid, "low": mid - v}[direction]
        top = gap.max()
        if unit <= 0:
            if zero == "skip":
                break
            score = math.inf if top > 0 else 0.0
        else:
            score = max(float(top), 0.0) / unit
        tied = [i for i, g in zip(left, gap) if g == top]
        pick = min(tied, key=lambda i: (x[i], i))
        limit = esd_critical(n, k, alpha, "both" if direction == "both" else "one")
        steps.append((pick, score, limit, score > limit))
        left.remove(pick)
    cut = next((i for i, t in enumerate(steps) if not t[3]), len(steps)) if stop == "first" else max((i + 1 for i, t in enumerate(steps) if t[3]), default=0)
    return [(p, c, lam, i < cut) for i, (p, c, lam, _) in enumerate(steps)]


def _first_steps(x: np.ndarray, series: np.ndarray, alpha: float = 0.05, direction: str = "both", scale: float = 1.0, zero: str = "skip"):
    """(series, position, score, critical value) of the first test of many short series at once, as esd_steps gives it.

    x: values, series: their rising numbers from 0. Series without a test are left out."""
    sizes = np.bincount(series)
    start = np.cumsum(sizes) - sizes

    def middle(v):
        return np.where(sizes % 2, v[start + sizes // 2], (v[start + np.maximum(sizes // 2 - 1, 0)] + v[start + sizes // 2]) / 2)

    at = np.arange(len(x))
    order = np.lexsort((at, x, series))
    s = x[order]
    mid = middle(s)
    off = np.abs(s - mid[series])
    unit = middle(off[np.lexsort((off, series))]) * scale
    end = start + sizes - 1
    low, high = mid - s[start], s[end] - mid
    take_low = np.full(len(sizes), direction == "low") if direction != "both" else low >= high
    gap = np.where(take_low, low, high)
    top = np.minimum.reduceat(np.where(s == s[end][series], at, len(x)), start)  # of equal values the earliest goes first
    with np.errstate(divide="ignore", invalid="ignore"):
        score = np.where(unit > 0, np.maximum(gap, 0.0) / unit, np.where(gap > 0, np.inf, 0.0))
    tested = np.flatnonzero((sizes > 2) & ((unit > 0) | (zero != "skip")))
    tail = "both" if direction == "both" else "one"
    kinds, which = np.unique(sizes[tested], return_inverse=True)
    limit = np.array([esd_critical(int(n), 1, alpha, tail) for n in kinds], float)[which]
    return tested, order[np.where(take_low, start, top)][tested], score[tested], limit


def _tests(x: np.ndarray, series: np.ndarray, how: dict):
    """(position, k, score, critical value, is_anomaly) of every test of every series, in order of the series.

    Series with one test are done together, the others one by one."""
    sizes = np.bincount(series)
    start = np.cumsum(sizes) - sizes
    few = {"alpha", "direction", "scale", "zero"}
    short = np.zeros(len(sizes), bool)
    if how.get("center", "median") == "median" and how.get("spread", "mad") == "mad":
        bound = how.get("bound")
        short = np.maximum(1, (0.02 * sizes).astype(np.int64)) == 1 if bound is None else np.full(len(sizes), bound == 1)
    found = []
    if short.any():
        own = short[series]
        at = np.flatnonzero(own)
        names = np.flatnonzero(short)
        which, place, score, limit = _first_steps(x[own], np.searchsorted(names, series[own]), **{k: v for k, v in how.items() if k in few})
        found.append((names[which], at[place], np.ones(len(which), np.int32), score, limit, score > limit))
    for i in np.flatnonzero(~short):
        steps = esd_steps(x[start[i] : start[i] + sizes[i]], **how)
        if steps:
            p, c, lam, a = zip(*steps)
            found.append((np.full(len(p), i), start[i] + np.array(p), np.arange(1, len(p) + 1, dtype=np.int32), np.array(c, float), np.array(lam, float), np.array(a, bool)))
    if not found:
        return (np.zeros(0, np.int64), np.zeros(0, np.int32), np.zeros(0), np.zeros(0), np.zeros(0, bool))
    parts = [np.concatenate(p) for p in zip(*found)]
    order = np.lexsort((parts[2], parts[0]))
    return tuple(p[order] for p in parts[1:])


def _direction(x: np.ndarray, series: np.ndarray, at: np.ndarray) -> np.ndarray:
    """high or low: on which side of its series' median a value lies."""
    sizes = np.bincount(series)
    start = np.cumsum(sizes) - sizes
    s = x[np.lexsort((x, series))]
    mid = np.where(sizes % 2, s[start + sizes // 2], (s[start + np.maximum(sizes // 2 - 1, 0)] + s[start + sizes // 2]) / 2)
    return np.where(x[at] >= mid[series[at]], "high", "low")


def detect(points: DataFrame, keys: list[str], resid: str = "resid", max_points: int = 5_000_000, redecompose=None, **how) -> DataFrame:
    """One row for each test: keys + SCHEMA. points: keys, ts, value, resid (null: not testable).

    One shuffle on the keys; a task reads its series in order, a batch of whole series at a time, so that many short series
    cost little more than their points. A series over max_points is refused.
    redecompose(values) -> residuals, if given, is applied anew before each test, over the values left.
    """
    types = {f.name: f for f in points.schema.fields}
    out = T.StructType([types[k] for k in keys] + T._parse_datatype_string(SCHEMA).fields)

    if redecompose:

        def run(pdf: pd.DataFrame) -> pd.DataFrame:
            if len(pdf) > max_points:
                raise ValueError(f"series of {len(pdf)} points; cut it by time first")
            pdf = pdf.sort_values("ts", kind="stable").reset_index(drop=True)
            live = pdf[pdf[resid].notna()].reset_index(drop=True)
            steps = _with_redecomposition(live["value"].to_numpy(float), redecompose, **how)
            r = live[resid].to_numpy(float)
            mid = float(np.median(r)) if len(r) else 0.0
            rows = [
                {**{k: pdf[k].iloc[0] for k in keys}, "k": i + 1, "ts": live["ts"].iloc[p], "value": live["value"].iloc[p], "resid": r[p], "score": c, "lambda": lam, "direction": "high" if r[p] >= mid else "low", "is_anomaly": bool(a)}
                for i, (p, c, lam, a) in enumerate(steps)
            ]
            return pd.DataFrame(rows, columns=[f.name for f in out.fields])

        return points.groupBy(*keys).applyInPandas(run, out)

    columns = [f.name for f in out.fields]

    def whole(held: list[pa.RecordBatch]):
        """The tests of whole series."""
        table = pa.Table.from_batches(held).combine_chunks()
        fresh, r = table.column("_new").to_numpy(), table.column("_resid").to_numpy()
        series = np.cumsum(fresh) - 1
        if len(series) and np.bincount(series).max() > max_points:
            raise ValueError(f"series of {np.bincount(series).max()} points; cut it by time first")
        live = np.flatnonzero(~np.isnan(r))
        if not len(live):
            return
        names, series = np.unique(series[live], return_inverse=True)
        at, k, score, limit, odd = _tests(r[live], series, how)
        if not len(at):
            return
        told = table.take(pa.array(live[at]))
        made = {"k": pa.array(k, pa.int32()), "ts": told.column("_ts"), "value": told.column("_value"), "resid": pa.array(r[live[at]]), "score": pa.array(score), "lambda": pa.array(limit), "direction": pa.array(_direction(r[live], series, at).tolist(), pa.string()), "is_anomaly": pa.array(odd)}
        yield from pa.table([made[c] if c in made else told.column(c) for c in columns], columns).to_batches()

    def run_all(batches):
        held, size = [], 0
        for batch in batches:
            starts = np.flatnonzero(batch.column(batch.schema.get_field_index("_new")).to_numpy())
            if len(starts) and (held or starts[-1]):
                cut = int(starts[-1])  # the last series may go on in the next batch
                yield from whole([*held, batch.slice(0, cut)])
                held, size, batch = [], 0, batch.slice(cut)
            size += batch.num_rows
            if size > max_points:
                raise ValueError(f"series of over {max_points} points; cut it by time first")
            held.append(batch)
        if held:
            yield from whole(held)

    # a row that differs from the one before in any key begins a series
    rows = points.select(*keys, F.col("ts").cast("timestamp").alias("_ts"), F.col("value").cast("double").alias("_value"), F.coalesce(F.col(resid).cast("double"), F.lit(float("nan"))).alias("_resid"))
    before = Window.partitionBy(*keys).orderBy(F.col("_ts").asc_nulls_last())
    rows = rows.withColumn("_new", (F.row_number().over(before) == 1).cast("int"))
    return rows.mapInArrow(run_all, out)


def _with_redecomposition(values, decompose, bound=None, alpha=0.05, stop="first", **how):
    """Decompose the values left, test one point, remove it, and so on; a removed value is bridged linearly."""
    values, n = np.array(values, float), len(values)
    gone, steps = [], []
    for k in range(1, (default_bound(n) if bound is None else bound) + 1):
        live = np.setdiff1d(np.arange(n), gone)
        bridged = np.interp(np.arange(n), live, values[live])
        r = np.asarray(decompose(bridged), float)[live]
        found = esd_steps(r, bound=1, alpha=alpha, **how)
        if not found:
            break
        p, c, _, _ = found[0]
        limit = esd_critical(n, k, alpha)
        steps.append((int(live[p]), c, limit, c > limit))
        gone.append(int(live[p]))
    cut = next((i for i, t in enumerate(steps) if not t[3]), len(steps)) if stop == "first" else max((i + 1 for i, t in enumerate(steps) if t[3]), default=0)
    return [(p, c, lam, i < cut) for i, (p, c, lam, _) in enumerate(steps)]


def one_shot_score(points: DataFrame, keys: list[str], resid: str = "resid", scale: float = 1.0) -> DataFrame:
    """points with score = |resid - median| / (scale * MAD); null where the deviation is zero. Two aggregations, no Python."""
    mid = points.groupBy(*keys).agg(F.median(resid).alias("mid"))
    near = points.join(mid, keys).withColumn("off", F.abs(F.col(resid) - F.col("mid")))
    spread = near.groupBy(*keys).agg(F.median("off").alias("mad"))
    return near.join(spread, keys).withColumn("score", F.when(F.col("mad") > 0, F.col("off") / (F.col("mad") * scale))).drop("mid", "off", "mad")
