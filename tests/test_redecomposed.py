"""The outlier test with a new decomposition before each step, on more than three planted spikes."""

import datetime

import numpy as np
from pyspark.sql import functions as F

from tuneloom.operators import stl
from tuneloom.plans import workloads


def test_all_planted_spikes_are_tested(spark, monkeypatch):
    draw = np.random.default_rng(4)
    y = 10 * np.sin(np.arange(720) * 2 * np.pi / 24) + draw.normal(size=720)
    spikes = [50, 133, 260, 377, 480, 601]
    y[spikes] += [60, -70, 80, 90, -100, 110]
    start = datetime.datetime(2024, 1, 1)
    frame = spark.createDataFrame([("m", start + datetime.timedelta(hours=i), float(v)) for i, v in enumerate(y)], "metric string, ts timestamp, value double")
    monkeypatch.setattr(workloads, "hourly", lambda *a: frame)
    got = workloads.esd_redecomposed(spark, "").select("k", F.unix_timestamp(F.col("ts").cast("timestamp")).alias("s"), "is_anomaly").orderBy("k").collect()
    first = frame.agg(F.unix_timestamp(F.min("ts"))).first()[0]
    found = [(r["s"] - first) // 3600 for r in got if r["is_anomaly"]]
    want, at = [], np.arange(720)
    for _ in range(len(found)):
        left = np.setdiff1d(at, want)
        r = stl.stl(np.interp(at, left, y[left]), 24)[2][left]  # what was removed is bridged
        want.append(int(left[np.argmax(np.abs(r - np.median(r)))]))
    assert len(got) == 14 and found == want and set(spikes) <= set(found)
