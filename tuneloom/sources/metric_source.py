"""A Python data source of metric scrapes: spark.read.format("metric_scrape").

Options: metrics (comma-separated), start (epoch seconds), count, step (seconds), partitions. Values follow a daily wave with a
slope by rule, so a read can be repeated; a real scraper overrides sample().
"""

from __future__ import annotations

import datetime
import math
import zlib

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class Stretch(InputPartition):
    def __init__(self, metric: str, first: int, last: int):
        self.metric, self.first, self.last = metric, first, last


class MetricReader(DataSourceReader):
    def __init__(self, options):
        self.metrics = [m for m in options.get("metrics", "load").split(",") if m]
        self.start, self.count, self.step = int(options.get("start", 1704067200)), int(options.get("count", 60)), int(options.get("step", 1))
        self.parts = int(options.get("partitions", 1))

    def partitions(self):
        edges = [self.count * i // self.parts for i in range(self.parts + 1)]
        return [Stretch(m, a, b) for m in self.metrics for a, b in zip(edges, edges[1:]) if b > a]

    def sample(self, metric: str, second: int) -> float:
        phase = zlib.crc32(metric.encode()) % 86400
        return round(50 + 10 * math.sin(2 * math.pi * (second + phase) / 86400) + (second - self.start) / 86400, 6)

    def read(self, partition):
        for i in range(partition.first, partition.last):
            second = self.start + i * self.step
            yield partition.metric, datetime.datetime.fromtimestamp(second, datetime.timezone.utc), self.sample(partition.metric, second)


class MetricSource(DataSource):
    @classmethod
    def name(cls):
        return "metric_scrape"

    def schema(self):
        return "metric string, ts timestamp, value double"

    def reader(self, schema):
        return MetricReader(self.options)
