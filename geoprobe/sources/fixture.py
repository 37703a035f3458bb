"""A data source that makes capture rows: `spark.read.format("captures").option("rows", n).load()`."""

from __future__ import annotations

import hashlib
import math

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from .tables import REGIONS

SCHEMA = "image_id long, region int, area double, site string, heading int, lat double, lon double, eligible boolean"


def _unit(text: str) -> float:
    return int(hashlib.md5(text.encode()).hexdigest()[:8], 16) / 2**32


def capture(i: int, users: int = 100, days: int = 30) -> tuple:
    """The i-th capture, by the recipe of the captures made from `events`, with user and day drawn by hashes."""
    user, day = int(_unit(f"user|{i}") * users), int(_unit(f"day|{i}") * days)
    region, area, _ = REGIONS[user % len(REGIONS)]
    site = f"{user}|2024-01-{day + 1:02d}"
    south, west = 34.0 + 0.05 * (region // 4), -118.4 + 0.08 * (region % 4)
    lat = south + _unit(f"lat|{site}") * math.sqrt(area) / 111.195
    lon = west + _unit(f"lon|{site}") * math.sqrt(area) / (111.195 * math.cos(math.radians(south)))
    return i, region, area, site, i % 4 * 90, lat, lon, True


class _Reader(DataSourceReader):
    def __init__(self, rows: int, parts: int):
        self.rows, self.parts = rows, max(1, parts)

    def partitions(self):
        edges = [self.rows * k // self.parts for k in range(self.parts + 1)]
        return [InputPartition((a, b)) for a, b in zip(edges, edges[1:], strict=False)]

    def read(self, partition):
        for i in range(*partition.value):
            yield capture(i)


class Captures(DataSource):
    @classmethod
    def name(cls):
        return "captures"

    def schema(self):
        return SCHEMA

    def reader(self, schema):
        return _Reader(int(self.options.get("rows", 1000)), int(self.options.get("partitions", 4)))
