"""A generated scan as a Spark data source: ``spark.read.format("skyscan").option("circles", 32)...load()``.

Every circle is one interval, scanned ``rescans`` times at ``samples`` angles; a partition is a piece of at most ``chunk``
samples of one circle, so that partitions are independent and of one size at any scan length."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

SCHEMA = "interval_id long, t long, scan int, angle double, pix long"
DEFAULTS = {"circles": 32, "rescans": 4, "samples": 1024, "radius": 30.0, "rows": 32, "cols": 64, "chunk": 1 << 20}
BATCH = 1 << 16


def pixels(angle: np.ndarray, lon0: float, radius: float, rows: int, cols: int) -> np.ndarray:
    """Equal-area cylindrical cells of points on a circle about an equatorial centre; rounded before the floor."""
    r = math.radians(radius)
    turn = (lon0 + np.arctan2(np.sin(angle) * math.sin(r), math.cos(r))) / (2 * math.pi)
    turn -= np.floor(np.round(turn, 9))
    row = np.floor(np.round((math.sin(r) * np.cos(angle) + 1) / 2 * rows, 9)).astype(np.int64)
    return row * cols + np.floor(np.round(turn * cols, 9)).astype(np.int64) % cols


class Piece(InputPartition):
    def __init__(self, circle: int, lo: int, hi: int):
        self.circle, self.lo, self.hi = circle, lo, hi


class ScanReader(DataSourceReader):
    def __init__(self, options: dict):
        self.o = options

    def partitions(self):
        n = self.o["rescans"] * self.o["samples"]
        return [Piece(c, lo, min(lo + self.o["chunk"], n)) for c in range(self.o["circles"]) for lo in range(0, n, self.o["chunk"])]

    def read(self, piece: Piece):
        o = self.o
        for lo in range(piece.lo, piece.hi, BATCH):
            t = np.arange(lo, min(lo + BATCH, piece.hi))
            angle = t % o["samples"] * (2 * math.pi / o["samples"])
            pix = pixels(angle, piece.circle * (2 * math.pi / o["circles"]), o["radius"], o["rows"], o["cols"])
            yield pa.record_batch([np.full(len(t), piece.circle, np.int64), t, (t // o["samples"]).astype(np.int32), angle, pix], names=["interval_id", "t", "scan", "angle", "pix"])


class SkyScan(DataSource):
    @classmethod
    def name(cls) -> str:
        return "skyscan"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> ScanReader:
        o = {k: type(v)(self.options.get(k, v)) for k, v in DEFAULTS.items()}
        for k in ("circles", "rescans", "samples", "chunk", "rows", "cols"):
            if o[k] < 1:
                raise ValueError(f"{k} is at least 1")
        return ScanReader(o)


def scan(spark: SparkSession, **options) -> DataFrame:
    unknown = set(options) - set(DEFAULTS)
    if unknown:
        raise ValueError(f"options {sorted(unknown)} are unknown; there are {sorted(DEFAULTS)}")
    spark.dataSource.register(SkyScan)
    return spark.read.format("skyscan").options(**options).load()
