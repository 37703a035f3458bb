"""Image folders as rasters, and small report sinks."""

from __future__ import annotations

import re

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import workers_can_import

_HEAD = re.compile(rb"P([56])\s+(?:#[^\n]*\n\s*)*(\d+)\s+(\d+)\s+(\d+)\s")


def decode_pnm(data: bytes) -> np.ndarray:
    """Height x width x channels of a binary PGM or PPM image of 8-bit samples."""
    m = _HEAD.match(data)
    if not m or int(m[4]) > 255:
        raise ValueError("not an 8-bit binary PGM or PPM")
    channels = 3 if m[1] == b"6" else 1
    w, h = int(m[2]), int(m[3])
    return np.frombuffer(data, np.uint8, h * w * channels, m.end()).reshape(h, w, channels)


def resized(image: np.ndarray, side: int) -> np.ndarray:
    """The shorter edge scaled to `side` by nearest samples, the longer one cropped around its centre."""
    h, w = image.shape[:2]
    scale = side / min(h, w)
    nh, nw = max(side, round(h * scale)), max(side, round(w * scale))
    out = image[(np.arange(nh) * h // nh)][:, (np.arange(nw) * w // nw)]
    top, left = (nh - side) // 2, (nw - side) // 2
    return out[top : top + side, left : left + side]


def image_folder(spark: SparkSession, path: str, side: int = 224, pattern: str = "*.p[gp]m") -> DataFrame:
    """path, pixels (side x side x channels bytes, row by row) of every image file below a folder."""
    workers_can_import(spark)

    @F.pandas_udf("binary")
    def pixels(content: pd.Series) -> pd.Series:
        return content.map(lambda b: resized(decode_pnm(bytes(b)), side).tobytes())

    files = spark.read.format("binaryFile").option("pathGlobFilter", pattern).option("recursiveFileLookup", "true").load(path)
    return files.select("path", pixels("content").alias("pixels"))


def prompt_file(spark: SparkSession, path: str) -> DataFrame:
    """condition, region, text from CSV with a header."""
    return spark.read.schema("condition string, region int, text string").option("header", "true").csv(path)


def write_report(table: DataFrame, path: str, kind: str = "csv") -> None:
    """A small result table as one CSV or JSON file."""
    one = table.coalesce(1).write.mode("overwrite")
    one.option("header", "true").csv(path) if kind == "csv" else one.json(path)
