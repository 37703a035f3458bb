"""Scalar expressions that stay inside generated code, with the SQL text of their twins."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

EARTH_KM = 6371.0088


def hash01(text: Column) -> Column:
    """A number in [0, 1) from the first 32 bits of the MD5 of a string: the same at any partitioning and in any engine."""
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long") / F.lit(4294967296.0)


def seeded(seed: int, purpose: str, key: Column) -> Column:
    """hash01 of `seed|purpose|key`."""
    return hash01(F.concat(F.lit(f"{seed}|{purpose}|"), key.cast("string")))


def hash01_sql(text: str) -> str:
    return f"(('0x' || substr(md5({text}), 1, 8))::BIGINT / 4294967296.0::DOUBLE)"


def haversine_km(lat1: Column, lon1: Column, lat2: Column, lon2: Column) -> Column:
    a = F.pow(F.sin(F.radians(lat2 - lat1) / 2), 2) + F.cos(F.radians(lat1)) * F.cos(F.radians(lat2)) * F.pow(F.sin(F.radians(lon2 - lon1) / 2), 2)
    return 2 * EARTH_KM * F.asin(F.sqrt(F.least(F.lit(1.0), a)))


def haversine_sql(lat1: str, lon1: str, lat2: str, lon2: str) -> str:
    return (
        f"(2 * {EARTH_KM}::DOUBLE * asin(sqrt(least(1.0::DOUBLE, pow(sin(radians({lat2} - {lat1}) / 2), 2) + cos(radians({lat1})) * cos(radians({lat2})) * pow(sin(radians({lon2} - {lon1}) / 2), 2)))))"
    )


def rounded(x: Column, digits: int = 6) -> Column:
    """Half-up at a fixed number of digits by floor, which engines agree on where their round() differs."""
    scale = float(10**digits)
    return F.floor(x * scale + 0.5) / scale


def rounded_sql(x: str, digits: int = 6) -> str:
    return f"(floor(({x}) * {10**digits}::DOUBLE + 0.5) / {10**digits}::DOUBLE)"


#: SQL functions that the planner sees through, for use in queries written as text.
SQL_FUNCTIONS = (
    "CREATE OR REPLACE TEMPORARY FUNCTION hash01(s STRING) RETURNS DOUBLE RETURN CAST(conv(substr(md5(s), 1, 8), 16, 10) AS BIGINT) / 4294967296.0D",
    f"CREATE OR REPLACE TEMPORARY FUNCTION haversine_km(a DOUBLE, b DOUBLE, c DOUBLE, d DOUBLE) RETURNS DOUBLE RETURN 2 * {EARTH_KM}D * asin(sqrt(least(1.0D, pow(sin(radians(c - a) / 2), 2) + cos(radians(a)) * cos(radians(c)) * pow(sin(radians(d - b) / 2), 2))))",
)


def register_sql(spark) -> None:
    for text in SQL_FUNCTIONS:
        spark.sql(text)
