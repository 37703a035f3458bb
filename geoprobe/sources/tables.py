"""The given tables with explicit schemas, and the captures that stand in for georeferenced views."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.scalars import hash01, hash01_sql

#: Region number, area in km2, name (the areas of the published sampling table, in the order of its split).
REGIONS = ((0, 5.13, "downtown"), (1, 7.69, "pasadena"), (2, 8.98, "beverly hills"), (3, 6.42, "santa monica"), (4, 6.16, "hollywood"), (5, 6.18, "long beach"), (6, 3.08, "venice beach"), (7, 3.08, "koreatown"))
SCHEMAS = {
    "events": "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string",
    "documents": "doc_id long, text string, lang string, source string, n_chars long",
    "labels": "doc_id long, quality int, toxic int",
    "embeddings": "vec_id long, embedding array<float>, label int",
    "pages": "page_id long, url string, html string",
    "benchmark": "item_id long, text string",
}


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables; columns that a query doesn't use are pruned from the scan."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def assert_schema(df: DataFrame, name: str) -> DataFrame:
    """Fail unless `df` has the columns of a known table with types of the same family."""
    kinds = lambda text: {part.split()[0]: part.split(" ", 1)[1] for part in text.split(", ")}
    family = {"int": "integral", "bigint": "integral", "long": "integral", "smallint": "integral"}
    here, wanted = dict(df.dtypes), kinds(SCHEMAS[name])
    wrong = [c for c, t in wanted.items() if c not in here or family.get(here[c], here[c]) != family.get(t, t)]
    if wrong:
        raise TypeError(f"{name}: columns {wrong} are missing or of another type")
    return df


def region_dim(spark: SparkSession) -> DataFrame:
    """Eight regions: a fixed dimension of eight rows, small enough to broadcast anywhere."""
    return spark.createDataFrame(list(REGIONS), "region int, area double, name string")


def captures(spark: SparkSession, sf_dir: str, eligible: str = "true") -> DataFrame:
    """One view per event: region, site (user and day), heading, and a position from hashes of the site."""
    events = load(spark, sf_dir, "events").select("event_id", "user_id", "ts", "event_type")
    region = F.pmod(F.col("user_id"), F.lit(8)).cast("int")
    seen = events.select(
        F.col("event_id").alias("image_id"), region.alias("region"), F.concat_ws("|", F.col("user_id").cast("string"), F.date_format("ts", "yyyy-MM-dd")).alias("site"),
        (F.pmod(F.col("event_id"), F.lit(4)) * 90).cast("int").alias("heading"), F.expr(eligible).alias("eligible"), "ts",
    )
    u, w = hash01(F.concat(F.lit("lat|"), "site")), hash01(F.concat(F.lit("lon|"), "site"))
    south = F.lit(34.0) + F.lit(0.05) * F.floor(F.col("region") / 4)
    west = F.lit(-118.4) + F.lit(0.08) * F.pmod(F.col("region"), F.lit(4))
    side = F.sqrt("area")
    placed = seen.join(F.broadcast(region_dim(spark)), "region").withColumns({"lat": south + u * side / 111.195, "lon": west + w * side / (111.195 * F.cos(F.radians(south)))})
    return placed.select("image_id", "region", "area", "site", "heading", "lat", "lon", "eligible", "ts")


_DIM = ", ".join(f"({r}, {a}::DOUBLE, '{n}')" for r, a, n in REGIONS)
CAPTURES_SQL = f"""
region_dim(region, area, name) AS (SELECT col0::INT, col1, col2 FROM (VALUES {_DIM}) v(col0, col1, col2)),
seen AS (SELECT event_id AS image_id, (user_id % 8)::INT AS region, user_id::VARCHAR || '|' || strftime(ts, '%Y-%m-%d') AS site,
  ((event_id % 4) * 90)::INT AS heading, event_type, ts FROM events),
captures AS (SELECT image_id, region, area, site, heading, event_type, ts,
  34.0::DOUBLE + 0.05::DOUBLE * (region // 4) + {hash01_sql("'lat|' || site")} * sqrt(area) / 111.195::DOUBLE AS lat,
  -118.4::DOUBLE + 0.08::DOUBLE * (region % 4) + {hash01_sql("'lon|' || site")} * sqrt(area) / (111.195::DOUBLE * cos(radians(34.0::DOUBLE + 0.05::DOUBLE * (region // 4)))) AS lon
  FROM seen JOIN region_dim USING (region))"""
