"""Density-balanced sampling and splits by exact hash ranks."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.scalars import seeded

#: Hash buckets of each group in a two-phase rank: a group of 10^11 rows still sorts under two million rows at a time, and the
#: counts of eight groups are half a million rows.
BUCKETS = 1 << 16


def bucketed_rank(df: DataFrame, group: str, score: Column, key: str, name: str = "rank", buckets: int = BUCKETS) -> DataFrame:
    """Adds the exact rank of each row in its group by (score, key), score in [0, 1).

    A plain window over a handful of groups would sort all rows in as many tasks. Here rows are counted per hash bucket,
    buckets get their offset from a window over those small counts, and only the rows of one bucket are sorted."""
    cut = df.withColumn("_score", score).withColumn("_bucket", F.floor(F.col("_score") * buckets).cast("int"))
    counts = cut.groupBy(group, "_bucket").agg(F.count("*").alias("_n"))
    ahead = Window.partitionBy(group).orderBy("_bucket").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.select(F.col(group).alias("_g"), F.col("_bucket").alias("_b"), F.coalesce(F.sum("_n").over(ahead), F.lit(0)).alias("_before"))
    inside = Window.partitionBy(group, "_bucket").orderBy("_score", key)
    joined = cut.join(offsets, (F.col(group) == F.col("_g")) & (F.col("_bucket") == F.col("_b")))
    return joined.withColumn(name, (F.col("_before") + F.row_number().over(inside)).cast("long")).drop("_score", "_bucket", "_g", "_b", "_before")


def region_density(captures: DataFrame) -> DataFrame:
    """region, area, n, density of the eligible views."""
    return captures.where("eligible").groupBy("region", "area").agg(F.count("*").alias("n")).withColumn("density", F.col("n") / F.col("area"))


def common_density(density: DataFrame) -> DataFrame:
    """One row: the smallest density and the region that binds it; it stays in the plan."""
    return density.agg(F.min("density").alias("common"), F.min_by("region", F.struct("density", "region")).alias("binding_region"))


def quotas(density: DataFrame, rounding: str = "round") -> DataFrame:
    """region, n, area, density, quota = min(n, common density x area, rounded half up, down or up)."""
    turn = {"round": lambda x: F.floor(x + 0.5), "floor": F.floor, "ceil": F.ceil}[rounding]
    common = F.min("density").over(Window.partitionBy(F.lit(0)))  # a row per region; the pool is counted once
    return density.select("region", "n", "area", "density", F.least(F.col("n"), turn(common * F.col("area"))).cast("long").alias("quota"))


def density_sample(captures: DataFrame, seed: int = 42, rounding: str = "round", exact: bool = True) -> DataFrame:
    """The eligible views of an area-proportional sample, with quota and n of their region; `exact=False` takes each view
    with probability quota / n instead (no rank, no further shuffle)."""
    eligible = captures.where("eligible")
    limits = quotas(region_density(captures), rounding).select(F.col("region").alias("_r"), "quota", F.col("n").alias("pool"))
    score = seeded(seed, "s", F.col("image_id"))
    if not exact:
        return eligible.join(F.broadcast(limits), F.col("region") == F.col("_r")).where(score < F.col("quota") / F.col("pool")).drop("_r")
    ranked = bucketed_rank(eligible, "region", score, "image_id", "sample_rank")
    return ranked.join(F.broadcast(limits), F.col("region") == F.col("_r")).where("sample_rank <= quota").drop("_r", "sample_rank")


def stratified_split(sample: DataFrame, seed: int = 42, fractions: tuple[float, float] = (0.70, 0.85), rounding: str = "floor") -> DataFrame:
    """Adds split (train, val, test) by region-wise hash rank. `floor` cuts each region at the floors of its cumulative
    shares; `largest_remainder` gives the regions with the largest remainders one more until the totals fit."""
    ranked = bucketed_rank(sample, "region", seeded(seed, "p", F.col("image_id")), "image_id", "split_rank")
    sizes = sample.groupBy("region").agg(F.count("*").alias("size"))
    if rounding == "floor":
        cuts = sizes.select(F.col("region").alias("_r"), *(F.floor(F.col("size") * f).alias(f"cut{i}") for i, f in enumerate(fractions)))
    else:
        total = sizes.agg(F.sum("size").alias("total"))
        spread = sizes.crossJoin(total)
        columns = []
        for i, f in enumerate(fractions):
            rest = F.col("size") * f - F.floor(F.col("size") * f)
            order = Window.partitionBy("total").orderBy(rest.desc(), "region")
            missing = F.floor(F.col("total") * f + 0.5) - F.sum(F.floor(F.col("size") * f)).over(Window.partitionBy("total"))
            columns.append((F.floor(F.col("size") * f) + F.when(F.row_number().over(order) <= missing, 1).otherwise(0)).alias(f"cut{i}"))
        cuts = spread.select(F.col("region").alias("_r"), *columns)
    side = F.when(F.col("split_rank") <= F.col("cut0"), "train").when(F.col("split_rank") <= F.col("cut1"), "val").otherwise("test")
    return ranked.join(F.broadcast(cuts), F.col("region") == F.col("_r")).withColumn("split", side).drop("_r", "cut0", "cut1", "split_rank")


def grouped_split(rows: DataFrame, key: str, seed: int = 42, fractions: tuple[float, float] = (0.70, 0.85)) -> DataFrame:
    """Adds split by a hash of the group key alone, so all rows of a group fall on one side without any shuffle."""
    score = seeded(seed, "g", F.col(key))
    return rows.withColumn("split", F.when(score < fractions[0], "train").when(score < fractions[1], "val").otherwise("test"))


def sampling_table(captures: DataFrame, seed: int = 42) -> DataFrame:
    """Per region, and in total under region -1: area, available, sampled."""
    taken = density_sample(captures, seed).groupBy("region").agg(F.count("*").alias("sampled"))
    parts = region_density(captures).join(taken, "region").select("region", "area", "n", "sampled")
    rolled = parts.rollup("region").agg(F.sum("area").alias("area"), F.sum("n").alias("available"), F.sum("sampled").alias("sampled"))
    return rolled.select(F.coalesce("region", F.lit(-1)).alias("region"), F.floor(F.col("area") * 100 + 0.5).cast("long").alias("area_hundredths"), F.col("available").cast("long").alias("available"), F.col("sampled").cast("long").alias("sampled"))


def write_split(rows: DataFrame, path: str) -> None:
    """Persist a split once; later steps read it instead of drawing it again."""
    rows.write.mode("overwrite").partitionBy("split").parquet(path)
