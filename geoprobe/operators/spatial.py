"""Region membership, spatial entanglement of test and training views, and region centroids."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.scalars import haversine_km

#: A degree of latitude in km, and the most southern latitude difference factor for a grid cell's width.
DEGREE_KM = 111.195


def inside_ring(lon: Column, lat: Column, ring: Column) -> Column:
    """Ray casting over an array of (lon, lat) corners, as one expression."""
    n = F.size(ring)

    def crossed(i):
        a, b = F.element_at(ring, i + 1), F.element_at(ring, F.pmod(i + 1, n) + 1)
        return (a["lat"] > lat) != (b["lat"] > lat), a, b

    def step(inside, i):
        over, a, b = crossed(i)
        return F.when(over & (lon < (b["lon"] - a["lon"]) * (lat - a["lat"]) / (b["lat"] - a["lat"]) + a["lon"]), ~inside).otherwise(inside)

    return F.aggregate(F.sequence(F.lit(0), n - 1), F.lit(False), step)


def with_boxes(region_dim: DataFrame) -> DataFrame:
    """Regions with their square ring and its bounding box."""
    south = F.lit(34.0) + F.lit(0.05) * F.floor(F.col("region") / 4)
    west = F.lit(-118.4) + F.lit(0.08) * F.pmod(F.col("region"), F.lit(4))
    north, east = south + F.sqrt("area") / DEGREE_KM, west + F.sqrt("area") / (DEGREE_KM * F.cos(F.radians(south)))
    corner = lambda x, y: F.struct(x.alias("lon"), y.alias("lat"))
    return region_dim.select("region", south.alias("south"), west.alias("west"), north.alias("north"), east.alias("east"), F.array(corner(west, south), corner(east, south), corner(east, north), corner(west, north)).alias("ring"))


#: Side of the cells (degrees) by which points meet regions.
CELL = 0.01


def assign_region(points: DataFrame, boxes: DataFrame, cell: float = CELL) -> DataFrame:
    """Adds `found`: the region whose polygon holds the point, null outside all. Regions are dealt to the grid cells that their
    boxes touch, so points meet them in an equi-join on cells; box and polygon are tested on what shares a cell. The cells are
    broadcast only if the planner finds them small."""
    reach = lambda low, high: F.sequence(F.floor(F.col(low) / cell).cast("long"), F.floor(F.col(high) / cell).cast("long"))
    cells = boxes.withColumnRenamed("region", "found").withColumn("cell_y", F.explode(reach("south", "north"))).withColumn("cell_x", F.explode(reach("west", "east")))
    same = (F.floor(F.col("lat") / cell).cast("long") == F.col("cell_y")) & (F.floor(F.col("lon") / cell).cast("long") == F.col("cell_x"))
    near = F.col("lat").between(F.col("south"), F.col("north")) & F.col("lon").between(F.col("west"), F.col("east"))
    return points.join(cells, same & near & inside_ring(F.col("lon"), F.col("lat"), F.col("ring")), "left").drop("south", "west", "north", "east", "ring", "cell_y", "cell_x")


def eligible_points(points: DataFrame, boxes: DataFrame) -> DataFrame:
    """The points inside some region's polygon: the filter that stands before sampling."""
    return assign_region(points, boxes).where("found is not null").drop("found")


def site_overlap(rows: DataFrame) -> DataFrame:
    """The test views whose site is also a training site."""
    train = rows.where("split = 'train'").select("site").distinct()
    return rows.where("split = 'test'").join(train, "site", "left_semi")


def near_training(rows: DataFrame, radius_km: float = 0.05) -> DataFrame:
    """The test views with a training site within the radius.

    Positions fall into cells of the radius' size; training sites, once each, are copied to the nine cells around
    them, so the range join is an equi-join on cells with an exact distance filter, and a semi-join stops at the first match."""
    height = radius_km / DEGREE_KM

    def cell(df: DataFrame) -> DataFrame:
        row = F.floor(F.col("lat") / height).cast("long")
        # A cell is at least as wide as the radius at the row's northern edge, where degrees of longitude are shortest.
        return df.withColumn("cy", row)

    def column(lon: Column, row: Column) -> Column:
        return F.floor(lon / (height / F.cos(F.radians((row + 2) * height)))).cast("long")

    test = cell(rows.where("split = 'test'")).withColumn("cx", column(F.col("lon"), F.col("cy")))
    sites = cell(rows.where("split = 'train'").select(F.col("lat").alias("lat"), F.col("lon").alias("lon")).distinct())
    spread = sites.withColumn("cy", F.explode(F.array(*(F.col("cy") + d for d in (-1, 0, 1))))).withColumn("cx", column(F.col("lon"), F.col("cy")))
    spread = spread.withColumn("cx", F.explode(F.array(*(F.col("cx") + d for d in (-1, 0, 1))))).select("cy", "cx", F.col("lat").alias("lat2"), F.col("lon").alias("lon2"))
    close = (test["cy"] == spread["cy"]) & (test["cx"] == spread["cx"]) & (haversine_km(test["lat"], test["lon"], spread["lat2"], spread["lon2"]) <= radius_km)
    return test.join(spread, close, "left_semi").drop("cy", "cx")


def near_pairs(points: DataFrame, key: str, radius_km: float) -> DataFrame:
    """Pairs (a, b, distance) of different positions within the radius, each position known by its smallest key (views at one
    position are no pairs): the same equi-join on cells."""
    height = radius_km / DEGREE_KM
    column = lambda lon, row: F.floor(lon / (height / F.cos(F.radians((row + 2) * height)))).cast("long")
    places = points.groupBy("lat", "lon").agg(F.min(key).alias("id")).withColumn("cy", F.floor(F.col("lat") / height).cast("long"))
    left = places.withColumn("cx", column(F.col("lon"), F.col("cy"))).select(F.col("id").alias("a"), F.col("lat").alias("lat1"), F.col("lon").alias("lon1"), "cy", "cx")
    spread = places.withColumn("cy", F.explode(F.array(*(F.col("cy") + d for d in (-1, 0, 1))))).withColumn("cx", column(F.col("lon"), F.col("cy")))
    spread = spread.withColumn("cx", F.explode(F.array(*(F.col("cx") + d for d in (-1, 0, 1))))).select(F.col("id").alias("b"), F.col("lat").alias("lat2"), F.col("lon").alias("lon2"), "cy", "cx")
    distance = haversine_km(F.col("lat1"), F.col("lon1"), F.col("lat2"), F.col("lon2"))
    return left.join(spread, ["cy", "cx"]).where("a < b").withColumn("distance", distance).where(F.col("distance") <= radius_km).select("a", "b", "distance")


def overlap_audit(rows: DataFrame, radius_km: float = 0.05) -> DataFrame:
    """One row: test views, those at a training site, within the radius of one, and beyond."""
    same = site_overlap(rows).select("image_id", F.lit(1).alias("same"))
    near = near_training(rows, radius_km).select("image_id", F.lit(1).alias("near"))
    test = rows.where("split = 'test'").select("image_id").join(same, "image_id", "left").join(near, "image_id", "left")
    return test.agg(F.count("*").alias("n_test"), F.count("same").alias("same_site"), F.count("near").alias("within"), (F.count("*") - F.count("near")).alias("beyond"))


def heading_overlap(rows: DataFrame) -> DataFrame:
    """Per heading: test views at a training site, and those whose heading occurs there in training."""
    train = rows.where("split = 'train'").groupBy("site").agg(F.collect_set("heading").alias("headings"))
    joined = rows.where("split = 'test'").join(train, "site")
    shared = F.array_contains("headings", F.col("heading"))
    return joined.groupBy("heading").agg(F.count("*").alias("n"), F.count_if(shared).alias("same_heading"), F.count_if(~shared).alias("other_heading"))


def buffered_split(rows: DataFrame, radius_km: float = 0.05) -> DataFrame:
    """The rows without the test views within the radius of a training site."""
    near = near_training(rows, radius_km).select("image_id")
    return rows.join(near, "image_id", "left_anti")


def centroids(rows: DataFrame, source: str = "train") -> DataFrame:
    """region, c_lat, c_lon: the mean training position (or of all rows)."""
    kept = rows.where("split = 'train'") if source == "train" else rows
    return kept.groupBy("region").agg(F.avg("lat").alias("c_lat"), F.avg("lon").alias("c_lon"))


def outer_rings(views: DataFrame) -> DataFrame:
    """region, ring: the southmost, eastmost, northmost and westmost view of each region, counter-clockwise (of equals, by the other coordinate)."""
    up, across = F.struct("lat", "lon"), F.struct("lon", "lat")
    outer = views.groupBy("region").agg(F.min(up).alias("s"), F.max(across).alias("e"), F.max(up).alias("n"), F.min(across).alias("w"))
    return outer.select("region", F.array(*(F.struct(F.col(f"{c}.lon").alias("lon"), F.col(f"{c}.lat").alias("lat")) for c in "senw")).alias("ring"))


def polygon_centroids(boxes: DataFrame) -> DataFrame:
    """region, c_lat, c_lon: the centre of mass of each region's ring (weighted corners of its triangles with the origin); null without an area."""
    ring, n = F.col("ring"), F.size("ring")
    first = F.element_at(ring, 1)
    # Corners relative to the first one, which keeps the products small.
    at = lambda i: F.struct((F.element_at(ring, F.pmod(i, n) + 1)["lon"] - first["lon"]).alias("x"), (F.element_at(ring, F.pmod(i, n) + 1)["lat"] - first["lat"]).alias("y"))
    zero = F.struct(F.lit(0.0).alias("area"), F.lit(0.0).alias("x"), F.lit(0.0).alias("y"))

    def step(so_far, i):
        p, q = at(i), at(i + 1)
        cross = p["x"] * q["y"] - q["x"] * p["y"]
        return F.struct((so_far["area"] + cross).alias("area"), (so_far["x"] + (p["x"] + q["x"]) * cross).alias("x"), (so_far["y"] + (p["y"] + q["y"]) * cross).alias("y"))

    sums = F.aggregate(F.sequence(F.lit(0), n - 1), zero, step)
    return boxes.select("region", first.alias("first"), sums.alias("s")).select("region", (F.col("first.lat") + F.try_divide("s.y", 3 * F.col("s.area"))).alias("c_lat"), (F.col("first.lon") + F.try_divide("s.x", 3 * F.col("s.area"))).alias("c_lon"))


def centroid_error(predicted: DataFrame, centres: DataFrame, by: list[str]) -> DataFrame:
    """n rows, how many of them are unplaced (their prediction, column pred, is null or has no centre), and the mean km from where a view was
    taken to the centre of the region that was predicted, over the placed ones."""
    dim = centres.withColumnRenamed("region", "_r")
    joined = predicted.join(F.broadcast(dim), F.col("pred") == F.col("_r"), "left")
    km = F.when(F.col("_r").isNotNull(), haversine_km(F.col("lat"), F.col("lon"), F.col("c_lat"), F.col("c_lon")))
    return joined.groupBy(*by).agg(F.count("*").alias("n"), F.count_if(F.col("_r").isNull()).alias("unplaced"), F.avg(km).alias("km"))


def nearest_capture(rows: DataFrame) -> DataFrame:
    """Adds the view taken last before each one at the same site (as-of join with itself, as a window)."""
    order = Window.partitionBy("site").orderBy("ts", "image_id")
    return rows.withColumn("previous_id", F.lag("image_id").over(order))
