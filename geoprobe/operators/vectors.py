"""Feature vectors in array columns: class matrices, cosine scores, and 8 x 8 rasters scrambled or masked in SQL functions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.scalars import seeded

SIDE = 8


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def cosine(a: Column, b: Column) -> Column:
    return F.try_divide(dot(a, b), F.sqrt(dot(a, a)) * F.sqrt(dot(b, b)))


def class_matrix(vectors: DataFrame, label: str, width: int) -> DataFrame:
    """label, centre: the mean vector of each class. Positions are averaged as separate aggregates, so buffers stay flat."""
    means = vectors.groupBy(label).agg(*(F.avg(F.element_at("embedding", i + 1).cast("double")).alias(f"m{i}") for i in range(width)))
    return means.select(F.col(label).alias("of"), F.array(*(f"m{i}" for i in range(width))).alias("centre"))


def zero_shot(vectors: DataFrame, matrix: DataFrame) -> DataFrame:
    """Adds pred, the class of the most similar row of the matrix (K rows, broadcast), ties to the smallest class."""
    rows = F.array_sort(F.collect_list(F.struct("of", "centre")))
    table = matrix.agg(rows.alias("classes"))
    scored = F.transform("classes", lambda c: F.struct((-F.floor(cosine(F.col("embedding"), c["centre"]) * 1e9 + 0.5)).alias("less"), c["of"].alias("of")))
    return vectors.crossJoin(F.broadcast(table)).withColumn("pred", F.array_min(scored)["of"]).drop("classes")


def block_order(key: Column, n: int, seed: int, scope: str = "image") -> Column:
    """A seeded permutation of the blocks of an n-pixel grid, per image or the same for all: blocks ranked by a hash."""
    per = SIDE // n
    base = key.cast("string") if scope == "image" else F.lit("all")
    ranked = F.transform(F.sequence(F.lit(0), F.lit(per * per - 1)), lambda i: F.struct(F.md5(F.concat(F.lit(f"{seed}|x{n}|"), base, F.lit("|"), i.cast("string"))).alias("h"), i.alias("i")))
    return F.transform(F.array_sort(ranked), lambda r: r["i"])


def scrambled(vectors: DataFrame, n: int, seed: int = 42, scope: str = "image") -> DataFrame:
    """The rasters with their n x n-pixel blocks moved; what is inside a block stays."""
    per = SIDE // n
    order = vectors.withColumn("_order", block_order(F.col("vec_id"), n, seed, scope))

    def source(p):
        row, col = F.floor(p / SIDE), p % SIDE
        block = F.element_at("_order", (F.floor(row / n) * per + F.floor(col / n) + 1).cast("int"))
        return (F.floor(block / per) * n + row % n) * SIDE + (block % per) * n + col % n

    moved = F.transform(F.sequence(F.lit(0), F.lit(SIDE * SIDE - 1)), lambda p: F.element_at("embedding", (source(p) + 1).cast("int")))
    return order.withColumn("embedding", moved).drop("_order")


def bright_mask(vectors: DataFrame) -> DataFrame:
    """Adds cue_mask: the pixels of the upper half above zero (a stand-in for a broad cue), as positions."""
    positions = F.filter(F.sequence(F.lit(0), F.lit(SIDE * SIDE // 2 - 1)), lambda p: F.element_at("embedding", p + 1) > 0.1)
    return vectors.withColumn("cue_mask", positions)


def varied_mask(vectors: DataFrame, rows: int = 2) -> DataFrame:
    """Adds cue_mask: the pixels of the band of `rows` rows whose values vary most (a stand-in for a textured cue), the upper one
    of equals; variances are compared in whole millionths."""
    width = rows * SIDE

    def spread(b):
        own = F.slice("embedding", b * width + 1, width)
        total = F.aggregate(own, F.lit(0.0), lambda s, x: s + x.cast("double"))
        squares = F.aggregate(own, F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double"))
        return F.floor((squares - total * total / width) * 1e6 + 0.5).cast("long")

    bands = F.transform(F.sequence(F.lit(0), F.lit(SIDE // rows - 1)), lambda b: F.struct((-spread(b)).alias("less"), b.alias("b")))
    best = F.array_min(bands)["b"]
    return vectors.withColumn("cue_mask", F.sequence(best * width, best * width + width - 1))


def random_mask(vectors: DataFrame, seed: int = 42) -> DataFrame:
    """Adds random_mask: as many positions as cue_mask, drawn over the whole raster by a hash of image and position."""
    ranked = F.array_sort(F.transform(F.sequence(F.lit(0), F.lit(SIDE * SIDE - 1)), lambda p: F.struct(F.md5(F.concat(F.lit(f"{seed}|m|"), F.col("vec_id").cast("string"), F.lit("|"), p.cast("string"))).alias("h"), p.alias("p"))))
    return vectors.withColumn("random_mask", F.array_sort(F.transform(F.slice(ranked, 1, F.size("cue_mask")), lambda r: r["p"])))


def filled(vectors: DataFrame, mask: str, fill: str = "zero") -> DataFrame:
    """The rasters with masked pixels set to zero or to the mean of the unmasked ones (0 if all are masked)."""
    keep = F.filter(F.sequence(F.lit(0), F.lit(SIDE * SIDE - 1)), lambda p: ~F.array_contains(mask, p))
    total = F.aggregate(keep, F.lit(0.0), lambda s, p: s + F.element_at("embedding", p + 1).cast("double"))
    value = F.lit(0.0) if fill == "zero" else F.coalesce(F.try_divide(total, F.size(keep)), F.lit(0.0))
    out = vectors.withColumn("_v", value)
    return out.withColumn("embedding", F.transform("embedding", lambda x, p: F.when(F.array_contains(mask, p), F.col("_v")).otherwise(x.cast("double")))).drop("_v")


def blurred(vectors: DataFrame) -> DataFrame:
    """A 3 x 3 binomial blur with edges repeated, in array functions."""

    def at(r, c):
        row, col = F.least(F.greatest(r, F.lit(0)), F.lit(SIDE - 1)), F.least(F.greatest(c, F.lit(0)), F.lit(SIDE - 1))
        return F.element_at("embedding", (row * SIDE + col + 1).cast("int")).cast("double")

    def pixel(p):
        r, c = F.floor(p / SIDE), p % SIDE
        return sum((at(r + i, c + j) * (2 - abs(i)) * (2 - abs(j)) for i in (-1, 0, 1) for j in (-1, 0, 1)), F.lit(0.0)) / 16

    return vectors.withColumn("embedding", F.transform(F.sequence(F.lit(0), F.lit(SIDE * SIDE - 1)), pixel))


def split_of(key: Column, purpose: str = "e") -> Column:
    score = seeded(42, purpose, key)
    return F.when(score < 0.7, "train").when(score < 0.85, "val").otherwise("test")


def permuted_labels(vectors: DataFrame, seed: int = 42) -> DataFrame:
    """Labels moved to other rows by hash order, inside hash blocks of bounded size: a control that holds no signal."""
    order = Window.partitionBy(F.floor(F.col("vec_id") / 64)).orderBy(F.md5(F.concat(F.lit(f"{seed}|l|"), F.col("vec_id").cast("string"))))
    whole = order.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return vectors.withColumn("label", F.coalesce(F.lead("label").over(order), F.first("label").over(whole)))
