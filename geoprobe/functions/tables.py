"""Table functions: blocks of a raster, and grid cells that a polygon's box touches."""

from __future__ import annotations

import math

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


@udtf(returnType="block int, top int, left int, height int, width int")
class ExplodeBlocks:
    """The whole n x n blocks of a side x side raster."""

    def eval(self, side: int, n: int):
        per = side // n
        for i in range(per * per):
            yield i, i // per * n, i % per * n, n, n


@udtf(returnType="cy long, cx long")
class PolygonCells:
    """Cells of a size (degrees) that a bounding box touches."""

    def eval(self, south: float, west: float, north: float, east: float, cell: float):
        for y in range(math.floor(south / cell), math.floor(north / cell) + 1):
            for x in range(math.floor(west / cell), math.floor(east / cell) + 1):
                yield y, x


def register(spark: SparkSession) -> None:
    spark.udtf.register("explode_blocks", ExplodeBlocks)
    spark.udtf.register("polygon_cells", PolygonCells)
