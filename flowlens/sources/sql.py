"""SQL surface: views over a graph, SQL functions and table functions."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


def register_views(spark: SparkSession, graph, prefix: str = "flow") -> None:
    for name in ("nodes", "edges", "kept_nodes", "kept_edges"):
        getattr(graph, name).createOrReplaceTempView(f"{prefix}_{name}")


@udtf(returnType="level int, cx long, cy long")
class CellsOf:
    """cells_of(x, y, levels): the cell of a position at every level."""

    def eval(self, x: int, y: int, levels: int):
        for level in range(1, levels + 1):
            yield level, x // 30_000 >> level - 1, y // 30_000 >> level - 1


@udtf(returnType="tx long, ty long")
class TilesOf:
    """tiles_of(x0, y0, x1, y1, side): tiles of a given side that a half-open box meets."""

    def eval(self, x0: int, y0: int, x1: int, y1: int, side: int):
        for tx in range(x0 // side, (max(x1, x0 + 1) - 1) // side + 1):
            for ty in range(y0 // side, (max(y1, y0 + 1) - 1) // side + 1):
                yield tx, ty


def register_functions(spark: SparkSession) -> None:
    spark.udtf.register("cells_of", CellsOf)
    spark.udtf.register("tiles_of", TilesOf)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION cell_x(x BIGINT, level INT) RETURNS BIGINT RETURN shiftright(x div 30000, level - 1)")
    spark.sql("""CREATE OR REPLACE TEMPORARY FUNCTION great_circle_km(x1 DOUBLE, y1 DOUBLE, x2 DOUBLE, y2 DOUBLE) RETURNS DOUBLE RETURN 2 * 6371.0088 * asin(sqrt(
        pow(sin((radians(y2 / 3600000D) - radians(y1 / 3600000D)) / 2), 2) + cos(radians(7 + y1 / 3600000D)) * cos(radians(7 + y2 / 3600000D)) * pow(sin((radians(x2 / 3600000D) - radians(x1 / 3600000D)) / 2), 2)))""")
