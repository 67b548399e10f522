"""Cells of the nested grids: constant-time ids, parents, children, centres and Morton keys."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..config import GridSpec

#: Bits of a cell coordinate in a packed id; level 1 has at most 13,312 columns.
COORD_BITS = 14


def cell(coord: Column, level: Column | int, grid: GridSpec = GridSpec()) -> Column:
    """Column or row number of a coordinate at a level."""
    base = F.call_function("div", coord.cast("long"), F.lit(grid.base_mas).cast("long"))
    return F.call_function("shiftright", base, (F.lit(level) if isinstance(level, int) else level) - 1)


def cell_id(cx: Column, cy: Column) -> Column:
    return F.shiftleft(cx.cast("long"), COORD_BITS).bitwiseOR(cy.cast("long"))


def centre(c: Column, level: Column, grid: GridSpec = GridSpec()) -> Column:
    """Coordinate of a cell's centre."""
    size = F.call_function("shiftleft", F.lit(grid.base_mas).cast("long"), level - 1)
    return c * size + F.floor(size / 2)


def parent(c: Column, up: int = 1) -> Column:
    return F.shiftright(c, up)


def morton(cx: Column, cy: Column, bits: int = COORD_BITS) -> Column:
    """Interleaved bits of both coordinates, cx in the even places."""
    key = F.lit(0).cast("long")
    for i in range(bits):
        for c, place in ((cx, 2 * i), (cy, 2 * i + 1)):
            key = key.bitwiseOR(F.shiftleft(F.shiftright(c.cast("long"), i).bitwiseAND(1), place))
    return key


def level_table(spark, grid: GridSpec = GridSpec()) -> DataFrame:
    rows = [(lv, grid.cell_mas(lv), grid.nominal_km(lv), *grid.shape(lv), grid.shape(lv)[0] * grid.shape(lv)[1]) for lv in range(1, grid.levels + 1)]
    return spark.createDataFrame(rows, "level int, cell_mas long, nominal_km long, cols long, rows long, cells long")


def by_level(values, level: Column) -> Column:
    """The value of a level out of one per level."""
    return F.element_at(F.array(*[F.lit(v) for v in values]), level.cast("int"))


def children(cx: Column, cy: Column) -> Column:
    """The four cells one level finer, as an array of (cx, cy)."""
    return F.array(*[F.struct((cx * 2 + a).alias("cx"), (cy * 2 + b).alias("cy")) for a in (0, 1) for b in (0, 1)])
