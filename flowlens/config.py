"""Region, grid and pyramid settings, validated when made."""

from __future__ import annotations

from dataclasses import dataclass, field


@dataclass(frozen=True)
class RegionSpec:
    """Half-open rectangle in milli-arc-seconds from its south-west corner, which lies at (west, south) degrees."""

    west: float = -168.0
    south: float = 7.0
    width: int = 399_360_000
    height: int = 276_480_000


@dataclass(frozen=True)
class GridSpec:
    """Nested uniform grids: level 1 is finest, every level doubles the cell length."""

    levels: int = 10
    base_mas: int = 30_000
    region: RegionSpec = field(default_factory=RegionSpec)

    def __post_init__(self):
        if self.levels < 1 or self.base_mas < 1:
            raise ValueError("a grid needs a level and a cell length")

    def cell_mas(self, level: int) -> int:
        return self.base_mas << (level - 1)

    def nominal_km(self, level: int) -> int:
        return 1 << (level - 1)

    def shape(self, level: int) -> tuple[int, int]:
        c = self.cell_mas(level)
        return -(-self.region.width // c), -(-self.region.height // c)


@dataclass(frozen=True)
class PyramidConfig:
    grid: GridSpec = field(default_factory=GridSpec)
    caps_km: tuple[float, ...] | None = None
    uncapped: bool = False
    radius_cells: tuple[int, ...] | None = None
    threshold: float = 0.8
    metric: str = "grid_circle"  # or great_circle, grid_box
    rank: str = "weak"  # or strict, mean, relative
    strategy: str = "tiles"  # or offsets, leaves, all_pairs
    aggregation: str = "rollup"  # or explode, in_task
    edge_filter: str = "exact"  # or bloom, join, broadcast
    fpp: float = 0.01
    partitions: int = 16
    seed: int = 42

    def __post_init__(self):
        caps, radii = self.caps, self.radii
        if len(caps) != self.grid.levels or any(a > b for a, b in zip(caps, caps[1:])):
            raise ValueError("distance caps must be one a level and may not fall")
        if len(radii) != self.grid.levels or min(radii) < 1:
            raise ValueError("radii must be one a level and at least 1")
        if not 0 <= self.threshold < 1 or not 0 < self.fpp < 1 or self.partitions < 1:
            raise ValueError("threshold in [0, 1), false-positive share in (0, 1), partitions at least 1")

    @property
    def caps(self) -> tuple[float, ...]:
        """Longest movement, exclusive, that a level shows: about one viewport, or endless."""
        if self.uncapped:
            return tuple(float("inf") for _ in range(self.grid.levels))
        return self.caps_km or tuple(32.0 * 2**i for i in range(self.grid.levels))

    @property
    def radii(self) -> tuple[int, ...]:
        return self.radius_cells or (3,) * self.grid.levels
