"""The grid: equal cells over a box."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.cells import grid_cell

#: The virtual start and end.
START, END = -1, -2


@dataclass(frozen=True)
class Grid:
    """n x n cells; cell = cy * n + cx."""

    n: int
    xmin: float
    xmax: float
    ymin: float
    ymax: float

    @property
    def cells(self) -> int:
        return self.n * self.n

    @property
    def width(self) -> float:
        return (self.xmax - self.xmin) / self.n

    @property
    def height(self) -> float:
        return (self.ymax - self.ymin) / self.n

    @property
    def states(self) -> int:
        """Directed pairs of cells that touch."""
        return 4 * (self.n - 1) * (2 * self.n - 1)

    def neighbours(self, cell: int) -> list[int]:
        x, y = cell % self.n, cell // self.n
        return [v * self.n + u for v in range(max(0, y - 1), min(self.n, y + 2)) for u in range(max(0, x - 1), min(self.n, x + 2)) if (u, v) != (x, y)]

    def pairs(self) -> list[tuple[int, int]]:
        """All touching pairs, in the order of their state ids."""
        return [(a, b) for a in range(self.cells) for b in self.neighbours(a)]

    def centre(self, cell: int) -> tuple[float, float]:
        return self.xmin + (cell % self.n + 0.5) * self.width, self.ymin + (cell // self.n + 0.5) * self.height


def make_grid(points: DataFrame, n: int, bounds: tuple[float, float, float, float] | None = None) -> Grid:
    """A grid over the points' box (one scan of two columns), or over known bounds (none)."""
    if bounds is None:
        # + 0.0: statistics may hold a minimum of -0.0
        row = points.agg(*[(f(c) + F.lit(0.0)) for c in ("x", "y") for f in (F.min, F.max)]).first()
        bounds = tuple(0.0 if v is None else v for v in row)
    return Grid(n, *map(float, bounds))


def assign_cell(points: DataFrame, grid: Grid, outside: str = "clamp") -> DataFrame:
    """points with the cell; those outside the box go to the nearest cell, or away with outside="drop"."""
    if outside == "drop":
        points = points.where(F.col("x").between(grid.xmin, grid.xmax) & F.col("y").between(grid.ymin, grid.ymax))
    return points.where(F.col("x").isNotNull() & F.col("y").isNotNull()).withColumn("cell", grid_cell(F.col("x"), F.col("y"), grid))


def state_domain(spark: SparkSession, grid: Grid) -> DataFrame:
    """(state_id, src, dst, kind): the touching pairs, then begins, then ends."""
    c = spark.range(grid.cells).select(F.col("id").cast("int").alias("src"))
    moves = F.array(*[F.struct(F.lit(dx).alias("dx"), F.lit(dy).alias("dy")) for dy in (-1, 0, 1) for dx in (-1, 0, 1) if (dx, dy) != (0, 0)])
    x, y = F.col("src") % grid.n + F.col("m.dx"), F.floor(F.col("src") / grid.n).cast("int") + F.col("m.dy")
    inner = c.withColumn("m", F.explode(moves)).where((x >= 0) & (x < grid.n) & (y >= 0) & (y < grid.n)).select("src", (y * grid.n + x).alias("dst"))
    from pyspark.sql import Window

    inner = inner.withColumn("state_id", F.row_number().over(Window.orderBy("src", "dst")) - 1).select("state_id", "src", "dst", F.lit("intra").alias("kind"))
    s = grid.states
    begin = c.select((F.col("src") + s).alias("state_id"), F.lit(START).alias("src"), F.col("src").alias("dst"), F.lit("begin").alias("kind"))
    end = c.select((F.col("src") + s + grid.cells).alias("state_id"), "src", F.lit(END).alias("dst"), F.lit("end").alias("kind"))
    return inner.unionByName(begin).unionByName(end)
