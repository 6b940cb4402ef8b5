"""Choosing the side of the grid from public statistics, at no budget."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def noise(eps: float) -> float:
    e = math.exp(eps)
    return e / (e - 1) ** 2


def objective(n_grid: float, reports: float, points: float, r: float, eps_t: float) -> float:
    """Estimation error plus non-uniformity error of a range query over a share r of the space."""
    return n_grid * math.sqrt(reports * r * noise(eps_t)) + math.sqrt(r) * points / n_grid


def recommend(users: float, mean_points: float, f: float, eps: float, lam: float = 2.5, form: str = "fourth_root", least: int = 2) -> tuple[float, int]:
    """The side as computed and as used. "fourth_root" is the minimum of the objective; "printed" takes the square root of the same number."""
    eps_t = eps * f / mean_points
    radicand = users * mean_points / noise(eps_t)
    value = lam * (radicand**0.25 if form == "fourth_root" else radicand**0.5)
    return value, max(least, round(value))


def argmin_grid(reports: float, points: float, r: float, eps_t: float, largest: int = 512) -> int:
    """The whole side with the least objective, by trying all."""
    return min(range(1, largest + 1), key=lambda n: objective(n, reports, points, r, eps_t))


def statistics(points: DataFrame) -> DataFrame:
    """(users, points, mean_points) of a set of points."""
    out = points.agg(F.count_distinct("traj_id").alias("users"), F.count("*").alias("points"))
    return out.withColumn("mean_points", F.col("points") / F.col("users"))


def recommend_for(points: DataFrame, f: float, eps: float, lam: float = 2.5, form: str = "fourth_root") -> int:
    row = statistics(points).first()
    return recommend(row["users"], row["mean_points"], f, eps, lam, form)[1]
