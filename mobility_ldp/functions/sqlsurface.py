"""The functions under names in SQL."""

from __future__ import annotations

from pyspark.sql import SparkSession

#: name -> (arguments, type, body); n is the grid's side.
SCALARS = {
    "grid_cell": ("x DOUBLE, y DOUBLE, x0 DOUBLE, x1 DOUBLE, y0 DOUBLE, y1 DOUBLE, n INT", "INT", "CAST(CASE WHEN y1 = y0 THEN 0 ELSE greatest(0, least(n - 1, floor((y - y0) / (y1 - y0) * n))) END AS INT) * n + CAST(CASE WHEN x1 = x0 THEN 0 ELSE greatest(0, least(n - 1, floor((x - x0) / (x1 - x0) * n))) END AS INT)"),
    "cell_x": ("cell INT, n INT", "INT", "pmod(cell, n)"),
    "cell_y": ("cell INT, n INT", "INT", "CAST(floor(cell / n) AS INT)"),
    "cell_distance": ("a INT, b INT, n INT", "INT", "greatest(abs(pmod(a, n) - pmod(b, n)), abs(CAST(floor(a / n) AS INT) - CAST(floor(b / n) AS INT)))"),
    "oue_q": ("eps DOUBLE", "DOUBLE", "1 / (exp(eps) + 1)"),
    "oue_estimate": ("ones DOUBLE, reports DOUBLE, eps DOUBLE", "DOUBLE", "(ones - reports / (exp(eps) + 1)) / (0.5 - 1 / (exp(eps) + 1))"),
    "oue_variance": ("reports DOUBLE, eps DOUBLE", "DOUBLE", "reports * 4 * exp(eps) / ((exp(eps) - 1) * (exp(eps) - 1))"),
    "keyed_uniform": ("key STRING", "DOUBLE", "CAST(CAST(conv(substring(md5(key), 1, 12), 16, 10) AS BIGINT) AS DOUBLE) / 281474976710656D"),
}


def register(spark: SparkSession) -> list[str]:
    """Make the scalar functions temporary SQL functions of this session."""
    for name, (args, kind, body) in SCALARS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS {kind} RETURN {body}")
    return list(SCALARS)


def register_synthesizer(spark: SparkSession, model, name: str = "synthesize_trips") -> None:
    """A table function name(n, seed) that yields (traj_id, cells) from a fitted model."""
    import numpy as np
    from pyspark.sql.functions import udtf

    from ..operators.synthesis import Walker

    walker = Walker(model)

    class Synthesize:
        def eval(self, n: int, seed: int):
            for a in range(0, n, 4096):
                ids = np.arange(a, min(n, a + 4096))
                cells, lengths, _, _ = walker.walk(ids, seed)
                for i, row, k in zip(ids.tolist(), cells, lengths.tolist(), strict=True):
                    yield i, row[:k].tolist()

    spark.udtf.register(name, udtf(Synthesize, returnType="traj_id bigint, cells array<int>"))
