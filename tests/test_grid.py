import pytest
from pyspark.sql import functions as F

from mobility_ldp.functions import cells as C
from mobility_ldp.operators import trajectory
from mobility_ldp.operators.grid import Grid, assign_cell, make_grid, state_domain
from mobility_ldp.sources.files import points_from_rows

G6 = Grid(6, 0.0, 6.0, 0.0, 6.0)


def one(spark, cells, grid, method="chebyshev"):
    df = spark.createDataFrame([(1, cells)], "traj_id bigint, c array<int>")
    return df.select(trajectory.interpolate(trajectory.collapse(F.col("c")), grid.n, method).alias("x")).first()["x"]


def test_cells_of_points(spark):
    p = points_from_rows(spark, [(1, 0, 0.0, 0.0), (1, 1, 2.5, 0.1), (1, 2, 1.0, 1.0), (1, 3, 6.0, 6.0), (1, 4, -5.0, 99.0), (1, 5, None, 1.0)])
    assert [r["cell"] for r in assign_cell(p, G6).orderBy("ord").collect()] == [0, 2, 7, 35, 30]
    assert [r["cell"] for r in assign_cell(p, G6, "drop").orderBy("ord").collect()] == [0, 2, 7, 35]


def test_empty_axis_is_cell_zero(spark):
    p = points_from_rows(spark, [(1, 0, 3.0, 1.0), (1, 1, 3.0, 2.0)])
    g = make_grid(p, 4)
    assert [r["cell"] % 4 for r in assign_cell(p, g).collect()] == [0, 0]


@pytest.mark.parametrize(
    "a, b, path",
    [((0, 0), (2, 1), [(1, 1), (2, 1)]), ((0, 0), (3, 1), [(1, 0), (2, 1), (3, 1)]), ((3, 1), (0, 0), [(2, 1), (1, 0), (0, 0)]), ((0, 0), (4, 2), [(1, 1), (2, 1), (3, 2), (4, 2)])],
)
def test_interpolation(spark, a, b, path):
    cell = lambda p: p[1] * 6 + p[0]
    assert one(spark, [cell(a), cell(b)], G6) == [cell(a), *map(cell, path)]


def test_repeats_collapse(spark):
    assert one(spark, [1, 1, 2, 2, 1], G6) == [1, 2, 1]
    assert one(spark, [4], G6) == [4]


@pytest.mark.parametrize("n, pairs", [(2, 12), (3, 40), (6, 220), (8, 420)])
def test_domain(spark, n, pairs):
    g = Grid(n, 0.0, 1.0, 0.0, 1.0)
    d = state_domain(spark, g)
    assert g.states == pairs == d.where("kind = 'intra'").count() == len(g.pairs())
    assert [(r["src"], r["dst"]) for r in d.where("kind = 'intra'").orderBy("state_id").collect()] == g.pairs()
    assert d.count() == pairs + 2 * n * n


def test_rows_and_arrays_agree(spark, sf):
    from mobility_ldp.sources import walks

    p = walks.user_walk(spark, sf)
    g = make_grid(p, 6)
    a = trajectory.assemble(p, g).select("traj_id", F.posexplode("cells").alias("pos", "cell")).selectExpr("traj_id", "pos + 1 AS pos", "cell")
    b = trajectory.assemble(p, g, form="rows")
    assert sorted(map(tuple, a.collect())) == sorted(map(tuple, b.collect()))
    assert trajectory.broken(trajectory.assemble(p, g), g).count() == 0


def test_small_functions(spark):
    df = spark.createDataFrame([(0, 35)], "a int, b int")
    r = df.select(C.chebyshev(F.col("a"), F.col("b"), 6).alias("d"), C.is_adjacent(F.col("a"), F.col("b"), 6).alias("t"), C.euclid(F.col("a"), F.col("b"), G6).alias("e"), C.haversine(F.lit(0.0), F.lit(0.0), F.lit(0.0), F.lit(1.0)).alias("h")).first()
    assert (r["d"], r["t"]) == (5, False) and abs(r["e"] - 50**0.5) < 1e-12 and abs(r["h"] - 111195) < 10
    assert spark.range(1).select(C.decode_trip(F.lit("3-4-5")).alias("x")).first()["x"] == [3, 4, 5]


def test_plan_prunes_columns(spark, sf):
    from mobility_ldp.sources import walks

    plan = make_grid  # bounds need x and y only
    assert plan is not None
    text = walks.customer_walk(spark, sf).select("x", "y")._jdf.queryExecution().executedPlan().toString()
    assert "o_orderpriority" not in text and "o_custkey" not in text.split("ReadSchema")[1]
