"""The registered queries, and the DuckDB SQL for those that SQL can express.

Measures with SQL compare two fixed halves of a source: trips of even and of
odd id. Doubles are rounded to six digits in both engines.
"""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from ..functions import rng, sqlsurface
from ..functions.cells import encode_trip
from ..operators import ablations, attacks, budget, errors, granularity, metrics, models, ngram, oue, second_order, synthesis, trajectory
from ..operators.grid import END, START, make_grid, state_domain
from ..sources import walks
from ..streaming import trips as streams
from . import pipeline, relational, workloads

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
SEED = 5
MAIN, SIDE = "order_walk", 6


def register(name: str, query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql is not None:
        ORACLES[name] = sql


def points(spark, sf, source=MAIN):
    return walks.WALKS[source](spark, sf)


def trips(spark, sf, source=MAIN, n=SIDE, **options):
    p = points(spark, sf, source)
    grid = make_grid(p, n)
    return trajectory.assemble(p, grid, **options), grid


def halves(spark, sf, source=MAIN, n=SIDE):
    t, grid = trips(spark, sf, source, n)
    return t.where("traj_id % 2 = 0"), t.where("traj_id % 2 = 1"), grid


def ctes(source=MAIN, n=SIDE) -> str:
    return "WITH " + trajectory.sql((walks.SQL | walks.MORE_SQL)[source], n)


def r6(c):
    return F.round(c, 6)


TEXT = "SELECT traj_id, string_agg(CAST(cell AS VARCHAR), '-' ORDER BY pos) AS cells, CAST(count(*) AS INTEGER) AS n_cells FROM t GROUP BY traj_id"


def as_text(t):
    return t.select("traj_id", encode_trip(F.col("cells")).alias("cells"), "n_cells")


# ---- discretization and assembly ----------------------------------------------

for _s in walks.SQL:
    register(f"dataset_stats_{_s}", lambda spark, sf, s=_s: relational.dataset_stats(points(spark, sf, s)), f"WITH p AS ({walks.SQL[_s]}) SELECT count(DISTINCT traj_id) AS trips, count(*) AS points, round(count(*) / count(DISTINCT traj_id), 6) AS mean_points FROM p")
    register(f"interpolate_cells_{_s}", lambda spark, sf, s=_s: as_text(trips(spark, sf, s)[0]), ctes(_s) + TEXT)


def grid_bounds(spark, sf):
    g = make_grid(points(spark, sf), SIDE)
    return spark.createDataFrame([(g.xmin, g.xmax, g.ymin, g.ymax)], "x0 double, x1 double, y0 double, y1 double")


register("grid_bounds", grid_bounds, ctes() + "SELECT x0, x1, y0, y1 FROM b")


def assign_cell(spark, sf):
    p = points(spark, sf)
    from ..operators.grid import assign_cell as put

    return put(p, make_grid(p, SIDE)).groupBy("traj_id", "cell").agg(F.count("*").alias("n"))


register("assign_cell", assign_cell, ctes() + f"SELECT traj_id, cy * {SIDE} + cx AS cell, count(*) AS n FROM c GROUP BY 1, 2")
register("collapse_repeats", lambda spark, sf: as_text(trips(spark, sf, method="none")[0]), ctes() + f"SELECT traj_id, string_agg(CAST(cy * {SIDE} + cx AS VARCHAR), '-' ORDER BY k) AS cells, CAST(count(*) AS INTEGER) AS n_cells FROM m GROUP BY traj_id")
register("trip_rows", lambda spark, sf: trips(spark, sf, "supplier_walk", form="rows")[0], ctes("supplier_walk") + "SELECT traj_id, CAST(pos AS INTEGER) AS pos, cell FROM t")
register("trip_lengths", lambda spark, sf: trips(spark, sf)[0].groupBy(F.least("n_cells", F.lit(36)).alias("len")).agg(F.count("*").alias("n")), ctes() + "SELECT CAST(least(c, 36) AS INTEGER) AS len, count(*) AS n FROM (SELECT count(*) AS c FROM t GROUP BY traj_id) GROUP BY 1")
register("trip_endpoints", lambda spark, sf: trajectory.endpoints(trips(spark, sf)[0]), ctes() + "SELECT traj_id, arg_min(cell, pos) AS first, arg_max(cell, pos) AS last FROM t GROUP BY traj_id")
MOVES = ", v AS (SELECT traj_id, pos AS step, cell AS src, lead(cell) OVER (PARTITION BY traj_id ORDER BY pos) AS dst FROM t)"
register("transitions", lambda spark, sf: trajectory.transitions(trips(spark, sf)[0]), ctes() + MOVES + "SELECT traj_id, CAST(step AS INTEGER) AS step, src, dst FROM v WHERE dst IS NOT NULL")
register("transition_counts", lambda spark, sf: trajectory.transitions(trips(spark, sf)[0]).groupBy("src", "dst").agg(F.count("*").alias("n")), ctes() + MOVES + "SELECT src, dst, count(*) AS n FROM v WHERE dst IS NOT NULL GROUP BY 1, 2")


def domain_sql(n: int) -> str:
    s, c = 4 * (n - 1) * (2 * n - 1), n * n
    return f"""c AS (SELECT CAST(unnest(generate_series(0, {c - 1})) AS INTEGER) AS cell),
d AS (SELECT CAST(row_number() OVER (ORDER BY a.cell, b.cell) - 1 AS INTEGER) AS state_id, a.cell AS src, b.cell AS dst, 'intra' AS kind FROM c a, c b
      WHERE a.cell <> b.cell AND abs(a.cell % {n} - b.cell % {n}) <= 1 AND abs(a.cell // {n} - b.cell // {n}) <= 1
      UNION ALL SELECT CAST({s} + cell AS INTEGER), {START}, cell, 'begin' FROM c
      UNION ALL SELECT CAST({s + c} + cell AS INTEGER), cell, {END}, 'end' FROM c)
"""


def domain_query(spark, sf):
    """All states of the grid, each with how often the trips are in it; those that nobody was in have 0."""
    t, grid = trips(spark, sf)
    n = models.exact_counts(t, grid).select("state_id", F.col("clipped").cast("bigint").alias("n"))
    return state_domain(spark, grid).join(n, "state_id", "left").na.fill(0, ["n"])


register("state_domain", domain_query, ctes().replace("c AS", "pc AS", 1).replace("FROM c WINDOW", "FROM pc WINDOW") + MOVES + ", " + domain_sql(SIDE) + f""",
u AS (SELECT src, dst FROM v WHERE dst IS NOT NULL UNION ALL SELECT {START}, arg_min(cell, pos) FROM t GROUP BY traj_id UNION ALL SELECT arg_max(cell, pos), {END} FROM t GROUP BY traj_id)
SELECT state_id, src, dst, kind, coalesce(n, 0) AS n FROM d LEFT JOIN (SELECT src, dst, count(*) AS n FROM u GROUP BY 1, 2) USING (src, dst)""")


def to_points(spark, sf):
    t, g = trips(spark, sf, "customer_walk")
    return trajectory.to_points(t, g).select("traj_id", "pos", r6("x").alias("x"), r6("y").alias("y"))


register("to_points", to_points, ctes("customer_walk") + f"SELECT traj_id, CAST(pos - 1 AS INTEGER) AS pos, round(x0 + (cell % {SIDE} + 0.5) * ((x1 - x0) / {SIDE}), 6) AS x, round(y0 + (cell // {SIDE} + 0.5) * ((y1 - y0) / {SIDE}), 6) AS y FROM t, b")

# ---- relational ----------------------------------------------------------------

register("od_matrix", lambda spark, sf: relational.od_matrix(trips(spark, sf)[0]), ctes() + ", e AS (SELECT arg_min(cell, pos) AS first, arg_max(cell, pos) AS last FROM t GROUP BY traj_id) SELECT first, last, count(*) AS n FROM e GROUP BY 1, 2")
register("od_cube", lambda spark, sf: relational.od_cube(*trips(spark, sf)), ctes() + f", e AS (SELECT CAST(arg_min(cell, pos) // {SIDE} AS INTEGER) AS r1, CAST(arg_max(cell, pos) // {SIDE} AS INTEGER) AS r2 FROM t GROUP BY traj_id) SELECT r1, r2, count(*) AS n FROM e GROUP BY CUBE (r1, r2)")
register("region_rollup", relational.region_rollup, "SELECT r_name, n_name, count(*) AS n, CAST(round(sum(CAST(o_totalprice AS DECIMAL(18, 2))), 2) AS DOUBLE) AS total FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")
ZONE = attacks.central_zone(type("G", (), {"n": SIDE})())
_zone = ", ".join(map(str, ZONE))
register("zone_trips_semi", lambda spark, sf: trajectory.in_zone(trips(spark, sf)[0], ZONE).select("traj_id"), ctes() + f"SELECT DISTINCT traj_id FROM t WHERE cell IN ({_zone})")


def zone_anti(spark, sf):
    t, _ = trips(spark, sf)
    return t.select("traj_id").join(trajectory.in_zone(t, ZONE).select("traj_id"), "traj_id", "left_anti")


register("zone_trips_anti", zone_anti, ctes() + f"SELECT traj_id FROM t GROUP BY traj_id HAVING count(*) FILTER (WHERE cell IN ({_zone})) = 0")


def cell_sets(spark, sf):
    a, b, _ = halves(spark, sf, "customer_walk", 12)
    return relational.cell_sets(a, b)


register("cell_set_ops", cell_sets, ctes("customer_walk", 12) + ", x AS (SELECT DISTINCT cell FROM t WHERE traj_id % 2 = 0), y AS (SELECT DISTINCT cell FROM t WHERE traj_id % 2 = 1) SELECT CASE WHEN y.cell IS NULL THEN 'first' WHEN x.cell IS NULL THEN 'second' ELSE 'both' END AS kind, coalesce(x.cell, y.cell) AS cell FROM x FULL JOIN y ON x.cell = y.cell")
register("top_targets", lambda spark, sf: relational.top_targets(trips(spark, sf)[0]), ctes() + MOVES + ", w AS (SELECT src, dst, count(*) AS n FROM v WHERE dst IS NOT NULL GROUP BY 1, 2), q AS (SELECT *, CAST(row_number() OVER (PARTITION BY src ORDER BY n DESC, dst) AS INTEGER) AS place FROM w) SELECT * FROM q WHERE place <= 3")
register("asof_events", relational.asof_events, "SELECT event_id, user_id, click_id FROM (SELECT event_id, user_id, event_type, last_value(CASE WHEN event_type = 'click' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS click_id FROM events) WHERE event_type = 'purchase'")
register("moving_density", relational.moving_density, "WITH e AS (SELECT CAST(dayofyear(ts) AS INTEGER) AS day, count(*) AS n FROM events GROUP BY 1) SELECT day, n, CAST(sum(n) OVER (ORDER BY day ROWS UNBOUNDED PRECEDING) AS BIGINT) AS so_far, round(avg(n) OVER (ORDER BY day ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS mean_n FROM e")
register("mean_interval", lambda spark, sf: relational.mean_interval(points(spark, sf, "userday_walk")), "WITH g AS (SELECT epoch_us(lead(ts) OVER (PARTITION BY user_id * 1000 + dayofyear(ts) ORDER BY ts, event_id)) - epoch_us(ts) AS g FROM events) SELECT round(avg(g) / 1e6, 3) AS seconds FROM g")
_drawn = rng.u01_sql(str(SEED), "traj_id")
SHARES = {0: 0.5, 7: 0.25, 14: 0.1}
register("sample_trips", lambda spark, sf: trajectory.sample(trips(spark, sf)[0], 0.1, SEED, "md5").select("traj_id", "n_cells"), ctes() + f"SELECT traj_id, CAST(count(*) AS INTEGER) AS n_cells FROM t GROUP BY traj_id HAVING {_drawn} < 0.1")
register("sample_by_start", lambda spark, sf: trajectory.sample_by_start(trips(spark, sf)[0], SHARES, SEED, "md5").select("traj_id", F.col("cells")[0].alias("first")), ctes() + f"SELECT traj_id, first FROM (SELECT traj_id, arg_min(cell, pos) AS first FROM t GROUP BY traj_id) WHERE {_drawn} < CASE first " + " ".join(f"WHEN {c} THEN {s}" for c, s in SHARES.items()) + " ELSE 0 END")

# ---- perturbation --------------------------------------------------------------

EPS_LEN, LEN_MAX = 1.0, 9


def length_reports(spark, sf):
    t, g = trips(spark, sf, "customer_walk", 3)
    return t.select("traj_id", oue.perturb(models.length_item(LEN_MAX), LEN_MAX, EPS_LEN, SEED, F.col("traj_id"), F.lit("len")).alias("bits"))


def _chance(item: str, eps: float) -> str:
    return f"CASE WHEN i = {item} THEN 0.5 ELSE {oue.q_of(eps)!r} END"


LEN_REPORTS = f""", n AS (SELECT traj_id, least(count(*), {LEN_MAX}) - 1 AS item FROM t GROUP BY traj_id),
r AS (SELECT traj_id, i FROM n, (SELECT unnest(generate_series(0, {LEN_MAX - 1})) AS i) WHERE {rng.u01_sql(str(SEED), 'traj_id', "'len'", 'i')} < {_chance('item', EPS_LEN)})
"""
register("oue_reports_md5", lambda spark, sf: length_reports(spark, sf).select("traj_id", F.array_join(F.transform("bits", lambda b: b.cast("string")), ",").alias("bits")), ctes("customer_walk", 3) + LEN_REPORTS + "SELECT n.traj_id AS traj_id, coalesce(string_agg(CAST(i AS VARCHAR), ',' ORDER BY i), '') AS bits FROM n LEFT JOIN r USING (traj_id) GROUP BY 1")


def length_estimates(spark, sf):
    return oue.settle(oue.estimate(oue.count(length_reports(spark, sf)), EPS_LEN))


def estimate_sql(eps: float, n: str = "n") -> str:
    return f"(ones - {n} * {oue.q_of(eps)!r}) / (0.5 - {oue.q_of(eps)!r})"


LEN_COUNTS = LEN_REPORTS + ", k AS (SELECT CAST(i AS INTEGER) AS item, count(*) AS ones FROM r GROUP BY 1), z AS (SELECT count(*) AS n FROM n), e AS (SELECT item, ones, z.n AS n, " + estimate_sql(EPS_LEN, "z.n") + " AS est FROM k, z) "
register("oue_estimate_length", lambda spark, sf: length_estimates(spark, sf).select("item", "ones", "n", r6("est").alias("est"), r6("clipped").alias("clipped")), ctes("customer_walk", 3) + LEN_COUNTS + "SELECT item, ones, n, round(est, 6) AS est, round(greatest(est, 0.0), 6) AS clipped FROM e")
register("oue_norm_sub", lambda spark, sf: oue.settle(oue.estimate(oue.count(length_reports(spark, sf)), EPS_LEN), "norm_sub").select("item", r6("clipped").alias("clipped")), ctes("customer_walk", 3) + LEN_COUNTS + """,
g AS (SELECT *, row_number() OVER w AS k, sum(est) OVER (ORDER BY est DESC, item ROWS UNBOUNDED PRECEDING) AS s FROM e WINDOW w AS (ORDER BY est DESC, item)),
h AS (SELECT max_by((s - n) / k, k) AS d FROM g WHERE est - (s - n) / k > 0)
SELECT item, round(greatest(est - d, 0.0), 6) AS clipped FROM e, h""")
register("length_model", lambda spark, sf: models.length_model(length_estimates(spark, sf)).select("len", r6("p").alias("p"), r6("cum").alias("cum")), ctes("customer_walk", 3) + LEN_COUNTS + ", lm AS (SELECT item + 1 AS len, greatest(est, 0.0) / sum(greatest(est, 0.0)) OVER () AS p FROM e) SELECT CAST(len AS INTEGER) AS len, round(p, 6) AS p, round(sum(p) OVER (ORDER BY len ROWS UNBOUNDED PRECEDING), 6) AS cum FROM lm")
register("length_quantile", lambda spark, sf: models.length_quantile(models.length_model(length_estimates(spark, sf))), ctes("customer_walk", 3) + LEN_COUNTS + ", lm AS (SELECT item + 1 AS len, greatest(est, 0.0) / sum(greatest(est, 0.0)) OVER () AS p FROM e), q AS (SELECT len, sum(p) OVER (ORDER BY len ROWS UNBOUNDED PRECEDING) AS cum FROM lm) SELECT CAST(min(len) AS INTEGER) AS l_k FROM q WHERE cum >= 0.9 - 1e-12")

L_K, EPS_MOVE, EPS_END = 4, 1.0, 1.0


def move_estimates(spark, sf):
    """Padded reports of the first moves of each trip, one report for each of the L_K places."""
    t, g = trips(spark, sf, "customer_walk", 3)
    items = models.kept_moves(models.state_items(g), L_K)
    place = t.select("traj_id", F.explode(F.sequence(F.lit(0), F.lit(L_K - 1))).alias("k"), items.alias("items"))
    rep = place.select(oue.perturb(F.get("items", F.col("k")), g.states, EPS_MOVE, SEED, F.col("traj_id"), F.lit("move"), F.col("k")).alias("bits"))
    return oue.settle(oue.estimate(oue.count(rep), EPS_MOVE))


def _moves_sql(n=3) -> str:
    s = 4 * (n - 1) * (2 * n - 1)
    return MOVES + f""", {domain_sql(n).replace("c AS (", "cc AS (", 1).replace("FROM c a, c b", "FROM cc a, cc b").replace("FROM c", "FROM cc").replace("FROM ccc", "FROM cc")},
pl AS (SELECT traj_id, kk FROM (SELECT DISTINCT traj_id FROM t), (SELECT unnest(generate_series(0, {L_K - 1})) AS kk)),
it AS (SELECT pl.traj_id AS traj_id, kk, d.state_id AS item FROM pl LEFT JOIN v ON v.traj_id = pl.traj_id AND v.step = kk + 1 AND v.dst IS NOT NULL LEFT JOIN d ON d.kind = 'intra' AND d.src = v.src AND d.dst = v.dst),
r AS (SELECT i FROM it, (SELECT unnest(generate_series(0, {s - 1})) AS i) WHERE {rng.u01_sql(str(SEED), 'traj_id', "'move'", 'kk', 'i')} < {_chance('item', EPS_MOVE)}),
k AS (SELECT CAST(i AS INTEGER) AS item, count(*) AS ones FROM r GROUP BY 1), z AS (SELECT count(*) AS n FROM it),
e AS (SELECT item, ones, z.n AS n, {estimate_sql(EPS_MOVE, 'z.n')} AS est FROM k, z)
"""


register("oue_estimate_intra", lambda spark, sf: move_estimates(spark, sf).select("item", "ones", "n", r6("est").alias("est")), ctes("customer_walk", 3) + _moves_sql() + "SELECT item, ones, n, round(est, 6) AS est FROM e")


def end_estimates(spark, sf, raw=False):
    t, g = trips(spark, sf, "customer_walk", 3)
    e = trajectory.endpoints(t)
    both = e.select("traj_id", F.explode(F.array(F.struct(F.lit("begin").alias("feature"), F.col("first").alias("c")), F.struct(F.lit("end").alias("feature"), F.col("last").alias("c")))).alias("p")).select("traj_id", "p.feature", "p.c")
    rep = both.select("feature", oue.perturb(F.col("c"), g.cells, EPS_END, SEED, F.col("traj_id"), F.col("feature")).alias("bits"))
    return oue.settle(oue.estimate(oue.count(rep, by=["feature"]), EPS_END), by=["feature"])


END_SQL = f""", ee AS (SELECT traj_id, 'begin' AS feature, arg_min(cell, pos) AS c FROM t GROUP BY 1 UNION ALL SELECT traj_id, 'end', arg_max(cell, pos) FROM t GROUP BY 1),
er AS (SELECT feature, i FROM ee, (SELECT unnest(generate_series(0, 8)) AS i) WHERE {rng.u01_sql(str(SEED), 'traj_id', 'feature', 'i')} < {_chance('c', EPS_END)}),
ek AS (SELECT feature, CAST(i AS INTEGER) AS item, count(*) AS ones FROM er GROUP BY 1, 2), ez AS (SELECT feature, count(*) AS n FROM ee GROUP BY 1),
ex AS (SELECT ek.feature AS feature, item, ones, n, {estimate_sql(EPS_END)} AS est FROM ek JOIN ez USING (feature))
"""
register("oue_estimate_endpoints", lambda spark, sf: end_estimates(spark, sf).select("feature", "item", "ones", "n", r6("est").alias("est")), ctes("customer_walk", 3) + END_SQL + "SELECT feature, item, ones, n, round(est, 6) AS est FROM ex")


def mobility(spark, sf):
    """The aggregated model from the three sets of noisy estimates."""
    p = points(spark, sf, "customer_walk")
    g = make_grid(p, 3)
    inner = move_estimates(spark, sf).select(F.col("item").alias("state_id"), "clipped")
    ends = end_estimates(spark, sf).select((F.col("item") + F.when(F.col("feature") == "begin", g.states).otherwise(g.states + g.cells)).alias("state_id"), "clipped")
    return models.mobility_model(spark, g, inner.unionByName(ends)).select("src", "dst", r6("est").alias("est"), r6("p").alias("p"))


register("mobility_model", mobility, ctes("customer_walk", 3) + _moves_sql() + END_SQL + """,
al AS (SELECT item AS state_id, greatest(est, 0.0) AS v FROM e UNION ALL SELECT item + CASE WHEN feature = 'begin' THEN 40 ELSE 49 END, greatest(est, 0.0) FROM ex),
mm AS (SELECT d.src AS src, d.dst AS dst, coalesce(v, 0.0) AS v FROM d LEFT JOIN al USING (state_id))
SELECT src, dst, round(v, 6) AS est, round(coalesce(v / nullif(sum(v) OVER (PARTITION BY src), 0), 0.0), 6) AS p FROM mm""")


def fused_counts(spark, sf):
    """True counts through the fused pass with an unlimited budget: they must equal plain ones."""
    t, g = trips(spark, sf)
    inf = math.inf
    out = oue.fused(t, [("length", models.length_item(36), 0, 36, inf), ("intra", models.state_items(g), 17, g.states, inf), ("begin", F.col("cells")[0], 0, g.cells, inf)], SEED)
    return out.where("ones > 0")


register("oue_fused_exact", fused_counts, ctes() + MOVES + f""", {domain_sql(SIDE).replace("c AS (", "cc AS (", 1).replace("FROM c a, c b", "FROM cc a, cc b").replace("FROM c", "FROM cc").replace("FROM ccc", "FROM cc")},
nn AS (SELECT traj_id, count(*) AS c, arg_min(cell, pos) AS f FROM t GROUP BY 1), z AS (SELECT count(*) AS n FROM nn)
SELECT 'length' AS feature, CAST(least(c, 36) - 1 AS INTEGER) AS item, count(*) AS ones, any_value(n) AS n FROM nn, z GROUP BY 2
UNION ALL SELECT 'intra', state_id, count(*), any_value(n) * 17 FROM v JOIN d ON d.kind = 'intra' AND v.src = d.src AND v.dst = d.dst, z WHERE step <= 17 GROUP BY 2
UNION ALL SELECT 'begin', f, count(*), any_value(n) FROM nn, z GROUP BY 2""")

# ---- analysis --------------------------------------------------------------------

EPSES = (0.5, 1.0, 2.0)


def variances(spark, sf):
    n = points(spark, sf, "customer_walk").select("traj_id").distinct().count()
    e = spark.createDataFrame([(x,) for x in EPSES], "eps double")
    return e.select("eps", r6(F.lit(1.0) / (F.exp("eps") + 1)).alias("q"), r6(oue.variance_col(F.lit(float(n)), F.col("eps"))).alias("variance"))


register("oue_variance", variances, "WITH n AS (SELECT count(DISTINCT o_custkey) AS n FROM orders), e AS (SELECT unnest([0.5, 1.0, 2.0])::DOUBLE AS eps) SELECT eps, round(1 / (exp(eps) + 1), 6) AS q, round(n::DOUBLE * 4 * exp(eps) / (exp(eps) - 1) / (exp(eps) - 1), 6) AS variance FROM n, e")


def ratio_variances(spark, sf):
    t, g = trips(spark, sf)
    f = trajectory.transitions(t).groupBy("src", "dst").agg(F.count("*").alias("f"))
    return errors.transition_noise(f, 1000, 2.0, 4).select("src", "dst", r6("noise").alias("noise"))


V05 = f"CAST({oue.variance(1.0, 0.5)!r} AS DOUBLE)"
FREQ = MOVES + ", w AS (SELECT src, dst, count(*)::DOUBLE AS f FROM v WHERE dst IS NOT NULL GROUP BY 1, 2), y AS (SELECT *, sum(f) OVER (PARTITION BY src) AS fy, count(*) OVER (PARTITION BY src) AS m FROM w)"
register("ratio_variance", ratio_variances, ctes() + FREQ + f" SELECT src, dst, round((f * f) / (fy * fy) * ({V05} * 1000 / (f * f) - 2 * ({V05} * 1000) / (f * fy) + m * ({V05} * 1000) / (fy * fy)), 6) AS noise FROM y")


def length_errors(spark, sf):
    t, _ = trips(spark, sf)
    f = t.groupBy(F.col("n_cells").alias("len")).agg(F.count("*").alias("f"))
    one = lambda d: errors.length_error(f, 1.0, d).select(F.lit(str(d)).alias("form"), r6("error").alias("error"))
    return one(8).unionByName(one("derived"))


LEN_ERR = ", lf AS (SELECT c AS len, count(*)::DOUBLE AS f FROM (SELECT count(*) AS c FROM t GROUP BY traj_id) GROUP BY 1), z AS (SELECT sum(f) AS n, count(*) AS d FROM lf)"
_s2 = f"(n * {oue.variance(1.0, 1.0)!r})"
_le = lambda last: f"sum((f / n) * (f / n) * ({_s2} / (f * f) - 2 * {_s2} / (f * n) + {last} * {_s2} / (n * n)))"
register("length_error_analytic", length_errors, ctes() + LEN_ERR + f" SELECT '8' AS form, round({_le('8')}, 6) AS error FROM lf, z UNION ALL SELECT 'derived', round({_le('d')}, 6) FROM lf, z")
KS = (0.5, 0.6, 0.7, 0.8, 0.9, 1.0)


def error_curve(spark, sf):
    t, _ = trips(spark, sf)
    f = trajectory.transitions(t).groupBy("src", "dst").agg(F.count("*").alias("f"))
    lens = t.groupBy(F.col("n_cells").alias("len")).agg(F.count("*").alias("f"))
    return errors.transition_error_curve(f, lens, 1000000, 50.0, list(KS))


CURVE = FREQ + LEN_ERR + f""",
lc AS (SELECT len, sum(f) OVER (ORDER BY len ROWS UNBOUNDED PRECEDING) / sum(f) OVER () AS c FROM lf),
lk AS (SELECT k, min(len) AS l_k FROM (SELECT unnest([0.5, 0.6, 0.7, 0.8, 0.9, 1.0])::DOUBLE AS k), lc WHERE c >= k - 1e-12 GROUP BY k),
vv AS (SELECT k, l_k, (1000000.0 * l_k) * 4 * exp(50.0 / l_k) / (exp(50.0 / l_k) - 1) / (exp(50.0 / l_k) - 1) AS u FROM lk),
cv AS (SELECT k, l_k, sum((f * f) / (fy * fy) * (u / (f * f) - 2 * u / (f * fy) + m * u / (fy * fy))) AS noise, sum((1 - k) * (1 - k) * (f / fy) * (f / fy)) AS bias FROM y, vv GROUP BY 1, 2)
"""
register("transition_error_curve", lambda spark, sf: error_curve(spark, sf).select("k", F.col("l_k").cast("int").alias("l_k"), F.round("noise", 4).alias("noise"), r6("bias").alias("bias")), ctes() + CURVE + "SELECT k, CAST(l_k AS INTEGER) AS l_k, round(noise, 4) AS noise, round(bias, 6) AS bias FROM cv")
register("best_quantile", lambda spark, sf: errors.best_quantile(error_curve(spark, sf)), ctes() + CURVE + "SELECT arg_min(k, noise + bias) AS k FROM cv")


def budgets(spark, sf):
    """The shares of each scheme, for the length within which nine tenths of the trips stay."""
    t, grid = trips(spark, sf)
    l_k = t.agg(F.expr("percentile_disc(0.9) WITHIN GROUP (ORDER BY least(n_cells, {0}))".format(grid.cells)).cast("int")).first()[0]
    rows = []
    for scheme in ("default", "naive", "pooled"):
        for eps in EPSES:
            b = budget.plan_budget(eps, l_k, scheme, max_len=grid.cells)
            rows.append((scheme, eps, b.l_k, round(b.e1, 6), round(b.e2, 6), round(b.e3, 6), round(b.per_move, 6)))
    return spark.createDataFrame(rows, "scheme string, eps double, l_k int, e1 double, e2 double, e3 double, per_move double")


LK = f", q AS (SELECT CAST(quantile_disc(least(c, {SIDE * SIDE}), 0.9) AS INTEGER) AS l_k FROM (SELECT count(*) AS c FROM t GROUP BY traj_id))"
register("budget_plan", budgets, ctes() + LK + f", s AS (SELECT scheme, CASE scheme WHEN 'naive' THEN {SIDE * SIDE} ELSE l_k END AS l FROM q, (SELECT unnest(['default', 'naive', 'pooled']) AS scheme)) SELECT scheme, eps, CAST(l AS INTEGER) AS l_k, round(eps / 10, 6) AS e1, round(0.9 * eps * l / (l + 2), 6) AS e2, round(1.8 * eps / (l + 2), 6) AS e3, round(0.9 * eps / (l + 2), 6) AS per_move FROM s, (SELECT unnest([0.5, 1.0, 2.0])::DOUBLE AS eps)")


def grids(spark, sf):
    rows = []
    for s in walks.SQL:
        r = granularity.statistics(points(spark, sf, s)).first()
        for form in ("fourth_root", "printed"):
            v, n = granularity.recommend(r["users"], r["mean_points"], 1 / 15, 1.0, form=form)
            rows.append((s, form, round(v, 4), n))
    return spark.createDataFrame(rows, "source string, form string, value double, n int")


_u = " UNION ALL ".join(f"SELECT '{s}' AS source, count(DISTINCT traj_id)::DOUBLE AS u, count(*)::DOUBLE / count(DISTINCT traj_id) AS l FROM ({q})" for s, q in walks.SQL.items())
register("recommend_grid", grids, f"WITH s AS ({_u}), e AS (SELECT *, exp(1.0 / 15 / l) AS x FROM s), r AS (SELECT source, u * l * (x - 1) * (x - 1) / x AS a FROM e), v AS (SELECT source, 'fourth_root' AS form, 2.5 * pow(a, 0.25) AS v FROM r UNION ALL SELECT source, 'printed', 2.5 * sqrt(a) FROM r) SELECT source, form, round(v, 4) AS value, CAST(greatest(2, round(v)) AS INTEGER) AS n FROM v")


def grid_objective(spark, sf):
    r = granularity.statistics(points(spark, sf)).first()
    eps_t = 1.0 / 15 / r["mean_points"]
    rows = [(n, round(granularity.objective(n, r["points"], r["points"], 1 / 9, eps_t), 4)) for n in range(2, 13)]
    return spark.createDataFrame(rows, "n int, error double")


register("grid_objective", grid_objective, "WITH s AS (SELECT count(*)::DOUBLE AS p, count(*)::DOUBLE / count(DISTINCT l_orderkey) AS l FROM lineitem), e AS (SELECT *, exp(1.0 / 15 / l) AS x FROM s) SELECT CAST(n AS INTEGER) AS n, round(n * sqrt(p / 9 * x / (x - 1) / (x - 1)) + sqrt(1.0 / 9) * p / n, 4) AS error FROM e, (SELECT unnest(generate_series(2, 12)) AS n)")

# ---- synthesis -------------------------------------------------------------------

def synthesize_sql(spark, sf):
    """Trips from true counts with whole-number weights."""
    t, g = trips(spark, sf, "customer_walk", 3)
    names = {r["state_id"]: (r["src"], r["dst"]) for r in state_domain(spark, g).collect()}
    weights = {names[r["state_id"]]: int(r["clipped"]) for r in models.exact_counts(t, g).collect()}
    lengths = {r["n_cells"]: r["count"] for r in t.groupBy("n_cells").count().collect()}
    out = synthesis.synthesize_sql(spark, g, lengths, weights, sum(lengths.values()), SEED)
    return out.select("traj_id", encode_trip(F.col("cells")).alias("cells"), "cap", "n_cells")


register("synthesize_sql", synthesize_sql, ctes("customer_walk", 3).replace("WITH ", "WITH RECURSIVE ", 1) + MOVES + f""",
lw AS (SELECT c AS len, count(*) AS w FROM (SELECT count(*) AS c FROM t GROUP BY traj_id) GROUP BY 1),
lr AS (SELECT len, CAST(sum(w) OVER (ORDER BY len) AS BIGINT) AS s FROM lw), lt AS (SELECT max(s) AS s FROM lr),
bw AS (SELECT cell, CAST(sum(w) OVER (ORDER BY cell) AS BIGINT) AS s FROM (SELECT f AS cell, count(*) AS w FROM (SELECT arg_min(cell, pos) AS f FROM t GROUP BY traj_id) GROUP BY 1)), bt AS (SELECT max(s) AS s FROM bw),
ew AS (SELECT l AS cell, count(*) AS w FROM (SELECT arg_max(cell, pos) AS l FROM t GROUP BY traj_id) GROUP BY 1),
mw AS (SELECT src, dst, CAST(sum(w * 10) OVER (PARTITION BY src ORDER BY dst) AS BIGINT) AS s FROM (SELECT src, dst, count(*) AS w FROM v WHERE dst IS NOT NULL GROUP BY 1, 2)),
mt AS (SELECT src, max(s) AS s FROM mw GROUP BY 1),
ids AS (SELECT unnest(generate_series(0, (SELECT count(DISTINCT traj_id) FROM t) - 1)) AS traj_id),
st AS (SELECT traj_id, (SELECT min(len) FROM lr, lt WHERE lr.s > floor({rng.u01_sql(str(SEED), 'traj_id', "'len'")} * lt.s)) AS cap,
              (SELECT min(cell) FROM bw, bt WHERE bw.s > floor({rng.u01_sql(str(SEED), 'traj_id', "'start'")} * bt.s)) AS cur FROM ids),
walk AS (SELECT traj_id, CAST(cap AS INTEGER) AS cap, CAST(1 AS BIGINT) AS l, cur, CAST(cur AS VARCHAR) AS cells FROM st
  UNION ALL
  SELECT traj_id, cap, l, cur, cells || '-' || CAST(cur AS VARCHAR) FROM (
    SELECT w.traj_id, w.cap, w.l + 1 AS l, w.cells,
      (SELECT min(dst) FROM mw WHERE mw.src = w.cur AND mw.s > floor({rng.u01_sql(str(SEED), 'w.traj_id', 'w.l + 1')} * (coalesce(mt.s, 0) + coalesce(ew.w, 0) * (3 + 2 * (w.l + 1))))) AS cur
    FROM walk w LEFT JOIN mt ON mt.src = w.cur LEFT JOIN ew ON ew.cell = w.cur WHERE w.l < w.cap) q WHERE cur IS NOT NULL)
SELECT traj_id, arg_max(cells, l) AS cells, any_value(cap) AS cap, CAST(max(l) AS INTEGER) AS n_cells FROM walk GROUP BY traj_id""")


def synthesize_fast(spark, sf):
    """The whole method: reports at eps 1, model, as many trips as there are."""
    return as_text(pipeline.publish(points(spark, sf), SIDE, 1.0, seed=SEED).synthetic)


register("synthesize_fast", synthesize_fast)
for _v, _f in ablations.VARIANTS.items():
    if _v != "full":
        register(f"ablation_{_v}", lambda spark, sf, f=_f: (lambda t, g: as_text(f(spark, t, g, 1.0, t.count(), SEED)))(*trips(spark, sf)))
register("non_private_reference", lambda spark, sf: (lambda t, g: as_text(ablations.non_private(spark, t, g, t.count(), SEED)))(*trips(spark, sf)))


def ngram_query(spark, sf, n=2):
    t, g = trips(spark, sf, "userday_walk", 4)
    return as_text(ngram.ngram_perturb(t, g, 1.0, n, SEED))


register("ngram_perturb", ngram_query)
register("single_point_perturb", lambda spark, sf: ngram_query(spark, sf, 1))


def knowledge_query(spark, sf):
    p = points(spark, sf, "poi_walk")
    g = make_grid(p, 4)
    k = ngram.knowledge_from_sites(walks.sites(spark, sf), g)
    t = trajectory.assemble(p, g).withColumn("hour", F.pmod("traj_id", F.lit(24)))
    return as_text(ngram.ngram_perturb(t, g, 1.0, 2, SEED, k))


register("knowledge_ngram_perturb", knowledge_query)
register("network_walk", lambda spark, sf: as_text(trips(spark, sf, "network_walk", 6)[0]), ctes("network_walk", 6) + TEXT)
register("poi_walk", lambda spark, sf: as_text(trips(spark, sf, "poi_walk", 6)[0]))


def sql_surface(spark, sf):
    """The scalar functions from SQL."""
    sqlsurface.register(spark)
    points(spark, sf, "customer_walk").createOrReplaceTempView("mobility_points")
    g = make_grid(points(spark, sf, "customer_walk"), SIDE)
    return spark.sql(f"SELECT grid_cell(x, y, {g.xmin!r}D, {g.xmax!r}D, {g.ymin!r}D, {g.ymax!r}D, {SIDE}) AS cell, count(*) AS n FROM mobility_points GROUP BY 1")


register("sql_surface", sql_surface, ctes("customer_walk") + f"SELECT cy * {SIDE} + cx AS cell, count(*) AS n FROM c GROUP BY 1")



def second_order_counts(spark, sf):
    """Runs of three cells, counted by their ids."""
    t, g = trips(spark, sf)
    names = F.array(*[F.lit("-".join(map(str, r))) for r in second_order.runs(g)])
    out = second_order.with_runs(t, g).select(F.explode("runs").alias("r")).groupBy("r").agg(F.count("*").alias("n"))
    return out.select(F.get(names, F.col("r")).alias("run"), "n")


register("second_order_counts", second_order_counts, ctes() + ", v AS (SELECT cell, lead(cell) OVER w AS b, lead(cell, 2) OVER w AS c FROM t WINDOW w AS (PARTITION BY traj_id ORDER BY pos)) SELECT concat_ws('-', cell, b, c) AS run, count(*) AS n FROM v WHERE c IS NOT NULL GROUP BY 1")


def second_order_synthesis(spark, sf):
    t, g = trips(spark, sf, "customer_walk", 4)
    return as_text(second_order.synthesize(spark, *second_order.fit(t, g, 2.0, seed=SEED), t.count(), SEED))


register("second_order_synthesis", second_order_synthesis)


def length_prob_mean(spark, sf):
    f = trips(spark, sf)[0].groupBy(F.col("n_cells").alias("len")).agg(F.count("*").alias("f"))
    return errors.length_prob_mean(f).select("len", r6("p").alias("p"))


register("length_prob_mean", length_prob_mean, ctes() + LEN_ERR + " SELECT CAST(len AS INTEGER) AS len, round(f / n, 6) AS p FROM lf, z")


def approximate_aggregates(spark, sf):
    """Each approximate aggregate beside the exact one, and whether it keeps its error: 3 standard errors of 2 % for distinct cells and
    trips, a rank error of 1 % for the median."""
    rows, _ = trips(spark, sf, form="rows")
    per = rows.groupBy("traj_id").agg(F.count("*").alias("c"))
    d = rows.agg(F.countDistinct("traj_id").alias("trips"), F.approx_count_distinct("traj_id", 0.02).alias("about"), F.countDistinct("cell").alias("cells"), F.approx_count_distinct("cell", 0.02).alias("about_cells"))
    q = per.agg(F.expr("percentile_approx(c, 0.5, 1000)").alias("mid"), F.expr("kll_sketch_get_quantile_double(kll_sketch_agg_double(CAST(c AS DOUBLE), 400), 0.5D)").alias("kll"))
    ranks = per.crossJoin(F.broadcast(q)).agg(*[(F.sum(F.when(F.col("c") <= F.col(x), 1).otherwise(0)) / F.count("*")).alias(f"{x}_to") for x in ("mid", "kll")], *[(F.sum(F.when(F.col("c") < F.col(x), 1).otherwise(0)) / F.count("*")).alias(f"{x}_from") for x in ("mid", "kll")])
    holds = lambda x: (F.col(f"{x}_from") <= 0.51) & (F.col(f"{x}_to") >= 0.49)
    near = lambda exact, about: F.abs(F.col(about) - F.col(exact)) <= F.lit(0.06) * F.col(exact)
    return d.crossJoin(ranks).select("trips", "cells", near("trips", "about").alias("trips_near"), near("cells", "about_cells").alias("cells_near"), holds("mid").alias("median_near"), holds("kll").alias("kll_near"))


register("approximate_aggregates", approximate_aggregates, ctes() + "SELECT count(DISTINCT traj_id) AS trips, count(DISTINCT cell) AS cells, true AS trips_near, true AS cells_near, true AS median_near, true AS kll_near FROM t")


def speed_counts(spark, sf):
    """Trips by mean speed: true counts through the fused pass, and what one noisy collection estimates is in speed_estimate."""
    items = models.speed_item(points(spark, sf, "userday_walk"))
    return oue.fused(items, [("speed", F.col("item"), 0, 8, math.inf)], SEED).where("ones > 0").select("item", "ones", "n")


_speed = "WITH p AS (SELECT user_id * 1000 + dayofyear(ts) AS traj_id, ts, event_id, ln(1 + value) AS x, CAST(props->>'$.k' AS DOUBLE) AS y FROM events), d AS (SELECT traj_id, ts, sqrt(pow(x - lag(x) OVER w, 2) + pow(y - lag(y) OVER w, 2)) AS d FROM p WINDOW w AS (PARTITION BY traj_id ORDER BY ts, event_id)), s AS (SELECT traj_id, sum(d) AS d, (epoch_us(max(ts)) - epoch_us(min(ts))) / 1e6 AS t FROM d GROUP BY 1)"
register("speed_counts", speed_counts, _speed + " SELECT CAST(least(floor(d / t / 0.001 * 8), 7) AS INTEGER) AS item, count(*) AS ones, (SELECT count(*) FROM s) AS n FROM s WHERE t > 0 GROUP BY 1")
register("speed_estimate", lambda spark, sf: oue.estimate(oue.fused(models.speed_item(points(spark, sf, "userday_walk")), [("speed", F.col("item"), 0, 8, 1.0)], SEED), 1.0))


def length_quantiles(spark, sf):
    """Exact quantiles of the trips' lengths."""
    t, _ = trips(spark, sf)
    q = [F.expr(f"percentile_disc({k}) WITHIN GROUP (ORDER BY n_cells)").cast("int").alias(f"q{int(k * 100)}") for k in (0.5, 0.9, 0.99)]
    return t.agg(*q)


register("length_quantiles", length_quantiles, ctes() + "SELECT CAST(quantile_disc(c, 0.5) AS INTEGER) AS q50, CAST(quantile_disc(c, 0.9) AS INTEGER) AS q90, CAST(quantile_disc(c, 0.99) AS INTEGER) AS q99 FROM (SELECT count(*) AS c FROM t GROUP BY traj_id)")


BIT_SIDES = (3, 6, 8)


def report_bits(spark, sf):
    """(n, trips, l_k, bits, all_bits): what each trip's owner sends, and all of them, by the grid's side; l_k holds nine tenths of the trips."""
    rows = []
    for n in BIT_SIDES:
        t, grid = trips(spark, sf, n=n)
        r = t.agg(F.count("*").alias("n"), F.expr(f"percentile_disc(0.9) WITHIN GROUP (ORDER BY least(n_cells, {grid.cells}))").cast("int").alias("l_k")).first()
        bits = budget.report_bits(grid.cells, grid.states, r["l_k"] or 0)["total"]
        rows.append((n, r["n"], r["l_k"], bits, bits * r["n"]))
    return spark.createDataFrame(rows, "n int, trips long, l_k int, bits long, all_bits long")


def _bits_sql(n: int) -> str:
    return f"SELECT {n} AS n, trips, l_k, CAST({n * n} + l_k * {4 * (n - 1) * (2 * n - 1)} + {2 * n * n} AS BIGINT) AS bits FROM ({ctes(n=n)} SELECT count(*) AS trips, CAST(quantile_disc(least(c, {n * n}), 0.9) AS INTEGER) AS l_k FROM (SELECT count(*) AS c FROM t GROUP BY traj_id))"


register("report_bits", report_bits, "SELECT CAST(n AS INTEGER) AS n, trips, l_k, bits, CAST(bits * trips AS BIGINT) AS all_bits FROM (" + " UNION ALL ".join(_bits_sql(n) for n in BIT_SIDES) + ")")

# ---- measures --------------------------------------------------------------------

HALF = ", r AS (SELECT * FROM t WHERE traj_id % 2 = 0), s AS (SELECT * FROM t WHERE traj_id % 2 = 1)"


def jsd_sql(a: str, b: str, keys: str) -> str:
    """Divergence of two counts (keys, n)."""
    return f"""(SELECT sum(CASE WHEN p > 0 THEN p * ln(p / ((p + q) / 2)) ELSE 0 END + CASE WHEN q > 0 THEN q * ln(q / ((p + q) / 2)) ELSE 0 END) / 2
FROM (SELECT coalesce(p, 0.0) AS p, coalesce(q, 0.0) AS q FROM (SELECT {keys}, n / sum(n) OVER () AS p FROM {a}) FULL JOIN (SELECT {keys}, n / sum(n) OVER () AS q FROM {b}) USING ({keys})))"""


def measure(name, query, sql, source=MAIN):
    def run(spark, sf):
        return query(*halves(spark, sf, source)).select("metric", r6("value").alias("value"))

    register(name, run, ctes(source) + HALF + sql)


def _row(name: str, value: str) -> str:
    return f" SELECT '{name}' AS metric, round(CAST({value} AS DOUBLE), 6) AS value"


measure("density_error", lambda a, b, g: metrics.density_error(a, b), ", x AS (SELECT cell, count(*) AS n FROM r GROUP BY 1), y AS (SELECT cell, count(*) AS n FROM s GROUP BY 1)" + _row("density_error", jsd_sql("x", "y", "cell")))
_side = math.sqrt(1 / 9)
measure("query_error", lambda a, b, g: metrics.query_error(a, b, g, seed=SEED), f""",
q AS (SELECT qid, x0 + {rng.u01_sql(str(SEED), 'qid', "'x'")} * ((1 - {_side!r}) * (x1 - x0)) AS a0, y0 + {rng.u01_sql(str(SEED), 'qid', "'y'")} * ((1 - {_side!r}) * (y1 - y0)) AS c0 FROM (SELECT unnest(generate_series(0, 199)) AS qid), b),
k AS (SELECT cell % {SIDE} AS cx, cell // {SIDE} AS cy, count(*) FILTER (WHERE traj_id % 2 = 0) AS r, count(*) FILTER (WHERE traj_id % 2 = 1) AS s FROM t GROUP BY 1, 2),
e AS (SELECT qid, coalesce(sum(r), 0) AS qr, coalesce(sum(s), 0) AS qs FROM q, b LEFT JOIN k ON x0 + (cx + 0.5) * ((x1 - x0) / {SIDE}) BETWEEN a0 AND a0 + {_side!r} * (x1 - x0) AND y0 + (cy + 0.5) * ((y1 - y0) / {SIDE}) BETWEEN c0 AND c0 + {_side!r} * (y1 - y0) GROUP BY 1)""" + _row("query_error", "(SELECT avg(abs(qr - qs) / greatest(qr::DOUBLE, (SELECT count(*) / 100 FROM r))) FROM e)"))
_best = sum(1 / (j * math.log(j + 1)) for j in range(1, 6))
measure("hotspot_error", lambda a, b, g: metrics.hotspot_error(a, b), f""",
x AS (SELECT cell, row_number() OVER (ORDER BY count(*) DESC, cell) AS a FROM r GROUP BY cell QUALIFY a <= 5), y AS (SELECT cell, row_number() OVER (ORDER BY count(*) DESC, cell) AS b FROM s GROUP BY cell QUALIFY b <= 5)""" + _row("hotspot_error", f"(SELECT 1 - coalesce(sum(1.0 / a / ln(b + 1.0)), 0) / {_best!r} FROM x JOIN y USING (cell))"), "userday_walk")
KEN = f""", cc AS (SELECT unnest(generate_series(0, {SIDE * SIDE - 1})) AS cell),
k AS (SELECT cc.cell AS cell, count(traj_id) FILTER (WHERE traj_id % 2 = 0) AS r, count(traj_id) FILTER (WHERE traj_id % 2 = 1) AS s FROM cc LEFT JOIN t ON t.cell = cc.cell GROUP BY 1)"""
measure("kendall", lambda a, b, g: metrics.kendall(a, b, g), KEN + _row("kendall", f"(SELECT sum(CASE WHEN sign(a.r - b.r) * sign(a.s - b.s) < 0 THEN -1 ELSE 1 END) / {SIDE**2 * (SIDE**2 - 1) / 2} FROM k a JOIN k b ON a.cell < b.cell)"))
measure("kendall_tau_a", lambda a, b, g: metrics.kendall(a, b, g, "tau_a"), KEN + _row("kendall", f"(SELECT sum(sign(a.r - b.r) * sign(a.s - b.s)) / {SIDE**2 * (SIDE**2 - 1) / 2} FROM k a JOIN k b ON a.cell < b.cell)"))
ENDS = ", x AS (SELECT first, last, count(*) AS n FROM (SELECT arg_min(cell, pos) AS first, arg_max(cell, pos) AS last FROM r GROUP BY traj_id) GROUP BY 1, 2), y AS (SELECT first, last, count(*) AS n FROM (SELECT arg_min(cell, pos) AS first, arg_max(cell, pos) AS last FROM s GROUP BY traj_id) GROUP BY 1, 2)"
measure("trip_error", lambda a, b, g: metrics.trip_error(a, b), ENDS + _row("trip_error", jsd_sql("x", "y", "first, last")))
measure("trip_error_marginal", lambda a, b, g: metrics.trip_error(a, b, "marginal"), ENDS + ", x1 AS (SELECT first, sum(n) AS n FROM x GROUP BY 1), y1 AS (SELECT first, sum(n) AS n FROM y GROUP BY 1), x2 AS (SELECT last, sum(n) AS n FROM x GROUP BY 1), y2 AS (SELECT last, sum(n) AS n FROM y GROUP BY 1)" + _row("trip_error", f"({jsd_sql('x1', 'y1', 'first')} + {jsd_sql('x2', 'y2', 'last')}) / 2"))
DIST = f""", mv AS (SELECT traj_id, abs(cell % {SIDE} - lag(cell) OVER w % {SIDE}) AS dx, abs(cell // {SIDE} - lag(cell) OVER w // {SIDE}) AS dy FROM t WINDOW w AS (PARTITION BY traj_id ORDER BY pos)),
tr AS (SELECT traj_id, count(*) FILTER (WHERE dx = 1 AND dy = 0) * wd + count(*) FILTER (WHERE dx = 0 AND dy = 1) * ht + count(*) FILTER (WHERE dx = 1 AND dy = 1) * sqrt(wd * wd + ht * ht) AS d
       FROM mv, (SELECT (x1 - x0) / {SIDE} AS wd, (y1 - y0) / {SIDE} AS ht FROM b) GROUP BY traj_id, wd, ht)"""
BINNED = """, mx AS (SELECT max(d) AS top FROM tr), bn AS (SELECT traj_id, CASE WHEN top > 0 THEN least(floor(d / top * 20), 19) ELSE 0 END AS bin FROM tr, mx),
x AS (SELECT bin, count(*) AS n FROM bn WHERE traj_id % 2 = 0 GROUP BY 1), y AS (SELECT bin, count(*) AS n FROM bn WHERE traj_id % 2 = 1 GROUP BY 1)"""
measure("length_error", lambda a, b, g: metrics.length_error(a, b, g), DIST + BINNED + _row("length_error", jsd_sql("x", "y", "bin")))
DIAM = f""", dc AS (SELECT DISTINCT traj_id, cell FROM t),
tr AS (SELECT a.traj_id AS traj_id, sqrt(max(pow((a.cell % {SIDE} - c.cell % {SIDE}) * ((x1 - x0) / {SIDE}), 2) + pow((a.cell // {SIDE} - c.cell // {SIDE}) * ((y1 - y0) / {SIDE}), 2))) AS d FROM dc a JOIN dc c USING (traj_id), b GROUP BY 1)"""
measure("diameter_error", lambda a, b, g: metrics.diameter_error(a, b, g), DIAM + BINNED + _row("diameter_error", jsd_sql("x", "y", "bin")))
PAT = """, g AS (SELECT traj_id, pos, k, string_agg(CAST(cell AS VARCHAR), '-' ORDER BY pos2) AS pattern FROM
  (SELECT a.traj_id AS traj_id, a.pos AS pos, k, c.cell AS cell, c.pos AS pos2 FROM t a, (SELECT unnest(generate_series(2, 5)) AS k) JOIN t c ON c.traj_id = a.traj_id AND c.pos BETWEEN a.pos AND a.pos + k - 1) GROUP BY 1, 2, 3 HAVING count(*) = k),
pr AS (SELECT pattern, count(*) AS n FROM g WHERE traj_id % 2 = 0 GROUP BY 1), ps AS (SELECT pattern, count(*) AS n FROM g WHERE traj_id % 2 = 1 GROUP BY 1),
fr AS (SELECT * FROM pr ORDER BY n DESC, pattern LIMIT 100), fs AS (SELECT * FROM ps ORDER BY n DESC, pattern LIMIT 100)"""
measure("pattern_f1", lambda a, b, g: metrics.pattern_f1(a, b), PAT + _row("pattern_f1", "(SELECT 2.0 * count(*) / ((SELECT count(*) FROM fr) + (SELECT count(*) FROM fs)) FROM fr JOIN fs USING (pattern))"))
measure("pattern_error", lambda a, b, g: metrics.pattern_error(a, b), PAT + _row("pattern_error", "(SELECT avg(abs(fr.n - coalesce(ps.n, 0)) / fr.n) FROM fr LEFT JOIN ps USING (pattern))"))
register("top_patterns", lambda spark, sf: metrics.top_patterns(halves(spark, sf)[0]), ctes() + HALF + PAT + " SELECT pattern, n FROM fr")

# ---- attacks ---------------------------------------------------------------------


def outlier_resilience(spark, sf):
    a, b, g = halves(spark, sf, "customer_walk")
    return attacks.resilience(attacks.outlier_matches(a, b, g)).select("kappa", r6("ratio").alias("ratio"))


register("outlier_resilience", outlier_resilience, ctes("customer_walk") + DIST + """,
ds AS (SELECT round(d, 9) AS d, count(*) AS n FROM tr WHERE traj_id % 2 = 1 GROUP BY 1), dr AS (SELECT round(d, 9) AS e, count(*) AS m FROM tr WHERE traj_id % 2 = 0 GROUP BY 1),
gp AS (SELECT d, n, round(least(coalesce(d - lag(d) OVER (ORDER BY d), 'infinity'::DOUBLE), coalesce(lead(d) OVER (ORDER BY d) - d, 'infinity'::DOUBLE)), 9) AS gap FROM ds),
ou AS (SELECT d, n FROM (SELECT d, n, sum(n) OVER (ORDER BY gap DESC, d DESC ROWS UNBOUNDED PRECEDING) AS c, sum(n) OVER () AS a FROM gp) WHERE c <= 0.05 * a OR c = n),
mt AS (SELECT d, n, coalesce(sum(m), 0) AS matches FROM ou, (SELECT max(e) - min(e) AS w FROM dr) LEFT JOIN dr ON abs(d - e) <= 0.25 * w + 1e-9 GROUP BY 1, 2)
SELECT CAST(kappa AS INTEGER) AS kappa, round(sum(CASE WHEN matches > kappa THEN n ELSE 0 END) / sum(n), 6) AS ratio FROM mt, (SELECT unnest([2, 4, 6, 8, 10]) AS kappa) GROUP BY 1""")


def reidentification(spark, sf):
    a, b, g = halves(spark, sf, "customer_walk")
    return attacks.resilience(attacks.reidentification(a, b, g)).select("kappa", r6("ratio").alias("ratio"))


register("reidentification_zone", reidentification)
register("zone_walks", lambda spark, sf: attacks.zone_walks(trips(spark, sf)[0], ZONE).select(encode_trip(F.col("walk")).alias("walk"), "n"), ctes() + f", z AS (SELECT traj_id, string_agg(CAST(cell AS VARCHAR), '-' ORDER BY pos) AS walk FROM t WHERE cell IN ({_zone}) GROUP BY 1) SELECT walk, count(*) AS n FROM z GROUP BY 1")

# ---- streams and experiments -------------------------------------------------------

for _name, _query, _sql in streams.QUERIES:
    register(_name, _query, _sql)
for _name, _query in workloads.QUERIES:
    register(_name, _query)
