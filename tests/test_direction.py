"""Which method wins, at budgets where these small tables carry signal."""

from pyspark.sql import functions as F

from mobility_ldp.plans import workloads

SF = "/root/testdata/sf0.01"


def test_more_budget_helps_and_the_synthesizer_wins(spark):
    t = workloads.utility(spark, SF, ("userday_walk",), (0.5, 1e4), n=4)
    v = {(r["eps"], r["method"], r["metric"]): r["value"] for r in t.collect()}
    assert v[1e4, "synthesizer", "density_error"] < v[0.5, "synthesizer", "density_error"]
    assert v[0.5, "synthesizer", "length_error"] < 0.7
    assert v[1e4, "ngram", "density_error"] < v[0.5, "ngram", "density_error"]


def test_ablation_direction(spark):
    t = workloads.ablation(spark, SF, ("customer_walk",), 1e5, n=4).drop("source")
    v = {(r["variant"], r["metric"]): r["value"] for r in t.collect()}
    assert v["full", "trip_error"] < v["no_endpoints", "trip_error"]
    assert v["full", "density_error"] < v["no_endpoints", "density_error"]


def test_speed_up(spark):
    t = workloads.component_times(spark, SF, "order_walk", n=6)
    v = {r["component"]: r["per_1000"] for r in t.collect()}
    assert v["synthesizer total"] < v["ngram total"]


def test_scalability_is_linear(spark):
    t = workloads.scalability(spark, SF, ("order_walk",), multiples=(1, 4), methods=("synthesizer",)).orderBy("trips").collect()
    assert t[1]["seconds"] < 6 * max(t[0]["seconds"], 1.0)


def test_zone_attack_table(spark):
    t = workloads.attack_comparison(spark, SF, ("userday_walk",), 1e3, 4, methods=("synthesizer",))
    assert t.where(F.col("ratio").between(0, 1)).count() == 10


def test_only_assembly_shuffles_user_data(spark, sf):
    cost = {r["component"]: r for r in workloads.stage_costs(spark, sf).collect()}
    assert cost["assemble"]["shuffle_bytes"] > 10 * cost["collect and fit"]["shuffle_bytes"] / max(1, cost["collect and fit"]["stages"]) > 0
    assert cost["synthesize"]["shuffle_bytes"] == 0 == cost["ngram"]["shuffle_bytes"]
    assert cost["synthesize"]["task_seconds"] > 0


def test_settings_come_back_in_order(spark, sf):
    rows = workloads.utility(spark, sf, ("userday_walk", "poi_walk"), (1.0,), ("synthesizer", "ngram"), seeds=(1, 2), n=3).collect()
    assert len(rows) == 2 * 2 * 9
    trips, grid = workloads._trips(spark, sf, "userday_walk", 3)
    one = {r["metric"]: r["value"] for r in workloads.metrics.evaluate_all(trips, workloads.published(spark, trips, grid, "ngram", 1.0, 1), grid).collect()}
    two = {r["metric"]: r["value"] for r in workloads.metrics.evaluate_all(trips, workloads.published(spark, trips, grid, "ngram", 1.0, 2), grid).collect()}
    got = {r["metric"]: r["value"] for r in rows if r["source"] == "userday_walk" and r["method"] == "ngram"}
    assert all(abs(got[m] - (one[m] + two[m]) / 2) < 1e-9 for m in one)
