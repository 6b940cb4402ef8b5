"""Every query of the engine with SQL gives the same rows as that SQL, at sf0.01."""

import pytest

from mobility_ldp.plans import queries

SF = "/root/testdata/sf0.01"


def norm(v):
    if isinstance(v, float):
        return repr(round(v, 9) + 0.0)
    return "null" if v is None else str(int(v) if isinstance(v, bool) else v)


@pytest.mark.parametrize("name", list(queries.ORACLES))
def test_against_sql(spark, duck, name):
    df = queries.QUERIES[name](spark, SF)
    cols = sorted(df.columns)
    got = sorted(tuple(norm(r[c]) for c in cols) for r in df.collect())
    names, rows = duck(queries.ORACLES[name])
    assert sorted(names) == cols
    at = [names.index(c) for c in cols]
    assert got == sorted(tuple(norm(r[i]) for i in at) for r in rows)


@pytest.mark.parametrize("name", ["budget_plan", "network_walk", "report_bits", "state_domain"])
def test_reads_the_trips_of_a_table(spark, tmp_path, name):
    """With other rows in the table the query says something else."""
    import os

    for f in os.listdir(SF):
        if f != "lineitem.parquet":
            os.symlink(f"{SF}/{f}", tmp_path / f)
    spark.read.parquet(f"{SF}/lineitem.parquet").where("l_linenumber <= 2").write.parquet(str(tmp_path / "lineitem.parquet"))
    ask = lambda folder: sorted(map(str, queries.QUERIES[name](spark, folder).collect()))
    assert ask(str(tmp_path)) != ask(SF)


def test_rows_only(spark, sf):
    for name in ("synthesize_fast", "ngram_perturb", "single_point_perturb", "knowledge_ngram_perturb", "ablation_no_endpoints", "ablation_pooled_transitions", "ablation_no_reweight", "non_private_reference", "reidentification_zone", "sample_trips", "network_walk", "poi_walk", "stream_reports", "workload_role_changes"):
        assert queries.QUERIES[name](spark, sf).count() > 0, name
