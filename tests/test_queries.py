"""Every query with SQL gives what DuckDB gives, on the smallest tables."""

import math

import duckdb
import pytest

from calib import catalogue

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SLOW = {"fig3a_spec_bgd_svm", "fig3b_spec_igd_lr", "fig3c_methods_svm", "fig6b_two_param", "table3_systems", "igd_sync_modes"}


@pytest.fixture(scope="module")
def duck(sf):
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return c


def plain(v):
    if isinstance(v, bool) or v is None:
        return v
    if isinstance(v, float):
        return "nan" if math.isnan(v) else round(v, 9) + 0.0
    if hasattr(v, "isoformat"):
        return v.isoformat()
    return float(v) if type(v).__name__ == "Decimal" else v


@pytest.mark.parametrize("name", sorted(catalogue.ORACLES))
def test_same_as_sql(name, spark, sf, duck):
    df = catalogue.QUERIES[name](spark, sf)
    cols = sorted(df.columns)
    ours = sorted((tuple(plain(r[c]) for c in cols) for r in df.collect()), key=repr)
    rel = duck.sql(catalogue.ORACLES[name])
    at = [list(rel.columns).index(c) for c in cols]
    assert ours == sorted((tuple(plain(r[i]) for i in at) for r in rel.fetchall()), key=repr)


@pytest.mark.parametrize("name", sorted(set(catalogue.QUERIES) - set(catalogue.ORACLES) - SLOW))
def test_runs(name, spark, sf):
    assert catalogue.QUERIES[name](spark, sf).count() > 0


#: Queries that once made their rows up: without their table they must fail.
READERS = "loss_weights_kinds bayes_normal phi_from_history em_mixture bayes_bivariate adaptive_steps_sim fig2_stop_loss join_theta_overlap asof_trace overhead_measure coverage_measure prune_hit_rate".split()


@pytest.mark.parametrize("name", READERS)
def test_reads_its_table(name, spark, tmp_path):
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        catalogue.QUERIES[name](spark, str(tmp_path)).collect()
