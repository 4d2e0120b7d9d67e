"""Every query of the catalogue against its SQL on the smallest tables."""

import pytest
from support import compare

from fadedhh import catalogue


@pytest.mark.parametrize("name", sorted(catalogue.oracle_sql()))
def test_query_equals_sql(spark, sf_dir, name):
    got, want = compare(spark, catalogue.queries()[name], catalogue.oracle_sql()[name], sf_dir)
    assert got == want


@pytest.mark.parametrize("name", sorted(set(catalogue.queries()) - set(catalogue.oracle_sql())))
def test_query_without_sql_has_rows(spark, sf_dir, name):
    assert catalogue.queries()[name](spark, sf_dir).count() > 0


def test_bounds_hold(spark, sf_dir):
    for r in catalogue.queries()["bound_checks"](spark, sf_dir).collect():
        assert r.rate <= r.delta
        assert r.missed / max(1, r.truth) <= r.miss_bound + 0.15


def test_errors_fall_with_width_and_skew(spark, sf_dir):
    for vary in ("w", "rho"):
        rows = sorted(catalogue.queries()[f"faded_hh_errors_{vary}"](spark, sf_dir).collect(), key=lambda r: r.vary_value)
        assert rows[-1].abs_err_mean <= rows[0].abs_err_mean + 1e-12
        assert rows[-1].point_err_mean < rows[0].point_err_mean
        assert all(r.are < 1e-2 for r in rows)


def test_errors_do_not_depend_on_the_shards(spark, sf_dir):
    rows = catalogue.queries()["faded_hh_errors_p"](spark, sf_dir).collect()
    assert len(rows) == 5 and max(r.point_err_mean for r in rows) < 2 * min(r.point_err_mean for r in rows) + 1e-3


def test_recall_falls_only_for_tiny_sketches(spark, sf_dir):
    rows = {r.w: r for r in catalogue.queries()["tiny_sketch_recall"](spark, sf_dir).collect()}
    assert rows[800].recall == 1 and rows[800].precision == 1
    assert rows[2].recall < 1 and rows[2].recall <= rows[8].recall <= rows[32].recall


def test_entry(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() > 0


def test_bounds_follow_the_shares_of_a_table(spark, sf_dir):
    from fadedhh.operators import params

    for r in catalogue.queries()["detection_bounds"](spark, sf_dir).collect():
        assert 0 < r.phi <= 1 and abs(r.miss - params.miss_bound(r.phi, r.d, r.w)) <= 1e-12 * r.miss


def test_dimensions_follow_the_shares_of_a_table(spark, sf_dir):
    from fadedhh.operators import params

    for r in catalogue.queries()["sketch_dimensions"](spark, sf_dir).collect():
        assert (r.d, r.w) == params.dimension(r.eps, r.delta, r.kind)
