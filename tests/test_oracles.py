"""Every registered query with an oracle gives what DuckDB gives; the others run and have rows.

The trained experiments have no oracle; what must hold of their values is asserted one by one.
"""

import pytest

from spanfocus import registry
from tests.oracle_tools import assert_same, connect

SLOW = {
    "workload_needles_by_method", "seconds_per_sample", "workload_calculator_budgets", "workload_needles_trained_on_pieces", "budget_needles",
    "ablation_needles", "calculator_selections", "workload_long_range_median_trained", "published_geometry_scores",
}


@pytest.fixture(scope="module")
def con(sf):
    return connect(sf)


@pytest.mark.parametrize("name", sorted(registry.oracle_sql()))
def test_query_equals_oracle(spark, sf, con, name):
    assert_same(registry.queries()[name](spark, sf), con, registry.oracle_sql()[name])


@pytest.mark.parametrize("name", sorted(registry.queries().keys() - registry.oracle_sql().keys() - SLOW))
def test_query_runs(spark, sf, name):
    assert registry.queries()[name](spark, sf).count() > 0


def rows_of(spark, sf, name):
    return registry.queries()[name](spark, sf).collect()


def test_needles_of_calculators_trained_on_pieces(spark, sf):
    made = rows_of(spark, sf, "workload_needles_trained_on_pieces")
    lengths = {64 * k for k in range(1, 9)} | {None}
    assert {(r.piece_len, r.context_len) for r in made} == {(p, n) for p in (64, 128, 256, 512) for n in lengths}
    for p in (64, 128, 256, 512):
        own = {r.context_len: r.accuracy for r in made if r.piece_len == p}
        mean = own.pop(None)
        assert mean == pytest.approx(sum(own.values()) / 8, abs=1e-5)
        # Few spans leave few wrong answers: the shortest context is the easiest.
        assert own[64] == max(own.values()) and all(0 <= a <= 1 for a in own.values())


def test_needles_of_budgets_and_ablations(spark, sf):
    made = rows_of(spark, sf, "budget_needles")
    assert {(r.budget, r.method) for r in made} == {(b, m) for b in ("12.5%", "25%", "37.5%", "50%") for m in ("dependency", "delta", "random_1")}
    assert all(0 < r.accuracy < 1 for r in made)
    made = rows_of(spark, sf, "ablation_needles")
    assert {r.variant for r in made} == {"full", "flat_sigma", "flat_length"} and len(made) == 3 * 9


def test_calculators_on_two_budgets(spark, sf):
    made = {r.setting: r for r in rows_of(spark, sf, "workload_calculator_budgets")}
    assert made["large"].pearson == pytest.approx(1) and made["large"].spearman == pytest.approx(1)
    assert -1 <= made["small"].pearson <= 1 and 0 <= made["small"].overlap_at_n <= 1
    [both] = rows_of(spark, sf, "calculator_selections")
    assert both.in_both <= min(both.in_a, both.in_b) and both.overlap_share == pytest.approx(both.in_both / min(both.in_a, both.in_b), abs=1e-5)


def test_long_range_medians_of_a_trained_calculator(spark, sf):
    made = rows_of(spark, sf, "workload_long_range_median_trained")
    assert {r.piece_len for r in made} == {64, 128, 256, 512} and all(0 < r.median_focus < 8 and r.n_pairs > 0 for r in made)


def test_published_geometry_runs(spark, sf):
    made = rows_of(spark, sf, "published_geometry_scores")
    # More rows and more columns add terms that are never negative.
    assert made and all(0 < r.full_4_4 < r.full_2_2 and r.full_4_4 < r.full_4_2 < r.full_2_2 for r in made)


def test_seconds_are_positive(spark, sf):
    made = rows_of(spark, sf, "seconds_per_sample")
    assert {(r.row_stride, r.col_stride) for r in made} == {(4, 4), (2, 4), (4, 2), (2, 2)} and all(r.seconds > 0 for r in made)
