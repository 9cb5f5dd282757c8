import pytest

import __spark_entry__ as entry
from treecount.plans import templates as T

MOVED = ("agg_grouping_sets_runs", "average_concurrency", "bit_mask_ops", "concurrency_histogram", "math_binomials", "measured_rho_spans", "model_fit", "model_large_comm", "model_rho", "model_steps", "model_totals", "n_colorings_grid")


@pytest.mark.parametrize("name", MOVED)
def test_query_reads_a_given_table(spark, tmp_path, name):
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        entry.queries()[name](spark, str(tmp_path)).collect()


def test_grid_equals_the_number_of_colourings(spark):
    rows = entry.queries()["n_colorings_grid"](spark, "/root/testdata/sf0.001").collect()
    assert rows and all((r.n, r.t) == T.n_colorings(r.k, r.eps, r.delta) for r in rows)
