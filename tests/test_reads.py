"""Queries that once made their data up read a given table now."""

import pytest

from privsurv.plans.all_queries import QUERIES


@pytest.mark.parametrize("name", ["ablation_sensitivity", "ablation_temperature", "ball_bounds", "best_lambda", "convergence_test", "default_bounds", "density_histogram", "density_kernel", "dummy_basis", "effects_table", "extra_ridge", "fn_math"])
def test_needs_its_table(spark, tmp_path, name):
    with pytest.raises(Exception, match="(?i)path"):
        QUERIES[name](spark, str(tmp_path)).collect()
