", ", "Queries that once only repeated printed numbers read the given tables.", ", "

import pytest

from spanfocus import registry

READING = ["task_rollup_published", "improvement_published", "improvement_over_double_budget", "table_inconsistencies", "perplexity_margins_published", "cost_counters", "ablation_published", "strides_published", "needles_by_piece_published"]


@pytest.mark.parametrize("name", READING)
def test_query_fails_without_its_table(spark, tmp_path, name):
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        registry.queries()[name](spark, str(tmp_path)).collect()
