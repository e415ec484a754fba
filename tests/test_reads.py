"""What registered queries read, and how."""

import pytest

from backtrail import queries, surface_queries

SMALL = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", ["measure_label_depth", "replay_select_drop_field"])
def test_result_comes_from_the_tables(spark, name):
    assert any("lineitem" in f for f in queries.QUERIES[name](spark, SMALL).inputFiles())


def test_view_is_counted_by_label_columns(spark):
    """No label text is made and taken apart again for every pair."""
    plan = surface_queries.QUERIES["io_sql_views"](spark, SMALL)._jdf.queryExecution().optimizedPlan().toString()
    assert "concat_ws" not in plan and "split" not in plan
