import re

import pytest

from callweave.llm import queries
from tests.conftest import DATA


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("name", ["op3_secret_scan", "op5_source_mix", "op7_line_dedup"])
def test_native_operators_run_no_python(name, spark):
    assert not re.search("Python|Pandas|InArrow", plan(queries.QUERIES[name](spark, DATA)))


@pytest.mark.parametrize("name", sorted(queries.QUERIES))
def test_no_operator_joins_all_with_all(name, spark):
    text = plan(queries.QUERIES[name](spark, DATA))
    assert "CartesianProduct" not in text and "BroadcastNestedLoopJoin" not in text


@pytest.mark.parametrize("name", ["op1_byte_bpe", "op4_main_text", "op9_quality"])
def test_map_only_operators_read_only_what_they_need(name, spark):
    text = plan(queries.QUERIES[name](spark, DATA))
    assert "SortMergeJoin" not in text and not re.search(r"ReadSchema: struct<[^>]*(source|lang|n_chars)", text)
