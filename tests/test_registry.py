import pytest

import __spark_entry__ as entry
from dictparse import queries as core
from tests.conftest import SF

FAST = [n for n in core.SQL if not n.startswith(("decode_check_", "contiguity_", "reference_order_", "stream_", "part_")) and n not in ("flex_bound",)]


@pytest.mark.parametrize("name", FAST)
def test_query_agrees_with_its_sql(agree, name):
    agree(core.QUERIES[name], core.SQL[name])


def test_registry(spark):
    assert set(entry.oracle_sql()) <= set(entry.queries())
    df = entry.entry(spark)
    assert df.columns == ["lang", "pair_cut", "pair_run", "step"] and df.count() == 4


@pytest.mark.parametrize("name", ["example_cut", "example_flex_fixed"])
def test_written_tokens_come_from_a_table(spark, name):
    df = core.QUERIES[name](spark, SF)
    assert any(f.endswith("events.parquet") for f in df.inputFiles())
    assert {r.token[0] for r in df.select("token").collect()} <= {"'", "#"}
