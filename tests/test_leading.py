"""Texts asked for their first symbols are the beginnings of the whole texts, and no larger part of a table is gathered for them."""

import pytest
from pyspark.sql import functions as F

from dictparse import queries as core
from dictparse.sources import workloads as W
from tests.conftest import SF


@pytest.mark.parametrize("name", W._JOINED)
@pytest.mark.parametrize("most", [1, 700])
def test_beginnings(spark, name, most):
    whole = {r.id: r.text[:most] for r in W.CATALOG[name](spark, SF).collect()}
    rows = W.CATALOG[name](spark, SF, most=most).collect()
    assert {r.id: r.text[:most] for r in rows} == whole


@pytest.mark.parametrize("separator", ["", "\n"])
@pytest.mark.parametrize("one", [True, False])
def test_odd_pieces(spark, separator, one):
    pieces = [(None, 1, ""), (None, 2, None), (None, 2, "ab"), (None, None, "xy"), (None, 4, ""), (None, 5, "cdé"), (None, 5, "f"), (None, 9, "ghi")]
    if not one:
        pieces += [("b", 1, None), ("b", 2, ""), ("c", 3, "z")]
    rows = spark.createDataFrame(pieces, "k string, o int, p string")
    whole = {r.k: r.text for r in W.concatenated(rows, ["k"], [F.col("o")], F.col("p"), separator).collect()}
    for most in (1, 3, 6, 14):
        got = {r.k: r.text for r in W.concatenated(rows, ["k"], [F.col("o")], F.col("p"), separator, most, one).collect()}
        assert {k: t[:most] for k, t in got.items()} == {k: t[:most] for k, t in whole.items()}


def test_no_whole_text_is_gathered(spark):
    plan = core.rel_large_sizes(spark, SF)._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("_last") >= len(W._JOINED)
