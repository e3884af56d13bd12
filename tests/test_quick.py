"""The quick parses are those of the reference, and texts go through their factors and back where they stand."""

import random

import pytest
from pyspark.sql import functions as F

from dictparse import queries as core
from dictparse.kernels import quick
from dictparse.kernels.parse import Parse
from dictparse.kernels.tokens import decode
from dictparse.operators.factorize import factor_counts, round_trip
from tests.conftest import SF

CHECKED = ["pair", "pair_cut", "pair_run", "step", "seeded", "step_run", *core.FLEX.values()]
RANDOM = random.Random(5)
TEXTS = ["", "a", "é😀é😀é\n\0", *("a" * k for k in range(2, 20)), *("".join(RANDOM.choice("ab" if k % 2 else "abcd") for _ in range(RANDOM.randint(1, 60))) * RANDOM.choice([1, 1, 3]) for k in range(200))]


@pytest.mark.parametrize("name", CHECKED)
def test_quick_parses_are_the_reference_ones(name):
    scheme, _, look = name.partition("+")
    for text in TEXTS:
        p = Parse(text, scheme, look or "none")
        assert quick.parsed(text, scheme, look or "none") == (p.phrases, p.entries)
        assert decode(p.phrases, p.entries, scheme) == text


def test_quick_look_ahead_counts(spark):
    rows = spark.createDataFrame([*enumerate(TEXTS)], "id int, text string")
    for name in core.FLEX.values():
        scheme, _, look = name.partition("+")
        for r in factor_counts(rows, "text", ["id"], schemes=[name]).collect():
            p = Parse(TEXTS[r.id], scheme, look)
            kinds = [f[2] for f in p.phrases]
            assert (r.z, r.combine_n, r.cut_n, r.repeat_n, r.trie_nodes, r.split_nodes) == (len(kinds), *(kinds.count(k) for k in ("combine", "cut", "repeat")), p.rules.trie.nodes, p.rules.trie.split_nodes)


@pytest.mark.parametrize("name", CHECKED)
def test_no_factor_leaves_its_task(agree, spark, name):
    query = f"decode_check_{core.measures.column_name(name)}"
    plan = core.QUERIES[query](spark, SF)._jdf.queryExecution().executedPlan().toString()
    # factor rows were once shuffled and grouped for the decoder
    assert "FlatMapGroupsInArrow" not in plan and plan.count("MapInArrow") == 1
    agree(core.QUERIES[query], core.SQL[query])


def test_round_trip_of_odd_texts(spark):
    rows = spark.createDataFrame([(k, t) for k, t in enumerate([None, *TEXTS, TEXTS[2]])], "id int, text string")
    want = {r.id: (r.n, r.m) for r in rows.where("length(text) > 0").select("id", F.length("text").alias("n"), F.md5("text").alias("m")).collect()}
    assert {r.id: (r.n, r.md5) for r in round_trip(rows, "text", ["id"], "pair_run+flex_own").collect()} == want
