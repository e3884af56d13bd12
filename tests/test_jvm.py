"""The compiled parses are the quick ones, and no text is shuffled for a round trip."""

import pytest
from pyspark.sql import functions as F

from dictparse import queries as core
from dictparse.kernels import jvm, quick
from dictparse.operators.factorize import factor_counts, joined_counts, round_trip
from dictparse.sources import workloads as W
from tests.conftest import SF
from tests.test_quick import CHECKED, TEXTS

KINDS = ("combine", "cut", "repeat", "extend", "entry")


def _numbers(factors):
    none = lambda v: -1 if v is None else v
    sym = lambda v: -1 if v is None else ord(v)
    return "".join(f"{b} {n} {KINDS.index(k)} {none(r1)} {sym(s1)} {none(r2)} {sym(s2)} {none(p)} " for b, n, k, r1, s1, r2, s2, p in factors)


@pytest.mark.parametrize("name", CHECKED)
def test_compiled_parses_are_the_quick_ones(spark, name):
    scheme, _, look = name.partition("+")
    rows = spark.createDataFrame([*enumerate(TEXTS)], "id int, text string")
    made = [jvm.function(spark, what, F.col("text"), scheme, look or "none").alias(what) for what in ("Written", "Back")]
    for r in rows.select("id", *made).collect():
        phrases, entries = quick.parsed(TEXTS[r.id], scheme, look or "none")
        assert r.Written == f"{_numbers(phrases)};{_numbers(entries or [])}" and r.Back == TEXTS[r.id]


def test_compiled_counts(spark):
    rows = spark.createDataFrame([*enumerate([*TEXTS, None])], "id int, text string")
    columns = ["id", "block_id", "scheme", "n", "sigma", "z", "combine_n", "cut_n", "repeat_n", "trie_nodes", "split_nodes"]
    both = [factor_counts(rows, "text", ["id"], schemes=CHECKED, reuse_equal_texts=False, **more) for more in ({}, {"engine": "jvm"}, {"engine": "jvm", "apart": True})]
    assert both[0].dtypes == both[1].dtypes == both[2].dtypes
    there, here, apart = ({(r.id, r.scheme): r for r in d.select(*columns).collect()} for d in both)
    # a parse by step or seeded takes no dictionary when counted
    assert there == here == apart and len(there) == len(TEXTS) * len(CHECKED)


def test_tallies_are_the_compiled_counts(spark):
    rows = spark.createDataFrame([(str(k), 0, t) for k, t in enumerate(TEXTS)], "name string, place int, piece string")
    columns = ["name", "scheme", "n", "sigma", "z", "combine_n", "cut_n", "repeat_n", "trie_nodes", "split_nodes"]
    both = [factor_counts(rows, "piece", ["name"], schemes=CHECKED, engine="jvm"), joined_counts([(rows, "")], CHECKED)]
    there, tallied = (sorted(d.select(*columns).collect()) for d in both)
    assert there == tallied and len(there) == len(TEXTS) * len(CHECKED)


def test_a_round_trip_shuffles_no_text(spark):
    rows = spark.range(64, numPartitions=16).select(F.col("id").cast("string").alias("id"), F.repeat(F.lit("ab"), 5).alias("text"))
    # copies were once gathered by their hashes
    back = round_trip(rows, "text", ["id"], "step")
    assert "Exchange" not in back._jdf.queryExecution().executedPlan().toString() and back.count() == 64


def test_large_texts_take_no_python_stage(spark):
    for query in (core.rel_large, core.rel_large_flex, core.flex_bound):
        assert "MapInArrow" not in query(spark, SF)._jdf.queryExecution().executedPlan().toString()


JOINED = ("markup", "languages", "event_values", "flags", "quantities", "records")


def test_large_texts_are_no_rows(spark):
    # each large text was once gathered as an array of its pieces, joined to one string and dealt out for each scheme
    for query in (core.rel_large, core.rel_large_flex):
        plan = query(spark, SF)._jdf.queryExecution().optimizedPlan().toString()
        assert "collect_list" not in plan and "array_join" not in plan


def test_counts_of_pieces_are_those_of_the_texts(spark):
    schemes = ["pair_run", "step", "seeded+flex_fixed"]
    texts = W.catalog(spark, SF, [*JOINED]).withColumn("name", F.concat_ws(":", "corpus", "id"))
    columns = ["name", "scheme", "n", "sigma", "z", "combine_n", "cut_n", "repeat_n", "trie_nodes", "split_nodes"]
    whole = factor_counts(texts, "text", ["name"], schemes=schemes, reuse_equal_texts=False).select(*columns)
    apart = joined_counts(W.catalog_pieces(spark, SF, [*JOINED]), schemes)
    assert whole.dtypes == apart.select(*columns).dtypes
    assert sorted(whole.collect()) == sorted(apart.select(*columns).collect())


def test_counts_of_odd_pieces(spark):
    pieces = [("a", 1, ""), ("a", 2, None), ("a", 2, "ab"), ("a", None, "xyab"), ("a", 5, "cdé\U0001f600ab"), ("a", 5, "ab"), ("b", 1, None), ("c", 3, ""), ("d", 1, "zz"), ("d", 0, "z")]
    # more kinds of symbols than one byte, and than two, can number
    pieces += [("e", k, chr(0x4E00 + k % 300) * 3) for k in range(900)] + [("f", k, "".join(map(chr, range(0x10000 + 700 * k, 0x10000 + 700 * k + 1400)))) for k in range(100)]
    rows = spark.createDataFrame(pieces, "name string, o int, piece string").repartition(3)
    order, schemes = [F.col("o")], ["pair_cut", "step", "pair_run+flex_own"]
    columns = ["name", "scheme", "n", "sigma", "z", "combine_n", "cut_n", "repeat_n", "trie_nodes", "split_nodes"]
    for separator in ("", "\n"):
        whole = factor_counts(W.concatenated(rows, ["name"], order, F.col("piece"), separator), "text", ["name"], schemes=schemes, reuse_equal_texts=False)
        parts = joined_counts([(W.placed(rows, ["name"], order, F.col("piece"), separator), separator)], schemes)
        assert sorted(parts.select(*columns).collect()) == sorted(whole.select(*columns).collect())
