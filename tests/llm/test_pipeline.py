from collections import Counter

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from dictparse.llm.queries import QUERIES, SQL
from tests.conftest import SF


@pytest.mark.parametrize("name", sorted(SQL))
def test_query_agrees_with_its_sql(agree, name):
    agree(QUERIES[name], SQL[name])


def test_ten_queries():
    assert sorted(int(n[2:].split("_")[0]) for n in QUERIES) == [*range(1, 11)]


def test_stages(spark, tmp_path):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns, sizes = docs.columns, [docs.count()]
    for name, stage in corpus_pipeline.STAGES:
        stage(spark, docs, SF).write.parquet(str(tmp_path / name))
        docs = spark.read.parquet(str(tmp_path / name))
        if name != "packing":
            assert docs.columns == columns
            assert docs.where(F.col("n_chars") != F.length("text")).count() == 0
            sizes.append(docs.count())
    assert sizes == sorted(sizes, reverse=True) and sizes[-1] < sizes[0]
    whole = corpus_pipeline.run(spark, SF).select("doc_id", "piece", "length", "ids_crc32")
    assert sorted(map(tuple, whole.collect())) == sorted(map(tuple, docs.select("doc_id", "piece", "length", "ids_crc32").collect()))


@pytest.fixture(scope="module")
def odd_folder(spark, tmp_path_factory):
    """Documents with nulls in every column, empty and long texts, repeated rows and ids, and further columns with names used inside."""
    folder = tmp_path_factory.mktemp("odd")
    base = "a plain text about rivers and bridges in the old town " * 3
    rows = [(1, base, "en", "a", 1), (1, base, "en", "a", 1), (2, base + "end", None, None, None), (3, None, None, None, None), (4, "", "en", "a", 0), (None, base, "de", "b", 5), (None, None, None, None, None)]
    rows += [(k, f"a line that stands in all of these documents\nand own words {k} " + " ".join(f"w{k}x{j}" for j in range(40)), "en", "c", 7) for k in range(10, 16)]
    rows += [(20, "x" * 300_000, "en", "c", 7), (21, " \n\t\n", "en", "c", 7), (22, "idiot " * 5000, "en", "c", 7)]
    wide = "doc_id long, text string, lang string, source string, n_chars long, _own int, _kept int, _Score int, _doc int, rows int, _spans int, id int, `class` int"
    spark.createDataFrame([(*r, 1, 2, 3, 4, 5, 6, 7, 8) for r in rows], wide).coalesce(1).write.parquet(str(folder / "documents.parquet"))
    spark.createDataFrame([(1, 0, 1), (22, 1, None), (None, 1, 1), (10, None, 1)], "doc_id long, toxic int, quality int").write.parquet(str(folder / "labels.parquet"))
    spark.createDataFrame([("q1", "and own words 12 w12x0 w12x1 w12x2 w12x3 w12x4 w12x5 w12x6 w12x7", "t"), ("q2", None, None), (None, "never seen words", "t")], "item_id string, text string, task string").write.parquet(str(folder / "benchmark.parquet"))
    return str(folder)


def test_stages_on_odd_rows(spark, odd_folder):
    docs = spark.read.parquet(f"{odd_folder}/documents.parquet")
    kept = {}
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, odd_folder)
        assert out.columns == docs.columns
        kept[name] = out.collect()
        assert all(tuple(r)[5:] == (1, 2, 3, 4, 5, 6, 7, 8) for r in kept[name])
    assert Counter(r.doc_id for r in kept["line_dedup"]) == Counter(r.doc_id for r in docs.collect())
    lines = {r.doc_id: r.text for r in kept["line_dedup"] if r.doc_id in range(10, 16)}
    assert [k for k, t in lines.items() if t.startswith("a line")] == [15]
    # one row of an id; 1, 2 and the rows without id are one group, of which the missing id is the smallest
    assert sorted(-1 if r.doc_id is None else r.doc_id for r in kept["near_dedup"]) == [-1, 3, 4, *range(10, 16), 20, 21, 22]
    assert 12 not in {r.doc_id for r in kept["decontamination"]} and len(kept["decontamination"]) == docs.count() - 1
    packed = corpus_pipeline.STAGES[-1][1](spark, docs, odd_folder).collect()
    assert {r.doc_id for r in packed} == {r.doc_id for r in docs.collect()} and all(0 < r.length <= 1024 for r in packed)
    assert corpus_pipeline.run(spark, odd_folder).count() > 0


def test_stages_on_empty_tables(spark, odd_folder, tmp_path):
    for t in ("documents", "labels", "benchmark"):
        spark.read.parquet(f"{odd_folder}/{t}.parquet").where("false").write.parquet(str(tmp_path / f"{t}.parquet"))
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0
