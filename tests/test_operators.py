import pytest
from pyspark.sql import Window
from pyspark.sql import functions as F

from dictparse import measures
from dictparse.functions import columns as C
from dictparse.functions import udfs
from dictparse.kernels.parse import Parse
from dictparse.operators import decode as D
from dictparse.operators.factorize import factor_counts, factorize, parse_many
from dictparse.plans.spec import ParseSpec, named
from dictparse.sources import io
from dictparse.sources import workloads as W
from dictparse.streaming import online
from tests.conftest import SF

TEXTS = [(1, "aabbaabbbaabbbbbababaabccccbababc"), (2, ""), (3, None), (4, "a"), (5, "é😀é😀é\n\0"), (6, "aabbaabbbaabbbbbababaabccccbababc")]


@pytest.fixture(scope="module")
def rows(spark):
    return spark.createDataFrame([(i, t, "x", 7) for i, t in TEXTS], "id long, text string, kind string, len int")


def test_edge_texts(rows):
    f = factorize(rows, "text", ["id"], scheme="pair_cut", keep_text=True)
    got = {r.id: r.n for r in f.groupBy("id").agg(F.count("*").alias("n")).collect()}
    assert got == {1: 11, 4: 1, 5: len(Parse(TEXTS[4][1], "pair_cut").phrases), 6: 11}
    counts = {r.id: r.z for r in factor_counts(rows, "text", ["id"], schemes=["pair_cut"]).collect()}
    assert counts == got | {2: 0}


@pytest.mark.parametrize("name", ["pair", "pair_cut", "pair_run", "step", "seeded", "step_run", "pair_run+flex_fixed", "pair_run+flex_own", "pair_run+flex_longest", "seeded+flex_longest"])
def test_decoding(rows, name):
    spec = named(name)
    f = factorize(rows, "text", ["id"], scheme=spec.scheme, lookahead=spec.lookahead, roles=True)
    assert {r.id: r.text for r in D.decode(f, ["id"]).collect()} == {i: t for i, t in TEXTS if t}


def test_blocks(rows):
    f = factorize(rows, "text", ["id"], scheme="pair_run", block_symbols=10, roles=True)
    back = D.joined_blocks(D.decode(f, ["id"]), ["id"])
    assert {r.id: r.text for r in back.collect()} == {i: t for i, t in TEXTS if t}
    assert f.where("id = 1").agg(F.max("block_id")).first()[0] == 3


def test_bytes_and_empty_tables(spark, rows):
    counts = factor_counts(rows, "text", ["id"], schemes=["step"], symbols="byte")
    assert {r.id: r.n for r in counts.collect()}[5] == len(TEXTS[4][1].encode())
    assert factorize(rows.where("false"), "text", ["id"], scheme="pair").count() == 0


def test_spec_is_validated():
    for bad in ({"scheme": "none"}, {"scheme": "pair", "lookahead": "x"}, {"scheme": "pair", "children": "ternary"}):
        with pytest.raises(ValueError):
            ParseSpec(**bad)


def test_texts_over_a_limit_are_given_up(rows):
    counts = factor_counts(rows, "text", ["id"], schemes=["pair", "step"], stop_above=5)
    assert {(r.id, r.scheme): r.z for r in counts.where("id IN (1, 4)").collect()} == {(1, "pair"): None, (1, "step"): None, (4, "pair"): 1, (4, "step"): 1}


def test_scan_reads_two_columns(spark):
    docs = io.load(spark, SF, "documents")
    plan = factor_counts(docs, "text", ["doc_id"], schemes=["pair"], where="lang = 'en'", reuse_equal_texts=False)._jdf.queryExecution().toString()
    scan = [line for line in plan.splitlines() if "ReadSchema" in line][-1]
    assert "source" not in scan.split("ReadSchema")[1] and "EqualTo(lang,en)" in scan


def test_collage_gives_the_text(spark, rows):
    f = factorize(rows.where("id = 1"), "text", ["id"], scheme="pair_run")
    out = D.collage(f, ["id"]).orderBy("x", "k").collect()
    assert D.evaluate_collage([(r.x, r.form, r.a, r.b, r.len) for r in out]) == TEXTS[0][1]
    z = f.count()
    assert D.collage_size(f, ["id"]).first()["size"] <= 4 * z
    assert D.evaluate_collage([(1, "concat", "s:a", "s:b", 2), (2, "prefix_cut", "f:1", None, 1)]) == "abb"


def test_measures(spark):
    counts = spark.createDataFrame([(1, "pair", 100), (1, "pair_cut", 97), (1, "step", 150), (2, "pair", 10), (2, "pair_cut", 10), (2, "step", 12)], "id int, scheme string, z long")
    rel = {r.id: (float(r.pair_cut), float(r.step)) for r in measures.relative(counts, ["id"], ["pair", "pair_cut", "step"]).collect()}
    assert rel == {1: (-3.0, 50.0), 2: (0.0, 20.0)}
    assert {(r.id, r.scheme) for r in measures.winners(counts, ["id"]).collect()} == {(1, "pair_cut"), (2, "pair"), (2, "pair_cut")}
    assert {r.scheme: r.wins for r in measures.win_table(counts, ["id"]).collect()} == {"pair": 1, "pair_cut": 2}
    line = spark.createDataFrame([("a", n, 2.0 * n + 1) for n in range(5)], "s string, n int, seconds double")
    assert abs(measures.linearity(line, ["s"]).first()["slope"] - 2) < 1e-9


def test_functions(spark):
    udfs.register(spark)
    C.sql_functions(spark)
    r = spark.sql("SELECT power_prefix('ab', 5) AS p, is_prefix('a', 'ab') AS q, parse_count_pair_run('aaaa') AS z, size(parse_list_step('abab')) AS s, lce('babababb', 2, 4) AS e").first()
    assert tuple(r) == ("ababa", True, 1, 3, 4)
    spark.createDataFrame([(1, 1, "aab"), (1, 2, "baab"), (2, 1, "cc")], "k int, turn int, piece string").createOrReplaceTempView("_fragments")
    rows = spark.sql("SELECT x, piece FROM factors_of_group(TABLE(SELECT k, turn, piece AS fragment, 'pair_cut' AS scheme FROM _fragments) PARTITION BY k ORDER BY turn)").collect()
    expected = [(x, t[f[0] : f[0] + f[1]]) for t in ("aabbaab", "cc") for x, f in enumerate(Parse(t, "pair_cut").phrases, 1)]
    assert sorted(tuple(r) for r in rows) == sorted(expected)


def test_sinks(spark, rows, tmp_path):
    f = parse_many(rows, "text", ["id"], ["pair", "step"])
    io.write_factors(f, str(tmp_path / "factors"), ["id"])
    assert spark.read.parquet(str(tmp_path / "factors")).groupBy("scheme").count().count() == 2
    (tmp_path / "t").mkdir()
    (tmp_path / "t" / "a.txt").write_bytes("é\n".encode())
    assert io.read_texts(spark, str(tmp_path / "t")).first().text == "é\n"
    assert len(io.read_bytes(spark, str(tmp_path / "t")).first().text) == 3


def test_stream_is_independent_of_batches(spark, tmp_path):
    events = io.load(spark, SF, "events")
    for k in range(4):  # files in time order, with neighbours swapped over a few minutes
        at = F.percent_rank().over(Window.orderBy(F.xxhash64("event_id") % 120 + F.unix_timestamp("ts")))
        events.withColumn("_p", at).where(f"_p >= {k} / 4 AND (_p < {k + 1} / 4 OR {k} = 3)").drop("_p").coalesce(1).write.mode("append").parquet(str(tmp_path / "events"))
    stream = io.stream_events(spark, str(tmp_path / "events"))
    out = online.factors_of_stream(stream, "user_id", "ts", "event_id", F.substring("event_type", 1, 1))
    got = online.settled(online.run_to_table(out, checkpoint=str(tmp_path / "c")))
    expected = factorize(W.event_types(spark, SF), "text", ["id"], scheme="pair_cut")
    assert sorted((r.key, r.x, r.len) for r in got.collect()) == sorted((r.id, r.x, r.len) for r in expected.collect())


def test_stream_blocks(spark):
    stream = io.stream_events(spark, f"{SF}/events.parquet")
    out = online.factors_of_stream(stream, "user_id", "ts", "event_id", F.substring("event_type", 1, 1), block_symbols=10)
    got = online.settled(online.run_to_table(out))
    sums = got.groupBy("key").agg(F.sum("len").alias("n"), F.max("block_id").alias("b")).collect()
    sizes = {r.id: len(r.text) for r in W.event_types(spark, SF).collect()}
    assert {r.key: r.n for r in sums} == sizes and max(r.b for r in sums) > 0


def test_flagship_on_a_small_table(spark, tmp_path):
    from dictparse.queries import flagship
    from tests.test_kernels import plain

    docs = spark.read.parquet(f"{SF}/documents.parquet").where("length(text) BETWEEN 50 AND 900").orderBy("doc_id").limit(25)
    docs.coalesce(1).write.parquet(str(tmp_path / "documents.parquet"))
    total = {}
    for r in docs.collect():
        for scheme in ("pair", "pair_cut", "pair_run", "step"):
            total[r.lang, scheme] = total.get((r.lang, scheme), 0) + len(plain(r.text, scheme))
    for r in flagship(spark, str(tmp_path)).collect():
        for scheme in ("pair_cut", "pair_run", "step"):
            assert abs(float(r[scheme]) - (total[r.lang, scheme] / total[r.lang, "pair"] - 1) * 100) < 1e-3


def test_more_measures(spark):
    counts = spark.createDataFrame([(k, s, z) for k in range(40) for s, z in (("pair", 100), ("pair_cut", 90 + k % 3))], "id int, scheme string, z long")
    rel = measures.relative(counts, ["id"], ["pair", "pair_cut"])
    r = measures.improvement(rel, ["pair_cut"]).first()
    assert r.best == -10 and -10 < r["mean"] < -8
    few = measures.sampled(counts.where("scheme = 'pair'"), "id", 4)
    assert 0 < few.count() < 40 and few.exceptAll(measures.sampled(counts.where("scheme = 'pair'"), "id", 4)).isEmpty()
    e = measures.estimate(rel, "pair_cut").first()
    assert e.low < e["mean"] < e.high and e.texts == 40
    bits = spark.createDataFrame([("step", 120, 30)], "scheme string, bits long, symbols long")
    assert measures.compression_ratio(bits).first().ratio_e4 == 5000
    line = spark.createDataFrame([(1, float(k), 3.0 * k + 2) for k in range(6)], "g int, x double, y double")
    assert abs(line.groupBy("g").agg(udfs.linear_slope("x", "y").alias("s")).first().s - 3) < 1e-9


def _events(spark, tmp_path, parts):
    """A stream that reads one file of rows in each micro-batch."""
    schema = "event_id long, ts timestamp, user_id long, event_type string"
    for k, rows in enumerate(parts):
        spark.createDataFrame(rows, schema).coalesce(1).write.parquet(str(tmp_path / "in" / f"part={k}"))
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in" / "part=*"))


def _at(minute):
    import datetime

    return datetime.datetime(2024, 1, 1) + datetime.timedelta(minutes=minute)


def test_stream_dedup_and_joins(spark, tmp_path):
    rows = [[(1, _at(0), 7, "view"), (1, _at(1), 7, "view"), (2, _at(2), 8, "cart")], [(2, _at(3), 8, "cart"), (3, _at(4), 7, "buy")]]
    stream = _events(spark, tmp_path, rows)
    assert sorted(r.event_id for r in online.run_to_table(online.deduplicated(stream)).collect()) == [1, 2, 3]
    users = spark.createDataFrame([(7, "x")], "user_id long, name string")
    assert sorted(r.event_id for r in online.run_to_table(online.with_static(stream, users, ["user_id"])).collect()) == [1, 1, 3]
    pairs = online.run_to_table(online.near_in_time(stream.where("event_type = 'view'"), stream.where("event_type = 'buy'"), "user_id")).collect()
    assert sorted(map(tuple, pairs)) == [(7, 1, 3), (7, 1, 3)]


def test_upsert_can_run_again(spark, tmp_path):
    put = online.upsert(str(tmp_path / "t"), ["k"], ["at"])
    rows = lambda *r: spark.createDataFrame([*r], "k long, v string, at long")
    put(rows((1, "a", 1), (1, "b", 3), (2, "c", 1)), 0)
    put(rows((1, "late", 2), (2, "d", 5), (3, None, 1)), 1)
    put(rows((1, "late", 2), (2, "d", 5), (3, None, 1)), 1)  # again
    assert sorted((r.k, r.v) for r in online.latest(spark, str(tmp_path / "t"), ["k"], ["at"]).collect()) == [(1, "b"), (2, "d"), (3, None)]
    assert spark.read.parquet(str(tmp_path / "t")).count() == 5


def test_a_silent_key_ends(spark, tmp_path):
    parts = [[(k, _at(k), 1, "a" if k % 2 else "b") for k in range(6)], [(10, _at(300), 2, "a")], [(11, _at(900), 2, "b")], [(12, _at(901), 1, "c")], [(13, _at(2000), 2, "b")]]
    stream = _events(spark, tmp_path, parts)
    out = online.factors_of_stream(stream, "user_id", "ts", "event_id", F.col("event_type"), idle_ms=60 * 60 * 1000)
    got = online.run_to_table(out).where("key = 1 AND x > 0 AND final").orderBy("block_id", "x").collect()
    whole = [(f[0] + 1, f[1]) for f in Parse("bababa", "pair_cut").phrases]
    assert [(r.beg, r.len) for r in got if r.block_id == 0] == whole  # its rest became final when it fell silent
    assert [(r.beg, r.len) for r in got if r.block_id == 1] == [(1, 1)]


def test_sources(spark, tmp_path):
    docs = io.load(spark, SF, "nation", ["n_nationkey", "n_name"])
    docs.write.json(str(tmp_path / "n.json"))
    assert sorted(map(str, io.load_any(spark, str(tmp_path / "n.json"), "json", "n_nationkey long, n_name string").select("n_nationkey", "n_name").collect())) == sorted(map(str, docs.collect()))
    io.register(spark, SF)
    assert spark.table("nation").count() == docs.count()
    assert W.by_source(spark, SF).agg(F.sum(F.length("text"))).first()[0] == W.documents(spark, SF).agg(F.sum(F.length("text"))).first()[0]
