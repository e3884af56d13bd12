"""The registered queries of the parsing engine, with their SQL. Every query reads whole tables and whole texts."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from dictparse import measures
from dictparse.functions import columns as C
from dictparse.functions import udfs
from dictparse.operators import decode as D
from dictparse.operators.engines import cut_lineage
from dictparse.operators.factorize import factor_counts, factorize, joined_counts, parse_many, round_trip
from dictparse.plans import oracles as O
from dictparse.sources import workloads as W
from dictparse.sources.family_source import FamilySource
from dictparse.sources.io import load, stream_events
from dictparse.streaming import online

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}

SHORT = {"pair": "pair", "pair_cut": "cut", "pair_run": "run", "step": "step", "seeded": "seeded", "step_run": "step_run"}
FLEX = {
    "flex_fixed": "pair_run+flex_fixed", "flex_longest": "pair_run+flex_longest", "flex_own": "pair_run+flex_own", "cut_flex_fixed": "pair_cut+flex_fixed",
    "cut_flex_own": "pair_cut+flex_own", "cut_flex_longest": "pair_cut+flex_longest", "seeded_flex_fixed": "seeded+flex_fixed", "seeded_flex_longest": "seeded+flex_longest",
}
#: Whole-table text sets with SQL that gives the same texts: key column, Spark side, DuckDB side.
SETS: dict[str, tuple[str, Query, str]] = {
    "": ("item_id", W.items, "SELECT item_id AS id, text AS t FROM benchmark"),
    "user_": ("user_id", W.event_types, "SELECT user_id AS id, string_agg(left(event_type, 1), '' ORDER BY ts, event_id) AS t FROM events GROUP BY user_id"),
    "part_": ("p_partkey", W.part_names, "SELECT p_partkey AS id, p_name AS t FROM part"),
}


def add(name: str, sql: str | None = None):
    def put(f: Query) -> Query:
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return put


def _with(parses: dict[str, str], source: str, tail: str) -> str:
    """SQL: the named parses of a text set, then a query over them."""
    return f"WITH RECURSIVE {', '.join(O.parse(full, source, name) for name, full in parses.items())} {tail}"


def _parsed(prefix: str, full: str, **options) -> Query:
    key, texts, _ = SETS[prefix]
    scheme, _, look = full.partition("+")
    return lambda spark, sf: factorize(texts(spark, sf), "text", ["id"], scheme=scheme, lookahead=look or "none", keep_text=True, reuse_equal_texts=False, **options).withColumnRenamed("id", key)


# ---- factors of every scheme and look-ahead, against brute force

for _prefix, (_key, _, _source) in SETS.items():
    for _full, _short in SHORT.items():
        _cols = ["x", "beg", "len", "kind", "piece"]
        add(f"{_prefix}{_short}_factors", _with({"f": _full}, _source, f"SELECT id AS {_key}, {', '.join(_cols)} FROM f"))(lambda spark, sf, q=_parsed(_prefix, _full), k=_key, c=_cols: q(spark, sf).select(k, *c))
    for _short, _full in FLEX.items():
        _cols = ["x", "beg", "len", "piece"]
        add(f"{_prefix}{_short}_factors", _with({"f": _full}, _source, f"SELECT id AS {_key}, {', '.join(_cols)} FROM f"))(lambda spark, sf, q=_parsed(_prefix, _full), k=_key, c=_cols: q(spark, sf).select(k, *c))
for _full in ("pair", "pair_cut", "pair_run", "step", "seeded"):
    _cols = ["x", "kind", "ref1", "sym1", "ref2", "sym2", "len", "power"]
    add(f"{SHORT[_full]}_tokens", _with({"f": _full}, SETS[""][2], f"SELECT id AS item_id, {', '.join(_cols)} FROM f"))(lambda spark, sf, q=_parsed("", _full), c=_cols: q(spark, sf).select("item_id", *c))


@add("flex_longest_entries", _with({"f": "pair_run+flex_longest"}, SETS[""][2], "SELECT id AS item_id, x, len, entry_len FROM f"))
def flex_longest_entries(spark, sf):
    """Chosen phrases beside the longest factors that went into the dictionary at the same places."""
    rows = factorize(W.items(spark, sf), "text", ["id"], scheme="pair_run", lookahead="flex_longest", roles=True, reuse_equal_texts=False)
    pick = lambda r, c: F.max(F.when(F.col("role") == r, F.col("len"))).alias(c)
    return rows.groupBy(F.col("id").alias("item_id"), "x").agg(pick("phrase", "len"), pick("entry", "entry_len"))


# ---- worked examples and generated families: printed answers


def _values(rows: list[tuple], names: list[str], kinds: list[str]) -> str:
    show = lambda v: "NULL" if v is None else str(v) if isinstance(v, int) else "'" + v + "'"
    body = ", ".join("(" + ", ".join(show(v) for v in r) + ")" for r in rows)
    return f"SELECT {', '.join(f'CAST({n} AS {k}) AS {n}' for n, k in zip(names, kinds, strict=True))} FROM (VALUES {body}) v({', '.join(names)})"


def _token_text():
    return C.token_text(*(F.col(c) for c in ("kind", "ref1", "sym1", "ref2", "sym2", "len", "power"))).alias("token")


def _example(text: str, full: str) -> Query:
    scheme, _, look = full.partition("+")

    def run(spark, sf):
        rows = factorize(spark.createDataFrame([(1, text)], "id int, text string"), "text", ["id"], scheme=scheme, lookahead=look or "none", keep_text=True)
        return rows.select("x", "piece", _token_text())

    return run


#: The printed parses of the worked examples, as pieces and tokens.
_PRINTED = {
    "example_run": (W.EXAMPLE, "pair_run", "aa bb aabb baabb bbba ba baab cccc babab c", "''a''+''a''|2 ''b''+''b''|2 #1+#2|4 ''b''+#3|5 #2+#4|4 ''b''+''a''|2 #4|4 ''c''^4|4 #6^3|5 ''c''+0|1"),
    "example_look_greedy": (W.LOOKAHEAD_EXAMPLE, "pair_run", "aaa ba baaaa aa baaa b", "''a''^3|3 ''b''+''a''|2 #2+#1|5 ''a''+''a''|2 #2+#4|4 ''b''+0|1"),
    "example_flex_own": (W.LOOKAHEAD_EXAMPLE, "pair_run+flex_own", "aaa ba baaa aaabaaa b", "''a''^3|3 ''b''+''a''|2 #2+#1|4 #1+#3|7 ''b''+0|1"),
    "example_flex_longest": (W.LOOKAHEAD_EXAMPLE, "pair_run+flex_longest", "aaa ba baaa aaab aaab", "''a''^3|3 ''b''+''a''|2 #2+#1|4 #1+#2|4 #1+''b''|4"),
}
for _name, (_text, _full, _pieces, _tokens) in _PRINTED.items():
    add(_name, _values([(k, p, t) for k, (p, t) in enumerate(zip(_pieces.split(), _tokens.split(), strict=True), 1)], ["x", "piece", "token"], ["INTEGER", "VARCHAR", "VARCHAR"]))(_example(_text, _full))


_PART = "CASE WHEN {s} IS NOT NULL THEN '''' || {s} || '''' WHEN {r} > 0 THEN '#' || {r} ELSE '0' END"
_ONE, _TWO_PARTS = _PART.format(s="sym1", r="ref1"), _PART.format(s="sym2", r="ref2")


@add("example_cut", _with({"f": "pair_cut"}, SETS["user_"][2], f"SELECT id AS user_id, x, piece, {_ONE} || CASE WHEN kind = 'combine' THEN '+' || {_TWO_PARTS} ELSE '' END || '|' || len AS token FROM f"))
def example_cut(spark, sf):
    """Written tokens of each user's event types; the worked example's own are a test of the kernels."""
    return _parsed("user_", "pair_cut")(spark, sf).select("user_id", "x", "piece", _token_text())


def _look_ahead_tokens(source: str) -> str:
    """SQL: at each chosen place the longest factor over the greedy entries that end before it, cut to the chosen length."""
    places = f"places AS (SELECT c.id, c.x, c.beg AS pos, c.len AS chosen, t, length(t) AS n, list_transform(list_filter(coalesce(es, []), lambda e: e.stop <= c.beg), lambda e: e.s) AS ds FROM f c JOIN ({source}) USING (id) LEFT JOIN f_entries USING (id))"
    repeated = "CAST(ceil(chosen / (CASE WHEN sym1 IS NULL THEN b1 ELSE 1 END)) AS INTEGER)"
    body = f"CASE WHEN kind = 'combine' THEN {_ONE} || '+' || {_TWO_PARTS} WHEN kind = 'repeat' AND (sym1 IS NOT NULL OR {repeated} > 1) THEN {_ONE} || '^' || {repeated} ELSE {_ONE} END"
    return _with({"f": "pair_run+flex_fixed"}, source, f", {places} SELECT id AS user_id, x, substr(t, pos, chosen) AS piece, {body} || '|' || chosen AS token FROM ({O._step_sql('pair_run', 'places')})")


@add("example_flex_fixed", _look_ahead_tokens(SETS["user_"][2]))
def example_flex_fixed(spark, sf):
    """Written tokens of the look-ahead parse of each user's event types; the worked example's own are a test of the kernels."""
    return _parsed("user_", "pair_run+flex_fixed")(spark, sf).select("user_id", "x", "piece", _token_text())


@add("lce_example", "SELECT 4 AS direct, 4 AS by_udf, 3 AS bounded, 0 AS outside")
def lce_example(spark, sf):
    rows = spark.createDataFrame([(W.EXTENSION_EXAMPLE,)], "t string")
    at = lambda k: F.lit(k)
    return rows.select(C.lce(F.col("t"), at(2), at(4)).alias("direct"), udfs.lce_udf("t", at(2), at(4)).alias("by_udf"), C.bounded_lce(F.col("t"), at(2), at(4), at(3)).alias("bounded"), C.lce(F.col("t"), at(9), at(1)).alias("outside"))


#: The printed counts of the four-letter family (k; pair; pair_cut; pair_run).
_FAMILY = [(4, 24, 24, 24), (8, 56, 56, 51), (16, 144, 144, 99), (32, 416, 416, 195), (64, 1344, 1344, 387), (128, 4736, 4736, 771), (256, 17664, 17664, 1539)]


@add("family_counts", _values([(*r, 6 * r[0] + 3, 5 * r[0] + r[0] * r[0] // 4) for r in _FAMILY], ["k", "pair", "pair_cut", "pair_run", "linear", "quadratic"], ["INTEGER", *["BIGINT"] * 5]))
def family_counts(spark, sf):
    """The family on which only powers keep the count linear."""
    counts = factor_counts(W.family(spark, [r[0] for r in _FAMILY]), "text", ["id"], schemes=["pair", "pair_cut", "pair_run"])
    return measures.family_table(counts).withColumnRenamed("id", "k")


@add("family_source_counts", _values([(k, z) for k, _, _, z in _FAMILY[:4]], ["k", "z"], ["INTEGER", "BIGINT"]))
def family_source_counts(spark, sf):
    """The same texts from the data source."""
    spark.dataSource.register(FamilySource)
    rows = spark.read.format("text_family").option("ks", "4,8,16,32").load()
    return factor_counts(rows, "text", ["id"], schemes=["pair_run"]).select(F.col("id").alias("k"), "z")


@add("unary_counts", "SELECT CAST(k AS INTEGER) AS k, CAST(k AS BIGINT) AS pair, CAST(1 AS BIGINT) AS pair_run FROM range(1, 11) r(k)")
def unary_counts(spark, sf):
    """Runs of one letter: logarithmic with whole references, one factor with powers."""
    counts = factor_counts(W.unary(spark, [*range(1, 11)]), "text", ["id"], schemes=["pair", "pair_run"])
    return measures.wide(counts, ["id"], ["pair", "pair_run"]).withColumnRenamed("id", "k")


# ---- whole documents: parses decode to the texts they came from, and keep their laws


def _docs(spark, sf):
    return W.documents(spark, sf).withColumnRenamed("id", "doc_id")


def _decoded(texts: Query, key: str, full: str) -> Query:
    return lambda spark, sf: round_trip(texts(spark, sf).withColumnRenamed("id", key), "text", [key], full)


for _full in (*SHORT, *FLEX.values()):
    _tag = measures.column_name(_full)
    add(f"decode_check_{_tag}", "SELECT doc_id, length(text) AS n, md5(text) AS md5 FROM documents WHERE length(text) > 0")(_decoded(W.documents, "doc_id", _full))
for _full in ("pair_cut", "pair_run"):
    add(f"pages_decode_{_full}", "SELECT page_id, length(html) AS n, md5(html) AS md5 FROM pages WHERE length(html) > 0")(_decoded(W.pages, "page_id", _full))
    add(f"conv_decode_{_full}", "SELECT conv_id, length(t) AS n, md5(t) AS md5 FROM (SELECT conv_id, string_agg(text, chr(10) ORDER BY turn) AS t FROM conversations GROUP BY conv_id)")(_decoded(W.conversations, "conv_id", _full))
    add(f"props_decode_{_full}", "SELECT user_id, length(t) AS n, md5(t) AS md5 FROM (SELECT user_id, string_agg(props, '' ORDER BY ts, event_id) AS t FROM events GROUP BY user_id)")(_decoded(W.event_props, "user_id", _full))


def _contiguity(full: str) -> Query:
    def run(spark, sf):
        f = factorize(_docs(spark, sf), "text", ["doc_id"], scheme=full)
        before = F.lag("fin", 1, 0).over(Window.partitionBy("doc_id").orderBy("x"))
        return f.withColumn("_gap", F.col("beg") != before + 1).agg(F.count(F.when(F.col("_gap"), 1)).alias("violations"))

    return run


def _reference_order(full: str) -> Query:
    def run(spark, sf):
        f = factorize(_docs(spark, sf), "text", ["doc_id"], scheme=full)
        return f.agg(F.count(F.when((F.coalesce("ref1", F.lit(0)) >= F.col("x")) | (F.coalesce("ref2", F.lit(0)) >= F.col("x")), 1)).alias("violations"))

    return run


for _full, _short in SHORT.items():
    add(f"contiguity_{_short}", "SELECT CAST(0 AS BIGINT) AS violations")(_contiguity(_full))
    add(f"reference_order_{_short}", "SELECT CAST(0 AS BIGINT) AS violations")(_reference_order(_full))


@add("flex_bound", "SELECT scheme, CAST(0 AS BIGINT) AS violations FROM (VALUES ('pair_cut'), ('pair_run'), ('seeded')) v(scheme)")
def flex_bound(spark, sf):
    """Documents on which the look-ahead over a scheme's own greedy entries needs more factors than the scheme: none may."""
    schemes = ["pair_cut", "pair_run", "seeded"]
    counts = factor_counts(_docs(spark, sf), "text", ["doc_id"], schemes=[*schemes, *(f"{s}+flex_fixed" for s in schemes)], engine="jvm")
    greedy = counts.where(~F.col("scheme").contains("+")).select("doc_id", "scheme", F.col("z").alias("greedy"))
    ahead = counts.where(F.col("scheme").contains("+")).select("doc_id", F.substring_index("scheme", "+", 1).alias("scheme"), "z")
    return greedy.join(ahead, ["doc_id", "scheme"]).groupBy("scheme").agg(F.count(F.when(F.col("z") > F.col("greedy"), 1)).alias("violations"))


@add("work_counters", "SELECT doc_id, true AS steps_ok, true AS nodes_ok FROM documents WHERE text IS NOT NULL")
def work_counters(spark, sf):
    """Child lookups and trie size within their bounds on every document."""
    counts = factor_counts(_docs(spark, sf), "text", ["doc_id"], schemes=["pair_cut"], counters=True)
    return measures.work(counts).select("doc_id", "steps_ok", "nodes_ok")


@add("maximality", "SELECT CAST(0 AS BIGINT) AS violations")
def maximality(spark, sf):
    """pair_cut factors of the items that some rule could make longer, found by comparing all earlier factors."""
    f = _parsed("", "pair_cut")(spark, sf)
    texts = W.items(spark, sf).select(F.col("id").alias("item_id"), "text")
    here = f.join(texts, "item_id").select("item_id", "x", "len", F.expr("substring(text, beg)").alias("rest"))
    earlier = f.select("item_id", F.col("x").alias("y"), F.col("piece").alias("entry"))
    pairs = here.join(earlier, "item_id").where("y < x")
    longest = pairs.groupBy("item_id", "x").agg(F.max(F.when(F.startswith("rest", "entry"), F.length("entry")).otherwise(0)).alias("whole"), F.max(C.common_prefix(F.col("entry"), F.col("rest"))).alias("cut"), F.max("len").alias("len"))
    return longest.agg(F.count(F.when((F.col("cut") > F.col("len")) | (F.col("whole") > F.col("len")), 1)).alias("violations"))


# ---- counts and comparisons of schemes

_SMALL = {"pair": "pair", "cut": "pair_cut", "run": "pair_run", "step": "step", "seeded": "seeded", "flex_fixed": "pair_run+flex_fixed", "flex_own": "pair_run+flex_own", "flex_longest": "pair_run+flex_longest", "seeded_flex_fixed": "seeded+flex_fixed", "seeded_flex_longest": "seeded+flex_longest"}
_CUT_FLEX = {"pair": "pair", "cut": "pair_cut", "cut_flex_fixed": "pair_cut+flex_fixed", "cut_flex_own": "pair_cut+flex_own", "cut_flex_longest": "pair_cut+flex_longest"}


def _counts(spark, sf, prefix: str, schemes) -> DataFrame:
    key, texts, _ = SETS[prefix]
    return factor_counts(texts(spark, sf).withColumnRenamed("id", key), "text", [key], schemes=[*schemes])


def _relative(prefix: str, columns: dict[str, str]) -> Query:
    key = SETS[prefix][0]

    def run(spark, sf):
        table = measures.wide(_counts(spark, sf, prefix, columns.values()), [key], [*columns.values()])
        # ten-thousandths of a percent against pair
        return table.select(key, *(F.expr(f"{measures.column_name(full)} * 1000000 div pair - 1000000").alias(f"{short}_e4") for short, full in columns.items() if full != "pair"))

    return run


def _relative_sql(prefix: str, columns: dict[str, str]) -> str:
    key, _, source = SETS[prefix]
    counts = ", ".join(f"n_{short} AS (SELECT id, count(*) AS z FROM p_{short} GROUP BY id)" for short in columns)
    joins = " ".join(f"JOIN n_{short} USING (id)" for short in columns if short != "pair")
    shown = ", ".join(f"CAST(n_{short}.z * 1000000 // n_pair.z - 1000000 AS BIGINT) AS {short}_e4" for short in columns if short != "pair")
    return _with({f"p_{short}": full for short, full in columns.items()}, source, f", {counts} SELECT id AS {key}, {shown} FROM n_pair {joins}")


add("rel_small", _relative_sql("", _SMALL))(_relative("", _SMALL))
add("rel_users", _relative_sql("user_", _SMALL))(_relative("user_", _SMALL))
add("rel_small_cut_flex", _relative_sql("", _CUT_FLEX))(_relative("", _CUT_FLEX))

_GREEDY = {"pair": "pair", "cut": "pair_cut", "run": "pair_run", "step": "step", "seeded": "seeded"}


def _long_sql(prefix: str, columns: dict[str, str], tail: str) -> str:
    source = SETS[prefix][2]
    union = " UNION ALL ".join(f"SELECT id, '{full}' AS scheme, count(*) AS z FROM p_{short} GROUP BY id" for short, full in columns.items())
    return _with({f"p_{short}": full for short, full in columns.items()}, source, f", counts AS ({union}) {tail}")


_WON = "won AS (SELECT *, rank() OVER (PARTITION BY id ORDER BY z) AS place FROM counts)"


@add("winners_small", _long_sql("", _SMALL, f", {_WON} SELECT id AS item_id, scheme, z FROM won WHERE place = 1"))
def winners_small(spark, sf):
    return measures.winners(_counts(spark, sf, "", _SMALL.values()).select("item_id", "scheme", "z"), ["item_id"])


@add("win_table", _long_sql("", _SMALL, f", {_WON} SELECT scheme, count(*) AS wins FROM won WHERE place = 1 GROUP BY scheme"))
def win_table(spark, sf):
    return measures.win_table(_counts(spark, sf, "", _SMALL.values()), ["item_id"])


@add("improvement", _long_sql("", _GREEDY, ", r AS (SELECT c.id, c.scheme, c.z * 1000000 // p.z - 1000000 AS e4 FROM counts c JOIN counts p ON p.id = c.id AND p.scheme = 'pair' AND c.scheme <> 'pair') SELECT scheme, CAST(sum(e4) AS BIGINT) AS total_e4, CAST(min(e4) AS BIGINT) AS best_e4, CAST(max(e4) AS BIGINT) AS worst_e4, count(*) AS texts FROM r GROUP BY scheme"))
def improvement(spark, sf):
    """Sum, best and worst of each scheme's relative counts."""
    counts = _counts(spark, sf, "", _GREEDY.values()).select("item_id", "scheme", "z")
    base = counts.where("scheme = 'pair'").select("item_id", F.col("z").alias("p"))
    e4 = counts.where("scheme <> 'pair'").join(base, "item_id").withColumn("e4", F.expr("z * 1000000 div p - 1000000"))
    return e4.groupBy("scheme").agg(F.sum("e4").alias("total_e4"), F.min("e4").alias("best_e4"), F.max("e4").alias("worst_e4"), F.count("*").alias("texts"))


@add("step_run_ratio", _with({"a": "step", "b": "step_run"}, SETS[""][2], ", m AS (SELECT id, count(*) AS z FROM a GROUP BY id), n AS (SELECT id, count(*) AS z FROM b GROUP BY id) SELECT id AS item_id, m.z AS step, n.z AS step_run, CAST(n.z * 10000 // m.z AS BIGINT) AS ratio_e2 FROM m JOIN n USING (id)"))
def step_run_ratio(spark, sf):
    table = measures.wide(_counts(spark, sf, "", ["step", "step_run"]), ["item_id"], ["step", "step_run"])
    return table.withColumn("ratio_e2", F.expr("step_run * 10000 div step"))


@add("unpivot_counts", _long_sql("", _GREEDY, "SELECT id AS item_id, scheme, z FROM counts"))
def unpivot_counts(spark, sf):
    """Wide counts turned back into rows."""
    names = [*_GREEDY.values()]
    return measures.wide(_counts(spark, sf, "", names), ["item_id"], names).unpivot(["item_id"], names, "scheme", "z")


@add("scheme_grid", _long_sql("user_", _GREEDY, "SELECT scheme, CAST(sum(z) AS BIGINT) AS z, count(*) AS texts FROM counts GROUP BY scheme"))
def scheme_grid(spark, sf):
    """Every scheme on every text, the grid made by a cross join with the (fixed) list of schemes."""
    grid = spark.createDataFrame([(s,) for s in _GREEDY.values()], "scheme string")
    texts = W.event_types(spark, sf)
    wanted = texts.select("id").crossJoin(F.broadcast(grid))
    counts = factor_counts(texts, "text", ["id"], schemes=[*_GREEDY.values()])
    return wanted.join(counts, ["id", "scheme"]).groupBy("scheme").agg(F.sum("z").alias("z"), F.count("*").alias("texts"))


def _large(spark, sf, names: list[str], schemes: list[str]) -> DataFrame:
    return measures.relative(joined_counts(W.catalog_pieces(spark, sf, names), schemes), ["name"], schemes)


@add("rel_large")
def rel_large(spark, sf):
    """Counts on the large texts, whole: each language's prose, all mark-up, records, and the texts made from numeric tables."""
    return _large(spark, sf, ["languages", "markup", "records", "flags", "quantities", "event_values"], [*_GREEDY.values()])


@add("rel_large_flex")
def rel_large_flex(spark, sf):
    """The look-aheads on large texts, whole, against `pair`, in percent."""
    names = ["pair", "pair_run", "pair_run+flex_fixed", "pair_run+flex_own", "pair_run+flex_longest"]
    return _large(spark, sf, ["languages", "quantities", "event_values"], names)


#: Lengths at which the large texts are counted, as sizes of the experiment.
_SIZES = [10_000, 20_000, 40_000]


@add("rel_large_sizes")
def rel_large_sizes(spark, sf):
    """How the counts of the large texts grow: symbols for each factor at each size of the experiment."""
    texts = W.catalog(spark, sf, ["languages", "markup", "records", "flags", "quantities", "event_values"], _SIZES)
    counts = factor_counts(texts, "text", ["corpus", "id", "prefix"], schemes=[*_GREEDY.values()])
    return counts.select("corpus", "id", "prefix", "scheme", "n", "z", measures.percent(F.col("n"), F.col("z")).alias("symbols_each"))


def _factors_of(texts: Query, key: str, full: str) -> Query:
    return lambda spark, sf: factorize(texts(spark, sf).withColumnRenamed("id", key), "text", [key], scheme=full).select(key, "x", "beg", "len", "kind")


for _full in ("pair_cut", "pair_run"):
    add(f"pages_{SHORT[_full]}_factors")(_factors_of(W.pages, "page_id", _full))
    add(f"conv_{SHORT[_full]}_factors")(_factors_of(W.conversations, "conv_id", _full))
add("props_run_factors")(_factors_of(W.event_props, "user_id", "pair_run"))

#: Whole tables as many short texts, with SQL that gives the same ones.
_ORDERED = "string_agg({}, '' ORDER BY l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice) AS t FROM lineitem GROUP BY l_orderkey"
_GRIDS = {
    "flags_counts": (lambda spark, sf: W.flags(spark, sf, "l_orderkey"), "SELECT l_orderkey AS id, " + _ORDERED.format("chr(97 + 2 * (ascii(l_returnflag) % 3) + ascii(l_linestatus) % 2)")),
    "quant_counts": (lambda spark, sf: W.quantities(spark, sf, "l_orderkey"), "SELECT l_orderkey AS id, " + _ORDERED.format("chr(65 + CAST(trunc(l_quantity) AS INTEGER) % 20)")),
    "etype_counts": (W.event_types, SETS["user_"][2]),
}
for _name, (_texts, _source) in _GRIDS.items():
    _union = " UNION ALL ".join(f"SELECT '{full}' AS scheme, count(*) AS z FROM p_{short}" for short, full in _GREEDY.items())

    def _grid(spark, sf, texts=_texts):
        return factor_counts(texts(spark, sf), "text", ["id"], schemes=[*_GREEDY.values()]).groupBy("scheme").agg(F.sum("z").alias("z"))

    add(_name, _with({f"p_{short}": full for short, full in _GREEDY.items()}, _source, _union))(_grid)


@add("numeric_counts")
def numeric_counts(spark, sf):
    """Counts on quantised vectors, one text for each."""
    return measures.wide(factor_counts(W.vectors(spark, sf), "text", ["id"], schemes=[*_GREEDY.values()]), ["id"], [*_GREEDY.values()])


@add("pages_counts")
def pages_counts(spark, sf):
    return measures.wide(factor_counts(W.pages(spark, sf), "text", ["id"], schemes=[*_GREEDY.values()]), ["id"], [*_GREEDY.values()])


# ---- relational operators over factor tables (pair_cut factors of users' event types)

_U = SETS["user_"][2]


def _f(spark, sf) -> DataFrame:
    return _parsed("user_", "pair_cut")(spark, sf)


def _fsql(tail: str) -> str:
    return _with({"f": "pair_cut"}, _U, tail)


def relational(name: str, tail: str):
    return add(name, _fsql(tail))


@relational("factor_pieces", "SELECT id AS user_id, x, substr(s.t, f.beg, f.len) AS piece FROM f JOIN (" + _U + ") s USING (id)")
def factor_pieces(spark, sf):
    """Pieces cut out of the texts by a join."""
    f = factorize(W.event_types(spark, sf), "text", ["id"], scheme="pair_cut")
    return f.join(W.event_types(spark, sf), "id").select(F.col("id").alias("user_id"), "x", F.expr("substring(text, beg, len)").alias("piece"))


@relational("long_factors", "SELECT id AS user_id, x, len FROM f WHERE len >= 5 AND kind = 'combine'")
def long_factors(spark, sf):
    return _f(spark, sf).where("len >= 5 AND kind = 'combine'").select("user_id", "x", "len")


@relational("count_by_kind", "SELECT kind, count(*) AS factors, CAST(sum(len) AS BIGINT) AS symbols, max(len) AS longest FROM f GROUP BY kind")
def count_by_kind(spark, sf):
    return _f(spark, sf).groupBy("kind").agg(F.count("*").alias("factors"), F.sum("len").alias("symbols"), F.max("len").alias("longest"))


@relational("longest_piece", "SELECT id AS user_id, max(piece) AS last_piece, list_max(list(len)) AS longest FROM f GROUP BY id")
def longest_piece(spark, sf):
    return _f(spark, sf).groupBy("user_id").agg(F.max("piece").alias("last_piece"), F.array_max(F.collect_list("len")).alias("longest"))


@relational("distinct_pieces", "SELECT id AS user_id, count(DISTINCT piece) AS pieces FROM f GROUP BY id")
def distinct_pieces(spark, sf):
    return _f(spark, sf).groupBy("user_id").agg(F.countDistinct("piece").alias("pieces"))


@relational("kind_map", "SELECT id AS user_id, count(*) FILTER (WHERE kind = 'combine') AS combines, count(*) FILTER (WHERE kind = 'cut') AS cuts FROM f GROUP BY id")
def kind_map(spark, sf):
    """Counts by kind through a map column."""
    per = _f(spark, sf).groupBy("user_id", "kind").agg(F.count("*").alias("n")).groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("kind", "n"))).alias("m"))
    return per.select("user_id", F.coalesce(F.element_at("m", F.lit("combine")), F.lit(0)).cast("long").alias("combines"), F.coalesce(F.element_at("m", F.lit("cut")), F.lit(0)).cast("long").alias("cuts"))


@relational("factors_by_segment", "SELECT c_mktsegment, n_name, count(*) AS factors, CAST(sum(len) AS BIGINT) AS symbols FROM f JOIN customer ON c_custkey = id JOIN nation ON n_nationkey = c_nationkey GROUP BY c_mktsegment, n_name")
def factors_by_segment(spark, sf):
    """Inner joins with users' metadata; nation has 25 rows."""
    customers = load(spark, sf, "customer", ["c_custkey", "c_nationkey", "c_mktsegment"]).withColumnRenamed("c_custkey", "user_id")
    nations = F.broadcast(load(spark, sf, "nation", ["n_nationkey", "n_name"]))
    joined = _f(spark, sf).join(customers, "user_id").join(nations, F.col("c_nationkey") == F.col("n_nationkey"))
    return joined.groupBy("c_mktsegment", "n_name").agg(F.count("*").alias("factors"), F.sum("len").alias("symbols"))


@relational("join_hint_agreement", "SELECT h AS hint, count(*) AS rows FROM f JOIN customer ON c_custkey = id, (VALUES ('broadcast'), ('merge'), ('shuffle_hash')) v(h) GROUP BY h")
def join_hint_agreement(spark, sf):
    customers = load(spark, sf, "customer", ["c_custkey"]).withColumnRenamed("c_custkey", "user_id")
    one = lambda h: _f(spark, sf).join(customers.hint(h), "user_id").agg(F.lit(h).alias("hint"), F.count("*").alias("rows"))
    return one("broadcast").unionByName(one("merge")).unionByName(one("shuffle_hash"))


@relational("counts_with_labels", "SELECT id AS user_id, z, quality, toxic FROM (SELECT id, count(*) AS z FROM f GROUP BY id) LEFT JOIN labels ON doc_id = id")
def counts_with_labels(spark, sf):
    """Left outer join: texts without a label keep their counts."""
    labels = load(spark, sf, "labels").withColumnRenamed("doc_id", "user_id")
    return _f(spark, sf).groupBy("user_id").agg(F.count("*").alias("z")).join(labels, "user_id", "left").select("user_id", "z", "quality", "toxic")


@relational("texts_with_cut", "SELECT DISTINCT user_id FROM events WHERE user_id IN (SELECT id FROM f WHERE kind = 'cut')")
def texts_with_cut(spark, sf):
    users = load(spark, sf, "events", ["user_id"]).distinct()
    return users.join(_f(spark, sf).where("kind = 'cut'"), "user_id", "left_semi")


@relational("texts_without_cut", "SELECT DISTINCT user_id FROM events WHERE user_id NOT IN (SELECT id FROM f WHERE kind = 'cut')")
def texts_without_cut(spark, sf):
    users = load(spark, sf, "events", ["user_id"]).distinct()
    return users.join(_f(spark, sf).where("kind = 'cut'"), "user_id", "left_anti")


@relational("reference_edges", "SELECT a.id AS user_id, a.x, b.x AS used, b.len AS used_len, a.beg > b.beg AS earlier FROM f a JOIN f b ON a.id = b.id AND (a.ref1 = b.x OR a.ref2 = b.x)")
def reference_edges(spark, sf):
    f = _f(spark, sf)
    uses = f.select("user_id", "x", "beg", F.explode(F.array_distinct(F.array_compact(F.array("ref1", "ref2")))).alias("used")).where("used > 0")
    target = f.select("user_id", F.col("x").alias("used"), F.col("beg").alias("used_beg"), F.col("len").alias("used_len"))
    return uses.join(target, ["user_id", "used"]).select("user_id", "x", "used", "used_len", (F.col("beg") > F.col("used_beg")).alias("earlier"))


_DEPTH = """, d(id, x, depth) AS (
  SELECT id, x, 1 FROM f WHERE coalesce(ref1, 0) = 0 AND coalesce(ref2, 0) = 0
  UNION
  SELECT f.id, f.x, d.depth + 1 FROM f JOIN d ON f.id = d.id AND (f.ref1 = d.x OR f.ref2 = d.x))
SELECT id AS user_id, CAST(max(depth) AS INTEGER) AS depth FROM d GROUP BY id"""


@relational("reference_depth", _DEPTH)
def reference_depth(spark, sf):
    """The longest chain of references down to symbols, one round of joins a level; a factor counts once in a round, however many paths lead to it."""
    f = _f(spark, sf)
    edges = f.select("user_id", "x", F.explode(F.array_distinct(F.array_compact(F.array("ref1", "ref2")))).alias("used")).where("used > 0")
    edges = cut_lineage(edges)
    level = f.select("user_id").distinct().withColumn("depth", F.lit(1))
    deepest, front, depth = [level], edges.select("user_id", "x").distinct(), 1
    while not front.isEmpty():
        depth += 1
        deepest.append(front.select("user_id").distinct().withColumn("depth", F.lit(depth)))
        front = cut_lineage(front.withColumnRenamed("x", "used").join(edges, ["user_id", "used"]).select("user_id", "x").distinct())
    out = deepest[0]
    for d in deepest[1:]:
        out = out.unionByName(d)
    return out.groupBy("user_id").agg(F.max("depth").alias("depth"))


@relational("most_referenced", ", u AS (SELECT id, ref1 AS r FROM f WHERE ref1 > 0 UNION ALL SELECT id, ref2 FROM f WHERE ref2 > 0) SELECT id AS user_id, r AS x, count(*) AS uses FROM u GROUP BY id, r ORDER BY uses DESC, user_id, x LIMIT 20")
def most_referenced(spark, sf):
    """The twenty most used factors (a top-k report)."""
    f = _f(spark, sf)
    uses = f.select("user_id", F.explode(F.array_compact(F.array("ref1", "ref2"))).alias("x")).where("x > 0")
    return uses.groupBy("user_id", "x").agg(F.count("*").alias("uses")).orderBy(F.desc("uses"), "user_id", "x").limit(20)


_POSITIONS = f"positions AS (SELECT user_id AS id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS pos, event_type FROM events)"


def _purchases(spark, sf) -> DataFrame:
    events = load(spark, sf, "events", ["event_id", "ts", "user_id", "event_type"])
    return events.withColumn("pos", F.row_number().over(Window.partitionBy("user_id").orderBy("ts", "event_id"))).where("event_type = 'purchase'").select("user_id", "pos")


@relational("factor_at_position", f", {_POSITIONS} SELECT p.id AS user_id, p.pos, f.x FROM positions p JOIN f ON f.id = p.id AND p.pos BETWEEN f.beg AND f.beg + f.len - 1 WHERE event_type = 'purchase'")
def factor_at_position(spark, sf):
    """Range join: the factor that covers each purchase."""
    return _purchases(spark, sf).join(_f(spark, sf), "user_id").where("pos BETWEEN beg AND fin").select("user_id", "pos", "x")


@relational("asof_available", f", {_POSITIONS} SELECT p.id AS user_id, p.pos, (SELECT max(f.x) FROM f WHERE f.id = p.id AND f.beg + f.len - 1 < p.pos) AS x FROM positions p WHERE event_type = 'purchase'")
def asof_available(spark, sf):
    """As-of join: the last factor that ends before each purchase, by a window over the union of both sides."""
    ends = _f(spark, sf).select("user_id", F.col("fin").alias("pos"), "x", F.lit(1).alias("side"))
    asks = _purchases(spark, sf).select("user_id", "pos", F.lit(None).cast("int").alias("x"), F.lit(0).alias("side"))
    before = Window.partitionBy("user_id").orderBy("pos", "side").rowsBetween(Window.unboundedPreceding, -1)
    both = ends.unionByName(asks).withColumn("last", F.last("x", ignorenulls=True).over(before))
    return both.where("side = 0").select("user_id", "pos", F.col("last").alias("x"))


_TWO = {"f": "pair_cut", "g": "step"}


def _steps(spark, sf) -> DataFrame:
    return _parsed("user_", "step")(spark, sf)


@add("boundary_overlap", _with(_TWO, _U, "SELECT f.id AS user_id, f.x, count(*) AS overlaps FROM f JOIN g ON f.id = g.id AND f.beg <= g.beg + g.len - 1 AND g.beg <= f.beg + f.len - 1 GROUP BY f.id, f.x"))
def boundary_overlap(spark, sf):
    """Interval join: how many phrases of another scheme each factor meets."""
    g = _steps(spark, sf).select("user_id", F.col("beg").alias("g_beg"), F.col("fin").alias("g_fin"))
    return _f(spark, sf).join(g, "user_id").where("beg <= g_fin AND g_beg <= fin").groupBy("user_id", "x").agg(F.count("*").alias("overlaps"))


for _name, _op in (("common_boundaries", "INTERSECT"), ("only_cut_boundaries", "EXCEPT"), ("all_boundaries", "UNION")):

    def _boundaries(spark, sf, op=_op):
        a, b = (q(spark, sf).select("user_id", "beg") for q in (_f, _steps))
        return a.intersect(b) if op == "INTERSECT" else a.subtract(b) if op == "EXCEPT" else a.union(b).distinct()

    add(_name, _with(_TWO, _U, f"SELECT id AS user_id, beg FROM f {_op} SELECT id, beg FROM g"))(_boundaries)


@add("only_run_boundaries", _with({"f": "pair_run", "g": "pair_cut"}, _U, "SELECT id AS user_id, beg FROM f EXCEPT SELECT id, beg FROM g"))
def only_run_boundaries(spark, sf):
    return _parsed("user_", "pair_run")(spark, sf).select("user_id", "beg").subtract(_f(spark, sf).select("user_id", "beg"))


@add("factors_by_label", _with({"f": "pair_run"}, _U, "SELECT toxic, quality, kind, count(*) AS factors FROM f JOIN labels ON doc_id = id GROUP BY toxic, quality, kind"))
def factors_by_label(spark, sf):
    """Inner join with labels, null labels among the groups."""
    labels = load(spark, sf, "labels").withColumnRenamed("doc_id", "user_id")
    return _parsed("user_", "pair_run")(spark, sf).join(labels, "user_id").groupBy("toxic", "quality", "kind").agg(F.count("*").alias("factors"))


for _name, _how, _not in (("docs_with_power", "left_semi", ""), ("docs_without_power", "left_anti", "NOT ")):

    def _powers(spark, sf, how=_how):
        docs = load(spark, sf, "part", ["p_partkey", "p_brand"])
        return docs.join(_parsed("part_", "pair_run")(spark, sf).where("kind = 'repeat'"), "p_partkey", how)

    add(_name, _with({"f": "pair_run"}, SETS["part_"][2], f"SELECT p_partkey, p_brand FROM part WHERE p_partkey {_not}IN (SELECT id FROM f WHERE kind = 'repeat')"))(_powers)


def _doc_factors(spark, sf) -> DataFrame:
    """Every document's factors with its language, source and quality."""
    about = load(spark, sf, "documents", ["doc_id", "lang", "source"]).join(load(spark, sf, "labels", ["doc_id", "quality"]).groupBy("doc_id").agg(F.max("quality").alias("quality")), "doc_id", "left")
    return factorize(_docs(spark, sf), "text", ["doc_id"], scheme="pair_cut").join(about, "doc_id")


#: A document's factors cover it, so their lengths add up to its own.
_COVERED = "(SELECT d.doc_id, lang, source, quality, length(text) AS n FROM documents d LEFT JOIN (SELECT doc_id, max(quality) AS quality FROM labels GROUP BY doc_id) l ON l.doc_id = d.doc_id WHERE length(text) > 0)"


@add("rollup_lang_source", f"SELECT lang, source, count(DISTINCT doc_id) AS texts, CAST(sum(n) AS BIGINT) AS symbols FROM {_COVERED} GROUP BY ROLLUP (lang, source)")
def rollup_lang_source(spark, sf):
    return _doc_factors(spark, sf).rollup("lang", "source").agg(F.countDistinct("doc_id").alias("texts"), F.sum("len").alias("symbols"))


@add("grouping_sets_lang_quality", f"SELECT lang, quality, count(DISTINCT doc_id) AS texts, CAST(sum(n) AS BIGINT) AS symbols FROM {_COVERED} GROUP BY GROUPING SETS ((lang), (quality), ())")
def grouping_sets_lang_quality(spark, sf):
    f = _doc_factors(spark, sf)
    return f.groupingSets([["lang"], ["quality"], []], "lang", "quality").agg(F.countDistinct("doc_id").alias("texts"), F.sum("len").alias("symbols"))


@add("cube_kind_segment", _with({"f": "pair_run"}, _U, "SELECT kind, c_mktsegment, count(*) AS factors, CAST(sum(len) AS BIGINT) AS symbols FROM f JOIN customer ON c_custkey = id GROUP BY CUBE (kind, c_mktsegment)"))
def cube_kind_segment(spark, sf):
    customers = load(spark, sf, "customer", ["c_custkey", "c_mktsegment"]).withColumnRenamed("c_custkey", "user_id")
    return _parsed("user_", "pair_run")(spark, sf).join(customers, "user_id").cube("kind", "c_mktsegment").agg(F.count("*").alias("factors"), F.sum("len").alias("symbols"))


@add("cube_kind_lang")
def cube_kind_lang(spark, sf):
    return _doc_factors(spark, sf).cube("kind", "lang").agg(F.count("*").alias("factors"), F.sum("len").alias("symbols"))


@relational("rollup_segment", "SELECT c_mktsegment, kind, count(*) AS factors FROM f JOIN customer ON c_custkey = id GROUP BY ROLLUP (c_mktsegment, kind)")
def rollup_segment(spark, sf):
    customers = load(spark, sf, "customer", ["c_custkey", "c_mktsegment"]).withColumnRenamed("c_custkey", "user_id")
    return _f(spark, sf).join(customers, "user_id").rollup("c_mktsegment", "kind").agg(F.count("*").alias("factors"))


@relational("cube_segment", "SELECT c_mktsegment, kind, count(*) AS factors FROM f JOIN customer ON c_custkey = id GROUP BY CUBE (c_mktsegment, kind)")
def cube_segment(spark, sf):
    customers = load(spark, sf, "customer", ["c_custkey", "c_mktsegment"]).withColumnRenamed("c_custkey", "user_id")
    return _f(spark, sf).join(customers, "user_id").cube("c_mktsegment", "kind").agg(F.count("*").alias("factors"))


@relational("grouping_sets", "SELECT c_mktsegment, kind, count(*) AS factors FROM f JOIN customer ON c_custkey = id GROUP BY GROUPING SETS ((c_mktsegment), (kind), ())")
def grouping_sets(spark, sf):
    customers = load(spark, sf, "customer", ["c_custkey", "c_mktsegment"]).withColumnRenamed("c_custkey", "user_id")
    _f(spark, sf).join(customers, "user_id").createOrReplaceTempView("_set_factors")
    return spark.sql("SELECT c_mktsegment, kind, count(*) AS factors FROM _set_factors GROUP BY GROUPING SETS ((c_mktsegment), (kind), ())")


@relational("running_position", "SELECT id AS user_id, x, CAST(sum(len) OVER (PARTITION BY id ORDER BY x) AS BIGINT) AS upto, ntile(4) OVER (PARTITION BY id ORDER BY x) AS quarter FROM f")
def running_position(spark, sf):
    w = Window.partitionBy("user_id").orderBy("x")
    return _f(spark, sf).select("user_id", "x", F.sum("len").over(w).alias("upto"), F.ntile(4).over(w).alias("quarter"))


@relational("moving_len", "SELECT id AS user_id, x, CAST(sum(len) OVER (PARTITION BY id ORDER BY x ROWS BETWEEN 9 PRECEDING AND CURRENT ROW) AS BIGINT) AS ten FROM f")
def moving_len(spark, sf):
    return _f(spark, sf).select("user_id", "x", F.sum("len").over(Window.partitionBy("user_id").orderBy("x").rowsBetween(-9, 0)).alias("ten"))


@relational("range_density", "SELECT id AS user_id, x, count(*) OVER (PARTITION BY id ORDER BY beg RANGE BETWEEN 20 PRECEDING AND CURRENT ROW) AS near FROM f")
def range_density(spark, sf):
    return _f(spark, sf).select("user_id", "x", F.count("*").over(Window.partitionBy("user_id").orderBy("beg").rangeBetween(-20, 0)).alias("near"))


@relational("neighbours", "SELECT id AS user_id, x, lag(piece) OVER w AS before, lead(piece) OVER w AS after, first_value(piece) OVER w AS first FROM f WINDOW w AS (PARTITION BY id ORDER BY x)")
def neighbours(spark, sf):
    w = Window.partitionBy("user_id").orderBy("x")
    return _f(spark, sf).select("user_id", "x", F.lag("piece").over(w).alias("before"), F.lead("piece").over(w).alias("after"), F.first("piece").over(w).alias("first"))


@relational("top_factors", "SELECT id AS user_id, x, len, place FROM (SELECT *, CAST(dense_rank() OVER (PARTITION BY id ORDER BY len DESC) AS INTEGER) AS place FROM f) WHERE place <= 3")
def top_factors(spark, sf):
    """Each text's longest factors, three lengths deep (a top-k report)."""
    return _f(spark, sf).withColumn("place", F.dense_rank().over(Window.partitionBy("user_id").orderBy(F.desc("len")))).where("place <= 3").select("user_id", "x", "len", "place")


@relational("above_mean", "SELECT g.id AS user_id, g.z FROM (SELECT id, count(*) AS z FROM f GROUP BY id) g JOIN customer ON c_custkey = g.id WHERE g.z > (SELECT avg(h.z) FROM (SELECT id, count(*) AS z FROM f GROUP BY id) h JOIN customer c ON c.c_custkey = h.id WHERE c.c_mktsegment = customer.c_mktsegment)")
def above_mean(spark, sf):
    """Correlated subquery: texts above their segment's mean count."""
    load(spark, sf, "customer", ["c_custkey", "c_mktsegment"]).createOrReplaceTempView("_mean_customer")
    _f(spark, sf).groupBy("user_id").agg(F.count("*").alias("z")).join(spark.table("_mean_customer"), F.col("user_id") == F.col("c_custkey")).createOrReplaceTempView("_mean_counts")
    return spark.sql("SELECT user_id, z FROM _mean_counts a WHERE z > (SELECT avg(z) FROM _mean_counts b WHERE b.c_mktsegment = a.c_mktsegment)")


@relational("verify_pieces", "SELECT id AS user_id, true AS same FROM (SELECT DISTINCT id FROM f)")
def verify_pieces(spark, sf):
    """Ordered aggregation: a text's pieces joined in order are the text."""
    f = _f(spark, sf).groupBy("user_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("x", "piece"))), lambda r: r["piece"]), "").alias("joined"))
    return f.join(W.event_types(spark, sf).withColumnRenamed("id", "user_id"), "user_id").select("user_id", (F.col("joined") == F.col("text")).alias("same"))


@add("json_tokens", _with({"f": "pair_cut"}, SETS[""][2], "SELECT id AS item_id, '[' || string_agg('{\"x\":' || x || ',\"len\":' || len || ',\"kind\":\"' || kind || '\"}', ',' ORDER BY x) || ']' AS tokens FROM f GROUP BY id"))
def json_tokens(spark, sf):
    """A text's tokens as one JSON string, read back and written again."""
    kind = "array<struct<x:int,len:int,kind:string>>"
    listed = F.array_sort(F.collect_list(F.struct("x", "len", "kind")))
    rows = _parsed("", "pair_cut")(spark, sf).groupBy("item_id").agg(F.to_json(listed).alias("tokens"))
    return rows.select("item_id", F.to_json(F.from_json("tokens", kind)).alias("tokens"))


# ---- grammars, collages, sizes


@add("collage_size", _with({"f": "pair_run"}, SETS[""][2], ", parts AS (SELECT id, sym1 AS s FROM f WHERE sym1 IS NOT NULL UNION SELECT id, sym2 FROM f WHERE sym2 IS NOT NULL), sy AS (SELECT id, count(*) AS symbols FROM parts GROUP BY id), c AS (SELECT id, count(*) FILTER (WHERE kind = 'combine') AS concats, count(*) FILTER (WHERE kind = 'repeat') AS powers, count(*) FILTER (WHERE kind <> 'combine' OR ref2 > 0) AS cuts, max(x) AS phrases FROM f GROUP BY id) SELECT id AS item_id, symbols, concats, powers, cuts, CAST(phrases AS BIGINT) AS phrases, symbols + concats + powers + cuts AS size FROM c JOIN sy USING (id)"))
def collage_size(spark, sf):
    return D.collage_size(_parsed("", "pair_run")(spark, sf), ["item_id"])


@add("grammar_size", _with({"f": "pair"}, SETS[""][2], "SELECT id AS item_id, CAST(sum(1 + CASE WHEN ref2 = 0 THEN 0 ELSE 1 END) + count(*) AS BIGINT) AS size, count(*) AS z FROM f GROUP BY id"))
def grammar_size(spark, sf):
    return D.grammar_size(_parsed("", "pair")(spark, sf), ["item_id"])


_BITS = """CASE kind WHEN 'combine' THEN 2 + 2 * r + CASE WHEN {cut} AND coalesce(ref2, 0) > 0 THEN u ELSE 0 END WHEN 'extend' THEN 2 * r WHEN 'entry' THEN r ELSE 2 + r + u END"""


def _bits_sql(names: dict[str, str]) -> str:
    one = lambda n, full: f"SELECT id AS item_id, '{full}' AS scheme, CAST(sum({_BITS.format(cut='true' if full in ('pair_cut', 'pair_run') else 'false')}) AS BIGINT) AS bits, CAST(sum(len) AS BIGINT) AS symbols FROM (SELECT *, CAST(ceil(log2(x + 256)) AS BIGINT) AS r, 2 * CAST(floor(log2(len)) AS BIGINT) + 1 AS u FROM {n}) GROUP BY id"
    return _with(names, SETS[""][2], " UNION ALL ".join(one(n, full) for n, full in names.items()))


@add("encoded_bits", _bits_sql({"a": "pair", "b": "pair_cut", "c": "pair_run", "d": "step", "e": "seeded"}))
def encoded_bits(spark, sf):
    """Estimated stored size of each scheme's tokens."""
    rows = parse_many(W.items(spark, sf).withColumnRenamed("id", "item_id"), "text", ["item_id"], ["pair", "pair_cut", "pair_run", "step", "seeded"])
    return measures.encoded_bits(rows, ["item_id"])


@add("compression_ratio", "SELECT *, CAST(bits * 10000 // (symbols * 8) AS BIGINT) AS ratio_e4 FROM (" + SQL["encoded_bits"] + ")")
def compression_ratio(spark, sf):
    """Estimated stored size of each scheme's tokens against one byte a symbol."""
    return measures.compression_ratio(encoded_bits(spark, sf))


# ---- planning: reuse of equal texts, blocks


@add("reuse_equal_texts", "SELECT doc_id, true AS same FROM documents WHERE text IS NOT NULL")
def reuse_equal_texts(spark, sf):
    """Counts with each distinct text parsed once are the counts of every text."""
    once = factor_counts(_docs(spark, sf), "text", ["doc_id"], schemes=["pair_cut"], reuse_equal_texts=True).select("doc_id", "z")
    each = factor_counts(_docs(spark, sf), "text", ["doc_id"], schemes=["pair_cut"], reuse_equal_texts=False).select("doc_id", F.col("z").alias("each"))
    return once.join(each, "doc_id").select("doc_id", (F.col("z") == F.col("each")).alias("same"))


_BLOCK = 100


@add("blocked_counts", _with({"f": "pair_cut"}, f"SELECT id * 1000 + b AS id, substr(t, CAST(b * {_BLOCK} + 1 AS BIGINT), {_BLOCK}) AS t FROM (SELECT id, t, unnest(range(0, (length(t) - 1) // {_BLOCK} + 1)) AS b FROM ({SETS[''][2]}))", "SELECT CAST(id // 1000 AS BIGINT) AS item_id, CAST(id % 1000 AS INTEGER) AS block_id, count(*) AS z FROM f GROUP BY id"))
def blocked_counts(spark, sf):
    """Blocks of a text parsed with dictionaries of their own."""
    rows = factor_counts(W.items(spark, sf), "text", ["id"], schemes=["pair_cut"], block_symbols=_BLOCK, reuse_equal_texts=False)
    return rows.select(F.col("id").alias("item_id"), "block_id", "z")


@add("blocking_loss")
def blocking_loss(spark, sf):
    """What blocks of 2000 symbols cost on each document, in percent of its count."""
    whole = factor_counts(_docs(spark, sf), "text", ["doc_id"], schemes=["pair_cut"])
    blocked = factor_counts(_docs(spark, sf), "text", ["doc_id"], schemes=["pair_cut"], block_symbols=2000)
    return measures.blocking_loss(blocked, whole, ["doc_id"]).select("doc_id", "blocks_z", "whole_z", "loss")


@add("byte_symbols", "SELECT doc_id, strlen(text) AS n FROM documents WHERE text IS NOT NULL")
def byte_symbols(spark, sf):
    """Parsing UTF-8 bytes instead of code points: the length parsed."""
    return factor_counts(_docs(spark, sf), "text", ["doc_id"], schemes=["pair_cut"], symbols="byte").select("doc_id", "n")


# ---- other surfaces: UDFs, table functions, engines

for _engine, _key, _texts, _source in (("fold", "p_partkey", W.part_names, SETS["part_"][2]), ("recursive", "n_nationkey", W.nation_names, "SELECT n_nationkey AS id, n_name AS t FROM nation"), ("rounds", "n_nationkey", W.nation_names, "SELECT n_nationkey AS id, n_name AS t FROM nation")):

    def _engine_query(spark, sf, engine=_engine, key=_key, texts=_texts):
        return factorize(texts(spark, sf), "text", ["id"], scheme="pair_cut", engine=engine).select(F.col("id").alias(key), "x", "beg", "len", "kind")

    add(f"{_engine}_cut", _with({"f": "pair_cut"}, _source, f"SELECT id AS {_key}, x, beg, len, kind FROM f"))(_engine_query)


@add("udtf_cut", _with({"f": "pair_cut"}, SETS[""][2], "SELECT id AS item_id, x, len, piece FROM f"))
def udtf_cut(spark, sf):
    """The table function in SQL with LATERAL."""
    spark.udtf.register("factor_rows", udfs.factor_rows())
    W.items(spark, sf).createOrReplaceTempView("_udtf_items")
    return spark.sql("SELECT d.id AS item_id, f.x, f.len, f.piece FROM _udtf_items d, LATERAL factor_rows(d.text, 'pair_cut') f")


@add("udf_counts", _with({"f": "pair_run"}, SETS[""][2], "SELECT id AS item_id, CAST(count(*) AS INTEGER) AS z, CAST(count(*) AS INTEGER) AS listed FROM f GROUP BY id"))
def udf_counts(spark, sf):
    """The scalar functions: a count, and the list of factors."""
    return W.items(spark, sf).select(F.col("id").alias("item_id"), udfs.parse_count("pair_run")("text").alias("z"), F.size(udfs.parse_list("pair_run")("text")).alias("listed"))


@add("udaf_counts", _with({"f": "pair_cut"}, _U, "SELECT id AS user_id, CAST(count(*) AS INTEGER) AS z FROM f GROUP BY id"))
def udaf_counts(spark, sf):
    """The aggregate function over each user's events in order."""
    events = load(spark, sf, "events", ["event_id", "ts", "user_id", "event_type"])
    order = F.row_number().over(Window.partitionBy("user_id").orderBy("ts", "event_id"))
    rows = events.select("user_id", order.alias("k"), F.substring("event_type", 1, 1).alias("s"))
    return rows.groupBy("user_id").agg(udfs.corpus_count("pair_cut")("k", "s").alias("z"))


@add("ablation_agreement", "SELECT option, true AS same FROM (VALUES ('sorted'), ('unfused'), ('rank'), ('rolling')) v(option)")
def ablation_agreement(spark, sf):
    """Ordered children, separate searches and indexed extensions give the factors of the default."""
    texts = W.items(spark, sf)
    mark = lambda df: df.groupBy().agg(F.sum(F.xxhash64("id", "x", "beg", "len", "kind", "ref1", "ref2", "sym1", "sym2", "power").cast("decimal(38,0)")).alias("h"))
    one = lambda **o: mark(factorize(texts, "text", ["id"], scheme="pair_run", reuse_equal_texts=False, **o))
    out = None
    for name, o in (("sorted", {"children": "sorted"}), ("unfused", {"fused": False}), ("rank", {"lce": "rank"}), ("rolling", {"lce": "rolling"})):
        row = one(**o).crossJoin(one().withColumnRenamed("h", "d")).select(F.lit(name).alias("option"), (F.col("h") == F.col("d")).alias("same"))
        out = row if out is None else out.unionByName(row)
    return out


# ---- streams, replayed


@add("stream_factors", _with({"f": "pair_cut"}, _U, "SELECT id AS user_id, x, beg, len, kind FROM f"))
def stream_factors(spark, sf):
    """Each user's events as a stream: the online parse ends with the factors of the batch parse."""
    out = online.factors_of_stream(stream_events(spark, f"{sf}/events.parquet"), "user_id", "ts", "event_id", F.substring("event_type", 1, 1))
    return online.settled(online.run_to_table(out)).select(F.col("key").alias("user_id"), "x", "beg", "len", "kind")


@add("stream_counts", _with({"f": "pair_cut"}, _U, "SELECT id AS user_id, count(*) AS z FROM f GROUP BY id"))
def stream_counts(spark, sf):
    return stream_factors(spark, sf).groupBy("user_id").agg(F.count("*").alias("z"))


@add("stream_windows", "SELECT CAST(epoch(date_trunc('hour', ts)) AS BIGINT) AS start, event_type, count(*) AS events FROM events GROUP BY ALL")
def stream_windows(spark, sf):
    out = online.tumbling(stream_events(spark, f"{sf}/events.parquet")).select(F.unix_timestamp("w.start").alias("start"), "event_type", "events")
    return online.run_to_table(out, "complete")


@add("stream_sessions", "WITH g AS (SELECT *, CASE WHEN ts - lag(ts) OVER w < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, count(*) AS events FROM s GROUP BY user_id, k")
def stream_sessions(spark, sf):
    out = online.sessions(stream_events(spark, f"{sf}/events.parquet")).select("w", "user_id", "events")
    return online.run_to_table(out, "complete").select("user_id", "events")


# ---- the flagship


def flagship(spark: SparkSession, sf: str) -> DataFrame:
    """By language: factors of each scheme over all documents, against pair, in percent."""
    schemes = ["pair", "pair_cut", "pair_run", "step"]
    docs = load(spark, sf, "documents", ["doc_id", "lang", "text"])
    counts = factor_counts(docs, "text", ["doc_id", "lang"], schemes=schemes).groupBy("lang", "scheme").agg(F.sum("z").alias("z"))
    return measures.relative(counts, ["lang"], schemes)


add("relative_by_language")(flagship)
