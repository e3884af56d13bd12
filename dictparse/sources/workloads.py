"""The texts of the experiments, made from the given tables, and the generated families.

A workload is a DataFrame (id, text). Texts that are put together from rows are ordered by unique keys, so every run sees the same.
A parse needs its whole text in one worker, so a text made from a table must fit there: such workloads (languages, markup, records,
flags, quantities, event values as one text) are the experiments' single large texts. They come joined, or by their pieces
(`catalog_pieces`). On larger tables take one text for each value of a column (`by`), or parse in blocks.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from dictparse.sources.io import load

#: Lineitem rows have no key; this order is total up to equal rows.
LINE_ORDER = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate")


def _leading(rows: DataFrame, key: str, order: list[Column], piece: Column, separator: str, most: int, one: bool) -> DataFrame:
    """Of each group the rows, first in order, whose pieces hold its first `most` symbols; groups of equal rows in order stay whole.

    Where the last of these rows lies is found from lengths alone. One group (`one`) may have a row for each symbol, so only its first
    rows that add symbols are looked at, each of which adds one at least.
    """
    grown = F.coalesce(F.length(piece) + len(separator), F.lit(0))
    sizes = rows.select(F.col(key).alias("_k"), F.struct(*order).alias("_o"), grown.cast("long").alias("_n"))
    if one:
        sizes = sizes.orderBy(F.col("_n") == 0, "_o").limit(most + 1 + len(separator))
    before = F.sum("_n").over(Window.partitionBy("_k").orderBy("_o").rowsBetween(Window.unboundedPreceding, -1))
    # a separator follows the last piece too in these sums, so they may be too large by one
    last = sizes.withColumn("_before", before).where(F.coalesce("_before", F.lit(0)) < most + len(separator)).groupBy("_k").agg(F.max("_o").alias("_last"))
    near = rows.withColumn("_o", F.struct(*order)).join(F.broadcast(last), F.col(key).eqNullSafe(F.col("_k")))  # a row for each text
    return near.where(F.col("_o") <= F.col("_last")).drop("_k", "_o", "_last")


def concatenated(rows: DataFrame, keys: list[str], order: list[Column], piece: Column, separator: str = "", most: int | None = None, one: bool = False) -> DataFrame:
    """One text for each group, its pieces in order. With `most` (and one key) no more of them than hold a text's first `most` symbols."""
    if most is not None:
        rows = _leading(rows, keys[0], order, piece, separator, most, one)
    listed = F.array_sort(F.collect_list(F.struct(*order, piece.alias("_piece"))))
    return rows.groupBy(*keys).agg(F.array_join(F.transform(listed, lambda r: r["_piece"]), separator).alias("text"))


def placed(rows: DataFrame, keys: list[str], order: list[Column], piece: Column, separator: str = "", most: int | None = None, one: bool = False) -> DataFrame:
    """The pieces that `concatenated` joins, each in a row with its place."""
    return rows.select(*keys, F.struct(*order).alias("place"), piece.alias("piece"))


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "documents", ["doc_id", "text"]).select(F.col("doc_id").alias("id"), "text")


def items(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "benchmark", ["item_id", "text"]).select(F.col("item_id").alias("id"), "text")


def part_names(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "part", ["p_partkey", "p_name"]).select(F.col("p_partkey").alias("id"), F.col("p_name").alias("text"))


def nation_names(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "nation", ["n_nationkey", "n_name"]).select(F.col("n_nationkey").alias("id"), F.col("n_name").alias("text"))


def pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mark-up, the most repetitive of the large texts."""
    return load(spark, sf_dir, "pages", ["page_id", "html"]).select(F.col("page_id").alias("id"), F.col("html").alias("text"))


def markup(spark: SparkSession, sf_dir: str, most: int | None = None, join=concatenated) -> DataFrame:
    """All pages as one text."""
    rows = load(spark, sf_dir, "pages", ["page_id", "html"]).withColumn("_all", F.lit("pages"))
    return join(rows, ["_all"], [F.col("page_id")], F.coalesce("html", F.lit("")), most=most, one=True).withColumnRenamed("_all", "id")


def conversations(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "conversations", ["conv_id", "turn", "text"])
    return concatenated(rows, ["conv_id"], [F.col("turn")], F.col("text"), "\n").withColumnRenamed("conv_id", "id")


def by_language(spark: SparkSession, sf_dir: str, most: int | None = None, join=concatenated) -> DataFrame:
    """Prose: the documents of a language as one text."""
    rows = load(spark, sf_dir, "documents", ["doc_id", "text", "lang"])
    return join(rows, ["lang"], [F.col("doc_id")], F.col("text"), most=most).withColumnRenamed("lang", "id")


def by_source(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "documents", ["doc_id", "text", "source"])
    return concatenated(rows, ["source"], [F.col("doc_id")], F.col("text")).withColumnRenamed("source", "id")


def event_types(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Five letters: each user's event types in time order."""
    rows = load(spark, sf_dir, "events", ["event_id", "ts", "user_id", "event_type"])
    return concatenated(rows, ["user_id"], [F.col("ts"), F.col("event_id")], F.substring("event_type", 1, 1)).withColumnRenamed("user_id", "id")


def event_props(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Log lines: each user's JSON properties in time order."""
    rows = load(spark, sf_dir, "events", ["event_id", "ts", "user_id", "props"])
    return concatenated(rows, ["user_id"], [F.col("ts"), F.col("event_id")], F.col("props")).withColumnRenamed("user_id", "id")


def event_values(spark: SparkSession, sf_dir: str, most: int | None = None, join=concatenated) -> DataFrame:
    """A hundred levels, as note numbers: all events' values in time order."""
    rows = load(spark, sf_dir, "events", ["event_id", "ts", "value"])
    level = F.expr("char(33 + cast(least(99, greatest(0, floor(coalesce(value, 0) / 5))) as int))")
    return join(rows.withColumn("_all", F.lit("values")), ["_all"], [F.col("ts"), F.col("event_id")], level, most=most, one=True).withColumnRenamed("_all", "id")


def _line_symbols(spark: SparkSession, sf_dir: str, name: str, symbol: Column, by: str | None, separator: str = "", most: int | None = None, join=concatenated) -> DataFrame:
    rows = load(spark, sf_dir, "lineitem", [*LINE_ORDER]).withColumn("_key", F.col(by) if by else F.lit(name))
    return join(rows, ["_key"], [F.col(c) for c in LINE_ORDER], symbol, separator, most, by is None).withColumnRenamed("_key", "id")


def flags(spark: SparkSession, sf_dir: str, by: str | None = None, most: int | None = None, join=concatenated) -> DataFrame:
    """Six letters, as for nucleotides: return flag and line status of each line (one text, or one for each value of a column)."""
    return _line_symbols(spark, sf_dir, "flags", F.expr("char(97 + 2 * (ascii(l_returnflag) % 3) + ascii(l_linestatus) % 2)"), by, most=most, join=join)


def quantities(spark: SparkSession, sf_dir: str, by: str | None = None, most: int | None = None, join=concatenated) -> DataFrame:
    """Twenty letters, as for amino acids: quantity modulo 20."""
    return _line_symbols(spark, sf_dir, "quantities", F.expr("char(65 + cast(l_quantity as int) % 20)"), by, most=most, join=join)


def records(spark: SparkSession, sf_dir: str, most: int | None = None, join=concatenated) -> DataFrame:
    """Program-like text: lines as delimited records, integers and strings only."""
    line = F.concat_ws("|", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_returnflag", "l_linestatus")
    return _line_symbols(spark, sf_dir, "records", line, None, "\n", most, join)


def vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Numeric data: each vector's components in 64 levels."""
    rows = load(spark, sf_dir, "embeddings", ["vec_id", "embedding"])
    return rows.select(F.col("vec_id").alias("id"), F.array_join(F.transform("embedding", lambda v: F.chr((48 + F.least(F.lit(63), F.greatest(F.lit(0), F.floor((v + 0.6) * 53)))).cast("long"))), "").alias("text"))


def family(spark: SparkSession, ks: list[int]) -> DataFrame:
    """The four-letter family on which only powers keep the factor count linear in k (k a power of two from 4).

    Four segments: runs of i a's and i c's for i from 2 to k; runs of i a's and bb for i below k; blocks (i a's, bb, k - i a's) each with
    i + 2 d's for i from 0 to k; k/2 times a word in which the k-th block alternates with the blocks k-1 down to k/2+1 and that ends with
    the k-th block and k - 1 a's.
    """
    rows = spark.createDataFrame([(k,) for k in ks], "id int")
    run = lambda c, n: F.repeat(F.lit(c), n)
    k = F.col("id")
    joined = lambda lo, hi, f: F.array_join(F.transform(F.sequence(lo, hi), f), "")
    block = lambda i: F.concat(run("a", i), F.lit("bb"), run("a", k - i))
    first = joined(F.lit(2), k, lambda i: F.concat(run("a", i), run("c", i)))
    second = joined(F.lit(0), k - 1, lambda i: F.concat(run("a", i), F.lit("bb")))
    third = joined(F.lit(0), k, lambda i: F.concat(block(i), run("d", i + 2)))
    half = (k / 2).cast("int")
    word = F.concat(joined(F.lit(1), half - 1, lambda i: F.concat(block(k), block(k - i))), block(k), run("a", k - 1))
    fourth = F.repeat(word, half)
    return rows.select("id", F.concat(first, second, third, fourth).alias("text"))


def unary(spark: SparkSession, ks: list[int]) -> DataFrame:
    """Runs of 2**(k+1) - 2 a's."""
    return spark.createDataFrame([(k, "a" * (2 ** (k + 1) - 2)) for k in ks], "id int, text string")


def prefix(df: DataFrame, n: int) -> DataFrame:
    return df.withColumn("text", F.substring("text", 1, n))


#: The worked examples.
EXAMPLE, LOOKAHEAD_EXAMPLE, EXTENSION_EXAMPLE = "aabbaabbbaabbbbbababaabccccbababc", "aaababaaaaaabaaab", "babababb"

CATALOG = {
    "documents": documents, "benchmark": items, "part_names": part_names, "nation_names": nation_names, "pages": pages, "markup": markup, "conversations": conversations, "languages": by_language, "sources": by_source,
    "event_types": event_types, "event_props": event_props, "event_values": event_values, "flags": flags, "quantities": quantities, "records": records, "vectors": vectors,
}


#: Texts put together from many rows, which can be asked for their first symbols only.
_JOINED = ("markup", "languages", "event_values", "flags", "quantities", "records")


def catalog(spark: SparkSession, sf_dir: str, names: list[str], prefixes: list[int] | None = None) -> DataFrame:
    """(corpus, id, prefix, text): the named workloads, whole (prefix null) or at the given prefix lengths."""
    out = None
    for name in names:
        texts = CATALOG[name](spark, sf_dir, most=max(prefixes)) if prefixes and name in _JOINED else CATALOG[name](spark, sf_dir)
        rows = texts.select(F.lit(name).alias("corpus"), F.col("id").cast("string").alias("id"), F.lit(None).cast("int").alias("prefix"), "text")
        for n in prefixes or [None]:
            one = rows if n is None else prefix(rows, n).withColumn("prefix", F.lit(n))
            out = one if out is None else out.unionByName(one)
    return out


def catalog_pieces(spark: SparkSession, sf_dir: str, names: list[str]) -> list[tuple[DataFrame, str]]:
    """The named workloads that are put together from rows, as pieces (name, place, piece) with their separators; a name is corpus:id."""
    out = []
    for name in names:
        rows = CATALOG[name](spark, sf_dir, join=placed)
        separator = "\n" if name == "records" else ""
        out.append((rows.select(F.concat_ws(":", F.lit(name), F.col("id").cast("string")).alias("name"), "place", "piece"), separator))
    return out
