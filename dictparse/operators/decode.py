"""Back from factor tables to texts, and the views of a parse as a grammar or a collage system."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dictparse.kernels.tokens import decode as decode_factors

_TOKEN = ["beg", "len", "kind", "ref1", "sym1", "ref2", "sym2", "power"]


def decode(factors: DataFrame, id_cols: list[str]) -> DataFrame:
    """(ids, block_id, scheme, text) from a factor table, with entry rows where the look-ahead has them (roles=True)."""
    kinds = {k: factors.schema[k].dataType.simpleString() for k in id_cols}
    has_roles = "role" in factors.columns
    keys = [*id_cols, "block_id", "scheme"]

    def run(table: pa.Table) -> pa.Table:
        roles = table["role"].to_pylist() if has_roles else ["phrase"] * table.num_rows
        rows = [*zip(roles, table["x"].to_pylist(), *(table[c].to_pylist() for c in _TOKEN), strict=True)]
        lists = {r: [(b - 1, *rest) for _, _, b, *rest in sorted(t for t in rows if t[0] == r)] for r in ("phrase", "entry")}
        scheme = table["scheme"][0].as_py()
        text = decode_factors(lists["phrase"], lists["entry"] or None, scheme.partition("+")[0])
        return pa.table({**{k: table[k].slice(0, 1) for k in keys}, "text": pa.array([text])})

    shape = ", ".join([*(f"`{k}` {v}" for k, v in kinds.items()), "block_id int", "scheme string", "text string"])
    return factors.groupBy(*keys).applyInArrow(run, shape)


def joined_blocks(decoded: DataFrame, id_cols: list[str]) -> DataFrame:
    """Texts from their decoded blocks."""
    pieces = F.array_sort(F.collect_list(F.struct("block_id", "text")))
    return decoded.groupBy(*id_cols, "scheme").agg(F.array_join(F.transform(pieces, lambda b: b["text"]), "").alias("text"))


def collage(factors: DataFrame, id_cols: list[str]) -> DataFrame:
    """The assignments of a collage system for pair_cut and pair_run factors.

    Each factor gives up to four: a symbol for either part, their concatenation or power, and a cut to the factor's length. `form` is
    symbol, concat, power, cut or empty; a and b name what is combined (f: a factor's variable, s: a symbol).
    """
    part = lambda ref, sym: F.when(F.col(sym).isNotNull(), F.concat(F.lit("s:"), sym)).when(F.col(ref) == 0, F.lit("e")).otherwise(F.concat(F.lit("f:"), F.col(ref).cast("string")))
    a, b = part("ref1", "sym1"), part("ref2", "sym2")
    none = F.lit(None).cast("string")
    make = lambda form, x, y: F.struct(F.lit(form).alias("form"), x.alias("a"), y.alias("b"), F.col("len").alias("len"))
    body = F.when(F.col("kind") == "combine", F.array(make("concat", a, b))).when(F.col("kind") == "repeat", F.array(make("power", a, F.col("power").cast("string")), make("cut", none, none))).otherwise(F.array(make("cut", a, none)))
    symbols = F.filter(F.array(F.when(F.col("sym1").isNotNull(), make("symbol", F.col("sym1"), none)), F.when(F.col("sym2").isNotNull(), make("symbol", F.col("sym2"), none))), lambda s: s.isNotNull())
    # a second part that is cut needs a cut of the concatenation
    whole = F.concat(symbols, body)
    cut_second = (F.col("kind") == "combine") & F.col("ref2").isNotNull() & (F.col("ref2") > 0)
    rows = factors.withColumn("_all", F.when(cut_second, F.concat(whole, F.array(make("cut", none, none)))).otherwise(whole))
    return rows.select(*id_cols, "x", F.posexplode("_all").alias("k", "one")).select(*id_cols, "x", "k", "one.*")


def collage_size(factors: DataFrame, id_cols: list[str]) -> DataFrame:
    """Assignments by form, in all, and the length of the phrase sequence. A symbol is assigned once for a text."""
    rows = collage(factors, id_cols)
    symbols = F.countDistinct(F.when(F.col("form") == "symbol", F.col("a")))
    count = lambda form: F.count(F.when(F.col("form") == form, 1))
    out = rows.groupBy(*id_cols).agg(symbols.alias("symbols"), count("concat").alias("concats"), count("power").alias("powers"), count("cut").alias("cuts"), F.max("x").cast("long").alias("phrases"))
    return out.withColumn("size", F.col("symbols") + F.col("concats") + F.col("powers") + F.col("cuts"))


def evaluate_collage(assignments: list[tuple[int, str, str | None, str | None, int]]) -> str:
    """The text of one collage system: (x, form, a, b, len) in order; each x ends with its last form."""
    value: dict[str, str] = {"e": ""}
    name = lambda v: v[2:] if v.startswith("s:") else value[v]
    last, order = "", []
    for x, form, a, b, length in assignments:
        if form == "symbol":
            continue
        if form == "concat":
            last = name(a) + name(b)
        elif form == "power":
            last = name(a) * int(b)
        elif form == "prefix_cut":
            last = (name(a) if a else last)[-length:]
        else:
            last = (name(a) if a else last)[:length]
        value[f"f:{x}"] = last
        order = order if order and order[-1] == x else [*order, x]
    return "".join(value[f"f:{x}"] for x in order)


def grammar_rules(factors: DataFrame, id_cols: list[str]) -> DataFrame:
    """pair factors as the rules of a straight-line grammar: left side x, right side of one or two symbols; the start rule has z."""
    side = lambda ref, sym: F.coalesce(F.col(sym), F.when(F.col(ref) > 0, F.concat(F.lit("N"), F.col(ref).cast("string"))))
    return factors.select(*id_cols, "x", F.array_compact(F.array(side("ref1", "sym1"), side("ref2", "sym2"))).alias("right"))


def grammar_size(factors: DataFrame, id_cols: list[str]) -> DataFrame:
    """Total length of the right sides, with the start rule's."""
    return grammar_rules(factors, id_cols).groupBy(*id_cols).agg((F.sum(F.size("right")) + F.count("*")).alias("size"), F.count("*").alias("z"))
