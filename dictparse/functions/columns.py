"""String functions of the engine as Column expressions; they stay in the JVM."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def common_prefix(a: Column, b: Column, most: Column | None = None) -> Column:
    """Length of the common prefix of two strings."""
    limit = F.least(F.length(a), F.length(b)) if most is None else F.least(F.length(a), F.length(b), most)
    return F.coalesce(F.array_max(F.filter(F.sequence(F.lit(0), limit.cast("int")), lambda n: F.substring(a, F.lit(1), n) == F.substring(b, F.lit(1), n))), F.lit(0))


def lce(text: Column, i: Column, j: Column) -> Column:
    """Longest common extension of the suffixes at two 1-based positions."""
    n = F.length(text)
    inside = (i >= 1) & (j >= 1) & (i <= n) & (j <= n)
    return F.when(inside, common_prefix(F.substring(text, i, n), F.substring(text, j, n))).otherwise(F.lit(0))


def bounded_lce(text: Column, i: Column, j: Column, limit: Column) -> Column:
    return F.least(lce(text, i, j), limit.cast("int"))


def power_prefix(base: Column, length: Column) -> Column:
    """The first `length` symbols of the endless repetition of a string."""
    return F.substring(F.repeat(base, F.ceil(length / F.length(base)).cast("int")), F.lit(1), length.cast("int"))


def is_prefix(a: Column, b: Column) -> Column:
    """Whether the second string begins with the first."""
    return F.startswith(b, a)


def token_text(kind: Column, ref1: Column, sym1: Column, ref2: Column, sym2: Column, length: Column, power: Column) -> Column:
    """A token in one line: parts joined by +, a power as ^k, the length after |."""
    part = lambda r, s: F.when(s.isNotNull(), F.concat(F.lit("'"), s, F.lit("'"))).when(r > 0, F.concat(F.lit("#"), r.cast("string"))).otherwise(F.lit("0"))
    body = F.when(kind == "repeat", F.concat(part(ref1, sym1), F.lit("^"), power.cast("string"))).when(kind.isin("combine", "extend"), F.concat_ws("+", part(ref1, sym1), part(ref2, sym2))).otherwise(part(ref1, sym1))
    return F.concat(body, F.lit("|"), length.cast("string"))


def sql_functions(spark) -> None:
    """power_prefix and is_prefix as SQL functions."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION power_prefix(base STRING, n INT) RETURNS STRING RETURN substring(repeat(base, CAST(ceil(n / length(base)) AS INT)), 1, n)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION is_prefix(a STRING, b STRING) RETURNS BOOLEAN RETURN startswith(b, a)")
