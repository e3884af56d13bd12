"""The kernels as SQL and DataFrame functions: scalar, table-valued and aggregate."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from dictparse.kernels.lce import bounded_match, suffix_match
from dictparse.operators.factorize import factor_row, parse, seen
from dictparse.plans.spec import FACTOR, FACTOR_LIST, columns, named


def parse_count(scheme: str):
    """Column function: factor count of a text; null for null."""
    spec = named(scheme)

    @F.pandas_udf(T.IntegerType())
    def count(text: pd.Series) -> pd.Series:
        return text.map(lambda t: None if t is None else len(parse(t, spec).phrases)).astype("Int32")

    return count


def parse_list(scheme: str):
    """Column function: the factors of a text as an array of structs."""
    spec = named(scheme)
    names = [n for n, _ in FACTOR]

    @F.pandas_udf(FACTOR_LIST)
    def factors(text: pd.Series) -> pd.Series:
        one = lambda t: [dict(zip(names, factor_row(x, f), strict=True)) | {"piece": t[f[0] : f[0] + f[1]]} for x, f in enumerate(parse(t, spec).phrases, 1)]
        return text.map(lambda t: None if t is None else one(t))

    return factors


@F.pandas_udf(T.IntegerType())
def lce_udf(text: pd.Series, i: pd.Series, j: pd.Series) -> pd.Series:
    return pd.Series([suffix_match(t, int(a), int(b)) for t, a, b in zip(text, i, j, strict=True)], dtype="int32")


@F.pandas_udf(T.IntegerType())
def bounded_lce_udf(text: pd.Series, i: pd.Series, j: pd.Series, limit: pd.Series) -> pd.Series:
    return pd.Series([bounded_match(t, int(a), int(b), int(m)) for t, a, b, m in zip(text, i, j, limit, strict=True)], dtype="int32")


def corpus_count(scheme: str):
    """Aggregate function over (order, piece): factor count of a group's pieces joined in order."""
    spec = named(scheme)

    @F.pandas_udf(T.IntegerType())
    def count(order: pd.Series, piece: pd.Series) -> int:
        text = "".join(piece.iloc[np.argsort(order.to_numpy(), kind="stable")])
        return len(parse(text, spec).phrases)

    return count


@F.pandas_udf(T.DoubleType())
def linear_slope(x: pd.Series, y: pd.Series) -> float:
    """Aggregate function: least-squares slope."""
    return float(np.polyfit(x.astype(float), y.astype(float), 1)[0]) if len(x) > 1 else float("nan")


class FactorRows:
    """Table function factor_rows(text, scheme): one row for each factor."""

    def eval(self, text: str, scheme: str):
        if text is None:
            return
        spec = named(scheme)
        own = seen(text, spec.symbols)
        for x, f in enumerate(parse(own, spec).phrases, 1):
            yield (*factor_row(x, f), own[f[0] : f[0] + f[1]])


class FactorOfGroup:
    """Table function over a table argument (fragment, scheme) partitioned by a key and ordered: factors of the joined fragments."""

    def __init__(self) -> None:
        self.parts: list[str] = []
        self.scheme = "pair_cut"

    def eval(self, row) -> None:
        self.parts.append(row["fragment"] or "")
        self.scheme = row["scheme"]

    def terminate(self):
        text = "".join(self.parts)
        for x, f in enumerate(parse(text, named(self.scheme)).phrases, 1):
            yield (*factor_row(x, f), text[f[0] : f[0] + f[1]])


FACTOR_ROWS = columns([*FACTOR, ("piece", "string")])


def factor_rows():
    return F.udtf(FactorRows, returnType=FACTOR_ROWS)


def register(spark: SparkSession) -> None:
    """All functions for SQL: parse_count_<scheme>, parse_list_<scheme>, lce, bounded_lce, factor_rows, factors_of_group."""
    for scheme in ("pair", "pair_cut", "pair_run", "step", "seeded", "step_run"):
        spark.udf.register(f"parse_count_{scheme}", parse_count(scheme))
        spark.udf.register(f"parse_list_{scheme}", parse_list(scheme))
    spark.udf.register("lce", lce_udf)
    spark.udf.register("bounded_lce", bounded_lce_udf)
    spark.udtf.register("factor_rows", factor_rows())
    spark.udtf.register("factors_of_group", F.udtf(FactorOfGroup, returnType=FACTOR_ROWS))
