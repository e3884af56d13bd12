"""Other ways to the same factors of pair_cut, for cross-checks: a fold in Catalyst, recursive SQL, and rounds of joins.

They compare all earlier strings and suit short texts. Columns: ids, x, beg, len, kind.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from dictparse.functions.columns import common_prefix


def factorize(df: DataFrame, text_col: str, id_cols: list[str], *, scheme: str, engine: str) -> DataFrame:
    if scheme != "pair_cut" or engine not in ENGINES:
        raise ValueError(f"no engine {engine!r} for {scheme!r}")
    return ENGINES[engine](df.select(*id_cols, F.col(text_col).alias("_text")).where("_text IS NOT NULL"), id_cols)


def _entry(entries: Column, rest: Column) -> Column:
    """Length of the longest whole entry that begins the rest, 1 at least."""
    fit = F.filter(entries, lambda e: F.startswith(rest, e))
    return F.greatest(F.lit(1), F.coalesce(F.array_max(F.transform(fit, F.length)), F.lit(1)))


def _cut(entries: Column, rest: Column) -> Column:
    near = F.filter(entries, lambda e: F.substring(e, 1, 1) == F.substring(rest, 1, 1))
    return F.coalesce(F.array_max(F.transform(near, lambda e: common_prefix(e, rest))), F.lit(0))


def fold(df: DataFrame, ids: list[str]) -> DataFrame:
    """One aggregate() over a step for each symbol; the state holds the place, the entries and the factors so far."""
    text, n = F.col("_text"), F.length("_text")
    state = "struct<pos:int,entries:array<string>,out:array<struct<beg:int,len:int,kind:string>>>"
    start = F.from_json(F.lit('{"pos":1,"entries":[],"out":[]}'), state)

    def step(s: Column, k: Column) -> Column:
        rest = F.substring(text, s["pos"], n)
        let = lambda v, body: F.element_at(F.transform(F.array(v), body), 1)
        second = lambda a: F.when(s["pos"] + a > n, F.lit(0)).otherwise(F.greatest(F.lit(1), _cut(s["entries"], F.substring(text, s["pos"] + a, n))))
        combined = let(_entry(s["entries"], rest), lambda a: a + second(a))
        found = let(F.struct(combined.alias("a"), _cut(s["entries"], rest).alias("c")), lambda v: F.struct(F.greatest(v["a"], v["c"]).alias("len"), F.when(v["a"] >= v["c"], F.lit("combine")).otherwise(F.lit("cut")).alias("kind")))
        grown = let(
            found,
            lambda f: F.struct(
                (s["pos"] + f["len"]).cast("int").alias("pos"),
                F.array_append(s["entries"], F.substring(text, s["pos"], f["len"])).alias("entries"),
                F.array_append(s["out"], F.struct(s["pos"].alias("beg"), f["len"].cast("int").alias("len"), f["kind"].alias("kind"))).alias("out"),
            ),
        )
        return F.when(s["pos"] > n, s).otherwise(grown)

    # every factor but the last has two symbols at least
    steps = F.sequence(F.lit(0), F.ceil(n / 2).cast("int"))
    parsed = df.where(n > 0).withColumn("_s", F.aggregate(steps, start, step))
    return parsed.select(*ids, F.posexplode("_s.out").alias("_k", "_f")).select(*ids, (F.col("_k") + 1).alias("x"), F.col("_f.beg").cast("long").alias("beg"), F.col("_f.len").alias("len"), F.col("_f.kind").alias("kind"))


def recursive(df: DataFrame, ids: list[str]) -> DataFrame:
    """WITH RECURSIVE: one level for each factor, all texts at once."""
    spark = df.sparkSession
    df.createOrReplaceTempView("_recursive_source")
    spark.conf.set("spark.sql.cteRecursionLevelLimit", "100000")
    spark.conf.set("spark.sql.cteRecursionRowLimit", "-1")
    key = ", ".join(f"`{c}`" for c in ids)
    entry = lambda rest: f"greatest(1, coalesce(array_max(transform(filter(ds, e -> startswith({rest}, e)), e -> length(e))), 1))"
    cut = lambda rest: f"coalesce(array_max(transform(filter(ds, e -> left(e, 1) = left({rest}, 1)), e -> array_max(filter(sequence(0, least(length(e), length({rest}))), n -> left(e, n) = left({rest}, n))))), 0)"
    rest = "substring(_text, pos)"
    return spark.sql(
        f"""WITH RECURSIVE run AS (
  SELECT {key}, _text, 1 AS pos, CAST(array() AS array<string>) AS ds, 0 AS x, 0 AS beg, 0 AS len, '' AS kind FROM _recursive_source
  UNION ALL
  SELECT {key}, _text, pos + size, array_append(ds, substring(_text, pos, size)), x + 1, pos, size, CASE WHEN a >= c THEN 'combine' ELSE 'cut' END FROM (
    SELECT *, greatest(a, c) AS size FROM (
      SELECT *, l1 + CASE WHEN pos + l1 > length(_text) THEN 0 ELSE greatest(1, {cut('substring(_text, pos + l1)')}) END AS a, {cut(rest)} AS c FROM (
        SELECT *, {entry(rest)} AS l1 FROM run WHERE pos <= length(_text)))))
SELECT {key}, x, CAST(beg AS BIGINT) AS beg, len, kind FROM run WHERE x > 0"""
    )


def rounds(df: DataFrame, ids: list[str]) -> DataFrame:
    """One factor of every unfinished text for each round, by joins of the frontier with the entries; each round cuts the lineage."""
    source = df.withColumn("_n", F.length("_text"))
    frontier = source.select(*ids, F.lit(1).alias("_pos"), F.lit(0).alias("_x"))
    done = None
    while True:
        here = frontier.join(source, ids).where("_pos <= _n")
        if not here.limit(1).count():
            break
        rest = F.substring(F.col("_text"), F.col("_pos"), F.col("_n"))
        known = done.select(*ids, "piece") if done is not None else frontier.where("false").select(*ids, F.lit("").alias("piece"))
        heads = here.withColumn("_rest", rest)
        first = heads.join(known, ids, "left").groupBy(*ids, "_text", "_n", "_pos", "_x", "_rest").agg(F.coalesce(F.max(F.when(F.startswith("_rest", "piece"), F.length("piece"))), F.lit(1)).alias("_l1"), F.coalesce(F.max(common_prefix(F.col("piece"), F.col("_rest"))), F.lit(0)).alias("_c"))
        ahead = first.withColumn("_l1", F.greatest("_l1", F.lit(1))).withColumn("_ahead", F.expr("substring(_text, _pos + _l1)"))
        both = ahead.join(known, ids, "left").groupBy(*ids, "_n", "_pos", "_x", "_rest", "_l1", "_c").agg(F.coalesce(F.max(common_prefix(F.col("piece"), F.col("_ahead"))), F.lit(0)).alias("_l2"))
        a = F.col("_l1") + F.when(F.col("_pos") + F.col("_l1") > F.col("_n"), 0).otherwise(F.greatest(F.lit(1), F.col("_l2")))
        found = both.withColumn("_a", a).withColumn("len", F.greatest("_a", "_c")).withColumn("kind", F.when(F.col("_a") >= F.col("_c"), "combine").otherwise("cut"))
        step = found.select(*ids, (F.col("_x") + 1).alias("x"), F.col("_pos").cast("long").alias("beg"), "len", "kind", F.expr("left(_rest, len)").alias("piece"))
        done = cut_lineage(step if done is None else done.unionByName(step))
        frontier = done.groupBy(*ids).agg((F.max(F.col("beg") + F.col("len"))).cast("int").alias("_pos"), F.max("x").alias("_x"))
    return done.drop("piece")


def cut_lineage(df: DataFrame) -> DataFrame:
    """A reliable checkpoint in the folder that the session names, or in one beside the warehouse, which the cluster shares too."""
    spark = df.sparkSession
    if spark.sparkContext.getCheckpointDir() is None:
        beside = f"{spark.conf.get('spark.sql.warehouse.dir').rstrip('/')}/dictparse-checkpoints"
        spark.sparkContext.setCheckpointDir(spark.conf.get("spark.checkpoint.dir", None) or beside)
    return df.checkpoint()


ENGINES = {"fold": fold, "recursive": recursive, "rounds": rounds}
