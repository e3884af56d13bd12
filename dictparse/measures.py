"""Cost measures over factor tables and parse summaries (id, scheme, z, ...)."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def count(factors: DataFrame, ids: list[str]) -> DataFrame:
    """Factors of each text and scheme, over its blocks."""
    return factors.groupBy(*ids, "scheme").agg(F.count("*").alias("z"))


def column_name(scheme: str) -> str:
    return scheme.replace("+", "_")


def wide(counts: DataFrame, ids: list[str], schemes: list[str]) -> DataFrame:
    """One column of counts for each scheme."""
    return counts.groupBy(*ids).pivot("scheme", schemes).agg(F.sum("z")).select(*ids, *(F.col(f"`{s}`").alias(column_name(s)) for s in schemes))


def percent(part, whole, digits: int = 4):
    """(part / whole - 1) * 100, null for an empty whole. Rounded half up in decimals, so engines agree."""
    return F.round((part.cast("decimal(28,0)") - whole) * 100 / F.nullif(whole.cast("decimal(28,0)"), F.lit(0)), digits).cast("decimal(18,4)")


def relative(counts: DataFrame, ids: list[str], schemes: list[str], base: str = "pair") -> DataFrame:
    """Each scheme's count against the base's, in percent; negative is better."""
    table = wide(counts, ids, [base, *(s for s in schemes if s != base)])
    return table.select(*ids, *(percent(F.col(column_name(s)), F.col(column_name(base))).alias(column_name(s)) for s in schemes if s != base))


def ranked(counts: DataFrame, ids: list[str]) -> DataFrame:
    return counts.withColumn("place", F.rank().over(Window.partitionBy(*ids).orderBy("z")))


def winners(counts: DataFrame, ids: list[str]) -> DataFrame:
    """The schemes with the fewest factors on each text, ties all."""
    return ranked(counts, ids).where("place = 1").drop("place")


def win_table(counts: DataFrame, ids: list[str]) -> DataFrame:
    return winners(counts, ids).groupBy("scheme").agg(F.count("*").alias("wins"))


def improvement(relatives: DataFrame, schemes: list[str]) -> DataFrame:
    """Mean, best and median of each scheme's percentages."""
    long = relatives.unpivot([], [column_name(s) for s in schemes], "scheme", "percent")
    return long.groupBy("scheme").agg(F.avg("percent").alias("mean"), F.min("percent").alias("best"), F.percentile_approx("percent", 0.5).alias("median"))


def ratio(counts: DataFrame, ids: list[str], scheme: str = "step_run", base: str = "step") -> DataFrame:
    """A scheme's count in percent of another's; over 100 means more factors."""
    table = wide(counts, ids, [scheme, base])
    return table.withColumn("ratio", F.round(F.col(scheme).cast("decimal(28,0)") * 100 / F.nullif(F.col(base).cast("decimal(28,0)"), F.lit(0)), 2).cast("decimal(18,2)"))


def median_time(runs: DataFrame, ids: list[str]) -> DataFrame:
    """Median of repeated runs (ids..., seconds)."""
    return runs.groupBy(*ids).agg(F.median("seconds").alias("seconds"), F.count("*").alias("runs"))


def linearity(points: DataFrame, ids: list[str], x: str = "n", y: str = "seconds") -> DataFrame:
    """Slope, intercept and r2 of a cost against the text length."""
    return points.groupBy(*ids).agg(F.regr_slope(y, x).alias("slope"), F.regr_intercept(y, x).alias("intercept"), F.regr_r2(y, x).alias("r2"))


def throughput(points: DataFrame) -> DataFrame:
    return points.withColumn("mib_s", F.col("n") / (1 << 20) / F.col("seconds"))


def work(summary: DataFrame) -> DataFrame:
    """Whether searches and trie keep to their bounds: child lookups at most 6n + 6z, nodes at most 2z + 1."""
    return summary.withColumn("steps_ok", F.col("child_steps") <= 6 * F.col("n") + 6 * F.col("z")).withColumn("nodes_ok", F.col("trie_nodes") <= 2 * F.col("z") + 1)


def family_table(counts: DataFrame) -> DataFrame:
    """Counts on the four-letter family beside the linear and the quadratic law."""
    k = F.col("id").cast("long")
    table = wide(counts, ["id"], ["pair", "pair_cut", "pair_run"])
    return table.withColumn("linear", 6 * k + 3).withColumn("quadratic", 5 * k + F.expr("id * id div 4"))


def encoded_bits(factors: DataFrame, ids: list[str], sigma: int = 256) -> DataFrame:
    """An estimate of stored size: two bits for the kind, ceil(log2(x + sigma)) for each part, a universal code for lengths and powers.

    Whole second parts need no length; a cut second part does, so each combination with a reference pays for one.
    """
    x, n = F.col("x"), F.col("len")
    reference = F.ceil(F.log2(x + sigma)).cast("long")
    universal = lambda v: 2 * F.floor(F.log2(v)).cast("long") + 1
    cut_second = (F.col("kind") == "combine") & (F.coalesce(F.col("ref2"), F.lit(0)) > 0) & ~F.col("scheme").startswith("pair+") & (F.col("scheme") != "pair")
    bits = F.when(F.col("kind") == "combine", 2 + 2 * reference + F.when(cut_second, universal(n)).otherwise(0)).when(F.col("kind").isin("cut", "repeat"), 2 + reference + universal(n)).when(F.col("kind") == "extend", 2 * reference).otherwise(reference)
    return factors.groupBy(*ids, "scheme").agg(F.sum(bits).alias("bits"), F.sum("len").alias("symbols"))


def compression_ratio(bits: DataFrame, symbol_bits: int = 8) -> DataFrame:
    """Estimated stored bits against those of the plain text, in ten-thousandths."""
    return bits.withColumn("ratio_e4", F.expr(f"bits * 10000 div (symbols * {symbol_bits})"))


def blocking_loss(blocked: DataFrame, whole: DataFrame, ids: list[str]) -> DataFrame:
    """What separate dictionaries cost: summed counts of a text's blocks against the whole text's, in percent."""
    summed = blocked.groupBy(*ids, "scheme").agg(F.sum("z").alias("blocks_z"))
    joined = summed.join(whole.select(*ids, "scheme", F.col("z").alias("whole_z")), [*ids, "scheme"])
    return joined.withColumn("loss", percent(F.col("blocks_z"), F.col("whole_z")))


def sampled(df: DataFrame, key: str, one_in: int) -> DataFrame:
    """A repeatable sample by key hash, for estimates of corpus percentages."""
    return df.where(F.pmod(F.xxhash64(key), F.lit(one_in)) == 0)


def estimate(relatives: DataFrame, scheme: str) -> DataFrame:
    """Mean percentage of a sample with its 95 % interval."""
    c = F.col(column_name(scheme)).cast("double")
    half = 1.96 * F.stddev_samp(c) / F.sqrt(F.count(c))
    return relatives.agg(F.avg(c).alias("mean"), (F.avg(c) - half).alias("low"), (F.avg(c) + half).alias("high"), F.count(c).alias("texts"))

