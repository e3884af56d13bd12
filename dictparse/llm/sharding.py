"""Shards by jump consistent hashing: key and shard count decide, and a new last shard takes only what moves into it.

Slots follow the key within a shard, then size and checksum, whatever the cluster's settings.

Edge cases: a null key counts as the key 0 and a null text as empty; repeated rows each get a slot of their own; an empty table
gives an empty result; further columns of the input are neither read nor returned.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from dictparse.llm.common import read, utf8_bytes, written

#: Fixed values of the jump hash: the multiplier of its 64-bit generator and its 31-bit range.
_MULTIPLIER, _RANGE = 2862933555777941757, float(1 << 31)
#: Identical rows that one step writes out; more of them are first dealt to several tasks.
_RUN = 4096


def jump(keys: np.ndarray, shards: int) -> np.ndarray:
    """The shard (0 to shards-1) of each 64-bit key; every step jumps to the next shard count at which the key would move."""
    if shards < 1:
        raise ValueError("at least one shard")
    state = keys.astype(np.int64).view(np.uint64).copy()
    at, ahead = np.zeros(len(state), np.int64), np.zeros(len(state), np.int64)
    moving = np.arange(len(state))
    while len(moving):
        at[moving] = ahead[moving]
        state[moving] = state[moving] * np.uint64(_MULTIPLIER) + np.uint64(1)
        draw = (state[moving] >> np.uint64(33)).astype(np.float64) + 1.0
        ahead[moving] = np.floor((at[moving] + 1) * (_RANGE / draw)).astype(np.int64)
        moving = moving[ahead[moving] < shards]
    return at


def shard_of(key: Column, shards: int) -> Column:
    """Column form of jump() for a whole-number key (hash other keys to 64 bits first)."""

    @F.pandas_udf(T.IntegerType())
    def of(k: pd.Series) -> pd.Series:
        return pd.Series(jump(k.to_numpy(np.int64), shards).astype(np.int32))

    return of(F.coalesce(key.cast("long"), F.lit(0)))


def with_slots(rows: DataFrame, shard: str = "shard", slot: str = "slot", blocks: int | None = None) -> DataFrame:
    """Adds a gapless position within each shard, in the order of the rows' columns, without gathering a shard in one task.

    Identical rows are counted first, so a hot key costs one row; rows are dealt into ranges of (shard, columns) and ranked in
    them; the ranges' sizes (at most one small row for each shard and range) give each range its first slot.
    """
    cols = rows.columns
    blocks = blocks or int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    counted = rows.groupBy(*cols).agg(F.count(F.lit(1)).alias("_n"))
    # the ranges come from a sample of the rows, so they are written down before they are read twice
    counted = written(counted.repartitionByRange(blocks, shard, *(c for c in cols if c != shard)).withColumn("_block", F.spark_partition_id()), "shard-rows")
    ahead = Window.partitionBy(shard).orderBy("_block").rowsBetween(Window.unboundedPreceding, -1)
    starts = counted.groupBy(shard, "_block").agg(F.sum("_n").alias("_size")).select(shard, "_block", F.coalesce(F.sum("_size").over(ahead), F.lit(0)).alias("_first"))
    inside = Window.partitionBy(shard, "_block").orderBy(*cols).rowsBetween(Window.unboundedPreceding, -1)
    ranked = counted.withColumn("_before", F.coalesce(F.sum("_n").over(inside), F.lit(0)))
    # at most blocks + shards rows of 20 bytes, fixed by the two parameters and not by the data
    ranked = ranked.join(F.broadcast(starts) if blocks <= 4096 else starts, [shard, "_block"])
    runs = ranked.withColumn("_run", F.explode(F.sequence(F.lit(0), F.floor((F.col("_n") - 1) / _RUN)))).repartition("_block", "_before", "_run")
    last = F.least(F.col("_n"), (F.col("_run") + 1) * _RUN) - 1
    return runs.withColumn("_k", F.explode(F.sequence(F.col("_run") * _RUN, last))).select(*cols, (F.col("_first") + F.col("_before") + F.col("_k")).cast("long").alias(slot))


def shard_documents(docs: DataFrame, shards: int = 8, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Every row's shard, its slot in it, and its shard once one more is appended."""
    rows = docs.select(F.col(key).cast("long").alias(key), (utf8_bytes(F.col(text)) + 1).cast("long").alias("size"), F.crc32(F.coalesce(F.col(text), F.lit("")).cast("binary")).alias("text_crc32"))
    placed = rows.withColumn("shard", shard_of(F.col(key), shards)).withColumn("grown_shard", shard_of(F.col(key), shards + 1))
    return with_slots(placed).select(key, "size", "text_crc32", F.lit("key").alias("law"), "shard", "slot", "grown_shard")


def op4_jump_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard of every document, in 8 shards by `key`."""
    return shard_documents(read(spark, sf_dir, "documents"))


QUERIES = {"op4_jump_shards": op4_jump_shards}

#: The checksum byte by byte over a table made from its polynomial, the jumps by recursion on unsigned 64-bit states.
SQL = {
    "op4_jump_shards": f"""
WITH RECURSIVE table_steps AS (
  SELECT CAST(b AS BIGINT) AS b, CAST(b AS BIGINT) AS v, 0 AS k FROM range(256) AS u(b)
  UNION ALL SELECT b, xor(v >> 1, 3988292384 * (v & 1)), k + 1 FROM table_steps WHERE k < 8
), crcs AS MATERIALIZED (
  SELECT list(v ORDER BY b) AS t FROM table_steps WHERE k = 8
), texts AS MATERIALIZED (
  SELECT row_number() OVER () AS r, doc_id,
    list_transform(regexp_extract_all(hex(encode(coalesce(text, ''))), '..'), lambda x: CAST('0x' || x AS BIGINT)) AS raw
  FROM documents
), jumps AS (
  SELECT r, n, CAST(0 AS BIGINT) AS here, CAST(0 AS BIGINT) AS ahead, (CAST(coalesce(doc_id, 0) AS HUGEINT) + {1 << 64}) % {1 << 64} AS state
  FROM texts, (VALUES (8), (9)) AS s(n)
  UNION ALL
  SELECT r, n, ahead, CAST(floor((ahead + 1) * ({_RANGE}::DOUBLE / CAST((state * {_MULTIPLIER} + 1) % {1 << 64} // {1 << 33} + 1 AS DOUBLE))) AS BIGINT),
    (state * {_MULTIPLIER} + 1) % {1 << 64}
  FROM jumps WHERE ahead < n
), places AS (
  SELECT r, n, CAST(max(here) AS INTEGER) AS shard FROM jumps GROUP BY r, n
), sized AS (
  SELECT t.doc_id, CAST(len(t.raw) + 1 AS BIGINT) AS size, p.shard, g.shard AS grown_shard,
    xor(list_reduce(list_prepend(CAST(4294967295 AS BIGINT), t.raw), lambda a, b: xor(a >> 8, list_extract(crcs.t, (xor(a, b) & 255) + 1))), 4294967295) AS text_crc32
  FROM texts t JOIN places p ON p.r = t.r AND p.n = 8 JOIN places g ON g.r = t.r AND g.n = 9, crcs
)
SELECT doc_id, size, text_crc32, 'key' AS law, shard, grown_shard,
  CAST(row_number() OVER (PARTITION BY shard ORDER BY doc_id NULLS FIRST, size, text_crc32) - 1 AS BIGINT) AS slot
FROM sized"""
}
