"""Line dedup over levelled sorted runs of line hashes; DataFrame operations only.

A line's key is the line without ASCII white space at both ends, A-Z lower-cased. Runs are Parquet tables sorted by the key's
128-bit hash with the number of documents and the largest document that hold it. Each batch is merge-anti-joined with the runs: keys
that no run holds make a run of their own, the others are only counted up in a log, so a key stands in one run, and compaction
(`fanout` runs of a level into one of the next) joins runs without counting. Counts are then taken only of keys in the log or with
enough documents in one batch, which are few beside the keys seen once. A line that many documents hold is joined by broadcast.

Edge cases: a null or empty text has one empty line; a null document id counts as one document before all others; rows that
share an id count as one document; an empty table gives an empty result; further columns, whatever their names, stay as they are.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from dictparse.llm.common import fresh, read, shared_dir, skewed_join, written

#: Fixed values of the contract: white space stripped from a line, and the letters that are folded.
_WHITE = " \t\n\x0b\x0c\r"
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_NO_ID = -(1 << 63)
MIN_POINTS, MIN_DOCS = 20, 3


def line_key(line: Column) -> Column:
    return F.translate(F.btrim(line, F.lit(_WHITE)), _UPPER, _LOWER)


def lines_of(text: Column) -> Column:
    return F.split(F.coalesce(text, F.lit("")), "\n", -1)


def _hashes(key: Column) -> tuple[Column, Column]:
    return F.xxhash64(key), F.xxhash64(F.lit(7), key)


def _doc(doc: Column) -> Column:
    return F.coalesce(doc.cast("long"), F.lit(_NO_ID))


def line_keys(docs: DataFrame, doc: str, text: str, min_points: int) -> DataFrame:
    """(h1, h2, doc) once for each document and key that is long enough."""
    lines = docs.select(_doc(F.col(doc)).alias("doc"), F.explode(lines_of(F.col(text))).alias("line")).select("doc", line_key(F.col("line")).alias("key"))
    h1, h2 = _hashes(F.col("key"))
    return lines.where(F.length("key") >= min_points).select(h1.alias("h1"), h2.alias("h2"), "doc").groupBy("h1", "h2", "doc").agg(F.lit(1).alias("_")).drop("_")


class LineRuns:
    """Levels of sorted runs (h1, h2, n_docs, max_doc) in the shared folder, and the log of keys that came again."""

    def __init__(self, spark: SparkSession, fanout: int = 4):
        self.spark, self.fanout, self.levels, self.log = spark, fanout, [[]], []
        shared_dir(spark)

    def runs(self) -> list[DataFrame]:
        return [r for level in self.levels for r in level]

    @staticmethod
    def _union(tables: list[DataFrame]) -> DataFrame:
        both = tables[0]
        for t in tables[1:]:
            both = both.unionByName(t)
        return both

    def unseen(self, rows: DataFrame) -> DataFrame:
        """The rows whose key no run holds: one merge anti-join for each run, both sides in key order."""
        for run in self.runs():
            rows = rows.join(run.select("h1", "h2").hint("merge"), ["h1", "h2"], "left_anti")
        return rows

    def add(self, keys: DataFrame) -> None:
        """A batch of (h1, h2, doc); a document must not come in two batches."""
        batch = keys.groupBy("h1", "h2").agg(F.count(F.lit(1)).alias("n_docs"), F.max("doc").alias("max_doc"))
        if self.runs():
            batch = written(batch.sortWithinPartitions("h1", "h2"), "line-batch")
        new = written(self.unseen(batch).sortWithinPartitions("h1", "h2"), "line-run-0")
        if self.runs():
            self.log.append(written(batch.join(new.select("h1", "h2").hint("merge"), ["h1", "h2"], "left_anti"), "line-log"))
        self.levels[0].append(new)
        self.compact()

    def compact(self) -> None:
        """Merges full levels downwards."""
        for n, level in enumerate(self.levels):
            if len(level) >= self.fanout:
                if n + 1 == len(self.levels):
                    self.levels.append([])
                merged = self._union(level).repartition("h1", "h2").sortWithinPartitions("h1", "h2")
                self.levels[n + 1].append(written(merged, f"line-run-{n + 1}"))
                self.levels[n] = []

    def repeated(self, min_docs: int) -> DataFrame:
        """Keys in at least so many documents, with the document that keeps its lines."""
        runs = self._union(self.runs())
        if not self.log:
            return runs.where(F.col("n_docs") >= min_docs).select("h1", "h2", "max_doc")
        again = written(self._union(self.log).groupBy("h1", "h2").agg(F.sum("n_docs").alias("more"), F.max("max_doc").alias("later")), "line-again")
        counted = runs.join(again, ["h1", "h2"], "left").where(F.col("n_docs") + F.coalesce("more", F.lit(0)) >= min_docs)
        return written(counted.select("h1", "h2", F.greatest("max_doc", "later").alias("max_doc")), "line-repeated")


def dropped_keys(docs: DataFrame, doc: str, text: str, min_points: int, min_docs: int, batches: int) -> DataFrame:
    """(doc, drops): for each document that loses lines, the hashes of their keys."""
    keys = line_keys(docs, doc, text, min_points).withColumn("batch", F.pmod(F.xxhash64("doc"), F.lit(batches)).cast("int"))
    keys = written(keys, "line-keys", by=["batch"])
    runs = LineRuns(docs.sparkSession)
    for b in range(batches):
        runs.add(keys.where(F.col("batch") == b).select("h1", "h2", "doc"))
    gone = skewed_join(keys.select("h1", "h2", "doc"), runs.repeated(min_docs), "h1", "h2", how="inner").where(F.col("doc") != F.col("max_doc"))
    return gone.groupBy("doc").agg(F.collect_list(F.struct("h1", "h2")).alias("drops"))


def drop_repeated_lines(docs: DataFrame, doc: str = "doc_id", text: str = "text", min_points: int = MIN_POINTS, min_docs: int = MIN_DOCS, batches: int = 4) -> DataFrame:
    """The documents, and as the last three columns _kept (the text without repeated lines), _n_lines and _n_dropped, or like names that are free."""
    own, gone, lines, stay, kept, n_lines, n_dropped = (fresh(docs, c) for c in ("_doc", "_drops", "_lines", "_stay", "_kept", "_n_lines", "_n_dropped"))
    drops = dropped_keys(docs, doc, text, min_points, min_docs, batches).select(F.col("doc").alias(own), F.col("drops").alias(gone))
    wide = docs.withColumn(own, _doc(F.col(doc))).join(drops.hint("shuffle_hash"), own, "left")

    def stays(line: Column) -> Column:
        key = line_key(line)
        h1, h2 = _hashes(key)
        return ~((F.length(key) >= min_points) & F.array_contains(F.col(gone), F.struct(h1.alias("h1"), h2.alias("h2"))))

    wide = wide.withColumn(lines, lines_of(F.col(text))).withColumn(stay, F.when(F.col(gone).isNull(), F.col(lines)).otherwise(F.filter(lines, stays)))
    whole = F.when(F.col(gone).isNull(), F.coalesce(F.col(text), F.lit(""))).otherwise(F.array_join(stay, "\n"))
    return wide.select(*docs.columns, whole.alias(kept), F.size(lines).cast("long").alias(n_lines), (F.size(lines) - F.size(stay)).cast("long").alias(n_dropped))


def op9_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, n_lines, n_dropped, kept_sha256 of every document."""
    docs = read(spark, sf_dir, "documents").select("doc_id", "text")
    return drop_repeated_lines(docs).select("doc_id", F.col("_n_lines").alias("n_lines"), F.col("_n_dropped").alias("n_dropped"), F.sha2(F.col("_kept"), 256).alias("kept_sha256"))


def dropping_sql(documents: str = "documents", min_points: int = MIN_POINTS, min_docs: int = MIN_DOCS) -> str:
    """CTEs ending in `deduped` (doc_id, text, n_lines, n_dropped) for DuckDB."""
    white = "' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)"
    return f"""split_lines AS (
  SELECT r, doc_id, pos, line, translate(trim(line, {white}), '{_UPPER}', '{_LOWER}') AS key
  FROM (SELECT r, doc_id, unnest(ls) AS line, unnest(range(1, len(ls) + 1)) AS pos
        FROM (SELECT row_number() OVER () AS r, doc_id, string_split(coalesce(text, ''), chr(10)) AS ls FROM {documents}))),
repeated AS (
  SELECT key, max(coalesce(doc_id, {_NO_ID})) AS keeper FROM split_lines WHERE length(key) >= {min_points}
  GROUP BY key HAVING count(DISTINCT coalesce(doc_id, {_NO_ID})) >= {min_docs}),
marked AS (
  SELECT s.*, (k.key IS NOT NULL AND coalesce(s.doc_id, {_NO_ID}) <> k.keeper) AS gone
  FROM split_lines s LEFT JOIN repeated k ON s.key = k.key),
deduped AS (
  SELECT r, doc_id, count(*) AS n_lines, count(*) FILTER (WHERE gone) AS n_dropped,
         coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT gone), '') AS text
  FROM marked GROUP BY r, doc_id)"""


QUERIES = {"op9_line_dedup": op9_line_dedup}
SQL = {"op9_line_dedup": f"WITH {dropping_sql()} SELECT doc_id, n_lines, n_dropped, sha256(text) AS kept_sha256 FROM deduped"}
