"""Parsing texts that arrive piece by piece, and the streaming jobs around it."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout
from pyspark.sql.types import IntegerType, StructField, StructType

from dictparse.kernels import lce as extensions
from dictparse.kernels import search
from dictparse.kernels.parse import Factor, Rules


class OnlineParser:
    """feed() takes more text and returns the factors that can't change any more; close() returns the rest.

    A pair_cut or pair_run factor is final once a symbol after it is known, as no search read further. A pair factor is final once
    none of its two descents ran into the end of what is known.
    """

    def __init__(self, scheme: str = "pair_cut"):
        if scheme not in ("pair", "pair_cut", "pair_run"):
            raise ValueError("only the pair schemes are parsed online")
        self.rules, self.at, self.x = Rules("", scheme), 0, 0

    def _extend(self, text: str) -> None:
        rules = self.rules
        rules.text += text
        rules.n = len(rules.text)
        rules.trie.text = rules.text
        if rules.lce:
            rules.lce = extensions.Direct(rules.text)

    def _final(self, found: Factor) -> bool:
        n = self.rules.n
        if found[0] + found[1] >= n:
            return False
        if self.rules.scheme != "pair":
            return True
        first = search.walk(self.rules.trie, self.at)
        second = self.at + max(first[1], 1)
        return self.at + first[3] < n and second + search.walk(self.rules.trie, second)[3] < n

    def _take(self, found: Factor) -> Factor:
        self.x += 1
        self.rules.lengths.append(found[1])
        self.rules.add(found[0], found[1], self.x)
        self.at += found[1]
        return found

    def feed(self, text: str) -> list[Factor]:
        self._extend(text)
        out = []
        while self.at < self.rules.n:
            found = self.rules.best(self.at)
            if not self._final(found):
                break
            out.append(self._take(found))
        return out

    def close(self) -> list[Factor]:
        out = []
        while self.at < self.rules.n:
            out.append(self._take(self.rules.best(self.at)))
        return out

    def resume(self, text: str, lengths: list[int]) -> None:
        """Takes up a parse from its text and the lengths of its final factors."""
        self._extend(text)
        for size in lengths:
            self._take((self.at, size, "", None, None, None, None, None))


STATE = "text string, lengths array<int>, block int, seen long, last timestamp, late long, times array<timestamp>, orders array<long>, pieces array<string>"
OUT = "key long, block_id int, x int, beg long, len int, kind string, final boolean, seen long, late long"


def _on_rows(scheme: str, block_symbols: int, idle_ms: int | None = None):
    """Rows wait until the watermark has passed them, are then appended in order, and what comes behind them is counted and left out.

    With idle_ms, a key whose last row the watermark has left that far behind is at its end: what remains is emitted as final, and
    rows that come later begin a block of their own.
    """

    def update(key: tuple, pdfs: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        text, lengths, block, seen, last, late, *waiting = state.get if state.exists else ("", [], 0, 0, None, 0, [], [], [])
        held = pd.DataFrame({"ts": pd.to_datetime(pd.Series([*waiting[0]], dtype="datetime64[ns]")), "ord": pd.Series([*waiting[1]], dtype="int64"), "piece": pd.Series([*waiting[2]], dtype="object")})
        parts = [p[["ts", "ord", "piece"]] for p in pdfs]
        fresh = pd.concat(parts) if parts else held.iloc[:0]
        rows = fresh if held.empty else held if fresh.empty else pd.concat([held, fresh])
        rows = rows.assign(piece=rows["piece"].fillna("")).sort_values(["ts", "ord"], kind="stable")
        if last is not None:
            behind = rows["ts"] < pd.Timestamp(last)
            late, rows = int(late) + int(behind.sum()), rows[~behind]
        ready = rows["ts"] <= pd.Timestamp(state.getCurrentWatermarkMs(), unit="ms")
        out: list[tuple] = []
        parser = OnlineParser(scheme)
        parser.resume(text, [*lengths])

        def feed(pieces: pd.Series, final: bool) -> None:
            nonlocal parser, block, seen
            for piece in pieces:
                seen += len(piece)
                emit(parser.feed(piece), final)
                if parser.rules.n >= block_symbols:  # state stays bounded: this block ends, the next has its own dictionary
                    emit(parser.close(), final)
                    parser, block = OnlineParser(scheme), block + 1

        def emit(factors: list[Factor], final: bool) -> None:
            for k, f in enumerate(factors, parser.x - len(factors) + 1):
                out.append([key[0], block, k, f[0] + 1, f[1], f[2], final, None, late])

        ended = bool(state.hasTimedOut)
        if ended:
            ready[:] = True
        feed(rows["piece"][ready], True)
        if ready.any():
            last = rows["ts"][ready].iloc[-1]
        if ended and parser.rules.n:
            emit(parser.close(), True)
            parser, block = OnlineParser(scheme), block + 1
        rest = rows[~ready]
        at = pd.Timestamp(last).to_pydatetime() if last is not None else None
        state.update((parser.rules.text, parser.rules.lengths[1:], block, seen, at, late, [t.to_pydatetime() for t in rest["ts"]], [int(o) for o in rest["ord"]], [*rest["piece"]]))
        if idle_ms is not None and not ended and len(rows):
            state.setTimeoutTimestamp(max(int(rows["ts"].max().timestamp() * 1000), state.getCurrentWatermarkMs()) + idle_ms)
        feed(rest["piece"], False)  # what the rest would be if nothing more came
        emit(parser.close(), False)
        out.append([key[0], block, 0, 0, 0, "", False, None, late])
        frame = pd.DataFrame(out, columns=[c.split()[0] for c in OUT.split(", ")])
        frame["seen"] = seen
        yield frame

    return update


def factors_of_stream(stream: DataFrame, key: str, ts: str, order: str, piece, scheme: str = "pair_cut", block_symbols: int = 1 << 20, watermark: str = "10 minutes", idle_ms: int | None = None) -> DataFrame:
    """Factor rows of every key as its pieces arrive. Rows with final = false are the rest at that moment; with idle_ms a key that falls
    silent for so long (in event time) ends, and its rest becomes final."""
    rows = stream.select(F.col(key).cast("long").alias("key"), F.col(ts).alias("ts"), F.col(order).alias("ord"), piece.alias("piece")).withWatermark("ts", watermark)
    return rows.groupBy("key").applyInPandasWithState(_on_rows(scheme, block_symbols, idle_ms), OUT, STATE, "append", GroupStateTimeout.NoTimeout if idle_ms is None else GroupStateTimeout.EventTimeTimeout)


def run_to_table(out: DataFrame, mode: str = "append", checkpoint: str | None = None) -> DataFrame:
    """Runs a stream over all there is now and returns its rows, as a Parquet table in the shared folder.

    Each micro-batch overwrites a part of its own, so a batch that is run again changes nothing; in complete mode the last part counts.
    """
    spark = out.sparkSession
    base = checkpoint or spark.conf.get("spark.checkpoint.dir", None) or f"{spark.conf.get('spark.sql.warehouse.dir').rstrip('/')}/dictparse-streams"
    path = f"{base}/stream-{uuid.uuid4().hex}"

    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/rows/part_={number}")

    query = out.writeStream.foreachBatch(put).outputMode(mode).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    rows = spark.read.schema(StructType([*out.schema, StructField("part_", IntegerType())])).parquet(f"{path}/rows")
    if mode == "complete":
        rows = rows.where(F.col("part_") == rows.agg(F.max("part_")).first()[0])
    return rows.drop("part_")


def settled(emitted: DataFrame) -> DataFrame:
    """The factors of a replayed stream: all final ones, and the rest as the last micro-batch left it."""
    last = F.max("seen").over(Window.partitionBy("key"))
    marked = emitted.withColumn("last", last).where("x > 0 AND (final OR seen = last)")
    return marked.dropDuplicates(["key", "block_id", "x", "beg"]).select("key", "block_id", "x", "beg", "len", "kind")


def tumbling(stream: DataFrame, size: str = "1 hour", slide: str | None = None) -> DataFrame:
    """Events of each type in each window, late ones up to the watermark."""
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return stream.withWatermark("ts", "10 minutes").groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("events"))


def sessions(stream: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """Each user's sessions: texts that a gap cuts."""
    return stream.withWatermark("ts", "10 minutes").groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("events"))


def deduplicated(stream: DataFrame) -> DataFrame:
    return stream.withWatermark("ts", "10 minutes").dropDuplicatesWithinWatermark(["event_id"])


def with_static(stream: DataFrame, static: DataFrame, on: list[str]) -> DataFrame:
    return stream.join(static, on)


def near_in_time(left: DataFrame, right: DataFrame, key: str, minutes: int = 5) -> DataFrame:
    """Pairs of rows of two streams with one key, the right one up to so many minutes after the left."""
    a = left.withWatermark("ts", "10 minutes").select(F.col(key).alias("k"), F.col("ts").alias("left_ts"), F.col("event_id").alias("left_id"))
    b = right.withWatermark("ts", "10 minutes").select(F.col(key).alias("k2"), F.col("ts").alias("right_ts"), F.col("event_id").alias("right_id"))
    near = F.expr(f"k = k2 AND right_ts >= left_ts AND right_ts <= left_ts + INTERVAL {minutes} MINUTES")
    return a.join(b, near).select("k", "left_id", "right_id")


def upsert(path: str, keys: list[str], order: list[str]):
    """A foreachBatch function that keeps the last row of each key, by `order`, in a Parquet table.

    A batch is reduced to one row a key and overwrites a version of its own, so running it again changes nothing; `latest` reads them.
    """

    def write(batch: DataFrame, batch_id: int) -> None:
        last = F.max_by(F.struct(*batch.columns), F.struct(*order, F.xxhash64(*batch.columns)))
        batch.groupBy(*(F.col(k).alias(f"key_{k}") for k in keys)).agg(last.alias("row")).select("row.*").write.mode("overwrite").parquet(f"{path}/version_={batch_id}")

    return write


def latest(spark: SparkSession, path: str, keys: list[str], order: list[str]) -> DataFrame:
    """The last row of each key; between versions `order` decides too, so late batches don't undo newer rows."""
    rows = spark.read.parquet(path)
    columns = [c for c in rows.columns if c != "version_"]
    last = F.max_by(F.struct(*columns), F.struct(*order, F.col("version_")))
    return rows.groupBy(*(F.col(k).alias(f"key_{k}") for k in keys)).agg(last.alias("row")).select("row.*")
