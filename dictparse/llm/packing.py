"""Best-fit packing of token pieces into sequences, in bulk-synchronous rounds.

Documents are tokenized in one pass; only their piece lengths go on. Pieces of one length are alike for packing, and so are open
sequences with one fill history, so both sorted sides of a round are run-length coded: at most `capacity` runs of pieces, each
drawn from a distributed count, and the sweep over them runs on the driver. A round takes the longest unpacked run, sweeps the gaps for its successor (the smallest gap that
holds it), lets the lower ranks win where pieces want the same gaps, updates the gaps, and repeats. The outcome is a table of
rank intervals (its size depends on the capacity, not on the data); each piece finds its place by its rank within its length,
which is counted in hashed blocks.

Edge cases: a null text is an empty one (its only token is the end token); a longer document is cut into full sequences behind a
possibly shorter first piece; repeated rows are packed each by itself; an empty table gives an empty result; further columns of
the input are not read.
"""

from __future__ import annotations

import bisect
import zlib
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from dictparse.llm.common import map_batches, read, texts_of, written

CAPACITY = 1024
END = 2
VOCABULARY = "byte_bpe_50k"
#: Text given to the tokenizer at once.
_SLICE = 1 << 20


def encoder(vocabulary: str = VOCABULARY):
    """text -> ids. The byte-level BPE of `<vocabulary>.json` by way of the same ranks in `<vocabulary>.tiktoken`."""
    import base64

    import public_tokenizers
    import tiktoken

    with open(public_tokenizers.path(f"{vocabulary}.tiktoken"), "rb") as f:
        ranks = {base64.b64decode(word): int(rank) for word, rank in map(bytes.split, f)}
    return tiktoken.Encoding("byte_bpe", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={}).encode_ordinary


def cut(n: int, capacity: int) -> list[tuple[int, int]]:
    """(start, length) of a document's pieces: the first takes the remainder, all others are full."""
    first = n % capacity or capacity
    return [(0, first)] + [(s, capacity) for s in range(first, n, capacity)]


def pieces(docs: DataFrame, doc: str = "doc_id", text: str = "text", capacity: int = CAPACITY, end: int = END, vocabulary: str = VOCABULARY, keep_ids: bool = False) -> DataFrame:
    """One row for each piece: its document, number, start, length, checksum, and its ids if wanted."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder(vocabulary)
        for batch in batches:
            names, texts = batch.column(0).to_pylist(), texts_of(batch, text)
            rows = defaultdict(list)
            for name, t in zip(names, texts, strict=True):
                ids = np.array([*encode(t.decode()), end], "<u4")
                for k, (start, size) in enumerate(cut(len(ids), capacity)):
                    own = ids[start : start + size]
                    for column, value in (("doc", name), ("piece", k), ("start", start), ("length", size), ("crc", zlib.crc32(own.tobytes()))):
                        rows[column].append(value)
                    if keep_ids:
                        rows["ids"].append(own.astype(np.int32))
            kinds = {"doc": pa.int64(), "piece": pa.int32(), "start": pa.int64(), "length": pa.int64(), "crc": pa.int64()} | ({"ids": pa.list_(pa.int32())} if keep_ids else {})
            yield pa.RecordBatch.from_arrays([pa.array(rows[c], kind) for c, kind in kinds.items()], names=["_" + c for c in kinds])

    schema = "_doc long, _piece int, _start long, _length long, _crc long" + (", _ids array<int>" if keep_ids else "")
    return map_batches(docs.select(F.col(doc).cast("long").alias("_doc"), F.col(text).alias(text)), run, schema)


class Gaps:
    """Open sequences by the space they have left; those with one fill history form a class."""

    def __init__(self) -> None:
        self.sizes: list[int] = []
        self.classes: dict[int, list[tuple[int, int]]] = defaultdict(list)  # space left: (first sequence, how many)

    def successor(self, size: int) -> int | None:
        k = bisect.bisect_left(self.sizes, size)
        return self.sizes[k] if k < len(self.sizes) else None

    def put(self, space: int, first: int, count: int) -> None:
        if count and space:
            if not self.classes[space]:
                bisect.insort(self.sizes, space)
            self.classes[space].append((first, count))

    def take(self, space: int) -> tuple[int, int]:
        got = self.classes[space].pop()
        if not self.classes[space]:
            self.sizes.remove(space)
        return got


def plan(counts: dict[int, int], capacity: int) -> list[tuple[int, int, int, int, int]]:
    """(length, first rank, ranks, first sequence, offset): ranks of a length go to as many successive sequences."""
    gaps, out, opened = Gaps(), [], 0
    for size in sorted(counts, reverse=True):
        rank, left = 0, counts[size]
        while left:
            space = gaps.successor(size)
            if space is None:
                first, space = opened, capacity
                count = max(1, left // (space // size))
                opened += count
            else:
                first, count = gaps.take(space)
            # as many sequences as this run fills to the last piece that fits, or one
            used = min(count, max(1, left // (space // size)))
            out.append((size, rank, used, first, capacity - space))
            gaps.put(space - size, first, used)
            gaps.put(space, first + used, count - used)
            rank, left = rank + used, left - used
    return out


def ranked(rows: DataFrame, within: str, order: list[str], blocks: int) -> DataFrame:
    """Adds _rank, gapless from 0 within each value of a column with few values, counted in hashed blocks."""
    rows = rows.withColumn("_block", F.pmod(F.xxhash64(*order), F.lit(blocks)).cast("int"))
    ahead = Window.partitionBy(within).orderBy("_block").rowsBetween(Window.unboundedPreceding, -1)
    sizes = rows.groupBy(within, "_block").agg(F.count(F.lit(1)).alias("_n"))
    starts = sizes.select(within, "_block", F.coalesce(F.sum("_n").over(ahead), F.lit(0)).alias("_first"))
    inside = Window.partitionBy(within, "_block").orderBy(*order)
    return rows.withColumn("_k", F.row_number().over(inside)).join(starts, [within, "_block"]).withColumn("_rank", F.col("_first") + F.col("_k") - 1).drop("_block", "_k", "_first")


def pack(rows: DataFrame, capacity: int = CAPACITY, blocks: int | None = None) -> DataFrame:
    """Adds sequence_id and offset to rows of pieces (_doc, _piece, _start, _length, _crc)."""
    spark = rows.sparkSession
    blocks = blocks or int(spark.conf.get("spark.sql.shuffle.partitions"))
    # at most `capacity` rows, whatever the data
    counts = {r["_length"]: r["count"] for r in rows.groupBy("_length").count().collect()}
    steps = plan(counts, capacity)
    schema = "_length long, _from long, _ranks long, _sequence long, offset long"
    frame = spark.createDataFrame(steps, schema)
    order = ["_doc", "_piece", "_start", "_crc"]
    by_rank = ranked(rows, "_length", order, blocks)
    # every step ends a run of lengths or of gaps, so steps are bounded by the capacity
    inside = (F.col("_rank") >= F.col("_from")) & (F.col("_rank") < F.col("_from") + F.col("_ranks"))
    placed = by_rank.join(F.broadcast(frame) if len(steps) <= 200_000 else frame, "_length").where(inside)
    return placed.withColumn("sequence_id", F.col("_sequence") + F.col("_rank") - F.col("_from")).drop("_rank", "_from", "_ranks", "_sequence")


def pack_documents(docs: DataFrame, doc: str = "doc_id", text: str = "text", capacity: int = CAPACITY) -> DataFrame:
    """One row for each piece with its place: doc, piece, start, length, ids_crc32, sequence_id, offset."""
    rows = written(pieces(docs, doc, text, capacity), "pieces")
    return pack(rows, capacity).select(F.col("_doc").alias(doc), F.col("_piece").alias("piece"), F.col("_start").alias("start"), F.col("_length").alias("length"), F.col("_crc").alias("ids_crc32"), "sequence_id", "offset")


def sequences(docs: DataFrame, doc: str = "doc_id", text: str = "text", capacity: int = CAPACITY) -> DataFrame:
    """The packed sequences themselves: sequence_id and its token ids in order of offset."""
    rows = written(pieces(docs, doc, text, capacity, keep_ids=True), "pieces-ids")
    placed = pack(rows, capacity)
    return placed.groupBy("sequence_id").agg(F.flatten(F.transform(F.array_sort(F.collect_list(F.struct("offset", "_ids"))), lambda x: x["_ids"])).alias("ids"))


def op6_best_fit(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset of every piece of every document, 1024 tokens a sequence."""
    return pack_documents(read(spark, sf_dir, "documents"))


QUERIES = {"op6_best_fit": op6_best_fit}
SQL: dict[str, str] = {}
