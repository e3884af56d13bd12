"""Benchmark decontamination with suffix arrays of the training texts.

Each shard (the texts of some megabytes, or one longer text) gets a suffix array over its words: suffixes in the order of their
first words, at least as many as a window has, by prefix doubling on ranks. Every test suffix is binary-searched in it by its first
window; the range found gives all places, and places that follow each other in text and item alike make up the longest verbatim
matches with their locations, whose words are the hits. Nothing is shuffled: the test items, a stated set, go to the shards in blocks
of bounded size. Arrays are built for each block of items; a benchmark of up to BLOCK_BYTES is one block.

Edge cases: a null text has no words; an item with fewer words than a window is one window, without words none; repeated rows
give repeated results; with an empty benchmark nothing is hit; further columns, whatever their names, are kept by `decontaminate`.
A text must fit in a Python worker some 30 times.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dictparse.llm.common import fresh, map_batches, read, texts_of

WINDOW = 10
#: Bytes of item texts that are sent to the executors at once.
BLOCK_BYTES = 16 << 20
#: Text of one shard.
SHARD_BYTES = 4 << 20

#: Bytes of a word are digits, letters (A-Z folded) and all bytes of non-ASCII characters.
_FOLD = bytes(b + 32 if 65 <= b <= 90 else b if b >= 128 or 48 <= b <= 57 or 97 <= b <= 122 else 32 for b in range(256))


def words(text: bytes) -> list[bytes]:
    return text.translate(_FOLD).split()


class Shard:
    """Word suffix array of some texts. `words` holds word numbers with 0 after each text."""

    def __init__(self, texts: list[list[bytes]], depth: int = 16):
        vocabulary: dict[bytes, int] = {}
        number = vocabulary.setdefault
        flat: list[int] = []
        starts = [0]
        for t in texts:
            flat += [number(w, len(vocabulary) + 1) for w in t]
            flat.append(0)
            starts.append(len(flat))
        self.vocabulary, self.starts = vocabulary, np.array(starts, np.int64)
        self.words = np.array(flat, np.int32)
        self.order = self._sorted(depth)

    def _sorted(self, depth: int) -> np.ndarray:
        n = len(self.words)
        rank, order, span = self.words.astype(np.int64), np.arange(n), 1
        if n < 2:
            return order
        while span < depth:
            ahead = np.zeros(n, np.int64)
            ahead[: n - span] = rank[span:] + 1 if span < n else 0
            pair = rank * (n + 2) + ahead
            order = np.argsort(pair)
            step = np.ones(n, np.int64)
            step[1:] = pair[order][1:] != pair[order][:-1]
            rank = np.empty(n, np.int64)
            rank[order] = np.cumsum(step)
            span *= 2
            if rank[order[-1]] == n:
                break
        return order

    def ranges(self, queries: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """For each row of word numbers (its first `length` count): the range of suffixes that begin so."""
        n, width = len(self.order), queries.shape[1]
        padded = np.concatenate([self.words, np.full(width, -1, np.int32)])
        lows = []
        for above in (False, True):
            lo, hi = np.zeros(len(queries), np.int64), np.full(len(queries), n, np.int64)
            while (open_ := np.flatnonzero(lo < hi)).size:
                mid = (lo[open_] + hi[open_]) >> 1
                got = padded[self.order[mid][:, None] + np.arange(width)]
                q = queries[open_]
                apart = (got != q) & (np.arange(width) < lengths[open_, None])
                first = apart.argmax(1)
                row = np.arange(len(open_))
                differs = apart[row, first]
                less = np.where(differs, got[row, first] < q[row, first], above)
                lo[open_] = np.where(less, mid + 1, lo[open_])
                hi[open_] = np.where(less, hi[open_], mid)
            lows.append(lo)
        return lows[0], lows[1]


class Items:
    """Windows of a block of test items."""

    def __init__(self, rows: list[tuple[str, bytes]], window: int):
        self.ids = [i for i, _ in rows]
        self.window = window
        self.words = [words(t) for _, t in rows]
        own: list[tuple[int, int, int]] = []
        for k, w in enumerate(self.words):
            size = min(window, len(w))
            own += [(k, at, size) for at in range(len(w) - size + 1 if size else 0)]
        self.windows = own

    def numbered(self, shard: Shard) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(item, place in it, word numbers, length) of the windows all of whose words the shard has."""
        get = shard.vocabulary.get
        numbers = [np.array([get(x, -1) for x in w], np.int32) for w in self.words]
        item, place, rows, size = [], [], [], []
        for k, at, n in self.windows:
            q = numbers[k][at : at + n]
            if q.min() > 0:
                item.append(k)
                place.append(at)
                rows.append(np.pad(q, (0, self.window - n)))
                size.append(n)
        return np.array(item, np.int64), np.array(place, np.int64), np.array(rows, np.int32).reshape(-1, self.window), np.array(size, np.int64)


def longest_matches(shard: Shard, items: Items) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(item, place in it, place in the shard, length) of every longest verbatim match of at least a window (or a short item)."""
    item, at, queries, size = items.numbered(shard)
    if not len(item) or not len(shard.order):
        none = np.zeros(0, np.int64)
        return none, none, none, none
    lo, hi = shard.ranges(queries, size)
    count = hi - lo
    which = np.repeat(np.arange(len(item)), count)
    place = shard.order[lo[which] + np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)]
    # windows one word apart in both belong to one match
    by = np.lexsort((place, place - at[which], item[which]))
    which, place = which[by], place[by]
    first = np.ones(len(which), bool)
    first[1:] = (item[which][1:] != item[which][:-1]) | (np.diff(place) != 1) | (np.diff(at[which]) != 1)
    begin = np.flatnonzero(first)
    last = np.r_[begin[1:], len(which)] - 1
    return item[which[begin]], at[which[begin]], place[begin], place[last] - place[begin] + size[which[last]] if len(begin) else begin


def _groups(batches: Iterator[pa.RecordBatch], text: str) -> Iterator[tuple[pa.RecordBatch, list[bytes]]]:
    """Slices of the batches with at most SHARD_BYTES of text, or one row."""
    for batch in batches:
        texts = texts_of(batch, text)
        begin, held = 0, 0
        for k, t in enumerate(texts):
            if held and held + len(t) > SHARD_BYTES:
                yield batch.slice(begin, k - begin), texts[begin:k]
                begin, held = k, 0
            held += len(t)
        if begin < len(texts):
            yield batch.slice(begin), texts[begin:]


def _blocks(items: DataFrame, item: str, text: str) -> Iterator[list[tuple[str, bytes]]]:
    """The item table in pieces of bounded bytes, one at a time on the driver."""
    held, size = [], 0
    for r in items.select(F.col(item).cast("string").alias("i"), F.coalesce(F.col(text), F.lit("")).alias("t")).toLocalIterator(prefetchPartitions=True):
        b = r.t.encode()
        if held and size + len(b) > BLOCK_BYTES:
            yield held
            held, size = [], 0
        held.append((r.i, b))
        size += len(b)
    if held:
        yield held


def mark(docs: DataFrame, benchmark: DataFrame, text: str = "text", item: str = "item_id", item_text: str = "text", window: int = WINDOW) -> DataFrame:
    """The documents, and as the last three columns _n_words, _spans (merged [from, to) word spans, flat) and _items (ids of items with
    an occurring window, sorted), or like names that are free."""
    spark = docs.sparkSession
    kinds = dict(zip((fresh(docs, c) for c in ("_n_words", "_spans", "_items")), ("bigint", "array<bigint>", "array<string>"), strict=True))
    out = docs.select("*", *((F.lit(0) if kind == "bigint" else F.array()).cast(kind).alias(c) for c, kind in kinds.items()))
    for rows in list_blocks(benchmark, item, item_text):
        sent = spark.sparkContext.broadcast(rows)

        def run(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            items = Items(sent.value, window)
            for batch, texts in _groups(batches, text):
                yield _marked(batch, texts, items)

        out = map_batches(out, run, ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in out.schema.fields))
    return out


def list_blocks(benchmark: DataFrame, item: str, item_text: str) -> Iterator[list[tuple[str, bytes]]]:
    """At least one block, so that words are counted even without items."""
    empty = True
    for rows in _blocks(benchmark, item, item_text):
        empty = False
        yield rows
    if empty:
        yield []


def _marked(batch: pa.RecordBatch, texts: list[bytes], items: Items) -> pa.RecordBatch:
    shard = Shard([words(t) for t in texts], items.window)
    item, _, place, size = longest_matches(shard, items)
    row = np.searchsorted(shard.starts, place, "right") - 1
    n_words = np.diff(shard.starts) - 1
    *kept, _, old_spans, old_items = batch.columns
    spans, names = old_spans.to_pylist(), old_items.to_pylist()
    by = np.lexsort((place, row))
    cuts = np.searchsorted(row[by], np.arange(len(texts) + 1))
    for k in np.unique(row).tolist():
        mine = by[cuts[k] : cuts[k + 1]]
        a = place[mine] - shard.starts[k]
        old = np.array(spans[k], np.int64).reshape(-1, 2)
        spans[k] = _merged(np.concatenate([a, old[:, 0]]), np.concatenate([a + size[mine], old[:, 1]]))
        names[k] = sorted({*names[k], *(items.ids[x] for x in np.unique(item[mine]).tolist() if items.ids[x] is not None)})
    new = [pa.array(n_words, pa.int64()), pa.array(spans, pa.list_(pa.int64())), pa.array(names, pa.list_(pa.string()))]
    return pa.RecordBatch.from_arrays([*kept, *new], names=batch.schema.names)


def _merged(begin: np.ndarray, end: np.ndarray) -> list[int]:
    by = np.argsort(begin, kind="stable")
    begin, reach = begin[by], np.maximum.accumulate(end[by])
    first = np.flatnonzero(np.r_[True, begin[1:] > reach[:-1]])
    last = np.r_[first[1:] - 1, len(begin) - 1]
    return np.stack([begin[first], reach[last]], 1).ravel().tolist()


def decontaminate(docs: DataFrame, benchmark: DataFrame, text: str = "text") -> DataFrame:
    """The documents in which no window of an item occurs; columns stay as they are."""
    marked = mark(docs, benchmark, text)
    return marked.where(F.size(marked.columns[-2]) == 0).select(*docs.columns)


def op2_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256, contaminated of every document."""
    docs = read(spark, sf_dir, "documents").select("doc_id", "text")
    marked = mark(docs, read(spark, sf_dir, "benchmark"))
    signed = F.transform("_spans", lambda x, k: F.when(k % 2 == 1, x).otherwise(-x))
    n_hit = F.aggregate(signed, F.lit(0).cast("long"), lambda total, x: total + x)
    return marked.select("doc_id", F.col("_n_words").alias("n_words"), n_hit.alias("n_hit"), F.size("_items").cast("long").alias("n_items"), F.sha2(F.array_join("_items", ","), 256).alias("items_sha256"), (n_hit > 0).alias("contaminated"))


_WORDS = r"regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"


def hits_sql(documents: str = "documents", benchmark: str = "benchmark", window: int = WINDOW) -> str:
    """CTEs ending in `hit_docs` (r, doc_id, n_words, n_hit, items) for DuckDB."""
    return f"""doc_words AS MATERIALIZED (SELECT row_number() OVER () AS r, doc_id, {_WORDS} AS ws FROM {documents}),
item_words AS (SELECT item_id, {_WORDS} AS ws FROM {benchmark}),
item_windows AS (
  SELECT DISTINCT item_id, least({window}, len(ws)) AS size, array_to_string(list_slice(ws, pos, pos + least({window}, len(ws)) - 1), ' ') AS win
  FROM (SELECT *, unnest(range(1, len(ws) - least({window}, len(ws)) + 2)) AS pos FROM item_words WHERE len(ws) > 0)),
sizes AS (SELECT DISTINCT size FROM item_windows),
doc_windows AS (
  SELECT r, pos, size, array_to_string(list_slice(ws, pos, pos + size - 1), ' ') AS win
  FROM (SELECT r, ws, size, unnest(range(1, len(ws) - size + 2)) AS pos FROM doc_words, sizes WHERE len(ws) >= size)),
found AS MATERIALIZED (SELECT w.r, w.pos, w.size, i.item_id FROM doc_windows w JOIN item_windows i USING (size, win)),
hit_words AS (SELECT r, count(DISTINCT p) AS n_hit FROM (SELECT r, unnest(range(pos, pos + size)) AS p FROM found) GROUP BY r),
hit_items AS (SELECT r, list_sort(list(DISTINCT CAST(item_id AS VARCHAR))) AS items FROM found WHERE item_id IS NOT NULL GROUP BY r),
hit_docs AS (
  SELECT d.r, doc_id, CAST(len(ws) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(items, []) AS items
  FROM doc_words d LEFT JOIN hit_words USING (r) LEFT JOIN hit_items USING (r))"""


QUERIES = {"op2_decontamination": op2_decontamination}
SQL = {
    "op2_decontamination": f"""WITH {hits_sql()}
SELECT doc_id, n_words, n_hit, CAST(len(items) AS BIGINT) AS n_items, sha256(coalesce(array_to_string(items, ','), '')) AS items_sha256, n_hit > 0 AS contaminated FROM hit_docs"""
}
