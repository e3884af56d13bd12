"""Removal of repeated passages by prefix-free parsing.

Triggers of a rolling hash cut texts into phrases that overlap in their triggers, so equal passages are cut alike. The phrases form a
dictionary, the texts a parse over it; a corpus position is known by its suffix of a phrase (dictionary order) and by what follows
(parse order). `corpus_order` combines both suffix arrays into the order of all suffixes of a text. Removal needs only which positions
of that order agree on `length` bytes, so over the whole corpus the same two parts are compared as classes, in fixed-width
fingerprints instead of ranks, level by level:

1. phrases: a window that holds a whole phrase which the corpus has once is unique. Most windows go here.
2. parse: for each trigger, the context of all windows that begin between it and the trigger before. If the corpus has the context
   twice, all of these windows are repeated; one context of each class stands for the class.
3. windows: what is left, and the windows of those that stand for a class, are counted one by one.

Texts are held in chunks of some megabytes in a table bucketed by chunk. At each level a chunk sends each distinct fingerprint once
(so copies add nothing), sorted, in blobs by group, and gets a bit for each back; no texts are shuffled. Groups, tasks and buckets grow
with the text, and a chunk only touches groups that it has something for.

At levels 2 and 3 fingerprints have 64 bits, plus the bits of the group they are dealt to, both made of two independent hashes. A false
match of two different windows has a chance of 2 ** -64 or less and isn't excluded. At level 1 a false match only leaves a window open.

Edge cases: null texts are empty; texts shorter than the window lose nothing; windows never cross texts; texts without triggers (runs of
one letter) are compared at level 3; repeated rows are repeats of each other; an empty table gives an empty result; further columns
are not read. A single text must fit in a worker's memory some 60 times.
"""

from __future__ import annotations

import atexit
import hashlib
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dictparse.llm.common import lean, map_batches, read, shared_dir, texts_of, utf8_bytes, written
from dictparse.llm.hashing import between, mix, powers, running

LENGTH = 200
#: Bytes of a trigger, and the mean distance between triggers.
WIDTH, EVERY = 12, 32
#: Text of a chunk and of a bucket of chunks, and fingerprints (in bytes) that one group compares.
CHUNK_BYTES, BUCKET_BYTES, GROUP_BYTES = 2 << 20, 16 << 20, 8 << 20


def trigger_places(data: np.ndarray, prefix: np.ndarray, width: int = WIDTH, every: int = EVERY) -> np.ndarray:
    if len(data) < width:
        return np.zeros(0, np.int64)
    h = prefix[width:] - prefix[:-width]
    h *= powers(0, True, len(prefix))[: len(h)]
    h *= np.uint64(0xC2B2AE3D27D4EB4F)
    return np.flatnonzero(h < np.uint64((1 << 64) // every))


def corpus_order(text: bytes, width: int = WIDTH, every: int = EVERY) -> np.ndarray:
    """The suffix array of a text from those of its dictionary and its parse."""
    data = np.frombuffer(text, np.uint8)
    cuts = trigger_places(data, running(data), width, every)
    begin = np.unique(np.concatenate([[0], cuts])).astype(np.int64)
    end = np.concatenate([begin[1:] + width, [len(data)]])  # a phrase ends with the next one's trigger
    phrases = [text[a:b] for a, b in zip(begin.tolist(), end.tolist(), strict=True)]
    # the last phrase ends with the text: a mark below all bytes makes it the smaller of two that agree so far
    closed = [b"".join(b"\1" + bytes([x]) for x in p) for p in phrases[:-1]] + [b"".join(b"\1" + bytes([x]) for x in phrases[-1]) + b"\0"]
    dictionary = sorted({p[2 * k :] for p in closed for k in range(len(p) // 2)})
    place = {s: k for k, s in enumerate(dictionary)}
    # parse order: ranks of phrase sequences, doubled
    names = {p: k for k, p in enumerate(sorted(set(closed)))}
    rank, span = np.array([names[p] for p in closed], np.int64) + 1, 1
    while span < len(rank):
        ahead = np.concatenate([rank[span:], np.zeros(span, np.int64)])
        rank = np.unique(rank * (len(rank) + 2) + ahead, return_inverse=True)[1] + 1
        span *= 2
    rank = np.append(rank, 0)
    first, second = np.empty(len(data), np.int64), np.empty(len(data), np.int64)
    for k, p in enumerate(closed):
        own = int(begin[k + 1] - begin[k]) if k + 1 < len(begin) else len(data) - int(begin[k])
        at = int(begin[k])
        first[at : at + own] = [place[p[2 * o :]] for o in range(own)]
        second[at : at + own] = rank[k + 1]
    return np.lexsort((second, first))


class Chunk:
    """Some texts in one array, with their triggers, phrases and anchors. Positions are window starts."""

    def __init__(self, data: np.ndarray, starts: np.ndarray, length: int):
        self.data, self.starts, self.length = data, starts, length
        self.prefix = running(data)
        cuts = trigger_places(data, self.prefix)
        text = np.searchsorted(starts, cuts, "right") - 1
        inside = cuts + WIDTH <= starts[text + 1]
        self.cuts, text = cuts[inside], text[inside]
        same = text[1:] == text[:-1]
        self.begin, self.end = self.cuts[:-1][same], self.cuts[1:][same] + WIDTH
        before = np.concatenate([[-1], self.cuts[:-1]])
        before = np.where(np.concatenate([[False], same]) if len(self.cuts) else np.zeros(0, bool), before[: len(self.cuts)], starts[text] - 1)
        self.lo = np.maximum(before + 1, self.cuts + WIDTH - length)
        self.hi = np.minimum(self.cuts, starts[text + 1] - length)
        some = self.lo <= self.hi
        self.lo, self.hi, self.anchor = self.lo[some], self.hi[some], self.cuts[some]

    def phrases(self) -> np.ndarray:
        return mix(between(self.prefix, self.begin, self.end) + (self.end - self.begin).astype(np.uint64))

    def _ranges(self, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        """How many of the closed ranges cover each position."""
        n = len(self.data) + 1
        keep = lo <= hi
        return np.cumsum(np.bincount(lo[keep], minlength=n + 1) - np.bincount(hi[keep] + 1, minlength=n + 1))[:n]

    def candidates(self, once: np.ndarray) -> np.ndarray:
        """Windows without a whole phrase that occurs once."""
        text_of = np.searchsorted(self.starts, self.begin[once], "right") - 1
        valid = self._ranges(self.starts[:-1], self.starts[1:] - self.length) > 0
        return valid & (self._ranges(np.maximum(self.end[once] - self.length, self.starts[text_of]), self.begin[once]) == 0)

    def whole(self, candidate: np.ndarray) -> np.ndarray:
        """Anchors all of whose windows are candidates."""
        upto = np.concatenate([[0], np.cumsum(candidate)])
        return np.flatnonzero(upto[self.hi + 1] - upto[self.lo] == self.hi + 1 - self.lo)

    def _named(self, lo: np.ndarray, hi: np.ndarray, shape: np.ndarray | int = 0) -> tuple[np.ndarray, np.ndarray]:
        """Fingerprints of [lo, hi) and the hashes that deal them to groups, each from both running hashes."""
        one, two = between(self.prefix, lo, hi), between(running(self.data, 1), lo, hi, 1)
        return mix(mix(one + shape) + two), mix(two * np.uint64(0xC2B2AE3D27D4EB4F) + one)

    def contexts(self, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        lo, hi = self.lo[at], self.hi[at]
        return self._named(lo, hi + self.length, ((hi - lo) << 16 | self.anchor[at] - lo).astype(np.uint64))

    def windows(self, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        return self._named(at, at + self.length, np.uint64(0))


def _dealt(keys: np.ndarray, spread: np.ndarray, groups: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Distinct keys in the order they are sent, the group of each, how often each came, and the place of every given key among them."""
    own, first, back, count = np.unique(keys, return_index=True, return_inverse=True, return_counts=True)
    group = (spread[first] % np.uint64(groups)).astype(np.int64)
    order = np.argsort(group, kind="stable")
    place = np.empty(len(own), np.int64)
    place[order] = np.arange(len(own))
    return own[order], group[order], count[order], place[back]


class Level:
    """A question to the whole corpus: which of a chunk's keys does it have twice, and which chunk is the first to have each?"""

    def __init__(self, groups: int):
        self.groups = groups

    def ask(self, chunk: int, keys: np.ndarray, spread: np.ndarray, twice: np.ndarray | None = None) -> list[tuple[int, int, bytes, bytes]]:
        own, group, count, place = _dealt(keys, spread, self.groups)
        more = count > 1
        if twice is not None:
            more[place[twice]] = True
        some, begin = np.unique(group, return_index=True)
        end = np.r_[begin[1:], len(group)] if len(group) else begin
        return [(g, chunk, own[a:b].tobytes(), np.packbits(more[a:b]).tobytes()) for g, a, b in zip(some.tolist(), begin.tolist(), end.tolist(), strict=True)]

    def hear(self, answers: list[dict] | None, keys: np.ndarray, spread: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """For every key: whether the corpus has it twice, and whether this is the place that stands for it."""
        own, group, _, place = _dealt(keys, spread, self.groups)
        twice, stands = np.zeros(len(own), bool), np.zeros(len(own), bool)
        for x in answers or ():
            a, b = np.searchsorted(group, [x["group"], x["group"] + 1]).tolist()
            bits = np.unpackbits(np.frombuffer(x["bits"], np.uint8))[: 2 * (b - a)].reshape(-1, 2).astype(bool)
            twice[a:b], stands[a:b] = bits[:, 0], bits[:, 1]
        first = np.zeros(len(keys), bool)
        first[np.unique(place, return_index=True)[1]] = True
        return twice[place], stands[place] & first


def _answers(asked: DataFrame, name: str, tasks: int, buckets: int) -> DataFrame:
    """(chunk, answers) from (group, chunk, keys, more), dealt out as the chunks are."""

    def compare(table: pa.Table) -> pa.Table:
        blobs = [np.frombuffer(x, np.uint64) for x in table["keys"].to_pylist()]
        more = np.concatenate([np.unpackbits(np.frombuffer(x, np.uint8))[: len(k)] for x, k in zip(table["more"].to_pylist(), blobs, strict=True)])
        own, first, back = np.unique(np.concatenate(blobs), return_index=True, return_inverse=True)
        twice = (np.bincount(back, 1 + more) >= 2)[back]
        stands = np.zeros(len(back), bool)
        stands[first] = True
        both, out, at = np.stack([twice, stands], 1), [], 0
        for k in blobs:
            out.append(np.packbits(both[at : at + len(k)]).tobytes())
            at += len(k)
        return pa.table({"group": table["group"], "chunk": table["chunk"], "bits": pa.array(out, pa.binary())})

    bits = written(asked.repartition(tasks, "group").groupBy("group").applyInArrow(compare, "group int, chunk long, bits binary"), name)
    return bits.repartition(buckets, "chunk").groupBy("chunk").agg(F.collect_list(F.struct("group", "bits")).alias(name))


def _chunks(docs: DataFrame, doc: str, text: str, buckets: int) -> DataFrame:
    """The texts in a table of chunks (chunk, data, sizes, docs), bucketed by chunk in the shared folder."""
    spark = docs.sparkSession

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        number = TaskContext.get().partitionId() << 32
        held: list[tuple[int | None, bytes]] = []
        size = 0

        def out() -> pa.RecordBatch:
            columns = [pa.array([number], pa.int64()), pa.array([b"".join(t for _, t in held)], pa.binary()), pa.array([[len(t) for _, t in held]], pa.list_(pa.int64())), pa.array([[d for d, _ in held]], pa.list_(pa.int64()))]
            return pa.RecordBatch.from_arrays(columns, names=["chunk", "data", "sizes", "docs"])

        for b in batches:
            for d, t in zip(b.column(0).to_pylist(), texts_of(b, text), strict=True):
                if held and size + len(t) > CHUNK_BYTES:
                    yield out()
                    number, held, size = number + 1, [], 0
                held.append((d, t))
                size += len(t)
        if held:
            yield out()

    rows = map_batches(docs.select(F.col(doc).cast("long").alias("_doc"), F.col(text).alias(text)), run, "chunk long, data binary, sizes array<long>, docs array<long>")
    name = f"dictparse_chunks_{uuid.uuid4().hex}"
    rows.write.option("compression", "zstd").option("path", f"{shared_dir(spark)}/{name}").bucketBy(buckets, "chunk").sortBy("chunk").saveAsTable(name)
    atexit.register(_drop, spark, name)
    return spark.table(name)


def _drop(spark: SparkSession, name: str) -> None:
    try:
        spark.sql(f"DROP TABLE IF EXISTS {name}")
    except Exception:  # the session is gone
        pass


def _over(table: DataFrame, answers: dict[str, DataFrame], make: Callable[[int, Chunk, dict, list], Iterator[pa.RecordBatch]], schema: str, length: int) -> DataFrame:
    names = [*answers]
    for a in answers.values():
        table = table.join(a, "chunk", "left")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            heard = {k: b.column(k) for k in names}
            for i in range(b.num_rows):
                starts = np.concatenate([[0], np.cumsum(np.array(b.column("sizes")[i].as_py(), np.int64))])
                chunk = Chunk(np.frombuffer(b.column("data")[i].as_py(), np.uint8), starts, length)
                yield from make(b.column("chunk")[i].as_py(), chunk, {k: v[i].as_py() for k, v in heard.items()}, b.column("docs")[i].as_py())

    return table.mapInArrow(lean(run), schema)


_ASKED = "group int, chunk long, keys binary, more binary"


def _sent(rows: list[tuple[int, int, bytes, bytes]]) -> Iterator[pa.RecordBatch]:
    columns = [*zip(*rows, strict=True)] or [[], [], [], []]
    kinds = (pa.int32(), pa.int64(), pa.binary(), pa.binary())
    yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=["group", "chunk", "keys", "more"])


def repeats(docs: DataFrame, doc: str = "doc_id", text: str = "text", length: int = LENGTH, keep_text: bool = False) -> DataFrame:
    """For every row: doc, n_bytes, n_removed, n_spans, kept_sha256, and the kept bytes if wanted."""
    spark = docs.sparkSession
    least = int(spark.conf.get("spark.sql.shuffle.partitions"))
    total = docs.agg(F.coalesce(F.sum(utf8_bytes(F.col(text))), F.lit(0))).first()[0]
    buckets = max(least, -(-total // BUCKET_BYTES))
    table = _chunks(docs, doc, text, buckets)
    # bytes of fingerprints that a level can get: one for each phrase, for each anchor, and at worst half of all windows
    one, two, three = (Level(max(least, -(-int(total * share) // GROUP_BYTES))) for share in (8 / EVERY, 8 / EVERY, 1.0))

    def phrases(number: int, c: Chunk, heard: dict, ids: list) -> Iterator[pa.RecordBatch]:
        k = c.phrases()
        yield from _sent(one.ask(number, k, k >> np.uint64(20)))

    def after_phrases(c: Chunk, heard: dict) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        k = c.phrases()
        twice, _ = one.hear(heard["phrase_bits"], k, k >> np.uint64(20))
        candidate = c.candidates(~twice)
        at = c.whole(candidate)
        return candidate, at, *c.contexts(at)

    def contexts(number: int, c: Chunk, heard: dict, ids: list) -> Iterator[pa.RecordBatch]:
        _, _, key, spread = after_phrases(c, heard)
        yield from _sent(two.ask(number, key, spread))

    def after_contexts(c: Chunk, heard: dict) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Windows known to be repeated, windows still open, and those that stand for a class."""
        candidate, at, key, spread = after_phrases(c, heard)
        twice, stands = two.hear(heard["context_bits"], key, spread)
        known = c._ranges(c.lo[at[twice]], c.hi[at[twice]]) > 0
        shown = at[twice & stands]
        return known, np.flatnonzero(candidate & ~known), np.flatnonzero(c._ranges(c.lo[shown], c.hi[shown]) > 0)

    def windows(number: int, c: Chunk, heard: dict, ids: list) -> Iterator[pa.RecordBatch]:
        _, open_, shown = after_contexts(c, heard)
        key, spread = c.windows(np.concatenate([open_, shown]))
        yield from _sent(three.ask(number, key, spread, np.arange(len(key)) >= len(open_)))

    def removed(number: int, c: Chunk, heard: dict, ids: list) -> Iterator[pa.RecordBatch]:
        known, open_, shown = after_contexts(c, heard)
        key, spread = c.windows(np.concatenate([open_, shown]))
        twice, _ = three.hear(heard["window_bits"], key, spread)
        start = np.flatnonzero(known)
        start = np.concatenate([start, open_[twice[: len(open_)]]])
        gone = c._ranges(start, start + length - 1)[:-1] > 0
        edge = gone & ~np.concatenate([[False], gone[:-1]])
        edge[c.starts[:-1][c.starts[:-1] < len(gone)]] = gone[c.starts[:-1][c.starts[:-1] < len(gone)]]
        upto, spans = (np.concatenate([[0], np.cumsum(x)]) for x in (gone, edge))
        kept = [c.data[a:b][~gone[a:b]].tobytes() for a, b in zip(c.starts[:-1], c.starts[1:], strict=True)]
        columns = [pa.array(ids, pa.int64()), pa.array(np.diff(c.starts)), pa.array(np.diff(upto[c.starts])), pa.array(np.diff(spans[c.starts])), pa.array([hashlib.sha256(x).hexdigest() for x in kept], pa.string())]
        yield pa.RecordBatch.from_arrays(columns + [pa.array(kept, pa.binary())] * keep_text, names=["_doc", "n_bytes", "n_removed", "n_spans", "kept_sha256"] + ["kept"] * keep_text)

    heard: dict[str, DataFrame] = {}
    for name, make, level in (("phrase_bits", phrases, one), ("context_bits", contexts, two), ("window_bits", windows, three)):
        heard[name] = _answers(_over(table, dict(heard), make, _ASKED, length), name, max(least, level.groups // 2), buckets)
    schema = "_doc long, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + ", kept binary" * keep_text
    return _over(table, heard, removed, schema, length).withColumnRenamed("_doc", doc)


def op5_prefix_free_parsing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 of every document, without what 200 bytes found elsewhere cover."""
    return repeats(read(spark, sf_dir, "documents"))


QUERIES = {"op5_prefix_free_parsing": op5_prefix_free_parsing}

#: Every window of 200 bytes by its 128-bit digest; texts as hexadecimal digits, in overlapping parts of 1000 windows.
SQL = {
    "op5_prefix_free_parsing": f"""
WITH texts AS MATERIALIZED (
  SELECT row_number() OVER () AS r, doc_id, hex(encode(coalesce(text, ''))) AS h FROM documents
), parts AS (
  SELECT r, c * 1000 AS base, substr(h, CAST(c * 2000 + 1 AS BIGINT), {2 * (1000 + LENGTH - 1)}) AS part FROM texts, unnest(range(0, length(h) // 2000 + 1)) AS u(c)
), windows AS MATERIALIZED (
  SELECT r, base + i AS pos, md5_number(substr(part, CAST(2 * i + 1 AS BIGINT), {2 * LENGTH})) AS w
  FROM parts, unnest(range(0, least(1000, length(part) // 2 - {LENGTH - 1}))) AS u(i)
), starts AS (
  SELECT r, pos FROM windows WHERE w IN (SELECT w FROM windows GROUP BY w HAVING count(*) > 1)
), edges AS (
  SELECT r, pos, CASE WHEN pos - lag(pos) OVER (PARTITION BY r ORDER BY pos) <= {LENGTH} THEN 0 ELSE 1 END AS opens FROM starts
), numbered AS (
  SELECT r, pos, sum(opens) OVER (PARTITION BY r ORDER BY pos) AS span FROM edges
), spans AS (
  SELECT r, min(pos) AS lo, max(pos) + {LENGTH} AS hi FROM numbered GROUP BY r, span
), behind AS (
  SELECT r, lo, hi, coalesce(lag(hi) OVER (PARTITION BY r ORDER BY lo), 0) AS upto FROM spans
), removed AS (
  SELECT b.r, sum(b.hi - b.lo) AS n_removed, count(*) AS n_spans, max(b.hi) AS ends,
    string_agg(substr(t.h, CAST(2 * b.upto + 1 AS BIGINT), CAST(2 * (b.lo - b.upto) AS BIGINT)), '' ORDER BY b.lo) AS kept
  FROM behind b JOIN texts t ON t.r = b.r GROUP BY b.r
)
SELECT t.doc_id, CAST(length(t.h) // 2 AS BIGINT) AS n_bytes, CAST(coalesce(d.n_removed, 0) AS BIGINT) AS n_removed, CAST(coalesce(d.n_spans, 0) AS BIGINT) AS n_spans,
  sha256(unhex(coalesce(d.kept, '') || substr(t.h, CAST(2 * coalesce(d.ends, 0) + 1 AS BIGINT)))) AS kept_sha256
FROM texts t LEFT JOIN removed d ON d.r = t.r"""
}
