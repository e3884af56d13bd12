"""Near-duplicate detection with SetSketch registers.

A document's set of word shingles gives M registers: the truncated logarithm (base BASE) of the smallest of exponentially spaced hash
values, so registers are small whole numbers, mergeable by taking the larger, and locality-sensitive. Equal sets (by a digest of 128
bits for each shingle) are one class, numbered when it is written. Bands of registers propose class pairs, in three passes: in each band
bucket every class is paired with the bucket's smallest; then, in buckets that still hold several components, each member outside the
bucket's largest one with its NEAREST likeliest partners; then every pair across components, so no proposed link between components is
left out. In each pass the joint likelihood of two register rows, given both set sizes, drops pairs that can't be similar; what remains
is confirmed on the words of both texts, exactly and not by hashes. Linked classes form components.

Hot groups: members of a bucket come in blocks, and blocks that hold only the bucket's largest component aren't looked at against each
other; a pair that shares several bands is looked at in the first of them; likely pairs stay inside their block, where each member names
its partners, and are never rows; what is confirmed together is of bounded size, and a text goes there once and not with every pair;
classes and components that hold many rows are joined by broadcast.

Edge cases: a text with fewer words than a shingle is its whole word sequence; one without words is empty and linked with nothing;
null texts are empty; a missing id is an id smaller than all others; rows that share an id are one document, linked whatever their
texts, and each returned; an empty table gives an empty result; further columns, whatever their names, are not read, and kept by
`keep_first`. A text must fit in a Python worker some 30 times.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dictparse.llm.common import fresh, lean, map_batches, read, skewed_join, texts_of, written
from dictparse.llm.hashing import mix

SIMILARITY = 80
#: Registers, those of one band, and the base of their logarithm. A pair at the limit meets in one of the 32 bands with
#: probability over 1 - 4e-6.
M, ROWS, BASE = 160, 5, 1.02
BANDS = M // ROWS
#: Standard deviations that an estimate may lie below the limit.
MARGIN = 5.0
#: Weight of a bucket's members looked at together, and of those whose texts are confirmed together (a text weighs its shingles and
#: LIGHT more); a member's likeliest partners that are tried first.
BLOCK, FAMILY, LIGHT, NEAREST = 1 << 17, 50_000, 50, 8
#: Rows that a worker looks at together, if they aren't of one bucket; words whose hashes it remembers.
TOGETHER, REMEMBERED = 16_384, 300_000
#: A-Z folded; words end at ASCII white space, as bytes.split() does it.
_FOLD = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))
_ODD = np.random.default_rng(20240229).integers(1, 1 << 63, (2, M, 1), dtype=np.uint64) * np.uint64(2) + np.uint64(1)
#: Added to registers, so that the largest possible minimum still has one above 0.
_OFFSET = 256
_NO_ID = -(1 << 63)


def words(text: bytes) -> list[bytes]:
    return text.translate(_FOLD).split()


class WordHashes:
    """128-bit hashes of words, remembered up to a bound."""

    def __init__(self) -> None:
        self.known: dict[bytes, bytes] = {}

    def _add(self, word: bytes) -> bytes:
        import xxhash

        self.known[word] = out = xxhash.xxh3_128_digest(word)
        return out

    def of(self, listed: list[bytes]) -> np.ndarray:
        if len(self.known) > REMEMBERED:
            self.known = {}
        get, add = self.known.get, self._add
        return np.frombuffer(b"".join([get(w) or add(w) for w in listed]), np.uint64).reshape(-1, 2)


def shingles(listed: list[bytes], width: int, hashes: WordHashes) -> tuple[np.ndarray, bytes]:
    """Sorted distinct 64-bit hashes of a word sequence's shingles, and the set's digest, made of 128 bits for each."""
    both = hashes.of(listed)
    n = len(both)
    if not n:
        return np.zeros(0, np.uint64), b""
    size = min(width, n)
    out = np.full((n - size + 1, 2), size, np.uint64)
    for k in range(size):
        out = mix(out * np.uint64(0xC2B2AE3D27D4EB4F) + both[k : n - size + 1 + k])
    order = np.argsort(out[:, 0], kind="stable")
    out = out[order]
    first = np.ones(len(out), bool)
    first[1:] = out[1:, 0] != out[:-1, 0]
    out = out[first]
    return np.ascontiguousarray(out[:, 0]), hashlib.blake2b(out.tobytes(), digest_size=16).digest()


def registers(hashes: np.ndarray) -> np.ndarray:
    """M truncated logarithms of minima, as 16-bit numbers."""
    least = np.full(M, np.iinfo(np.uint64).max)
    for at in range(0, len(hashes), 2048):
        values = hashes[None, at : at + 2048] * _ODD[0]
        values += _ODD[1]
        least = np.minimum(least, values.min(1))
    # -ln(1 - u) is exponential; the logarithm to BASE of its minimum, negated, truncated
    u = (least.astype(np.float64) + 0.5) / 2.0**64
    u = np.minimum(u, 1 - 2.0**-53)
    return np.clip(np.floor(-np.log(-np.log1p(-u)) / math.log(BASE)) + _OFFSET, 0, 65535).astype(np.uint16)


def likelihood_estimate(a: np.ndarray, b: np.ndarray, size_a: np.ndarray, size_b: np.ndarray) -> np.ndarray:
    """The most likely similarity of set pairs, from how many registers are larger in one, larger in the other, or equal.

    With sizes u and v (shares of their sum) and similarity j, a register of the first is larger with probability p(u - v j), and
    likewise for the second, where p(x) = -log_b(1 - x (b - 1) / b); the estimate is where the log-likelihood is largest on a grid.
    """
    more, fewer = (a > b).sum(-1).astype(np.float64), (a < b).sum(-1).astype(np.float64)
    equal = a.shape[-1] - more - fewer
    u = size_a / (size_a + size_b)
    v = 1 - u
    top = np.minimum(u / v, v / u)
    best, at = np.full(more.shape, -np.inf), np.zeros(more.shape)
    for step in np.linspace(0.0, 1.0, 41):
        j = top * step
        p, q = (-np.log1p(-np.clip(x, 0, 1) * (BASE - 1) / BASE) / math.log(BASE) for x in (u - v * j, v - u * j))
        rest = np.clip(1 - p - q, 1e-9, 1)
        value = more * np.log(np.maximum(p, 1e-9)) + fewer * np.log(np.maximum(q, 1e-9)) + equal * np.log(rest)
        better = value > best
        best, at = np.where(better, value, best), np.where(better, j, at)
    return at


def link_estimate(a: np.ndarray, b: np.ndarray, size_a: np.ndarray, size_b: np.ndarray, similarity: int) -> np.ndarray:
    """The estimated similarity of pairs that the registers don't rule out and whose sizes allow it; -1 for the others."""
    s, m = similarity / 100, a.shape[-1]
    least = s - MARGIN * math.sqrt(s * (1 - s) / m)
    small, large = np.minimum(size_a, size_b), np.maximum(size_a, size_b)
    near = np.flatnonzero((100 * small >= similarity * large) & ((a == b).sum(-1) >= (least - 0.05) * m))
    out = np.full(len(size_a), -1.0)
    if len(near):
        estimate = likelihood_estimate(a[near], b[near], size_a[near], size_b[near])
        out[near] = np.where(estimate >= least, estimate, -1.0)
    return out


def band_keys(regs: np.ndarray) -> np.ndarray:
    """A 64-bit key of every band of every row of registers; keys of different bands differ."""
    r = regs.reshape(len(regs), BANDS, ROWS).astype(np.uint64)
    key = np.arange(1, BANDS + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    for k in range(ROWS):
        key = mix((key + r[:, :, k]) * np.uint64(0xC2B2AE3D27D4EB4F))
    return key


def _regs(column: pa.Array | pa.ChunkedArray) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), np.uint16).reshape(-1, M)


def sketches(docs: DataFrame, doc: str, text: str, width: int) -> DataFrame:
    """(doc, n, class, regs) of every row: set size, digest of the set, registers (the last two null for an empty set)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = WordHashes()
        for b in batches:
            n, classes, regs = [], [], []
            for t in texts_of(b, "text"):
                h, named = shingles(words(t), width, hashes)
                n.append(len(h))
                classes.append(named or None)
                regs.append(registers(h).tobytes() if len(h) else None)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64()), pa.array(classes, pa.binary()), pa.array(regs, pa.binary())], names=["doc", "n", "class", "regs"])

    return map_batches(docs.select(F.col(doc).cast("long").alias("doc"), F.col(text).alias("text")), run, "doc long, n long, class binary, regs binary")


def _bands(nodes: DataFrame) -> DataFrame:
    """(key, id) of every band of every class."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                key = band_keys(_regs(b.column("regs")))
                yield pa.RecordBatch.from_arrays([pa.array(key.ravel().view(np.int64)), pa.array(np.repeat(b.column("id").to_numpy(), BANDS))], names=["key", "id"])

    return nodes.select("id", "regs").mapInArrow(lean(run), "key long, id long")


def _starred(pairs: DataFrame, nodes: DataFrame, similarity: int) -> DataFrame:
    """The pairs (a, b) that the registers of both sides don't rule out; many pairs may share their a."""
    a = nodes.select(F.col("id").alias("a"), F.col("n").alias("n_a"), F.col("regs").alias("r_a"))
    b = nodes.select(F.col("id").alias("b"), F.col("n").alias("n_b"), F.col("regs").alias("r_b"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for x in batches:
            if x.num_rows:
                n_a, n_b = x.column("n_a").to_numpy(), x.column("n_b").to_numpy()
                ok = np.flatnonzero(link_estimate(_regs(x.column("r_a")), _regs(x.column("r_b")), n_a, n_b, similarity) >= 0)
                yield x.select(["a", "b", "n_a", "n_b"]).take(pa.array(ok))

    return skewed_join(pairs.join(b, "b"), a, "a").select("a", "b", "n_a", "r_a", "n_b", "r_b").mapInArrow(lean(run), "a long, b long, n_a long, n_b long")


def exact_sets(texts: list[bytes], width: int) -> list[np.ndarray]:
    """Each text's distinct shingles as sorted numbers; equal numbers mean equal words, over all the texts given."""
    vocabulary: dict[bytes, int] = {}
    number = vocabulary.setdefault
    parts = []
    for t in texts:
        w = np.array([number(x, len(vocabulary) + 1) for x in words(t)], np.int64)
        parts.append(np.pad(w, (0, max(0, width - len(w)))))  # 0 is no word
    code = [w[: len(w) - width + 1] for w in parts]
    cuts = np.cumsum([len(c) for c in code])[:-1]
    flat = np.concatenate(code)
    for k in range(1, width):
        # two whole numbers to one, then numbered anew, so that they stay small
        flat = flat * (len(vocabulary) + 1) + np.concatenate([w[k : len(w) - width + 1 + k] for w in parts])
        if k + 1 < width:
            flat = np.unique(flat, return_inverse=True)[1]
    return [np.unique(c) for c in np.split(flat, cuts)]


def _confirmed(pairs: DataFrame, texts: DataFrame, width: int, similarity: int) -> DataFrame:
    """The pairs (a, b) whose sets meet the limit.

    Pairs near each other form a family (by the smallest id two steps away), so a text is sent once for each family and not for each
    pair. Large families are dealt with by pairs of blocks of about FAMILY shingles, small ones several at a time.
    """
    pairs = written(pairs, "near-pairs")
    both = pairs.select("a", "b").unionByName(pairs.select(F.col("b").alias("a"), F.col("a").alias("b")))
    one = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("g"))
    two = both.join(one.select(F.col("a").alias("b"), "g"), "b").groupBy("a").agg(F.min("g").alias("g"))
    grouped = written(pairs.join(two, "a").join(two.select(F.col("a").alias("b"), F.col("g").alias("h")), "b").withColumn("g", F.least("g", "h")).drop("h"), "near-groups")
    ends = grouped.select("g", F.explode(F.array(F.struct(F.col("a").alias("id"), F.col("n_a").alias("n")), F.struct(F.col("b").alias("id"), F.col("n_b").alias("n")))).alias("e")).distinct()
    sizes = written(ends.groupBy("g").agg(F.sum(F.col("e.n") + LIGHT).alias("n")), "near-sizes")
    small = F.col("n") <= FAMILY
    tasks = _tasks(sizes.where(small), "n")
    blocks = F.ceil(F.col("n") / FAMILY)
    own = lambda c: F.when(small, F.lit(-1)).otherwise(F.pmod(F.xxhash64(c), blocks))
    held = F.when(small, F.pmod(F.xxhash64("g"), F.lit(tasks))).otherwise(F.col("g"))
    placed = skewed_join(grouped, sizes, "g").select("a", "b", held.alias("g"), F.least(own("a"), own("b")).alias("x"), F.greatest(own("a"), own("b")).alias("y"))
    placed = written(placed, "near-placed-pairs")
    wanted = placed.select(F.col("g").alias("g_"), F.col("x").alias("x_"), F.col("y").alias("y_"), F.explode(F.array("a", "b")).alias("id")).distinct().join(texts, "id")

    def check(pairs: pa.Table, texts: pa.Table) -> pa.Table:
        sets = dict(zip(texts["id"].to_pylist(), exact_sets(texts["text"].to_pylist(), width), strict=True)) if pairs.num_rows else {}
        left, right = [], []
        for a, b in zip(pairs["a"].to_pylist(), pairs["b"].to_pylist(), strict=True):
            s, t = sets[a], sets[b]
            both = len(np.intersect1d(s, t, assume_unique=True))
            if 100 * both >= similarity * (len(s) + len(t) - both):
                left.append(a)
                right.append(b)
        return pa.table({"a": pa.array(left, pa.int64()), "b": pa.array(right, pa.int64())})

    return placed.groupBy("g", "x", "y").cogroup(wanted.groupBy("g_", "x_", "y_")).applyInArrow(check, "a long, b long")


def _signature(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())


def components(links: DataFrame, name: str = "component") -> DataFrame:
    """(id, root) of every node of the links (a, b): the smallest id it can reach, by alternating large-star and small-star rounds."""
    edges = written(links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v").distinct(), name)
    before = _signature(edges)
    while before[0]:
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = written(both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct(), name)
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        moved = large.join(low, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        edges = written(moved.unionByName(low.select("u", F.col("m").alias("v"))).distinct(), name)
        now = _signature(edges)
        if now == before:
            break
        before = now
    return edges.select(F.col("u").alias("id"), F.col("v").alias("root"))


def _merged(roots: DataFrame, links: DataFrame) -> DataFrame:
    """(id, root) after links (a, b) between ids join what they reach."""
    ends = links.join(roots.select(F.col("id").alias("a"), F.col("root").alias("u")), "a").join(roots.select(F.col("id").alias("b"), F.col("root").alias("v")), "b")
    found = components(ends.where("u <> v").select(F.col("u").alias("a"), F.col("v").alias("b")))
    moved = skewed_join(roots, found.select(F.col("id").alias("root"), F.col("root").alias("to")), "root")
    return written(moved.select("id", F.coalesce("to", "root").alias("root")), "near-roots")


class Bucket:
    """Members of some band buckets, row by row, those of one bucket (or pair of blocks) together."""

    def __init__(self, rows: pa.Table, group: np.ndarray, similarity: int):
        self.group, self.similarity = group, similarity
        self.key = rows["key"].to_numpy().view(np.uint64)
        self.ids, self.roots, self.own, self.n = (rows[c].to_numpy() for c in ("id", "root", "own", "n"))
        self.regs = _regs(rows["regs"])
        self.keys = band_keys(self.regs)

    def likely(self, cross: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(i, j, estimate) of the pairs across components that the registers don't rule out; `cross` marks rows whose group is a pair of blocks."""
        got: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        at = np.arange(len(self.ids))
        d = 1
        while True:
            at = at[at + d < len(self.ids)]
            at = at[self.group[at] == self.group[at + d]]  # a group that is too short stays too short
            if not len(at):
                break
            i, j = at, at + d
            small, large = np.minimum(self.n[i], self.n[j]), np.maximum(self.n[i], self.n[j])
            ok = (self.roots[i] != self.roots[j]) & (100 * small >= self.similarity * large) & (~cross[i] | (self.own[i] != self.own[j]))
            i, j = i[ok], j[ok]
            if len(i):
                same = self.keys[i] == self.keys[j]
                first = same.argmax(1)
                ok = self.keys[i, first] == self.key[i]
                i, j = i[ok], j[ok]
            for k in range(0, len(i), 8192):
                p, q = i[k : k + 8192], j[k : k + 8192]
                estimate = link_estimate(self.regs[p], self.regs[q], self.n[p], self.n[q], self.similarity)
                ok = estimate >= 0
                got.append((p[ok], q[ok], estimate[ok]))
            d += 1
        return tuple(np.concatenate(x) for x in zip(*got, strict=True)) if got else (at, at, np.zeros(0))

    def nearest(self, i: np.ndarray, j: np.ndarray, estimate: np.ndarray, most: int) -> tuple[np.ndarray, np.ndarray]:
        """Each member outside its group's largest component keeps so many of its likeliest partners."""
        _, component, size = np.unique(np.stack([self.group, self.roots]), axis=1, return_inverse=True, return_counts=True)
        component = component.ravel()
        largest = np.zeros(int(self.group.max()) + 1, np.int64)
        by = np.argsort(size[component], kind="stable")
        largest[self.group[by]] = component[by]
        a, b, e = np.concatenate([i, j]), np.concatenate([j, i]), np.concatenate([estimate, estimate])
        out = component[a] != largest[self.group[a]]
        a, b, e = a[out], b[out], e[out]
        order = np.lexsort((-e, a))
        a, b = a[order], b[order]
        begin = np.flatnonzero(np.r_[True, a[1:] != a[:-1]]) if len(a) else np.zeros(0, np.int64)
        rank = np.arange(len(a)) - np.repeat(begin, np.diff(np.r_[begin, len(a)]))
        a, b = a[rank < most], b[rank < most]
        pairs = np.unique(np.stack([np.minimum(a, b), np.maximum(a, b)]), axis=1)
        return pairs[0], pairs[1]


def _tasks(rows: DataFrame, weight: str) -> int:
    return 1 + int(rows.agg(F.coalesce(F.sum(weight), F.lit(0))).first()[0]) // FAMILY


def _partners(buckets: DataFrame, roots: DataFrame, nodes: DataFrame, similarity: int, nearest: int | None) -> DataFrame:
    """(key, x, y, whole, id, n, partners): members of a bucket's block (or pair of blocks x, y) with the ids of their likely partners.

    A pair across components is named by one of its two members, the other is a row too. With `nearest`, only so many of the
    likeliest partners of each member outside the bucket's largest component, within one block.
    """
    buckets = written(buckets.join(roots, "id").join(nodes.select("id", "n"), "id").select("key", "id", "root", "n"), "near-members")
    held = buckets.groupBy("key", "root").agg(F.sum(F.col("n") + LIGHT).alias("held"))
    mixed = held.groupBy("key").agg(F.sum("held").alias("size"), F.max("held").alias("most"), F.max_by("root", "held").alias("top"), F.count("*").alias("roots")).where("roots > 1").drop("roots")
    members = skewed_join(buckets, mixed, "key", how="inner").withColumn("whole", F.col("size") <= BLOCK)
    dealt = lambda weight: F.pmod(F.xxhash64("id"), F.ceil(weight / BLOCK))
    if nearest:
        pairs = members.withColumn("own", dealt(F.col("size"))).withColumn("x", F.col("own")).withColumn("y", F.col("own"))
    else:
        # blocks of the largest component have numbers below 0 and meet only the others
        top, others = F.col("root") == F.col("top"), F.col("size") - F.col("most")
        first, last, zero = -F.ceil(F.col("most") / BLOCK), F.ceil(others / BLOCK) - 1, F.lit(0).cast("long")
        own = F.when(F.col("whole"), F.lit(0)).when(top, -1 - dealt(F.col("most"))).otherwise(dealt(others))
        met = F.when(F.col("whole"), F.array(zero)).when(top, F.sequence(zero, last)).otherwise(F.sequence(first, last))
        pairs = members.withColumn("own", own).withColumn("met", F.explode(met)).withColumn("x", F.least("own", "met")).withColumn("y", F.greatest("own", "met"))

    def look(rows: pa.Table) -> pa.RecordBatch:
        key, x, y = (rows[c].to_numpy() for c in ("key", "x", "y"))
        edge = np.r_[True, (key[1:] != key[:-1]) | (x[1:] != x[:-1]) | (y[1:] != y[:-1])]
        bucket = Bucket(rows, np.cumsum(edge) - 1, similarity)
        i, j, estimate = bucket.likely(x != y)
        if nearest:
            i, j = bucket.nearest(i, j, estimate, nearest)
        by = np.argsort(i, kind="stable")
        i, j = i[by], j[by]
        at = np.unique(np.concatenate([i, j]))
        named = pa.ListArray.from_arrays(pa.array(np.searchsorted(i, np.r_[at, len(bucket.ids)]), pa.int32()), pa.array(bucket.ids[j], pa.int64()))
        some = rows.select(["key", "x", "y", "whole", "id", "n"]).take(pa.array(at))
        return some.append_column("partners", named).combine_chunks().to_batches()[0] if len(at) else None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        waiting: list[pa.RecordBatch] = []
        for b in batches:
            if not b.num_rows:
                continue
            waiting.append(b)
            if sum(w.num_rows for w in waiting) < TOGETHER:
                continue
            rows = pa.Table.from_batches(waiting)
            last = [rows[c][-1].as_py() for c in ("key", "x", "y")]
            same = np.logical_and.reduce([rows[c].to_numpy() == v for c, v in zip(("key", "x", "y"), last, strict=True)])
            cut = int(same.argmax())  # the last group may go on
            if cut and (found := look(rows.slice(0, cut))):
                yield found
            waiting = rows.slice(cut).combine_chunks().to_batches()
        if waiting and (found := look(pa.Table.from_batches(waiting))):
            yield found

    shape = pairs.select("key", F.col("x").cast("long").alias("x"), F.col("y").cast("long").alias("y"), F.col("own").cast("long").alias("own"), "whole", "id", "root", "n").join(nodes.select("id", "regs"), "id")
    return shape.repartition("key", "x", "y").sortWithinPartitions("key", "x", "y").mapInArrow(lean(run), "key long, x long, y long, whole boolean, id long, n long, partners array<long>")


def _across(buckets: DataFrame, roots: DataFrame, nodes: DataFrame, texts: DataFrame, width: int, similarity: int, nearest: int | None = None) -> DataFrame:
    """Confirmed links (a, b) of different components that share a bucket."""
    named = written(_partners(buckets, roots, nodes, similarity, nearest).withColumn("weight", F.col("n") + LIGHT), "near-partners")
    # whole buckets are confirmed several at a time, so a text that is in many of them goes there once
    tasks = _tasks(named.where("whole").select("id", "weight").distinct(), "weight")
    placed = named.withColumn("g", F.when(F.col("whole"), F.pmod(F.xxhash64("key"), F.lit(4 * tasks))).otherwise(F.col("key")))
    placed = placed.select("g", *(F.when(F.col("whole"), F.lit(-1 << 62)).otherwise(F.col(c)).alias(c) for c in ("x", "y")), "id", "partners")
    wanted = placed.select(F.col("g").alias("g_"), F.col("x").alias("x_"), F.col("y").alias("y_"), F.col("id").alias("member")).distinct().join(texts.withColumnRenamed("id", "member"), "member")

    def confirm(members: pa.Table, texts: pa.Table) -> pa.Table:
        sets = dict(zip(texts["member"].to_pylist(), exact_sets(texts["text"].to_pylist(), width), strict=True))
        left, right = [], []
        for i, others in zip(members["id"].to_pylist(), members["partners"].to_pylist(), strict=True):
            if others:
                own, them = sets[i], [sets[j] for j in others]
                sizes = np.array([len(t) for t in them])
                joined = np.concatenate(them)
                at = np.minimum(np.searchsorted(own, joined), len(own) - 1)
                both = np.add.reduceat(own[at] == joined, np.cumsum(sizes) - sizes, dtype=np.int64)
                linked = np.flatnonzero(100 * both >= similarity * (len(own) + sizes - both))
                left += [i] * len(linked)
                right += [others[k] for k in linked]
        return pa.table({"a": pa.array(left, pa.int64()), "b": pa.array(right, pa.int64())})

    return placed.groupBy("g", "x", "y").cogroup(wanted.groupBy("g_", "x_", "y_")).applyInArrow(confirm, "a long, b long").distinct()


def _texts(docs: DataFrame, doc: str, text: str, involved: DataFrame, width: int) -> DataFrame:
    """(id, text) of the nodes in question, read from their documents; rows that share an id are told apart by their sets."""
    source = docs.select(F.coalesce(F.col(doc).cast("long"), F.lit(_NO_ID)).alias("own"), F.col(text).alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = WordHashes()
        for b in batches:
            same = [shingles(words(t), width, hashes)[1] == c for t, c in zip(texts_of(b, "text"), b.column("class").to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([b.column("id"), b.column("text").cast(pa.binary())], names=["id", "text"]).filter(pa.array(same, pa.bool_()))

    got = source.join(involved.hint("shuffle_hash"), "own").select("id", "class", "text").mapInArrow(lean(run), "id long, text binary")
    return got.groupBy("id").agg(F.first("text").alias("text"))


def near_duplicates(docs: DataFrame, doc: str = "doc_id", text: str = "text", width: int = 5, similarity: int = SIMILARITY) -> DataFrame:
    """(doc, n, component) of every row; component is the smallest id that the row's document can reach, itself included."""
    rows = written(sketches(docs, doc, text, width).withColumn("own", F.coalesce("doc", F.lit(_NO_ID))), "sketches")
    full = rows.where("n > 0")
    # one node for each distinct set, with a document to read it from; its number is fixed as it is written
    nodes = written(full.groupBy("class").agg(F.min("own").alias("own"), F.first("n").alias("n"), F.first("regs").alias("regs")).withColumn("id", F.monotonically_increasing_id()), "near-nodes")
    keys = _bands(nodes)
    shared = keys.groupBy("key").agg(F.count("*").alias("size"), F.min("id").alias("least")).where("size > 1").drop("size")
    buckets = written(keys.join(shared, "key"), "near-buckets")  # rows of 16 bytes; a hot bucket is split as the session splits skewed joins
    texts = written(_texts(docs, doc, text, buckets.select("id").distinct().join(nodes.select("id", "own", "class"), "id"), width), "near-texts")
    roots = nodes.select("id", F.col("id").alias("root"))
    stars = written(buckets.where("id <> least").select(F.col("least").alias("a"), F.col("id").alias("b")).distinct(), "near-stars")
    roots = _merged(roots, _confirmed(_starred(stars, nodes, similarity), texts, width, similarity))
    for nearest in (NEAREST, None):
        roots = _merged(roots, _across(buckets, roots, nodes, texts, width, similarity, nearest))
    # rows that share an id are one document, whatever their sets
    several = full.join(full.groupBy("own").count().where("count > 1").select("own"), "own").select("own", "class").distinct().join(nodes.select("class", "id"), "class")
    several = several.join(several.groupBy("own").agg(F.min("id").alias("lo")), "own").where("id <> lo").select(F.col("lo").alias("a"), F.col("id").alias("b"))
    final = written(nodes.select("id", "own", "class").join(_merged(roots, several), "id"), "near-final")
    least = final.groupBy("root").agg(F.min("own").alias("least"))
    of_class = written(skewed_join(final.select("class", "root"), least, "root").select("class", "least"), "near-classes")
    whole = skewed_join(rows.select("doc", "own", "n", "class"), of_class, "class").withColumn("least", F.when(F.col("n") > 0, F.col("least")).otherwise(F.col("own")))
    return whole.select("doc", "n", F.when(F.col("least") != _NO_ID, F.col("least")).alias("component"))


def keep_first(docs: DataFrame, doc: str = "doc_id", text: str = "text", width: int = 5, similarity: int = SIMILARITY) -> DataFrame:
    """The rows of one document of each component, columns as they are; rows that share an id count once."""
    own, times = fresh(docs, "own"), fresh(docs, "rows")
    found = near_duplicates(docs, doc, text, width, similarity)
    found = found.select(F.coalesce("doc", F.lit(_NO_ID)).alias(own), F.col("doc").eqNullSafe(F.col("component")).alias("kept"))
    ids = written(found.groupBy(own).agg(F.max("kept").alias("kept"), F.count("*").alias(times)).where("kept").drop("kept"), "near-kept")
    keyed = docs.withColumn(own, F.coalesce(F.col(doc).cast("long"), F.lit(_NO_ID)))
    kept = keyed.join(ids.hint("shuffle_hash"), own)
    if not ids.where(F.col(times) > 1).limit(1).count():
        return kept.select(*docs.columns)
    # one of the rows of an id, by the content
    several = kept.where(F.col(times) > 1).groupBy(own).agg(F.min(F.struct(*docs.columns)).alias("row")).select("row.*")
    return kept.where(F.col(times) == 1).select(*docs.columns).unionByName(several)


def op10_setsketch(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, n_shingles, component_id, kept of every document: two words a shingle, linked from a similarity of 0.8."""
    found = near_duplicates(read(spark, sf_dir, "documents").select("doc_id", "text"), width=2)
    return found.select(F.col("doc").alias("doc_id"), F.col("n").alias("n_shingles"), F.col("component").alias("component_id"), F.col("doc").eqNullSafe(F.col("component")).alias("kept"))


QUERIES = {"op10_setsketch": op10_setsketch}
SQL = {
    "op10_setsketch": rf"""WITH RECURSIVE word_lists AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents),
sets AS MATERIALIZED (
  SELECT doc_id, list_sort(list_distinct(CASE WHEN len(ws) < 2 THEN ws ELSE list_transform(range(1, len(ws)), lambda k: ws[k] || ' ' || ws[k + 1]) END)) AS parts FROM word_lists),
classes AS MATERIALIZED (SELECT min(doc_id) AS id, parts FROM sets WHERE len(parts) > 0 GROUP BY parts),
entries AS (SELECT id, len(parts) AS n, unnest(parts) AS part FROM classes),
links AS MATERIALIZED (
  SELECT a.id AS x, b.id AS y FROM entries a JOIN entries b ON a.part = b.part AND a.id < b.id AND 100 * a.n >= 80 * b.n AND 100 * b.n >= 80 * a.n
  GROUP BY a.id, b.id, a.n, b.n HAVING 100 * count(*) >= 80 * (a.n + b.n - count(*))),
edges AS (SELECT x, y FROM links UNION ALL SELECT y, x FROM links),
reach AS (SELECT id, id AS least FROM classes UNION SELECT edges.y, reach.least FROM reach JOIN edges ON edges.x = reach.id AND reach.least < edges.y),
lowest AS (SELECT id, min(least) AS least FROM reach GROUP BY id)
SELECT s.doc_id, CAST(len(s.parts) AS BIGINT) AS n_shingles, coalesce(l.least, s.doc_id) AS component_id, s.doc_id = coalesce(l.least, s.doc_id) AS kept
FROM sets s LEFT JOIN classes c ON s.parts = c.parts AND len(s.parts) > 0 LEFT JOIN lowest l ON l.id = c.id"""
}
