"""Toxicity by weak supervision.

Many voters, lexicons and patterns, fire or stay silent on a text: a short fixed lexicon, lexicons of words and of word beginnings
taken from labelled training rows, and patterns over them. A generative label model, fitted by EM on how often each vote pattern
occurs in the whole corpus, estimates each voter's rates under both classes and the correlations that the class leaves between
voters; correlated voters share their weight. Its posterior labels train a linear classifier over votes and hashed words.

Labels are read only from rows whose crc32(id as text) mod 5 is not 0. The lexicons are learned from counts over all those rows; rows
of one label that share the smallest of their words' hashes under two hash functions (near copies) count as one, so a text copied
often is no evidence of its words. A bounded sample, the FITTED rows with the smallest id hashes, trains the classifier; the lexicons
are part of the model and hold at most LEXICON features.

Edge cases: a null text is an empty one and gets the score of a text without features; repeated rows are scored each; without usable
labels only the fixed lexicon votes; an empty table gives an empty result; further columns, whatever their names, are not inputs.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from itertools import chain, islice

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dictparse.llm.common import fresh, give_back, map_batches, read, texts_of, written

#: Labelled rows that train the classifier, at most; its hashed weights; features of the learned lexicons, at most.
FITTED, SPACE, LEXICON = 4_000, 1 << 18, 100_000
#: Lengths of words' beginnings that count as features of their own.
STEMS = (4, 6)
#: A small public lexicon of insults.
INSULTS = ("idiot", "moron", "stupid", "scum", "trash", "loser", "pathetic", "worthless", "disgusting", "clown", "imbecile", "dumb", "filthy", "vermin", "garbage")
#: Learned lexicons for each kind of feature (words, beginnings); a feature votes in the lexicon of its hash.
SPLIT = 2
#: Kinds of features, in a hash's last two bits: a word; a beginning in one, two, or three and more distinct words of the text.
KINDS = 4
_UPPER_RUN, _MARKS = re.compile(r"\b[^\W\d_a-z]{4,}\b"), re.compile(r"!{2,}")
PATTERNS = 4
VOTERS = 1 + KINDS * SPLIT + PATTERNS


_WORD = re.compile(r"[^\W_]+")


def _words(text: str) -> set[str]:
    return set(_WORD.findall(text.lower()))


class Hasher:
    """64-bit hashes of a text's features, remembered up to a bound."""

    def __init__(self, bound: int = 150_000):
        self.bound, self.known = bound, {}

    def _add(self, word: str) -> tuple[int, ...]:
        """The word's hash and those of its beginnings (0 where it has none), last two bits clear."""
        import xxhash

        hashed = xxhash.xxh3_64_intdigest
        stems = ((hashed((word[:n] + "\0").encode()) & ~3) if len(word) > n else 0 for n in STEMS)
        self.known[word] = out = (hashed(word.encode()) & ~3, *stems)
        return out

    def parts(self, text: str, words: set[str] | None = None) -> list[tuple[int, ...]]:
        """Hashes of a text's words, then of their beginnings by length (0 where a word has none); its words may be given."""
        if len(self.known) > self.bound:
            self.known = {}
        get, add = self.known.get, self._add
        each = [get(w) or add(w) for w in (_words(text) if words is None else words)]
        return [*zip(*each, strict=True)] or [()] * (1 + len(STEMS))

    def features(self, text: str, parts: list[tuple[int, ...]] | None = None) -> np.ndarray:
        """Hashes of a text's features; parts() of it may be given."""
        own, *stems = self.parts(text) if parts is None else parts
        counted = Counter(stems[0])
        for more in stems[1:]:
            counted.update(more)
        counted.pop(0, None)
        begin, n = np.fromiter(counted, np.uint64, len(counted)), np.fromiter(counted.values(), np.int64, len(counted))
        return np.concatenate([np.fromiter(own, np.uint64, len(own)), begin | np.uint64(1), begin[n > 1] | np.uint64(2), begin[n > 2] | np.uint64(3)])


def insult_hashes() -> np.ndarray:
    h = Hasher()
    return np.unique(np.concatenate([[x for x in h.features(w) if not x & np.uint64(3)] for w in INSULTS]).astype(np.uint64))


class Votes:
    """Turns a text into a bit pattern of fired voters."""

    def __init__(self, lexicon: np.ndarray):
        self.fixed, self.learned = set(insult_hashes().tolist()), set(lexicon.tolist())
        self.stems = {x & ~3 for x in self.learned if x & 3}
        self._forget()

    def _forget(self, bound: int = 150_000) -> None:
        self.hasher = Hasher(bound)
        #: Hashes of the words met; those that some lexicon may know; by beginning of a word met, whether a lexicon may know it.
        self.met: dict[str, int] = {}
        self.telling: set[str] = set()
        self.begun: dict[str, bool] = {}

    def __getstate__(self) -> dict:
        return self.__dict__ | {"hasher": Hasher(), "met": {}, "telling": set(), "begun": {}}

    def told(self, words: set[str]) -> list[tuple[int, ...]]:
        """parts() of those of a text's words that some lexicon may know; a word is looked up when it is first met."""
        import xxhash

        if len(self.met) > self.hasher.bound:
            self._forget(self.hasher.bound)
        hashed, begun, known = xxhash.xxh3_64_intdigest, self.begun, self.hasher.known
        for w in words.difference(self.met):
            own = self.met[w] = hashed(w.encode()) & ~3
            tells = own in self.fixed or own in self.learned
            for n in STEMS:
                if len(w) > n:
                    s = w[:n]
                    tells_too = begun.get(s)
                    if tells_too is None:
                        tells_too = begun[s] = hashed((s + "\0").encode()) & ~3 in self.stems
                    tells = tells or tells_too
            if tells:
                self.telling.add(w)
                self.hasher._add(w)
        return [*zip(*(known[w] for w in words & self.telling), strict=True)] or [()] * (1 + len(STEMS))

    def pattern(self, text: str, parts: list[tuple[int, ...]] | None = None) -> int:
        """The text's fired voters as bits; a hasher's parts() of it, or what is told of its words, may be given."""
        own, *stems = self.told(_words(text)) if parts is None else parts
        fixed, found, bits = len(self.fixed.intersection(own)), self.learned.intersection(own), 0
        words = len(found)
        for f in found:
            bits |= 1 << 1 + (f >> 7) % SPLIT
        known = self.stems.__contains__
        for begun in stems:
            for s, n in Counter(filter(known, begun)).items():
                for kind in range(1, 1 + min(n, 3)):
                    if s | kind in self.learned:
                        bits |= 1 << 1 + kind * SPLIT + (s >> 7) % SPLIT
        bits |= fixed > 0
        pattern = (words >= 2, words >= 4, fixed >= 2 or (words > 0 and _MARKS.search(text) is not None), words > 0 and _UPPER_RUN.search(text) is not None)
        for k, fired in enumerate(pattern):
            bits |= fired << 1 + KINDS * SPLIT + k
        return bits


def is_held_out(doc: str) -> F.Column:
    return F.coalesce(F.crc32(F.col(doc).cast("string").cast("binary")) % 5 == 0, F.lit(False))


def labelled_rows(docs: DataFrame, labels: DataFrame, doc: str, text: str, label: str) -> DataFrame:
    """All usable labelled rows: own, text, _y (1: toxic), _hash of the text, _row (unique) and _group, which near copies share."""
    marked = labels.where(~is_held_out(doc)).select(F.col(doc).alias("own"), F.col(label).alias("y")).where("own IS NOT NULL AND y IS NOT NULL")
    marked = marked.groupBy("own").agg((F.max("y").cast("int") == 1).cast("int").alias("_y"))
    # labels grow with the documents, so they are never broadcast: one plan at every size; held-out texts stay out of the shuffle
    rows = docs.where(~is_held_out(doc)).select(F.col(doc).alias("own"), F.coalesce(F.col(text), F.lit("")).alias("text")).join(marked.hint("merge"), "own")
    hashed = F.split(F.lower("text"), r"[^\p{L}\p{N}]+")
    least = [F.array_min(F.transform(hashed, make)) for make in (lambda w: F.xxhash64(w), lambda w: F.xxhash64(w, F.lit(1)))]
    rows = rows.withColumn("_group", F.xxhash64(*least)).withColumn("_hash", F.xxhash64("text")).withColumn("_row", F.monotonically_increasing_id())
    return written(rows, "labelled")


def training_rows(rows: DataFrame, most: int, votes: Votes) -> tuple[list[np.ndarray], np.ndarray]:
    """Features and vote patterns of so many labelled rows, those with the smallest id hashes (bounded, so they may come to the driver)."""
    chosen = rows.select("own", "_hash", "_row").orderBy(F.xxhash64("own"), "own", "_hash", "_row").limit(most).select("_row")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hasher = Hasher()
        for b in batches:
            texts = [t.decode() for t in texts_of(b, "text")]
            parts = [hasher.parts(t) for t in texts]
            own = [hasher.features(t, p) for t, p in zip(texts, parts, strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array([votes.pattern(t, p) for t, p in zip(texts, parts, strict=True)], pa.int64()), pa.array([f.tobytes() for f in own], pa.binary())], names=["p", "f"])

    # at most `most` rows of one number
    got = map_batches(rows.join(F.broadcast(chosen), "_row").select("text"), run, "p long, f binary").orderBy(F.xxhash64("f")).toLocalIterator()
    features, patterns = [], []
    for r in got:
        features.append(np.frombuffer(bytes(r.f), np.uint64))
        patterns.append(r.p)
    return features, np.array(patterns, np.int64)


def feature_counts(rows: DataFrame, at_once: int = 1 << 19) -> DataFrame:
    """f, total, hits: how many rows, and how many toxic ones, hold each feature; added up in the tasks before the shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hasher, held, size = Hasher(), [], 0

        def added() -> pa.RecordBatch:
            f, place = np.unique(np.concatenate([x for x, _ in held]), return_inverse=True)
            toxic = np.repeat(np.array([y for _, y in held], np.float64), [len(x) for x, _ in held])
            total, hits = np.bincount(place, minlength=len(f)), np.bincount(place, toxic, len(f)).astype(np.int64)
            return pa.RecordBatch.from_arrays([pa.array(f.view(np.int64)), pa.array(total, pa.int64()), pa.array(hits, pa.int64())], names=["f", "n", "h"])

        for b in batches:
            for t, y in zip(texts_of(b, "text"), b.column("_y").to_pylist(), strict=True):
                own = hasher.features(t.decode())
                if len(own):
                    held.append((own, y))
                    size += len(own)
                if size > at_once:
                    yield added()
                    held, size = [], 0
        if held:
            yield added()

    return map_batches(rows.select("_y", "text"), run, "f long, n long, h long").groupBy("f").agg(F.sum("n").alias("total"), F.sum("h").alias("hits"))


def learned_lexicon(labelled: DataFrame, chance: float = 0.01, most: int = LEXICON) -> tuple[np.ndarray, float]:
    """Features that toxic rows hold more often than chance allows over all features tried, and the share of toxic rows.

    All labelled rows are counted, near copies (one label, one group) once. Of more than `most` such features the clearest are taken.
    """
    one = labelled.groupBy("_y", "_group").agg(F.min(F.struct("own", "_hash", "_row")).alias("first"), F.count(F.lit(1)).alias("n"))
    one = written(one.select("_y", F.col("first._row").alias("_row"), "n"), "label-groups")
    sizes = {r["_y"]: r for r in one.groupBy("_y").agg(F.count(F.lit(1)).alias("groups"), F.sum("n").alias("n")).collect()}  # two labels
    if len(sizes) < 2:
        return np.zeros(0, np.uint64), float(min(sizes, default=0.1))
    base = sizes[1].groups / (sizes[0].groups + sizes[1].groups)
    counts = written(feature_counts(labelled.join(one.select("_row"), "_row", "left_semi")), "feature-counts")
    rate = F.col("hits") / F.col("total")
    inner = F.least(F.greatest(rate, F.lit(1e-9)), F.lit(1 - 1e-9))
    evidence = F.col("total") * (inner * F.log(inner / base) + (1 - inner) * F.log((1 - inner) / (1 - base)))
    enough = float(np.log(max(counts.count(), 1) / chance))
    clear = counts.where(F.col("hits") >= 3).withColumn("evidence", evidence).where((rate >= max(0.6, 3 * base)) & (F.col("evidence") > enough))
    taken = clear.orderBy(F.desc("evidence"), "f").limit(most).select("f").collect()
    return np.array([r.f for r in taken], np.int64).view(np.uint64), sizes[1].n / (sizes[0].n + sizes[1].n)


def _bits(patterns: np.ndarray) -> np.ndarray:
    return (patterns[:, None] >> np.arange(VOTERS) & 1).astype(np.float64)


class LabelModel:
    """P(class | votes): class prior, each voter's firing rate under both classes, and weights that discount correlated voters."""

    def __init__(self, patterns: np.ndarray, counts: np.ndarray, prior: float = 0.1, rounds: int = 50):
        votes, n = _bits(patterns), counts.astype(np.float64)
        self.weight = np.ones(VOTERS)
        self.prior = prior
        posterior = np.where(votes.sum(1) >= 2, 0.95, np.where(votes.sum(1) == 1, 0.5, 0.02))
        for _ in range(rounds):
            q, rest = posterior * n, (1 - posterior) * n
            self.prior = float(np.clip((q.sum() + 1) / (n.sum() + 2 / prior), 1e-4, 0.5))
            # a voter speaks for the toxic class: its prior counts say so
            self.fires = (votes.T @ q + 1) / (q.sum() + 2)
            self.errs = np.minimum((votes.T @ rest + 0.01) / (rest.sum() + 1), 0.5 * self.fires)
            self.correlation = sum(self._residual(votes, w, rate) for w, rate in ((q, self.fires), (rest, self.errs))) / 2
            self.weight = 1 / np.sqrt(np.abs(self.correlation).sum(1))
            posterior = self.posterior(patterns)

    @staticmethod
    def _residual(votes: np.ndarray, w: np.ndarray, rate: np.ndarray) -> np.ndarray:
        """Correlation of the voters within one class."""
        apart = votes - rate
        cov = (apart * w[:, None]).T @ apart / max(w.sum(), 1e-9)
        sd = np.sqrt(np.maximum(np.diag(cov), 1e-9))
        out = np.clip(cov / sd[:, None] / sd, -1, 1)
        np.fill_diagonal(out, 1)
        return out

    def posterior(self, patterns: np.ndarray) -> np.ndarray:
        votes = _bits(patterns)
        on = np.log(self.fires / self.errs)
        off = np.log((1 - np.minimum(self.fires, 0.999)) / (1 - self.errs))
        logit = np.log(self.prior / (1 - self.prior)) + (votes * on + (1 - votes) * off) @ self.weight
        return 1 / (1 + np.exp(-np.clip(logit, -30, 30)))


def _columns(features: np.ndarray) -> np.ndarray:
    return (features % np.uint64(SPACE)).astype(np.int64)


class Linear:
    """Logistic regression on votes and hashed features, fitted by whole-batch gradient steps."""

    def __init__(self, features: list[np.ndarray], patterns: np.ndarray, target: np.ndarray, rounds: int = 200):
        size = np.array([len(f) for f in features], np.int64)
        row = np.repeat(np.arange(len(features), dtype=np.int32), size)
        column = np.concatenate([_columns(f).astype(np.int32) for f in features]) if len(features) else np.zeros(0, np.int32)
        value = (1 / np.sqrt(np.maximum(size, 1))).astype(np.float32)[row]
        votes = _bits(patterns)
        self.bias, self.votes, self.words = -2.0, np.full(VOTERS, 0.5), np.zeros(SPACE)
        n = max(len(features), 1)
        grown = [1e-8, np.full(VOTERS, 1e-8), np.full(SPACE, 1e-8)]
        for _ in range(rounds if len(features) else 0):
            z = self.bias + votes @ self.votes + np.bincount(row, value * self.words[column], n)
            off = 1 / (1 + np.exp(-np.clip(z, -30, 30))) - target
            steps = (off.mean(), votes.T @ off / n + 1e-4 * self.votes, np.bincount(column, value * off[row], SPACE) / n + 1e-4 * self.words)
            grown = [g + s * s for g, s in zip(grown, steps, strict=True)]
            move = [0.3 * s / np.sqrt(g) for s, g in zip(steps, grown, strict=True)]
            self.bias, self.votes, self.words = self.bias - move[0], self.votes - move[1], self.words - 0.1 * move[2]
        self.words = self.words.astype(np.float32)

    def score(self, patterns: np.ndarray, features: list[np.ndarray]) -> np.ndarray:
        z = self.bias + _bits(patterns) @ self.votes
        z = z + [float(self.words[_columns(f)].sum()) / np.sqrt(max(len(f), 1)) for f in features]
        return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


class Scorer:
    """Scores of a batch of texts, equal to Linear.score() on their patterns and features up to rounding.

    Words and beginnings get numbers when they are first met; a batch's sums are then taken over arrays.
    """

    def __init__(self, votes: Votes, linear: Linear):
        self.votes, self.linear = votes, linear
        self._forget()

    def _forget(self) -> None:
        #: Numbers of words and of their beginnings (0: none); by word, its weight and its beginnings; by beginning, its weights by kind.
        self.number: dict[str, int] = {}
        self.begun: dict[str, int] = {"": 0}
        self.own, self.stems, self.kinds = np.zeros(0), np.zeros((0, len(STEMS)), np.int64), np.zeros((1, KINDS))

    def _meet(self, new: dict[str, int]) -> None:
        """Takes in new words, given with their hashes."""
        import xxhash

        number, begun, before = self.number, self.begun, len(self.begun)
        first = len(number)
        number.update(zip(new, range(first, first + len(new)), strict=True))
        stems = [[begun.setdefault(w[:n], len(begun)) if len(w) > n else 0 for w in new] for n in STEMS]
        weight = self.linear.words
        self.own = np.concatenate([self.own, weight[_columns(np.fromiter(new.values(), np.uint64, len(new)))]])
        self.stems = np.concatenate([self.stems, np.array(stems, np.int64).T])
        met = [*islice(begun, before, None)]
        h = np.fromiter((xxhash.xxh3_64_intdigest((s + "\0").encode()) & ~3 for s in met), np.uint64, len(met))
        kinds = weight[_columns(h[:, None] | np.arange(KINDS, dtype=np.uint64))]
        self.kinds = np.concatenate([self.kinds, kinds])

    def scores(self, texts: list[str]) -> np.ndarray:
        if len(self.number) > self.votes.hasher.bound:
            self._forget()
        patterns, each, new = [], [], {}
        for t in texts:
            words = _words(t)
            patterns.append(self.votes.pattern(t, self.votes.told(words)))
            each.append(words)
            for w in words.difference(self.number):
                new[w] = self.votes.met[w]
        self._meet(new)
        n, sizes = len(texts), [*map(len, each)]
        ids = np.fromiter(map(self.number.__getitem__, chain.from_iterable(each)), np.int64, sum(sizes))
        row = np.repeat(np.arange(n), sizes)
        pairs = np.concatenate([(row << 32 | s)[s > 0] for s in self.stems[ids].T])
        pairs, times = np.unique(pairs, return_counts=True)
        begin, of = pairs & 0xFFFFFFFF, pairs >> 32
        total, held = np.bincount(row, self.own[ids], n), np.bincount(row, minlength=n)
        for kind in range(1, KINDS):
            has = times >= kind
            total = total + np.bincount(of[has], self.kinds[begin[has], kind], n)
            held = held + np.bincount(of[has], minlength=n)
        z = self.linear.bias + _bits(np.array(patterns, np.int64)) @ self.linear.votes + total / np.sqrt(np.maximum(held, 1))
        return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def fit(docs: DataFrame, labels: DataFrame, doc: str = "doc_id", text: str = "text", label: str = "toxic", fitted: int = FITTED) -> tuple[Votes, LabelModel, Linear]:
    labelled = labelled_rows(docs, labels, doc, text, label)
    lexicon, prior = learned_lexicon(labelled)
    votes = Votes(lexicon)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counted: dict[int, int] = {}
        for b in batches:
            for t in texts_of(b, text):
                p = votes.pattern(t.decode())
                counted[p] = counted.get(p, 0) + 1
        yield pa.RecordBatch.from_arrays([pa.array([*counted], pa.int64()), pa.array([*counted.values()], pa.int64())], names=["p", "n"])

    # at most 2 ** VOTERS patterns, of all rows
    rows = map_batches(docs.select(text), run, "p long, n long").groupBy("p").agg(F.sum("n").alias("n")).collect()
    model = LabelModel(np.array([r.p for r in rows] or [0], np.int64), np.array([r.n for r in rows] or [1], np.int64), float(np.clip(prior, 0.01, 0.4)))
    # the whole texts are read again: some voters look at more than the features
    features, patterns = training_rows(labelled, fitted, votes)
    linear = Linear(features, patterns, model.posterior(patterns) if len(patterns) else np.zeros(0))
    del features
    give_back()
    return votes, model, linear


def scored(docs: DataFrame, labels: DataFrame, doc: str = "doc_id", text: str = "text", label: str = "toxic", fitted: int = FITTED) -> DataFrame:
    """The documents, and as the last column _score, or a like name that is free."""
    name = fresh(docs, "_score")
    votes, _, linear = fit(docs, labels, doc, text, label, fitted)
    sent = docs.sparkSession.sparkContext.broadcast((votes, linear))  # SPACE weights and a lexicon: fixed bounds

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = Scorer(*sent.value)
        for b in batches:
            score = scorer.scores([t.decode() for t in texts_of(b, text)])
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(score, pa.float64())], names=[*b.schema.names, name])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields)
    return map_batches(docs, run, f"{schema}, `{name}` double")


def drop_toxic(docs: DataFrame, labels: DataFrame, doc: str = "doc_id", text: str = "text") -> DataFrame:
    """The documents that score below 0.5; columns stay as they are."""
    found = scored(docs, labels, doc, text)
    return found.where(F.col(found.columns[-1]) < 0.5).select(*docs.columns)


def op8_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, held_out, score, predicted of every document."""
    docs = read(spark, sf_dir, "documents").select("doc_id", "text")
    return scored(docs, read(spark, sf_dir, "labels").select("doc_id", "toxic")).select("doc_id", is_held_out("doc_id").alias("held_out"), F.col("_score").alias("score"), (F.col("_score") >= 0.5).cast("int").alias("predicted"))


QUERIES = {"op8_toxicity": op8_toxicity}
SQL: dict[str, str] = {}
