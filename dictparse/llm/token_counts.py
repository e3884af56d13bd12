"""Token counts under a unigram model, by dynamic programming over a trie of distinct pre-tokens.

A text is split into pre-tokens. The distinct pre-tokens of some megabytes of text are put in a trie; walking it depth first, the
best forward score of each node (a prefix) is computed once from its ancestors' and shared by all pre-tokens below it; terminal
nodes keep the token count of the best segmentation, and a document sums the counts of its pre-tokens.

The vocabulary is a public byte-level one. A token of rank r scores -round(1000 ln(r + 2)) (a rank-frequency law, in whole
numbers, so ties are exact); the best segmentation has the largest sum, then the fewest tokens. Nothing is trained.

Edge cases: null and empty texts have no tokens; repeated rows are counted each; an empty table gives an empty result; further
columns are not read.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dictparse.llm.common import map_batches, read, texts_of

VOCABULARY = "byte_bpe_50k"
#: Distinct pre-tokens kept in a worker; beyond it the counts are dropped and computed again when needed.
KEPT = 400_000


def scores(vocabulary: str = VOCABULARY) -> dict[bytes, int]:
    import base64

    import public_tokenizers

    with open(public_tokenizers.path(f"{vocabulary}.tiktoken"), "rb") as f:
        return {base64.b64decode(word): -round(1000 * math.log(int(rank) + 2)) for word, rank in map(bytes.split, f)}


class Trie:
    """Forward scores along the distinct words in byte order: a node is a prefix, and the open path holds its ancestors' results."""

    def __init__(self, vocabulary: dict[bytes, int]):
        self.score = vocabulary
        self.longest = max(map(len, vocabulary), default=1)
        self.nodes = 0

    def counts(self, words: list[bytes]) -> dict[bytes, int]:
        """The token count of each word. Sorted words are the trie's paths: what two neighbours share is kept."""
        score, longest = self.score.get, self.longest
        best, used = [0], [0]  # of each prefix on the open path
        out: dict[bytes, int] = {}
        before = b""
        for w in sorted(set(words)):
            shared, most = 0, min(len(w), len(before))
            while shared < most and w[shared] == before[shared]:
                shared += 1
            del best[shared + 1 :], used[shared + 1 :]
            for end in range(shared + 1, len(w) + 1):
                top, fewest = None, 0
                for start in range(max(0, end - longest), end):
                    s = score(w[start:end])
                    if s is not None:
                        s += best[start]
                        n = used[start] + 1
                        if top is None or s > top or s == top and n < fewest:
                            top, fewest = s, n
                best.append(top)
                used.append(fewest)
                self.nodes += 1
            out[w] = used[-1]
            before = w
        return out


def count_tokens(docs: DataFrame, doc: str = "doc_id", text: str = "text", vocabulary: str = VOCABULARY) -> DataFrame:
    """doc, n_pretokens and n_tokens of every row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import public_tokenizers
        import regex

        split = regex.compile(public_tokenizers.PATTERN).findall
        trie = Trie(scores(vocabulary))
        known: dict[str, int] = {}
        for batch in batches:
            each = [Counter(split(t.decode())) for t in texts_of(batch, text)]
            fresh = {w for c in each for w in c if w not in known}
            if len(known) + len(fresh) > KEPT:
                known, fresh = {}, {w for c in each for w in c}
            by_bytes = {w.encode(): w for w in fresh}
            known |= {by_bytes[b]: n for b, n in trie.counts([*by_bytes]).items()}
            tokens = [sum(known[w] * n for w, n in c.items()) for c in each]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([sum(c.values()) for c in each], pa.int64()), pa.array(tokens, pa.int64())], names=["_doc", "n_pretokens", "n_tokens"])

    return map_batches(docs.select(F.col(doc).cast("long").alias("_doc"), F.col(text).alias(text)), run, "_doc long, n_pretokens long, n_tokens long").withColumnRenamed("_doc", doc)


def op3_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return count_tokens(read(spark, sf_dir, "documents"))


QUERIES = {"op3_token_counts": op3_token_counts}
SQL: dict[str, str] = {}
