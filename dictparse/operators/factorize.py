"""Parsing the texts of a DataFrame.

The plan is: project ids and text (so only they are read), group equal texts, split long ones into blocks, deal rows out evenly, and
one Arrow stage with the kernel. Each text is parsed by itself; Spark's part is the parallelism over texts and all that is done with
the factors.
"""

from __future__ import annotations

import hashlib
import resource
import time
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from dictparse.kernels import jvm, quick
from dictparse.kernels.parse import PAIRS, Factor, Parse, count_pairs, count_seeded, count_step
from dictparse.kernels.tokens import decode
from dictparse.plans.spec import FACTOR, SUMMARY, ParseSpec, columns, named

_ARROW = {"int": pa.int32(), "long": pa.int64(), "string": pa.string(), "double": pa.float64()}
#: Factor rows, and symbols of decoded texts, of one output batch.
_FLUSH, _FLUSH_SYMBOLS = 65_536, 1 << 22


def seen(text: str | None, symbols: str) -> str:
    """The text as the kernel sees it: code points, or one character for each byte of its UTF-8."""
    text = text or ""
    return text if symbols == "codepoint" else text.encode().decode("latin-1")


def factor_row(x: int, f: Factor) -> tuple:
    at, length, kind, ref1, sym1, ref2, sym2, power = f
    return (x, at + 1, at + length, length, kind, ref1, sym1, ref2, sym2, power)


def parse(text: str, spec: ParseSpec) -> Parse:
    return Parse(text, spec.scheme, spec.lookahead, **spec.options)


def _plain(spec: ParseSpec) -> bool:
    """Whether a parse has no option that kernels.quick doesn't."""
    return (spec.children, spec.lce, spec.fused, spec.symbol_runs, spec.stop_above) == ("hash", "direct", True, True, None) and quick.knows(spec.scheme, spec.lookahead)


def factors(text: str, spec: ParseSpec) -> tuple[list[Factor], list[Factor] | None]:
    """Phrases, and entries where these are others."""
    if _plain(spec):
        return quick.parsed(text, spec.scheme, spec.lookahead)
    p = parse(text, spec)
    return p.phrases, p.entries


def summary_row(text: str, spec: ParseSpec) -> tuple:
    began = time.perf_counter()
    if spec.lookahead == "none" and spec.scheme != "step_run" and (spec.children, spec.lce, spec.fused, spec.stop_above, spec.counters) == ("hash", "direct", True, None, False):
        # counting needs no tokens
        sigma = len(set(text))
        if spec.scheme in PAIRS:
            *kinds, nodes, split = count_pairs(text, spec.scheme)
            z = sum(kinds)
        else:  # a node for each entry, one lookup for each symbol
            z, kinds, split = count_step(text) if spec.scheme == "step" else count_seeded(text), [0, 0, 0], 0
            nodes = 1 + (z if spec.scheme == "step" else max(z - 1, 0) + sigma)
        took = (time.perf_counter() - began) * 1000
        return (len(text), sigma, z, *kinds, nodes, split, None, None, took, resource.getrusage(resource.RUSAGE_SELF).ru_maxrss / 1024)
    if spec.lookahead != "none" and not spec.counters and _plain(spec):
        counts = quick.count_ahead(text, spec.scheme, spec.lookahead)
        took = (time.perf_counter() - began) * 1000
        return (len(text), len(set(text)), *counts, None, None, took, resource.getrusage(resource.RUSAGE_SELF).ru_maxrss / 1024)
    p = parse(text, spec)
    took = (time.perf_counter() - began) * 1000
    kinds = [f[2] for f in p.phrases]
    trie = p.rules.trie
    counts = [kinds.count(k) for k in ("combine", "cut", "repeat")]
    return (len(text), len(set(text)), None if p.given_up else len(kinds), *counts, trie.nodes, trie.split_nodes, trie.lookups, trie.compared, took, resource.getrusage(resource.RUSAGE_SELF).ru_maxrss / 1024)


def _batch(rows: list[tuple], names: list[str], kinds: list[pa.DataType]) -> pa.RecordBatch:
    data = [*zip(*rows, strict=True)] or [()] * len(names)
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(data, kinds, strict=True)], names=names)


def dealt(df: DataFrame, tasks: int | None = None) -> DataFrame:
    """Rows dealt evenly to enough tasks; one file with one row group would otherwise keep one core busy."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    have = df.rdd.getNumPartitions()
    want = tasks or max(have, 2 * cores)
    return df.repartition(want) if have < want else df


def blocks_of(df: DataFrame, text: str, block_symbols: int | None) -> DataFrame:
    """Adds block_id and cuts texts into blocks of so many symbols; without a size each text is its block 0."""
    if not block_symbols:
        return df.withColumn("block_id", F.lit(0))
    last = F.greatest(F.floor((F.length(text) - 1) / block_symbols), F.lit(0)).cast("int")
    cut = df.withColumn("block_id", F.explode(F.sequence(F.lit(0), last)))
    return cut.withColumn(text, F.substring(text, F.col("block_id") * block_symbols + 1, F.lit(block_symbols)))


def _kernel(texts: DataFrame, keys: list[str], specs: list[ParseSpec], what: str, keep_text: bool) -> DataFrame:
    """The Arrow stage over (keys..., block_id, _text): factor rows, entry rows with them, one summary row for each parse, or the text back from its factors."""
    shape = SUMMARY if what == "summary" else [("text", "string")] if what == "decoded" else FACTOR + [("role", "string")] * (what == "roles") + [("piece", "string")] * keep_text
    names = [*keys, "block_id", "scheme", *(n for n, _ in shape)]
    key_fields = [f"`{k}` {texts.schema[k].dataType.simpleString()}" for k in keys]
    schema = ", ".join([*key_fields, "block_id int", "scheme string", columns(shape)])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows: list[tuple] = []
        symbols = 0
        for batch in batches:
            kinds = [*(batch.schema.field(k).type for k in keys), pa.int32(), pa.string(), *(_ARROW[k] for _, k in shape)]
            for *key, block, text in zip(*(batch.column(c).to_pylist() for c in (*keys, "block_id", "_text")), strict=True):
                if text is None:
                    continue
                for spec in specs:
                    own = seen(text, spec.symbols)
                    if what == "summary":
                        rows.append((*key, block, spec.name, *summary_row(own, spec)))
                        continue
                    phrases, entries = factors(own, spec)
                    if what == "decoded":
                        if phrases:
                            back = decode(phrases, entries, spec.scheme)
                            rows.append((*key, block, spec.name, back if spec.symbols == "codepoint" else back.encode("latin-1").decode()))
                            symbols += len(back)
                        if symbols >= _FLUSH_SYMBOLS:
                            yield _batch(rows, names, kinds)
                            rows, symbols = [], 0
                        continue
                    listed = [("phrase", phrases)] + ([("entry", entries)] if what == "roles" and entries is not None else [])
                    for role, found in listed:
                        for x, f in enumerate(found, 1):
                            rows.append((*key, block, spec.name, *factor_row(x, f), *((role,) if what == "roles" else ()), *((own[f[0] : f[0] + f[1]],) if keep_text else ())))
                    if len(rows) >= _FLUSH:
                        yield _batch(rows, names, kinds)
                        rows = []
            if rows:
                yield _batch(rows, names, kinds)
                rows, symbols = [], 0

    return texts.mapInArrow(run, schema)


def _dealt_once(keyed: DataFrame, block_symbols: int | None) -> DataFrame:
    """Each distinct text (or its blocks) once, by _hash."""
    distinct = keyed.groupBy("_hash").agg(F.first("_text").alias("_text"))
    # the group-by combines copies before its shuffle; its few merged partitions are then dealt out for the kernel
    session = keyed.sparkSession
    tasks = max(2 * session.sparkContext.defaultParallelism, int(session.conf.get("spark.sql.shuffle.partitions")))
    return blocks_of(distinct, "_text", block_symbols).repartition(tasks)


def parse_many(df: DataFrame, text_col: str, id_cols: list[str], specs: list[ParseSpec | str], *, what: str = "factors", keep_text: bool = False, block_symbols: int | None = None, reuse_equal_texts: bool = False, where: str | None = None) -> DataFrame:
    """Several parses of each text in one scan: factor rows ('factors', with entries: 'roles') or one row for each parse ('summary').

    `where` is applied below the Python stage, where it reaches the scan. With reuse_equal_texts each distinct text is parsed once.
    Null texts give no rows; empty ones no factors and a summary with z = 0.
    """
    specs = [named(s) if isinstance(s, str) else s for s in specs]
    if where:
        df = df.where(where)
    narrow = df.select(*id_cols, F.col(text_col).alias("_text")).where(F.col("_text").isNotNull())
    if not reuse_equal_texts:
        return _kernel(dealt(blocks_of(narrow, "_text", block_symbols)), id_cols, specs, what, keep_text)
    keyed = narrow.withColumn("_hash", F.sha2("_text", 256))
    once = _kernel(_dealt_once(keyed, block_symbols), ["_hash"], specs, what, keep_text)
    return keyed.select(*id_cols, "_hash").join(once, "_hash").drop("_hash")


def factorize(df: DataFrame, text_col: str, id_cols: list[str], *, scheme: str, lookahead: str = "none", symbols: str = "codepoint", lce: str = "direct", children: str = "hash", fused: bool = True, symbol_runs: bool = True, block_symbols: int | None = None, keep_text: bool = False, reuse_equal_texts: bool = True, roles: bool = False, where: str | None = None, engine: str = "kernel") -> DataFrame:
    """The factor table of every text: ids, block_id, scheme, the columns of spec.FACTOR, and the piece if wanted."""
    if engine != "kernel":
        from dictparse.operators import engines

        return engines.factorize(df, text_col, id_cols, scheme=scheme, engine=engine)
    spec = ParseSpec(scheme, lookahead, symbols, lce, children, fused, symbol_runs)
    return parse_many(df, text_col, id_cols, [spec], what="roles" if roles else "factors", keep_text=keep_text, block_symbols=block_symbols, reuse_equal_texts=reuse_equal_texts, where=where)


def factor_counts(df: DataFrame, text_col: str, id_cols: list[str], *, schemes: list[str], block_symbols: int | None = None, reuse_equal_texts: bool = True, where: str | None = None, engine: str = "kernel", apart: bool = False, **options) -> DataFrame:
    """One summary row for each text (or block) and scheme; no factor rows leave the workers.

    The engine 'jvm' has the default options only, gives no peak memory, and takes whole texts without a Python stage. There, for few
    large texts, `apart` deals each text out once for each scheme; else a task takes all schemes of its texts.
    """
    specs = [named(s, **options) for s in schemes]
    if engine != "jvm":
        return parse_many(df, text_col, id_cols, specs, what="summary", block_symbols=block_symbols, reuse_equal_texts=reuse_equal_texts, where=where)
    if block_symbols or not all(_plain(s) and s.symbols == "codepoint" and not s.counters for s in specs):
        raise ValueError("the engine 'jvm' has no such option")
    texts = df.where(where) if where else df
    texts = texts.select(*id_cols, F.col(text_col).alias("_text")).where(F.col("_text").isNotNull())
    each = F.explode(F.array(*(F.struct(F.lit(s.name).alias("scheme"), F.lit(s.scheme).alias("_rule"), F.lit(s.lookahead).alias("_look")) for s in specs))).alias("_spec")
    if apart:
        texts = texts.select("*", each).repartition(8 * df.sparkSession.sparkContext.defaultParallelism)
    else:
        texts = dealt(texts).select("*", each)
    found = texts.select(*id_cols, "_spec.scheme", jvm.function(df.sparkSession, "Summary", F.col("_text"), F.col("_spec._rule"), F.col("_spec._look")).alias("_found")).select(*id_cols, "scheme", "_found.*")
    return _summaries(found, id_cols)


def _summaries(found: DataFrame, id_cols: list[str]) -> DataFrame:
    """What a compiled parse counted, in the columns of all summaries."""
    columns_ = [(F.col(n) if n in found.columns else F.lit(None)).cast(k).alias(n) for n, k in SUMMARY]
    return found.select(*id_cols, F.lit(0).alias("block_id"), "scheme", *columns_)


def joined_counts(sets: list[tuple[DataFrame, str]], schemes: list[str]) -> DataFrame:
    """Summary rows of few large texts, given by their pieces: sets of rows (name, place, piece) in order of place and piece, and a set's separator.

    No text is ever a row or an array of its pieces: these are sorted over all tasks and glued to parts of some MB, which are dealt out
    once, by texts; for each text and scheme a task puts them together to a byte a symbol and counts there. Where an executor's heap
    can't hold two texts with their dictionaries, one waits for the other.
    """
    specs = [named(s) for s in schemes]
    if not all(_plain(s) for s in specs):
        raise ValueError("the compiled parses have no such option")
    session = sets[0][0].sparkSession
    cores = session.sparkContext.defaultParallelism
    tasks = max(2 * cores, int(session.conf.get("spark.sql.shuffle.partitions")))
    parts = sizes = None
    for rows, separator in sets:
        ranged = rows.repartitionByRange(tasks, "name", "place").sortWithinPartitions("name", "place", "piece").select("name", "piece")
        some = jvm.mapped(ranged, "Parts", [separator], "name string, task int, part int, text string").withColumn("separator", F.lit(len(separator)))
        size = rows.groupBy("name").agg(F.sum(F.coalesce(F.octet_length("piece") + len(separator), F.lit(0))).alias("bytes"))
        parts, sizes = (some, size) if parts is None else (parts.unionByName(some), sizes.unionByName(size))
    slots = 8 * cores
    # a row for each text; more texts than slots share them
    place = sizes.withColumn("slot", ((F.row_number().over(Window.orderBy(F.desc("bytes"), "name")) - 1) % slots).cast("int"))
    place = place.select("name", "slot", F.sum("bytes").over(Window.partitionBy("slot")).alias("bytes"))
    dealt_out = parts.join(F.broadcast(place), "name").select("name", "task", "part", "text", "separator", "bytes", "slot").repartitionById(slots, F.col("slot"))
    out = None
    for spec in specs:
        one = jvm.mapped(dealt_out, "Counts", [spec.scheme, spec.lookahead], f"name string, {jvm.summary_columns()}").withColumn("scheme", F.lit(spec.name))
        out = one if out is None else out.unionByName(one)
    return _summaries(out, ["name"])


def _digests(texts: DataFrame, keys: list[str]) -> DataFrame:
    """ids, and each text's length and md5."""
    kinds = ", ".join(f"`{k}` {texts.schema[k].dataType.simpleString()}" for k in keys)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            own = b.column("text").to_pylist()
            sums = [hashlib.md5(t.encode(), usedforsecurity=False).hexdigest() for t in own]
            yield pa.RecordBatch.from_arrays([*(b.column(k) for k in keys), pa.array([*map(len, own)], pa.int64()), pa.array(sums, pa.string())], names=[*keys, "n", "md5"])

    return texts.mapInArrow(run, f"{kinds}, n long, md5 string")


def round_trip(df: DataFrame, text_col: str, id_cols: list[str], spec: ParseSpec | str) -> DataFrame:
    """ids, n and md5 of every text that has factors, as its factors give it back: parsed and decoded where it stands.

    Neither factors nor texts are shuffled, but for a table of too few partitions; a factor table is read back by operators.decode.
    """
    spec = named(spec) if isinstance(spec, str) else spec
    texts = dealt(df.select(*id_cols, F.col(text_col).alias("_text")).where(F.length("_text") > 0))
    if _plain(spec) and spec.symbols == "codepoint":
        back = texts.select(*id_cols, jvm.function(df.sparkSession, "Back", F.col("_text"), spec.scheme, spec.lookahead).alias("text"))
        return _digests(back, id_cols)
    back = _kernel(texts.withColumn("block_id", F.lit(0)), id_cols, [spec], "decoded", False)
    return back.select(*id_cols, F.length("text").cast("long").alias("n"), F.md5("text").alias("md5"))
