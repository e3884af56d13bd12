"""Exact top-k inner products by a Voronoi join.

Vectors are turned to whole numbers. Pivots, as many as the data ask for, cut both sides into cells: each row goes to its nearest pivot,
and each cell is summed up by its size and its radius. Queries of a cell form blocks. For a block with pivot p and radius r, every row x
scores at least p.x - r|x| and at most p.x + r|x| with any query of the block; the k+1 best lower bounds over all rows give the block's
bar. A cell whose pivot c and radius s say that no row of it can reach the bar (p.c + r|c| + s|p| + rs) is left out for that block as a
whole, without looking at its rows; of the other cells the rows whose own upper bound reaches the bar are sent to the block, dealt to as
many tasks as their number needs, and the block's queries go to just these. Each task solves its part exactly; the parts' best k meet
in a ranking by query.

Edge cases: rows without id, without vector, or with a null or non-finite component take no part; a shorter vector counts as one that
ends in zeros; rows that share an id are rows of their own, queries each, and candidates of each other; equal scores go to the smaller
id; an empty table gives an empty result; further columns, whatever their names, are not read. Scores are 64-bit: components up to
2 ** 31 / sqrt(length) in whole numbers are safe.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from dictparse.llm.common import lean, read, written

SCALE = 256.0
#: Queries of one block, rows that one task solves against it, rows for each pivot, and most pivots (a bound of what the driver holds).
BLOCK, PART, CELL, PIVOTS = 512, 20_000, 4096, 1024
#: Numbers of a matrix that a worker holds at once.
_HELD = 1 << 22


def _matrix(values: list[bytes], dim: int) -> np.ndarray:
    return np.frombuffer(b"".join(values), "<i8").reshape(len(values), dim)


def quantized(rows: DataFrame, id_col: str, vector: str) -> tuple[DataFrame, int]:
    """(row, id, v): a number of each usable row, its id, its whole-number components as bytes; and how many components."""
    usable = rows.select(F.col(id_col).cast("long").alias("id"), F.col(vector).cast("array<double>").alias("e")).where("id IS NOT NULL AND e IS NOT NULL AND forall(e, x -> x IS NOT NULL AND NOT isnan(x) AND abs(x) < double('infinity'))")
    dim = usable.agg(F.max(F.size("e"))).first()[0] or 0
    whole = F.transform(F.concat("e", F.array_repeat(F.lit(0.0), F.lit(dim) - F.size("e"))), lambda x: F.floor(x * SCALE).cast("long"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            flat = b.column("e").flatten().to_numpy(zero_copy_only=False).astype("<i8").tobytes()
            w = 8 * dim
            v = [flat[k * w : k * w + w] for k in range(b.num_rows)]
            yield pa.RecordBatch.from_arrays([b.column("row"), b.column("id"), pa.array(v, pa.binary())], names=["row", "id", "v"])

    return usable.select(F.monotonically_increasing_id().alias("row"), "id", whole.alias("e")).mapInArrow(run, "row long, id long, v binary"), dim


def _slices(b: pa.RecordBatch, width: int) -> Iterator[pa.RecordBatch]:
    step = max(1, _HELD // max(width, 1))
    for at in range(0, b.num_rows, step):
        yield b.slice(at, step)


def top_k(rows: DataFrame, is_query: str, k: int = 5, id_col: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """query_id, rank, id and score of each query's k best rows; is_query is SQL over `id`."""
    spark = rows.sparkSession
    data, dim = quantized(rows, id_col, vector)
    data = written(data, "vectors")  # row numbers are fixed as they are written
    n, n_queries = data.count(), data.where(is_query).count()
    if not n_queries or n < 2:
        return spark.createDataFrame([], "query_id long, rank int, id long, score long")
    wanted = min(PIVOTS, 1 + n // CELL)
    pivots = _matrix([bytes(r.v) for r in data.orderBy(F.xxhash64("row"), "row").limit(wanted).select("v").collect()], dim).astype(np.float64)
    norms = np.sqrt((pivots * pivots).sum(1))

    def cell(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in _slices(whole, len(pivots) + dim):
                x = _matrix(b.column("v").to_pylist(), dim).astype(np.float64)
                at = (norms * norms - 2 * x @ pivots.T).argmin(1)
                far = np.sqrt(((x - pivots[at]) ** 2).sum(1))
                yield pa.RecordBatch.from_arrays([*b.columns, pa.array(at, pa.int32()), pa.array(far, pa.float64())], names=["row", "id", "v", "cell", "far"])

    data = written(data.mapInArrow(lean(cell), "row long, id long, v binary, cell int, far double"), "cells")
    queries = data.where(is_query)
    # one small row for each pivot, as summary of its rows and of its queries
    summary = data.groupBy("cell").agg(F.max("far").alias("far"), F.max(F.when(F.expr(is_query), F.col("far"))).alias("asked"), F.count(F.when(F.expr(is_query), 1)).alias("queries")).collect()
    reach = np.full(len(pivots), -np.inf)
    for r in summary:
        reach[r.cell] = r.far
    asked = [r for r in summary if r.queries]
    # queries of one cell share its pivot and radius, and so its bar; a cell with many queries only makes more blocks
    of_cell = np.array([r.cell for r in asked])
    radius = np.array([r.asked for r in asked]) * (1 + 1e-9) + 1e-6
    blocks = np.array([-(-r.queries // BLOCK) for r in asked])
    pivot = pivots[of_cell]

    def bounds(b: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
        x = _matrix(b.column("v").to_pylist(), dim).astype(np.float64)
        middle = x @ pivot.T
        spread = np.sqrt((x * x).sum(1))[:, None] * radius * (1 + 1e-9) + 1e-6 * (1 + np.abs(middle))
        return middle - spread, middle + spread

    def lower(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best = np.full((0, len(asked)), -np.inf)
        for whole in batches:
            for b in _slices(whole, len(asked) + dim):
                best = np.sort(np.concatenate([best, bounds(b)[0]]), 0)[-(k + 1) :]
        group, low = np.meshgrid(np.arange(len(asked)), np.arange(len(best)))
        yield pa.RecordBatch.from_arrays([pa.array(group.ravel(), pa.int32()), pa.array(best[low.ravel(), group.ravel()], pa.float64())], names=["b", "low"])

    lows = data.mapInArrow(lean(lower), "b int, low double").withColumn("n", F.row_number().over(Window.partitionBy("b").orderBy(F.desc("low")))).where(F.col("n") <= k + 1)
    bar = np.full(len(asked), -np.inf)
    for r in lows.groupBy("b").agg(F.min("low").alias("bar"), F.count("*").alias("n")).collect():
        if r.n == k + 1:
            bar[r.b] = r.bar
    # cells that a block's bar doesn't rule out as a whole
    middle = pivot @ pivots.T
    most = middle + radius[:, None] * norms + norms[of_cell][:, None] * reach + radius[:, None] * reach
    allowed = (most * (1 + np.sign(most) * 1e-9) + 1e-6 >= bar[:, None]) & np.isfinite(reach)

    def needed(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
        """Rows, and the pairs of a row and a query cell that its block needs."""
        for whole in batches:
            for b in _slices(whole, len(asked) + dim):
                yield b, *np.nonzero((bounds(b)[1] >= bar) & allowed[:, b.column("cell").to_numpy()].T)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(len(asked), np.int64)
        for _, _, to in needed(batches):
            total += np.bincount(to, minlength=len(asked))
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(asked)), pa.int32()), pa.array(total)], names=["b", "n"])

    parts = np.ones(len(asked), np.int64)
    for r in data.mapInArrow(lean(count), "b int, n long").groupBy("b").agg(F.sum("n").alias("n")).collect():
        parts[r.b] = max(1, -(-r.n // PART))

    def sent(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b, row, to in needed(batches):
            part = b.column("row").to_numpy()[row] * 0x9E3779B1 % parts[to]
            # a cell with several blocks of queries gets its rows once for each
            times = blocks[to]
            row, to, part = np.repeat(row, times), np.repeat(to, times), np.repeat(part, times)
            block = np.arange(len(row)) - np.repeat(np.cumsum(times) - times, times)
            for at in range(0, len(row), 20_000):
                cut = slice(at, at + 20_000)
                columns = [pa.array(to[cut], pa.int32()), pa.array(block[cut], pa.int64()), pa.array(part[cut], pa.int64()), *(b.column(c).take(pa.array(row[cut])) for c in ("row", "id", "v"))]
                yield pa.RecordBatch.from_arrays(columns, names=["b", "block", "part", "row", "id", "v"])

    near = data.mapInArrow(lean(sent), "b int, block long, part long, row long, id long, v binary")
    # at most PIVOTS rows
    places = spark.createDataFrame([(int(c), k, int(m), int(p)) for k, (c, m, p) in enumerate(zip(of_cell, blocks, parts, strict=True))], "cell int, b int, blocks long, parts long")
    asks = queries.join(F.broadcast(places), "cell").select("b", F.pmod(F.xxhash64("row"), F.col("blocks")).alias("block"), F.explode(F.sequence(F.lit(0).cast("long"), F.col("parts") - 1)).alias("part"), F.col("row").alias("query_row"), F.col("id").alias("query_id"), F.col("v").alias("q"))

    def solve(queries: pa.Table, rows: pa.Table) -> pa.Table:
        got: list[tuple[int, int, int, int, int]] = []
        if queries.num_rows and rows.num_rows:
            q, x = _matrix(queries["q"].to_pylist(), dim), _matrix(rows["v"].to_pylist(), dim)
            q_row, q_id, row, ids = queries["query_row"].to_numpy(), queries["query_id"].to_numpy(), rows["row"].to_numpy(), rows["id"].to_numpy()
            by = np.lexsort((row, ids))
            row, ids, x = row[by], ids[by], x[by]
            exact = float(np.abs(q).max(initial=0)) * float(np.abs(x).max(initial=0)) * dim < 2.0**53
            score = (q.astype(np.float64) @ x.T.astype(np.float64)).astype(np.int64) if exact else q @ x.T
            for i in range(len(q)):
                s = score[i]
                least = np.partition(s, len(s) - k - 1)[len(s) - k - 1] if len(s) > k + 1 else s.min()
                some = np.flatnonzero((s >= least) & (row != q_row[i]))
                some = some[np.argsort(-s[some], kind="stable")[:k]]
                got += [(q_row[i], q_id[i], r, a, b) for r, a, b in zip(row[some].tolist(), ids[some].tolist(), s[some].tolist(), strict=True)]
        columns = [*zip(*got, strict=True)] or [[]] * 5
        return pa.table([pa.array(c, pa.int64()) for c in columns], names=["query_row", "query_id", "row", "id", "score"])

    found = asks.groupBy("b", "block", "part").cogroup(near.groupBy("b", "block", "part")).applyInArrow(solve, "query_row long, query_id long, row long, id long, score long")
    order = Window.partitionBy("query_row").orderBy(F.desc("score"), "id", "row")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "id", "score")


def op7_voronoi_knn(spark: SparkSession, sf_dir: str) -> DataFrame:
    """query_id, rank, vec_id, score: the five best rows for every row whose vec_id is divisible by 50."""
    return top_k(read(spark, sf_dir, "embeddings"), "id % 50 = 0").withColumnRenamed("id", "vec_id")


QUERIES = {"op7_voronoi_knn": op7_voronoi_knn}
SQL = {
    "op7_voronoi_knn": """WITH whole AS (
  SELECT row_number() OVER () AS r, vec_id, list_transform(embedding, lambda x: CAST(floor(256 * CAST(x AS DOUBLE)) AS BIGINT)) AS v FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
scored AS (
  SELECT q.r AS query_row, q.vec_id AS query_id, x.r, x.vec_id, CAST(coalesce(list_sum(list_transform(list_zip(q.v, x.v), lambda z: z[1] * z[2])), 0) AS BIGINT) AS score
  FROM whole q JOIN whole x ON q.vec_id % 50 = 0 AND x.r <> q.r)
SELECT query_id, rank, vec_id, score FROM (SELECT *, CAST(row_number() OVER (PARTITION BY query_row ORDER BY score DESC, vec_id, r) AS INTEGER) AS rank FROM scored)
WHERE rank <= 5"""
}
