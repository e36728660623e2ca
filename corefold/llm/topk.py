"""Exact top-k search by histogram selection (operator 1).

Everything is scored. Tasks count scores in global histograms, finer each time and
only within the bin that holds a query's k-th value, until that value is known.
Then one pass keeps what reaches it, and ties go to the smaller id. Queries come in
blocks of a fixed number, so what is broadcast has a fixed size.

A task's counts below its own k-th bin cannot matter (the k-th value of all is no
less than that of one task), so each task sends at most k bins for each query.

Vectors that are null, empty, or hold a null or non-finite component take no part;
neither do null ids. A query is compared with the vectors of its own length. Repeated ids
are candidates once per row; a query has no candidate of its own id. Scores are exact for
any finite components (large ones are multiplied as whole numbers of any size); scores
beyond 2**61 are given, and tie, as 2**61. No query, or no candidate, gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from corefold.llm.common import written

RESULT = "query_id long, rank int, vec_id long, score long"
BINS = 512
#: Scores beyond this are given as this.
MOST = 1 << 61
#: Products of whole numbers are exact in float64 while sizes stay below this.
EXACT = 1 << 52


def integer_vectors(df: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding", scale: int = 256) -> DataFrame:
    """vec_id and v (floor(scale * component), whole numbers as doubles), of the vectors that take part."""
    usable = F.col(id_col).isNotNull() & F.col(vector_col).isNotNull() & F.forall(F.col(vector_col), lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))

    def whole(x: Column) -> Column:
        y = x.cast("double") * scale
        return F.when(F.abs(y) < float(1 << 53), F.floor(y).cast("double")).otherwise(y)  # larger doubles are whole

    return df.filter(F.coalesce(usable, F.lit(False))).select(F.col(id_col).cast("long").alias("vec_id"), F.transform(vector_col, whole).alias("v"))


def _matrix(column: pa.Array, dims: int) -> tuple[np.ndarray, np.ndarray]:
    """The rows of `dims` entries as a matrix, and which rows they are."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    sizes = np.diff(column.offsets.to_numpy())
    keep = np.flatnonzero(sizes == dims)
    flat = column.flatten().to_numpy()
    if len(keep) != len(sizes):
        flat = flat[np.repeat(sizes == dims, sizes)]
    return flat.reshape(-1, dims), keep


def _norms(matrix: np.ndarray) -> np.ndarray:
    """Length of each row; finite wherever the row is."""
    most = np.abs(matrix).max(axis=1, initial=1.0)
    return np.sqrt(((matrix / most[:, None]) ** 2).sum(axis=1)) * most


def exact_products(queries: np.ndarray, matrix: np.ndarray) -> np.ndarray:
    """queries @ matrix.T of whole numbers as int64, exact; beyond MOST it is MOST."""
    q, c = _norms(queries), _norms(matrix)
    with np.errstate(over="ignore", invalid="ignore"):
        scores = queries @ matrix.T
        rough = q[:, None] * c[None, :].max(initial=0.0) >= EXACT
        sure = np.where(np.isfinite(scores), scores, 0.0) if rough.any() else scores
        out = np.rint(np.clip(sure, -MOST, MOST)).astype(np.int64)
    # Large ones in whole numbers of any size.
    for i in np.flatnonzero(rough.ravel()).tolist():
        mine = list(map(int, queries[i].tolist()))
        for j in np.flatnonzero(q[i] * c >= EXACT).tolist():
            out[i, j] = max(-MOST, min(MOST, sum(a * b for a, b in zip(mine, map(int, matrix[j].tolist()), strict=True))))
    return out


def _scored(batches: Iterator[pa.RecordBatch], queries: np.ndarray, rows: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(ids, scores by query and candidate)."""
    for whole in batches:
        for at in range(0, whole.num_rows, rows):
            batch = whole.slice(at, rows)
            matrix, keep = _matrix(batch.column(1), queries.shape[1])
            if len(keep):
                yield batch.column(0).to_numpy()[keep], exact_products(queries, matrix)


def top_k(candidates: DataFrame, queries: DataFrame, k: int = 5, block: int = 4096) -> DataFrame:
    """Both: vec_id long, v array<double> of whole numbers. The k best candidates of each query by inner product."""
    spark = candidates.sparkSession
    largest: dict[int, float | None] = {}  # by vector length
    done = []
    for ids, vectors in _blocks(queries, block):
        dims = vectors.shape[1]
        if dims not in largest:
            largest[dims] = candidates.filter(F.size("v") == dims).agg(F.max(F.array_max(F.transform("v", F.abs))).alias("m")).first().m
        if largest[dims] is not None:
            # written, so that the plan does not grow with the number of blocks and a finished block stays finished
            done.append(written(_one_block(candidates, ids, vectors, k, largest[dims]))._written_at)
    return spark.read.schema(RESULT).parquet(*done) if done else spark.createDataFrame([], RESULT)


def _blocks(queries: DataFrame, block: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Queries of one length, a fixed number at a time; the driver holds one block."""
    held: dict[int, list] = {}
    for row in queries.select("vec_id", "v").orderBy("vec_id").toLocalIterator():
        group = held.setdefault(len(row.v), [])
        group.append(row)
        if len(group) == block:
            yield np.array([r.vec_id for r in group]), np.array([r.v for r in group], dtype=np.float64)
            group.clear()
    for size, group in held.items():
        if group and size:
            yield np.array([r.vec_id for r in group]), np.array([r.v for r in group], dtype=np.float64)


def _one_block(candidates: DataFrame, ids: np.ndarray, vectors: np.ndarray, k: int, most: float) -> DataFrame:
    """The rows of one block of queries; `most`: the largest size of a candidate's component."""
    spark = candidates.sparkSession
    n = len(ids)
    # no score is larger than the query's sum of sizes times the largest component
    with np.errstate(over="ignore"):
        reach = np.minimum(np.abs(vectors).sum(axis=1) * most * 1.001 + 1, float(MOST - 1024)).astype(np.int64) + 1024
    low, high = -reach, reach.copy()  # the k-th value is within low..high, or there are fewer than k candidates
    above = np.zeros(n, dtype=np.int64)  # candidates beyond high
    shared = spark.sparkContext.broadcast((ids, vectors))
    rows = max(64, (2 << 20) // n)
    width = int(high.max() - low.min()) + 1
    while width > 1:
        step = -(-(high - low + 1) // BINS)  # bin width of each query
        bounds = (low.copy(), high.copy(), step)

        def count(batches: Iterator[pa.RecordBatch], bounds=bounds) -> Iterator[pa.RecordBatch]:
            own, queries = shared.value
            lo, hi, each = (b[:, None] for b in bounds)
            total = np.zeros(n * BINS, dtype=np.int64)
            base = np.arange(n)[:, None] * BINS
            for found, scores in _scored(batches, queries, rows):
                ok = (scores >= lo) & (scores <= hi) & (own[:, None] != found[None, :])
                at = base + (scores - lo) // each
                total += np.bincount(at[ok], minlength=n * BINS)
            total = total.reshape(n, BINS)
            from_top = np.cumsum(total[:, ::-1], axis=1)[:, ::-1]
            q, b = np.nonzero((total > 0) & (from_top - total < k))
            yield pa.RecordBatch.from_arrays([pa.array(q.astype(np.int32)), pa.array(b.astype(np.int32)), pa.array(total[q, b])], names=["q", "b", "n"])

        # a fixed bound: k bins for each query of the block
        counts = candidates.select("vec_id", "v").mapInArrow(count, "q int, b int, n long").groupBy("q", "b").agg(F.sum("n").alias("n")).collect()
        found = np.zeros((n, BINS), dtype=np.int64)
        for r in counts:
            found[r.q, r.b] = r.n
        beyond = above[:, None] + np.cumsum(found[:, ::-1], axis=1)[:, ::-1]  # this bin and higher ones
        hit = beyond >= k
        some = hit.any(axis=1)
        b = np.where(some, BINS - 1 - np.argmax(hit[:, ::-1], axis=1), 0)
        above = np.where(some, beyond[np.arange(n), b] - found[np.arange(n), b], above)
        new_low = np.where(some, low + b * step, -reach)
        high = np.where(some, np.minimum(high, low + (b + 1) * step - 1), -reach)
        low = new_low
        width = int((high - low).max()) + 1

    kth = low  # exact, or below every score

    def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, queries = shared.value
        for found, scores in _scored(batches, queries, rows):
            q, c = np.nonzero((scores >= kth[:, None]) & (own[:, None] != found[None, :]))
            # of equal scores at most k can win in this batch
            order = np.lexsort((found[c], -scores[q, c], q))
            q, c = q[order], c[order]
            begin = np.searchsorted(q, q, side="left")
            best = np.arange(len(q)) - begin < k
            q, c = q[best], c[best]
            yield pa.RecordBatch.from_arrays([pa.array(own[q]), pa.array(found[c]), pa.array(scores[q, c])], names=["query_id", "vec_id", "score"])

    kept = candidates.select("vec_id", "v").mapInArrow(keep, "query_id long, vec_id long, score long")
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return kept.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k).select("query_id", F.col("rank").cast("int"), "vec_id", "score")


def search(df: DataFrame, every: int, k: int = 5, scale: int = 256, block: int = 4096) -> DataFrame:
    """Queries: the rows whose vec_id is divisible by `every`; candidates: every other row."""
    vectors = written(integer_vectors(df, scale=scale))
    return top_k(vectors, vectors.filter(F.col("vec_id") % every == 0), k, block)
