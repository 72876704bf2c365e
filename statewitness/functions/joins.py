"""Joins that Spark has no operator for, composed of those it has."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Most query vectors that are broadcast at once (64 floats each: some ten MB).
QUERY_BLOCK = 20_000
#: Queries and vectors that one matrix product takes (their product is some ten MB).
QUERY_CHUNK, VECTOR_CHUNK = 1_000, 4_000
#: More than single-precision products of 64 unit parts can be off.
SLACK = 1e-4


def as_of(left: DataFrame, right: DataFrame, by: list[str], left_ts: str, right_ts: str, value: str, direction: str = "backward") -> DataFrame:
    """Each left row with the nearest right row of its group at or before it (or after it).

    One union and one window sort by group and time; no pairs are made. Ties take the largest right
    value (backward) or the smallest (forward). Columns of the result: those of ``left`` and ``value``.
    """
    l = left.select("*", F.col(left_ts).alias("_t"), F.lit(None).cast(right.schema[value].dataType).alias("_v"), F.lit(1).alias("_side"))
    r = right.select(*by, F.col(right_ts).alias("_t"), F.col(value).alias("_v"), F.lit(0).alias("_side"))
    rows = l.unionByName(r, allowMissingColumns=True)
    if direction == "backward":
        w = Window.partitionBy(*by).orderBy("_t", "_side", "_v").rowsBetween(Window.unboundedPreceding, Window.currentRow)
        found = F.last("_v", ignorenulls=True).over(w)
    else:
        w = Window.partitionBy(*by).orderBy("_t", F.col("_side").desc(), "_v").rowsBetween(Window.currentRow, Window.unboundedFollowing)
        found = F.first("_v", ignorenulls=True).over(w)
    return rows.withColumn(value, found).filter("_side = 1").drop("_t", "_v", "_side")


def range_join(points: DataFrame, point: str, ranges: DataFrame, low: str, high: str, width: float) -> DataFrame:
    """Points in [low, high) of ranges, as an equi join on buckets of ``width`` (each range lists its buckets)."""
    bucket = lambda c: F.floor(c / width)
    wide = ranges.withColumn("_b", F.explode(F.sequence(bucket(F.col(low)), bucket(F.col(high)))))
    rows = points.withColumn("_b", bucket(F.col(point))).join(wide, "_b")
    return rows.filter((F.col(point) >= F.col(low)) & (F.col(point) < F.col(high))).drop("_b")


def salted_join(big: DataFrame, small: DataFrame, on: str, salts: int = 8, salt_from: Column | None = None) -> DataFrame:
    """Equi join whose hot keys are spread over ``salts`` tasks; the smaller side is repeated for each salt."""
    salt = F.pmod(F.xxhash64(*big.columns) if salt_from is None else F.xxhash64(salt_from), F.lit(salts))
    copies = small.withColumn("_s", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long"))))
    return big.withColumn("_s", salt).join(copies, [on, "_s"]).drop("_s")


def nearest_vectors(queries: DataFrame, vectors: DataFrame, k: int) -> DataFrame:
    """The k most alike vectors (cosine) of each query: (query, vec_id, cosine, rank).

    Equal queries are searched once, for k + 1 vectors (one may be the query itself); of equal vectors only the k + 1
    smallest ids can be among them. Queries are counted and broadcast in blocks of at most ``QUERY_BLOCK``, each with a scan of the
    vectors of its own; each task keeps its own best before ranks are given. Tables with missing, ragged or zero
    vectors, whose cosines are no numbers, are compared pair by pair.
    """
    n, odd = F.size("embedding"), F.exists("embedding", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) > 1e15))
    no_number = F.col("vec_id").isNull() | F.col("embedding").isNull() | odd | ~F.exists("embedding", lambda x: F.abs(x) > 1e-15)
    seen = vectors.select("vec_id", "embedding").union(queries.select("vec_id", "embedding")).agg(F.count_if(no_number).alias("odd"), F.min(n).alias("lo"), F.max(n).alias("hi")).first()
    blocks = lambda df: -(-df.count() // QUERY_BLOCK)
    final = Window.partitionBy("query").orderBy(F.desc("cosine"), "vec_id")
    if seen["odd"] or seen["lo"] != seen["hi"]:
        found = _in_blocks(queries, "vec_id", blocks(queries), lambda q: _nearest(q, vectors, k))
    else:
        kinds = queries.groupBy("embedding").agg(F.min("vec_id").alias("rep"))
        few = vectors.select("vec_id", "embedding").mapInArrow(_few_of_each(k + 1), "vec_id long, embedding array<float>").repartition(F.xxhash64("embedding"))
        best = _in_blocks(kinds, "rep", blocks(kinds), lambda q: few.mapInArrow(_best_in_task(q, k + 1), "rep long, vec_id long, cosine double"))
        top = Window.partitionBy("rep").orderBy(F.desc("cosine"), "vec_id")
        best = best.withColumn("r", F.row_number().over(top)).filter(F.col("r") <= k + 1).drop("r")
        named = queries.select(F.col("vec_id").alias("query"), "embedding").join(kinds, "embedding").select("query", "rep")
        found = named.join(best, "rep").filter("vec_id <> query").select("query", "vec_id", "cosine")
    return found.withColumn("rank", F.row_number().over(final)).filter(F.col("rank") <= k).select("query", "vec_id", "cosine", "rank")


def _in_blocks(queries: DataFrame, key: str, blocks: int, search: Callable[[DataFrame], DataFrame]) -> DataFrame:
    part = F.pmod(F.xxhash64(key), F.lit(max(blocks, 1)))
    return reduce(DataFrame.unionByName, [search(queries.filter(part == b) if blocks > 1 else queries) for b in range(max(blocks, 1))])


def _nearest(queries: DataFrame, vectors: DataFrame, k: int) -> DataFrame:
    """Each task's best k of every query, pair by pair."""
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)
    q = queries.select(F.col("vec_id").alias("query"), F.col("embedding").alias("q"))
    rows = vectors.select("vec_id", "embedding").crossJoin(F.broadcast(q)).filter("vec_id <> query")
    scored = rows.select("query", "vec_id", (dot(F.col("embedding"), F.col("q")) / F.sqrt(dot(F.col("embedding"), F.col("embedding")) * dot(F.col("q"), F.col("q")))).alias("cosine"), F.spark_partition_id().alias("part"))
    local = Window.partitionBy("query", "part").orderBy(F.desc("cosine"), "vec_id")
    return scored.withColumn("r", F.row_number().over(local)).filter(F.col("r") <= k).select("query", "vec_id", "cosine")


def _matrix(embedding: pa.Array) -> np.ndarray:
    rows = embedding.combine_chunks() if isinstance(embedding, pa.ChunkedArray) else embedding
    return rows.flatten().to_numpy(zero_copy_only=False).reshape(len(rows), -1)


def _smallest_ids(ids: np.ndarray, m: np.ndarray, k: int) -> np.ndarray:
    """Places of the k smallest ids of each distinct row of ``m``."""
    _, kind = np.unique(np.ascontiguousarray(m).view(f"V{m.shape[1] * m.itemsize}").ravel(), return_inverse=True)
    order = np.lexsort((ids, kind))
    return order[_places(kind[order]) < k]


def _places(groups: np.ndarray) -> np.ndarray:
    """Each row's place in its run of equal values."""
    starts = np.flatnonzero(np.r_[True, groups[1:] != groups[:-1]])
    return np.arange(len(groups)) - np.repeat(starts, np.diff(np.r_[starts, len(groups)]))


def _few_of_each(k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                yield b.take(pa.array(np.sort(_smallest_ids(b.column(0).to_numpy(), _matrix(b.column(1)), k))))

    return run


def _summed(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Row-wise dot products, summed in the order of the elements."""
    total = np.zeros(len(a))
    for j in range(a.shape[1]):
        total += a[:, j].astype(np.float64) * b[:, j]
    return total


def _best_in_task(queries: DataFrame, k: int):
    """A task's k best vectors of every query: single-precision products rule out what is too far, the rest is summed in full."""
    table = queries.select("rep", "embedding").toArrow()
    names, wanted = table.column("rep").to_numpy(), _matrix(table.column("embedding")) if table.num_rows else np.zeros((0, 1), np.float32)
    sent = queries.sparkSession.sparkContext.broadcast((names, wanted))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, wanted = sent.value
        unit = lambda m: (m / np.sqrt((m.astype(np.float64) ** 2).sum(axis=1))[:, None]).astype(np.float32)
        q, norms = unit(wanted), _summed(wanted, wanted)
        at, ids, cosines = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
        for batch in batches:
            for lo in range(0, batch.num_rows if len(names) else 0, VECTOR_CHUNK):
                part = batch.slice(lo, VECTOR_CHUNK)
                own, m = part.column(0).to_numpy(), _matrix(part.column(1))
                keep = _smallest_ids(own, m, k)
                own, m = own[keep], m[keep]
                u, own_norms = unit(m), _summed(m, m)
                floor = np.full(len(names), -np.inf)
                full = np.flatnonzero(_places(at) == k - 1)
                floor[at[full]] = cosines[full]
                for first in range(0, len(names), QUERY_CHUNK):
                    near = q[first : first + QUERY_CHUNK] @ u.T
                    least = floor[first : first + QUERY_CHUNK]
                    if len(own) >= k and np.isinf(least).any():
                        least = np.maximum(least, np.partition(near, len(own) - k, axis=1)[:, len(own) - k])
                    x, y = np.nonzero(near >= (least - SLACK)[:, None].astype(np.float32))
                    x += first
                    exact = _summed(m[y], wanted[x]) / np.sqrt(own_norms[y] * norms[x])
                    at, ids, cosines = np.r_[at, x], np.r_[ids, own[y]], np.r_[cosines, exact]
                order = np.lexsort((ids, -cosines, at))
                order = order[_places(at[order]) < k]
                at, ids, cosines = at[order], ids[order], cosines[order]
        yield pa.RecordBatch.from_arrays([pa.array(names[at], pa.int64()), pa.array(ids), pa.array(cosines)], names=["rep", "vec_id", "cosine"])

    return run
