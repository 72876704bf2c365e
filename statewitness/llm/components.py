"""Connected components by alternating star contractions, on DataFrames.

Each round points the neighbours of a vertex at the smallest of them: large-star moves larger
neighbours, small-star the smaller ones and the vertex itself. The edges become stars whose centres are
the smallest ids in a number of rounds that grows with the logarithm of the graph's size. A round takes
minima with partial aggregation and joins them back, so a hub with a third of all edges is one row of
the aggregate, and the join that brings it back is one that adaptive execution splits. Each round is
written to a scratch table: lineage stays short and nothing is gathered at the driver.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from statewitness.llm.arrow_text import tidied
from statewitness.llm.scratch import Scratch

#: Most edges that a task contracts by itself (some tens of MB).
TASK_EDGES = 500_000


def _star(edges: DataFrame) -> DataFrame:
    """Large-star: for x and its neighbours, those above x are linked to the smallest of x's set."""
    both = edges.select(F.col("a").alias("x"), F.col("b").alias("y")).union(edges.select(F.col("b").alias("x"), F.col("a").alias("y")))
    least = both.groupBy("x").agg(F.min("y").alias("m")).select("x", F.least("x", "m").alias("m"))
    return both.filter("y > x").join(least, "x").select(F.col("m").alias("a"), F.col("y").alias("b")).distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    """Small-star: x (larger end) and its smaller neighbours are linked to the smallest of those."""
    least = edges.groupBy("b").agg(F.min("a").alias("m"))
    linked = edges.join(least, "b")
    moved = linked.filter("a <> m").select(F.col("m").alias("a"), F.col("a").alias("b"))
    own = least.select(F.col("m").alias("a"), "b")
    return moved.union(own).distinct()


def _mark() -> tuple[Column, Column]:
    """What tells one round's edges from the next's, gathered while they are written."""
    return F.bit_xor(F.xxhash64("a", "b")).alias("x"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")).alias("s")


def components(edges: DataFrame, s: Scratch, name: str) -> DataFrame:
    """(id, component) for every vertex of ``edges`` (a, b) but the smallest of each component, which names it.

    The result reads the last round's table; the caller keeps or drops the tables whose names begin with ``name``.
    """
    now, mark, turn = edges.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).filter("a <> b").distinct(), None, 0
    while True:
        turn += 1
        new, seen = s.save_seen(_small_star(_star(now)), f"{name}-{turn}", *_mark())
        s.drop(f"{name}-{turn - 1}")
        now, old, mark = new, mark, seen
        if mark == old or not mark["n"]:
            return now.select(F.col("b").alias("id"), F.col("a").alias("component"))


def _least_roots(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(vertex, smallest vertex of its component) over edges, but for vertices that are the smallest themselves."""
    ids, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y, root = at[: len(a)], at[len(a) :], np.arange(len(ids))
    while True:
        lo, hi = np.minimum(root[x], root[y]), np.maximum(root[x], root[y])
        if (lo == hi).all():
            break
        np.minimum.at(root, hi, lo)
        while (root != root[root]).any():
            root = root[root]
    moved = np.flatnonzero(root != np.arange(len(ids)))
    return ids[moved], ids[root[moved]]


def _contracted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Stars in place of a partition's edges."""
    parts = [(x.column(0).to_numpy(), x.column(1).to_numpy()) for x in batches]
    if parts:
        ids, roots = _least_roots(*(np.concatenate(side) for side in zip(*parts)))
        yield pa.RecordBatch.from_arrays([pa.array(roots), pa.array(ids)], names=["a", "b"])


def grown(comp: DataFrame | None, edges: DataFrame, n_edges: int, s: Scratch, name: str, native: bool = False) -> DataFrame:
    """Components (id, component) of what ``comp`` links and of more edges (``n_edges`` of both, as counted).

    Edges are first contracted to stars inside tasks of some ``TASK_EDGES`` each, so a graph of one task is done
    in one stage and a larger one meets in star rounds with fewer edges. ``native`` leaves this out.
    """
    if comp is not None:
        edges = comp.select(F.col("component").alias("a"), F.col("id").alias("b")).union(edges.select("a", "b"))
    if native:
        return components(edges, s, name)
    tasks = -(-n_edges // TASK_EDGES) or 1
    stars = s.save(edges.select("a", "b").coalesce(tasks).mapInArrow(tidied(_contracted), "a long, b long"), f"{name}-stars")
    return stars.select(F.col("b").alias("id"), F.col("a").alias("component")) if tasks == 1 else components(stars, s, name)
