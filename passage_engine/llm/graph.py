"""Connected components of an edge table: contraction inside tasks, then rounds of star contraction."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import stored


def smallest_reached(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The nodes of the edges and the smallest node that each reaches."""
    nodes, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    i, j = at[: len(a)], at[len(a) :]
    root = np.arange(len(nodes))
    while True:
        low = np.minimum(root[i], root[j])
        new = root.copy()
        np.minimum.at(new, root[i], low)
        np.minimum.at(new, root[j], low)
        while (further := new[new]).tobytes() != new.tobytes():
            new = further
        if (new == root).all():
            return nodes, nodes[root]
        root = new


def contracted(edges: DataFrame, piece: int = 500_000) -> DataFrame:
    """Each task's edges (hi, lo) as stars around the smallest node, in pieces of at most so many edges."""

    def run(batches):
        held, size = [], 0

        def stars():
            nodes, roots = smallest_reached(*(np.concatenate(c) for c in zip(*held, strict=True)))
            out = nodes != roots
            return pa.record_batch([pa.array(nodes[out]), pa.array(roots[out])], names=["hi", "lo"])

        for b in batches:
            if b.num_rows:
                held.append((b.column(0).to_numpy(), b.column(1).to_numpy()))
                size += b.num_rows
            if size >= piece:
                yield stars()
                held, size = [], 0
        if held:
            yield stars()

    return edges.mapInArrow(run, "hi long, lo long")


def components(edges: DataFrame, one_task: int = 500_000) -> DataFrame:
    """Edges (a LONG, b LONG) to (node, root): root is the smallest node that can be reached.

    Nodes without an edge to another node are not returned. Each task first contracts its own edges
    to stars. While more than ``one_task`` edges are left, a round is a few joins and partial
    aggregates on the edge table; at most so many (16 bytes each) are finished in a single task.
    Nothing is gathered on the driver but counts and a checksum, and both ways give the same rows.
    """
    now = stored(contracted(edges.where("a <> b").select(F.greatest("a", "b").alias("hi"), F.least("a", "b").alias("lo"))), "edges")
    seen = None
    while (left := now.count()) > one_task:
        mark = (left, now.agg(F.sum(F.xxhash64("hi", "lo").cast("decimal(38,0)"))).first()[0])
        if mark == seen:
            break
        seen = mark
        both = now.select(F.col("hi").alias("u"), F.col("lo").alias("v")).union(now.select("lo", "hi"))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("hi"), F.col("m").alias("lo")).distinct()
        low = large.groupBy("hi").agg(F.min("lo").alias("m"))
        small = large.join(low, "hi")
        now = stored(small.select("hi", F.col("m").alias("lo")).union(small.where("lo <> m").select("lo", "m")).distinct(), "edges")
    if left <= one_task:
        now = stored(contracted(now.coalesce(1), max(1, one_task)), "edges")
    return now.select(F.col("hi").alias("node"), F.col("lo").alias("root")).union(now.select("lo", "lo").distinct().toDF("node", "root"))
