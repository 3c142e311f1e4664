"""Nearest neighbours by adaptive dimension scan within probed lists.

Vectors are rotated by a seeded random matrix and dealt to the lists of their nearest centroids
(k-means on a sample of bounded size; every vector is indexed). A list of many vectors is cut into
blocks of bounded size. A query meets the blocks of its nearest lists, as many as held the wanted
share of the true neighbours of sample queries within the sample, at any size of the table; there the
rotated columns are read block by block, and after each a hypothesis test on the partial distance
gives up candidates that are too far with high confidence. The others get their exact distance from
the original vectors.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import hash_share, stored


@dataclass
class Index:
    centroids: np.ndarray
    rotation: np.ndarray
    blocks: np.ndarray  # of each list
    sizes: np.ndarray
    probes: int
    least: int

    def near(self, x: np.ndarray) -> list[np.ndarray]:
        """The lists that each rotated vector meets, nearest first: ``probes``, or as many as hold ``least`` vectors."""
        order = np.argsort(_nearest(x, self.centroids), axis=1, kind="stable")
        enough = (np.cumsum(self.sizes[order], axis=1) < self.least).sum(axis=1) + 1
        return [row[: max(self.probes, n)] for row, n in zip(order, enough, strict=True)]


def usable(vectors: DataFrame, dim: int | None = None) -> tuple[DataFrame, int]:
    """Vectors that take part, as (vec_id, v array<double>), and their length.

    Null, empty, all-zero vectors and such with null or non-finite components take none, nor rows
    without vec_id, nor vectors of another length than ``dim`` (default: the commonest, then largest).
    """
    v = vectors.where("vec_id is not null and embedding is not null").select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("v"))
    ok = v.where(F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf"))) & F.exists("v", lambda x: x != 0))
    if dim is None:
        top = ok.groupBy(F.size("v").alias("d")).count().orderBy(F.desc("count"), F.desc("d")).first()
        dim = top.d if top else 1
    return ok.where(F.size("v") == dim), dim


def _matrix(col: pa.Array, dim: int) -> np.ndarray:
    return col.flatten().to_numpy(zero_copy_only=False).reshape(-1, dim)


def _nearest(x: np.ndarray, centroids: np.ndarray) -> np.ndarray:
    """Squared distances to the centroids, less the vectors' own part."""
    return (centroids * centroids).sum(axis=1) - 2 * x @ centroids.T


def probes_for(x: np.ndarray, centroids: np.ndarray, recall: float, k: int = 10, queries: int = 256) -> int:
    """The fewest lists that hold the wanted share of the k nearest of sample queries within the sample."""
    own = _nearest(x, centroids).argmin(axis=1)
    places = []
    for q in range(0, len(x), max(1, len(x) // queries)):
        dist = ((x - x[q]) ** 2).sum(axis=1)
        dist[q] = np.inf
        near = np.argpartition(dist, min(k, len(x) - 1) - 1)[:k] if len(x) > 1 else np.zeros(0, int)
        rank = np.argsort(np.argsort(_nearest(x[q : q + 1], centroids)[0], kind="stable"))
        places += rank[own[near]].tolist()
    return int(np.quantile(places, recall, method="higher")) + 1 if places else len(centroids)


def build(vectors: DataFrame, dim: int, sample: int = 20_000, lists: int | None = None, probes: int | None = None, recall: float = 0.98, least: int = 200, seed: int = 5, rounds: int = 8, rows_a_block: int = 4096) -> tuple[Index, DataFrame]:
    """Usable vectors to the index and the dealt vectors (list, block, vec_id, v).

    About ``sample`` vectors (chosen by vec_id) place the centroids and tell how many lists a query
    reads so as to find ``recall`` of its neighbours (``probes`` fixes the number); in any case as
    many as hold ``least`` vectors.
    """
    spark = vectors.sparkSession
    n = vectors.count()
    # sqrt(n)/4 lists up to 1024 keep both the centroids and the blocks a query meets bounded
    lists = lists or int(min(1024, max(8, round(n**0.5 / 4))))
    chosen = vectors.where(hash_share("vec_id") < min(1.0, sample / max(1, n))).toPandas().sort_values("vec_id", kind="stable")
    rng = np.random.default_rng(seed)
    rotation, _ = np.linalg.qr(rng.standard_normal((dim, dim)))
    x = np.array(chosen.v.tolist(), float).reshape(-1, dim) @ rotation
    x = np.unique(x, axis=0)
    centroids = x[rng.permutation(len(x))[:lists]] if len(x) else np.zeros((1, dim))
    for _ in range(rounds if len(x) > lists else 0):
        own = _nearest(x, centroids).argmin(axis=1)
        sums = np.zeros_like(centroids)
        np.add.at(sums, own, x)
        count = np.bincount(own, minlength=len(centroids))[:, None]
        centroids = np.where(count > 0, sums / np.maximum(count, 1), centroids)
    probes = probes or probes_for(x, centroids, recall)
    shared = spark.sparkContext.broadcast((centroids, rotation))

    def deal(batches):
        c, r = shared.value
        for b in batches:
            own = _nearest(_matrix(b.column("v"), dim) @ r, c).argmin(axis=1) if b.num_rows else np.zeros(0, int)
            yield pa.record_batch([pa.array(own.astype(np.int32)), b.column("vec_id"), b.column("v")], names=["list", "vec_id", "v"])

    dealt = stored(vectors.mapInArrow(deal, "list int, vec_id long, v array<double>"), "lists")
    sizes = {r.list: r["count"] for r in dealt.groupBy("list").count().collect()}
    blocks = np.array([max(1, -(-sizes.get(i, 0) // rows_a_block)) for i in range(len(centroids))], np.int32)
    at = F.array(*map(F.lit, blocks.tolist()))
    counts = np.array([sizes.get(i, 0) for i in range(len(centroids))], np.int64)
    return Index(centroids, rotation, blocks, counts, min(probes, len(centroids)), least), dealt.withColumn("block", F.pmod(F.xxhash64("vec_id"), F.element_at(at, F.col("list") + 1)).cast("int"))


def scan_block(ids: np.ndarray, x: np.ndarray, y: np.ndarray, q_id: int, q: np.ndarray, qr: np.ndarray, k: int, step: int = 16, epsilon: float = 2.5) -> tuple[np.ndarray, np.ndarray]:
    """The k nearest of one block: (ids, exact distances). x: original, y: rotated vectors.

    After d of D rotated columns the distance is estimated as partial * D / d; a candidate goes if
    the estimate is beyond (1 + epsilon / sqrt(d))^2 times the k-th best distance known, that of
    the k candidates nearest by the columns read so far.
    """
    live = np.flatnonzero(ids != q_id)
    dim = y.shape[1]
    if len(live) > 4 * k:
        first = ((y[live, :step] - qr[:step]) ** 2).sum(axis=1)
        guess = live[np.argpartition(first, k - 1)[:k]]
        limit = ((x[guess] - q) ** 2).sum(axis=1).max() * (1 + 1e-9)
        part, d = first, min(step, dim)
        while True:
            keep = part * (dim / d) <= limit * (1 + epsilon / d**0.5) ** 2 if d < dim else part <= limit + 1e-9
            live, part = live[keep], part[keep]
            if d >= dim:
                break
            e = min(d + step, dim)
            part = part + ((y[live, d:e] - qr[d:e]) ** 2).sum(axis=1)
            if e < dim and len(live) > 4 * k:
                guess = live[np.argpartition(part, k - 1)[:k]]
                limit = min(limit, ((x[guess] - q) ** 2).sum(axis=1).max() * (1 + 1e-9))
            d = e
    dist = np.sqrt(((x[live] - q) ** 2).sum(axis=1))
    best = np.lexsort((ids[live], dist))[:k]
    return ids[live][best], dist[best]


def search(vectors: DataFrame, queries: DataFrame, k: int = 10, **options) -> DataFrame:
    """Vectors (vec_id, embedding) and queries (vec_id) to (query_id, rank, vec_id, score).

    Each query's k nearest found, by Euclidean distance in double precision on the original
    vectors; ties go to the smaller vec_id; rank counts from 1. A query whose vector takes no part
    has no row. Rows that repeat a vec_id count as one vector, the first by content.
    """
    usable_rows, dim = usable(vectors)
    usable_rows = stored(usable_rows.groupBy("vec_id").agg(F.min("v").alias("v")), "vectors")
    index, dealt = build(usable_rows, dim, **options)
    spark = vectors.sparkSession
    shared = spark.sparkContext.broadcast(index)

    def probe(batches):
        ix = shared.value
        for b in batches:
            ids, x = b.column("vec_id").to_numpy(), _matrix(b.column("v"), dim)
            near = ix.near(x @ ix.rotation) if len(ids) else []
            rows = [(int(p), blk, i) for i, ps in enumerate(near) for p in ps for blk in range(ix.blocks[p])]
            yield pa.record_batch([pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.int32()), pa.array(ids[[r[2] for r in rows]] if rows else [], pa.int64()), b.column("v").take(pa.array([r[2] for r in rows], pa.int64()))], names=["list", "block", "query_id", "q"])

    asked = usable_rows.join(queries.select(F.col("vec_id").cast("long").alias("vec_id")).distinct(), "vec_id", "left_semi")
    probes = asked.mapInArrow(probe, "list int, block int, query_id long, q array<double>")

    def meet(vs: pd.DataFrame, qs: pd.DataFrame) -> pd.DataFrame:
        out: list[tuple] = []
        if len(vs) and len(qs):
            ids, x = vs.vec_id.to_numpy(), np.array(vs.v.tolist())
            y = x @ shared.value.rotation
            for q_id, q in zip(qs.query_id.tolist(), qs.q.tolist(), strict=True):
                q = np.array(q)
                found, dist = scan_block(ids, x, y, q_id, q, q @ shared.value.rotation, k)
                out += [(q_id, int(i), float(d)) for i, d in zip(found, dist, strict=True)]
        return pd.DataFrame(out, columns=["query_id", "vec_id", "score"]).astype({"query_id": "int64", "vec_id": "int64", "score": "float64"})

    met = dealt.select("list", "block", "vec_id", "v").groupBy("list", "block").cogroup(probes.groupBy("list", "block")).applyInPandas(meet, "query_id long, vec_id long, score double")
    w = Window.partitionBy("query_id").orderBy("score", "vec_id")
    return met.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
