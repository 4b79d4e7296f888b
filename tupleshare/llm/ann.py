"""Nearest neighbours by inner product over randomly rotated one-bit codes."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import materialize

INDEXED = "id long, vector array<double>, code binary, norm double, gain double"


@dataclass(frozen=True)
class Search:
    """`width`: how many standard errors of an estimate its bounds allow for. `block`: queries that are broadcast at
    once. `sample`: candidates, about, whose exact products give each query a first threshold."""

    k: int = 20
    width: float = 3.5
    block: int = 8192
    sample: int = 4096
    seed: int = 10


def rotation(dim: int, seed: int) -> np.ndarray:
    """A random orthogonal matrix."""
    q, r = np.linalg.qr(np.random.default_rng(seed).standard_normal((dim, dim)))
    return q * np.sign(np.diag(r))


def usable(vector: Column, dim: int | None) -> Column:
    """Not null, of the dimension, not all zero, and all components finite numbers."""
    whole = F.forall(vector, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    fits = vector.isNotNull() & (F.size(vector) > 0) & whole & F.exists(vector, lambda x: x != 0)
    return F.coalesce(fits if dim is None else fits & (F.size(vector) == dim), F.lit(False))


def encode(rotated_units: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The sign bits of rotated unit vectors, packed, and for each the inner product of the unit with its code read as
    a unit vector (the gain, by which an estimate is corrected)."""
    return np.packbits(rotated_units >= 0, axis=1), np.abs(rotated_units).sum(axis=1) / np.sqrt(rotated_units.shape[1])


def _indexing(dim: int, seed: int):
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        turn = rotation(dim, seed).T
        for b in batches:
            if len(b):
                x = np.stack(b["vector"].to_numpy()).astype(np.float64)
                scale = np.abs(x).max(axis=1)  # so that no square overflows
                norm = np.sqrt(((x / scale[:, None]) ** 2).sum(axis=1)) * scale
                codes, gain = encode((x / norm[:, None]) @ turn)
                yield pd.DataFrame({"id": b["id"], "vector": b["vector"], "code": [c.tobytes() for c in codes], "norm": norm, "gain": gain})

    return run


def products(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Row by row, added up from the first component to the last in double precision."""
    total = np.zeros(len(a))
    for d in range(a.shape[1]):
        total += a[:, d] * b[:, d]
    return total


def _best(q: np.ndarray, ids: np.ndarray, score: np.ndarray, k: int) -> np.ndarray:
    """Places of the k best of each q, in order: greater score, then smaller id."""
    order = np.lexsort((ids, -score, q))
    q = q[order]
    first = np.searchsorted(q, q, side="left")
    return order[np.arange(len(q)) - first < k]


class _Held:
    """The best so far of each query within a task, and the floor under which nothing can enter."""

    def __init__(self, ids: np.ndarray, x: np.ndarray, floor: np.ndarray, k: int):
        self.ids, self.x, self.floor, self.k = ids, x, floor.copy(), k
        self.q, self.id, self.score = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
        self.waiting: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        self.n_waiting = 0

    def offer(self, q: np.ndarray, ids: np.ndarray, vectors: np.ndarray) -> None:
        if len(q):
            score = products(self.x[q], vectors)
            ok = score >= self.floor[q]
            self.waiting.append((q[ok], ids[ok], score[ok]))
            self.n_waiting += int(ok.sum())
        if self.n_waiting > 4 * len(self.ids) + 50_000:
            self.merge()

    def merge(self) -> None:
        self.q, self.id, self.score = (np.concatenate([old, *new]) for old, *new in zip((self.q, self.id, self.score), *self.waiting, strict=True))
        self.waiting, self.n_waiting = [], 0
        keep = _best(self.q, self.id, self.score, self.k)
        self.q, self.id, self.score = self.q[keep], self.id[keep], self.score[keep]
        heads = np.searchsorted(self.q, np.arange(len(self.ids) + 1))
        full = np.flatnonzero(np.diff(heads) >= self.k)
        self.floor[full] = np.maximum(self.floor[full], self.score[heads[full] + self.k - 1])


def _scanning(shared, dim: int, s: Search):
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        query_ids, queries, floor = shared.value
        n, held = len(query_ids), _Held(query_ids, queries, floor, s.k)
        q_norm = np.sqrt((queries**2).sum(axis=1))
        turned = ((queries / q_norm[:, None]) @ rotation(dim, s.seed).T).astype(np.float32) / np.float32(np.sqrt(dim))
        single = queries.astype(np.float32)
        step, pairs = max(64, 2_000_000 // max(1, n)), max(1024, 2_000_000 // dim)  # bound the largest arrays to some 16 MB
        for b in batches:
            ids, norm, gain = b["id"].to_numpy(), b["norm"].to_numpy(), b["gain"].to_numpy()
            x = np.stack(b["vector"].to_numpy()) if len(b) else np.zeros((0, dim))
            packed = np.frombuffer(b"".join(b["code"]), np.uint8).reshape(len(b), -1)
            error = s.width * np.sqrt(np.maximum(0, 1 - gain * gain) / max(1, dim - 1)) / gain
            short = x.astype(np.float32)
            for at in range(0, len(b), step):
                part = slice(at, at + step)
                signs = np.unpackbits(packed[part], axis=1, count=dim).astype(np.float32) * 2 - 1
                # product <= |query| |vector| (estimate + error); compared as estimate * gain, for each row of the index
                scaled = signs @ turned.T
                ratio = held.floor / q_norm
                bar = (ratio - 1e-5 * np.abs(ratio)).astype(np.float32) * (gain[part] / norm[part]).astype(np.float32)[:, None] - (error[part] * gain[part]).astype(np.float32)[:, None]
                near = np.flatnonzero(scaled >= bar)
                for lo in range(0, len(near), pairs):
                    c, q = np.divmod(near[lo : lo + pairs], n)
                    c += at
                    rough = np.einsum("ij,ij->i", single[q], short[c])  # in single precision, far cheaper than the exact one
                    ok = (rough >= held.floor[q] - 1e-4 * q_norm[q] * norm[c]) & (ids[c] != query_ids[q])
                    c, q = c[ok], q[ok]
                    held.offer(q, ids[c], x[c])
        held.merge()
        yield pd.DataFrame({"query_id": query_ids[held.q], "id": held.id, "score": held.score})

    return run


def build_index(vectors: DataFrame, dim: int, seed: int = Search.seed, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """Every usable vector with its packed sign bits after the rotation, its length and its gain."""
    picked = vectors.select(F.col(id_col).cast("long").alias("id"), F.col(vector_col).cast("array<double>").alias("vector"))
    return picked.where(usable(F.col("vector"), dim) & F.col("id").isNotNull()).mapInPandas(_indexing(dim, seed), INDEXED)


def dimension(vectors: DataFrame, vector_col: str = "embedding") -> int:
    """The most frequent length among usable vectors (the least of several); 0 without any."""
    sizes = vectors.select(F.col(vector_col).cast("array<double>").alias("v")).where(usable(F.col("v"), None)).groupBy(F.size("v").alias("d")).count()
    top = sizes.orderBy(F.desc("count"), "d").first()
    return top["d"] if top else 0


def nearest(vectors: DataFrame, is_query: Column, search: Search = Search(), id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """(query_id, rank, vec_id, score): the k nearest of each query among all rows with another id.

    Queries go out in blocks of bounded size. Each task scans its part of the index: from the packed bits and the gain
    it estimates every inner product, adds the error bound, and computes the exact product, on the original vectors,
    of those only that may still be among the query's best. A sample's exact products give the first threshold; it
    rises with what the task finds. Each task returns k rows a query at most, so a vector that fills a third of the
    table costs no more than another.

    Vectors that are null, zero, hold null or non-finite components, or have another dimension than most, take no part;
    nor do rows without an id. Rows with the same id are candidates each, but one query (the first in order of the
    vector). Ties go to the smaller id. With fewer candidates than k all come back. Other columns are not read; an empty
    table gives an empty result.
    """
    spark, s = vectors.sparkSession, search
    empty = spark.createDataFrame([], f"query_id long, rank int, {id_col} long, score double")
    dim = dimension(vectors, vector_col)
    if not dim:
        return empty
    index = materialize(build_index(vectors, dim, s.seed, id_col, vector_col), "codes")
    rows = index.count()
    asked = index.withColumn(id_col, F.col("id")).where(is_query).groupBy("id").agg(F.min("vector").alias("vector"))
    n_queries = asked.count()
    blocks = -(-n_queries // s.block)
    share = min(1.0, s.sample / max(1, rows))
    sample = index.where(F.pmod(F.xxhash64("id", F.lit(s.seed)), F.lit(1 << 30)) < int(share * (1 << 30)) + 1).select("id", "vector").toPandas()
    sample_x = np.stack(sample["vector"].to_numpy()).astype(np.float64) if len(sample) else np.zeros((0, dim))
    sample_ids = sample["id"].to_numpy()

    found = []
    for b in range(blocks):
        block = asked.where(F.pmod(F.xxhash64("id"), F.lit(blocks)) == b).toPandas()
        if not len(block):
            continue
        ids, x = block["id"].to_numpy(), np.stack(block["vector"].to_numpy()).astype(np.float64)
        floor = np.full(len(ids), -np.inf)
        for at in range(0, len(ids), 512):
            score = x[at : at + 512] @ sample_x.T
            score[ids[at : at + 512, None] == sample_ids] = -np.inf
            if score.shape[1] >= s.k:
                kth = np.partition(score, -s.k, axis=1)[:, -s.k]
                floor[at : at + 512] = np.where(np.isfinite(kth), kth - 1e-9 * np.abs(kth), -np.inf)
        shared = spark.sparkContext.broadcast((ids, x, floor))
        best = index.mapInPandas(_scanning(shared, dim, s), "query_id long, id long, score double")
        if blocks > 1:  # one block is in the driver and the executors at a time
            best = materialize(best, "nearest")
            shared.destroy()
        found.append(best)
    if not found:
        return empty
    best = found[0]
    for more in found[1:]:
        best = best.unionAll(more)
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "id")
    ranked = best.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= s.k)
    return ranked.select("query_id", "rank", F.col("id").alias(id_col), "score")
