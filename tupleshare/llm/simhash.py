"""SimHash fingerprints and their links, found through tables of distances to reference fingerprints."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from itertools import combinations

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialize, text_function
from .components import components

SEED = 42
SHINGLE = 3
_BITS = ((np.arange(256)[:, None] >> np.arange(8)) & 1).astype(np.int64)
_BYTE_OF = np.arange(8, dtype=np.int64) * 256


def fingerprint(text: bytes | None, size: int = SHINGLE) -> int:
    """Of a UTF-8 text: A-Z lower-cased, words between ASCII white space, `size`-word shingles with repeats (the whole
    sequence if shorter). A bit is set if it is in over half of the shingles' XXH64. No words: 0."""
    words = (text or b"").lower().split()
    if not words:
        return 0
    shingles = map(b" ".join, zip(*(words[k:] for k in range(size)), strict=False)) if len(words) >= size else [b" ".join(words)]
    digest, seed = xxhash.xxh64_intdigest, SEED
    return majority(np.array([digest(s, seed) for s in shingles], dtype="<u8"))


def majority(hashes: np.ndarray) -> int:
    """The bits that are set in over half of the hashes; 0 without any."""
    bytes_ = hashes.view(np.uint8).reshape(-1, 8) + _BYTE_OF
    counts = np.bincount(bytes_.ravel(), minlength=2048).reshape(8, 256) @ _BITS
    return int.from_bytes(np.packbits((2 * counts > len(hashes)).ravel(), bitorder="little").tobytes(), "little")


def fingerprint_column(text: Column, size: int = SHINGLE) -> Column:
    def fp(texts: list) -> list:
        return np.array([fingerprint(t, size) for t in texts], dtype=np.uint64).view(np.int64).tolist()

    return text_function(fp, "long", pa.int64())(text)


@dataclass(frozen=True)
class PivotTables:
    """Reference fingerprints. The word is cut into `segments`; each has a table of Hamming distances, over its own
    bits, to `near` references. Another table has the distances of the whole word to `far` references.

    By the triangle inequality two fingerprints at distance d differ by at most d in every coordinate. At most `radius`
    differing bits touch at most `radius` segments, so in the tables of some `segments - radius` others the greatest
    coordinate difference is 0: such pairs, and no others, meet in a cell. There a pair is discarded if its greatest
    coordinate difference over the whole-word table is above `radius`; the rest are verified.
    """

    radius: int = 2
    segments: int = 5
    near: int = 12
    far: int = 8
    seed: int = 20

    def masks(self) -> list[int]:
        cuts = np.linspace(0, 64, self.segments + 1).round().astype(int)
        return [((1 << int(b)) - 1) ^ ((1 << int(a)) - 1) for a, b in zip(cuts, cuts[1:], strict=False)]

    def cells(self, fp: np.ndarray, masks: list[int] | None = None) -> np.ndarray:
        """A column for each choice of segments: a hash of the distances in their tables."""
        rng = np.random.default_rng(self.seed)
        parts = []
        for mask in masks or self.masks():
            mixed = np.zeros(len(fp), dtype=np.uint64)
            for _ in range(self.near):
                ref, mult = rng.integers(0, 2**64, 2, dtype=np.uint64)
                mixed += np.bitwise_count((fp ^ ref) & np.uint64(mask)) * (mult | np.uint64(1))
            parts.append(mixed)
        out = []
        for k, choice in enumerate(combinations(range(self.segments), self.segments - self.radius)):
            key = np.full(len(fp), k, dtype=np.uint64)
            for s in choice:
                key = (key ^ parts[s]) * np.uint64(0x9E3779B97F4A7C15)
                key ^= key >> np.uint64(29)
            out.append(key)
        return np.stack(out, axis=1) if out else np.zeros((len(fp), 0), np.uint64)

    def whole(self, fp: np.ndarray) -> np.ndarray:
        refs = np.random.default_rng(self.seed + 1).integers(0, 2**64, self.far, dtype=np.uint64)
        return np.bitwise_count(fp[:, None] ^ refs).astype(np.int8)


def _settle(label: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Gives the nodes of each link (i, j) the least label of their component."""
    while len(i):
        low = np.minimum(label[i], label[j])
        new = label.copy()
        np.minimum.at(new, i, low)
        np.minimum.at(new, j, low)
        np.minimum.at(new, label[i], low)
        np.minimum.at(new, label[j], low)
        new = new[new]
        if (new == label).all():
            break
        label = new
    return label


#: Fingerprints that are compared by the whole-word table at once; a larger cell is cut again by tables of the bits in
#: which its members differ, which are fewer at each level.
TOGETHER = 3000


def _pairs(fp: np.ndarray, pivots: PivotTables) -> tuple[np.ndarray, np.ndarray]:
    """Places (i, j) of the pairs within the radius: the whole-word table discards, the words decide."""
    table = pivots.whole(fp)
    order = np.argsort(table[:, 0], kind="stable")
    table, fp = table[order], fp[order]
    ends = np.searchsorted(table[:, 0], table[:, 0] + pivots.radius, side="right")
    heads, tails = [np.zeros(0, int)], [np.zeros(0, int)]
    for i in range(len(fp) - 1):
        j = np.arange(i + 1, ends[i])
        for c in range(1, pivots.far):
            if not len(j):
                break
            j = j[np.abs(table[j, c] - table[i, c]) <= pivots.radius]
        j = j[np.bitwise_count(fp[j] ^ fp[i]) <= pivots.radius]
        heads.append(np.full(len(j), i))
        tails.append(j)
    return order[np.concatenate(heads)], order[np.concatenate(tails)]


def _local_labels(fp: np.ndarray, pivots: PivotTables) -> np.ndarray:
    """Of each of the distinct, sorted fingerprints the place of the least one that it reaches within the cell."""
    label = np.arange(len(fp))
    if len(fp) <= TOGETHER:
        return _settle(label, *_pairs(fp, pivots))
    varying = int(np.bitwise_or.reduce(fp ^ fp[0]))
    bits = [1 << k for k in range(64) if varying >> k & 1]
    masks = [sum(map(int, part)) for part in np.array_split(np.array(bits, dtype=object), pivots.segments)]
    for key in pivots.cells(fp, masks).T:
        order = np.argsort(key, kind="stable")
        cuts = np.flatnonzero(key[order][1:] != key[order][:-1]) + 1
        heads, tails = [], []
        for members in np.split(order, cuts):
            if len(members) > 1:
                members.sort()
                heads.append(members)
                tails.append(members[_local_labels(fp[members], pivots)])
        if heads:
            label = _settle(label, np.concatenate(heads), np.concatenate(tails))
    return label


def cell_links(fp: np.ndarray, pivots: PivotTables) -> tuple[np.ndarray, np.ndarray]:
    """Links (a, b) that connect what is connected at the radius among the distinct fingerprints of one cell: from each
    to the least one of its local component, never all pairs."""
    fp = np.unique(fp)
    label = _local_labels(fp, pivots)
    keep = np.flatnonzero(label != np.arange(len(fp)))
    return fp[keep], fp[label[keep]]


def _probe(pivots: PivotTables):
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            fp = b["fp"].to_numpy().view(np.uint64)
            cells = pivots.cells(fp)
            yield pd.DataFrame({"cell": cells.ravel().view(np.int64), "fp": np.repeat(fp, cells.shape[1]).view(np.int64)})

    return run


def _meet(pivots: PivotTables):
    """Over rows that are sorted by cell; a cell may go on in the next batch."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        kept_cell, kept = None, []

        def close(groups: list[np.ndarray]) -> pd.DataFrame:
            ends = [cell_links(g, pivots) for g in groups]
            a, b = (np.concatenate([e[k] for e in ends]) if ends else np.zeros(0, np.uint64) for k in (0, 1))
            return pd.DataFrame({"a": a.view(np.int64), "b": b.view(np.int64)})

        for batch in batches:
            if not len(batch):
                continue
            cell, fp = batch["cell"].to_numpy(), batch["fp"].to_numpy().view(np.uint64)
            starts = np.flatnonzero(np.r_[True, cell[1:] != cell[:-1]])
            ends = np.r_[starts[1:], len(cell)]
            groups = []
            if kept and cell[0] != kept_cell:
                groups.append(np.concatenate(kept))
                kept = []
            for s, e in zip(starts[ends - starts > 1], ends[ends - starts > 1], strict=True):
                if s and e < len(cell):
                    groups.append(fp[s:e])
            if ends[0] < len(cell):
                groups.append(np.concatenate([*kept, fp[: ends[0]]]))
                kept = []
            kept_cell = cell[-1]
            kept.append(fp[starts[-1] :])
            yield close([g for g in groups if len(g) > 1])
        if kept:
            yield close([g for g in [np.concatenate(kept)] if len(g) > 1])

    return run


def fingerprint_links(fps: DataFrame, pivots: PivotTables | None = None) -> DataFrame:
    """Links (a, b) between distinct fingerprints `fp`, enough to connect all that is connected at the radius."""
    pivots = pivots or PivotTables()
    cells = fps.select("fp").mapInPandas(_probe(pivots), "cell long, fp long")
    return cells.repartition("cell").sortWithinPartitions("cell").mapInPandas(_meet(pivots), "a long, b long")


def near_duplicates(docs: DataFrame, pivots: PivotTables | None = None, size: int = SHINGLE, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: id, fingerprint (16 hex digits), component_id (the least id reachable by links).

    Equal fingerprints are one node, so copies are never paired. Null and empty texts have fingerprint 0 and are linked
    like any other. Rows without an id take part, but give no component its id; a component of only such rows has a
    null one. Repeated rows come back as often. Other columns are not read; an empty table gives an empty result.
    """
    marked, by_fp = _classes(docs, pivots, size, id_col, text_col)
    named = marked.join(by_fp, "fp")
    return named.select(F.col("id").alias(id_col), F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def _classes(docs: DataFrame, pivots: PivotTables | None, size: int, id_col: str, text_col: str) -> tuple[DataFrame, DataFrame]:
    """(id, fp) of the rows and (fp, component_id) of the fingerprints."""
    marked = materialize(docs.select(F.col(id_col).alias("id"), fingerprint_column(F.col(text_col), size).alias("fp")), "fingerprints")
    fps = marked.groupBy("fp").agg(F.min("id").alias("first"))
    labels = components(fingerprint_links(fps, pivots))
    rooted = fps.join(labels, fps["fp"] == labels["node"], "left").select("fp", "first", F.coalesce("label", "fp").alias("label"))
    classes = rooted.groupBy("label").agg(F.min("first").alias("component_id"))
    return marked, rooted.join(classes, "label").select("fp", "component_id")


#: Ids that may be broadcast to the scan of the documents; more are joined by shuffle.
BROADCAST_IDS = 1_000_000


def keep_first(docs: DataFrame, pivots: PivotTables | None = None, size: int = SHINGLE, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows, with all their columns, whose id is the least of their component, and rows without an id. Rows that share
    an id stay or go together."""
    marked, by_fp = _classes(docs, pivots, size, id_col, text_col)
    gone = marked.join(by_fp, "fp").where(F.col("id").isNotNull() & (F.col("id") != F.col("component_id"))).select(F.col("id").alias(id_col)).distinct()
    gone = materialize(gone, "near-copies")
    return docs.join(F.broadcast(gone) if gone.count() <= BROADCAST_IDS else gone, id_col, "left_anti")
