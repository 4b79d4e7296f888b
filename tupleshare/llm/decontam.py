"""Benchmark decontamination by spaced seeds: masks over token windows that ignore some positions."""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, materialize, text_function

#: The masks; 1 keeps a position of the window, 0 ignores it.
MASKS = ("1101100101", "110010111", "1011011", "11101001")
#: Bytes of benchmark text that are broadcast at once.
BLOCK_BYTES = 16_000_000
_TO_WORDS = bytes(c + 32 if 65 <= c <= 90 else c if 48 <= c <= 57 or 97 <= c <= 122 or c >= 128 else 32 for c in range(256))
HITS = "array<struct<item_id:bigint,at:int,matched:int,words:int>>"


@dataclass(frozen=True)
class Rule:
    """An item leaks into a text if, on one alignment, a run of `window` of its words (all, if it has fewer) has at
    least the share `similarity` of them in the text at the same places."""

    window: int = 20
    similarity: float = 0.8
    masks: tuple[str, ...] = MASKS


def tokens(text: bytes | None) -> list[bytes]:
    """Runs of ASCII letters and digits and of bytes beyond ASCII; A-Z lower-cased."""
    return (text or b"").translate(_TO_WORDS).split()


def substitutions(n: int, rule: Rule) -> int:
    """How many words of a run of n may differ."""
    return n - math.ceil(rule.similarity * n - 1e-9)


@lru_cache(maxsize=256)
def extra_masks(n: int, rule: Rule) -> tuple[str, ...]:
    """Masks for runs of just n words, so that whichever of their words differ, as many as the rule allows, some mask
    keeps none of these. What the common masks leave open is found by enumeration, and gets a mask of the whole run
    that ignores the very places; without substitutions that is the run itself."""
    kept = [{at + k for k, c in enumerate(m) if c == "1"} for m in rule.masks for at in range(n - len(m) + 1)]
    open_ = [set(p) for p in combinations(range(n), substitutions(n, rule)) if all(k & set(p) for k in kept)]
    return tuple("".join("0" if k in p else "1" for k in range(n)) for p in open_)


#: Hits and places of words that are expanded at once.
AT_ONCE = 400_000


class Seeds:
    """The windows of a block of items under every mask, by hash."""

    def __init__(self, items: list[tuple[int, bytes]], rule: Rule):
        self.rule, self.ids = rule, np.array([i for i, _ in items], dtype=np.int64)
        self.number: dict[bytes, int] = {}
        self.items = [np.array([self.number.setdefault(w, len(self.number) + 1) for w in tokens(t)], dtype=np.int64) for _, t in items]
        sizes = sorted({min(rule.window, len(i)) for i in self.items if len(i)})
        self.masks = [(m, None) for m in rule.masks] + [(m, n) for n in sizes for m in extra_masks(n, rule)]
        self.kept = [np.array([k for k, c in enumerate(m) if c == "1"]) for m, _ in self.masks]
        rng = np.random.default_rng(7)
        self.factors = [rng.integers(1, 2**64, len(k), dtype=np.uint64) | np.uint64(1) for k in self.kept]
        hashes, owners, places = [], [], []
        for m, (mask, only) in enumerate(self.masks):
            for k, item in enumerate(self.items):
                at = np.arange(len(item) - len(mask) + 1) if only in (None, min(rule.window, len(item))) else ()
                if len(at) > 0:
                    hashes.append(self.hash(item, at, m))
                    owners.append(np.full(len(at), k))
                    places.append(at)
        empty = np.zeros(0, np.int64)
        h, owner, place = np.concatenate([empty.astype(np.uint64), *hashes]), np.concatenate([empty, *owners]), np.concatenate([empty, *places])
        order = np.argsort(h, kind="stable")
        self.hashes, self.owner, self.place = h[order], owner[order], place[order]

    def hash(self, numbers: np.ndarray, at: np.ndarray, mask: int) -> np.ndarray:
        out = np.full(len(at), mask + 1, np.uint64)
        for offset, factor in zip(self.kept[mask], self.factors[mask], strict=True):
            out += numbers[at + offset].astype(np.uint64) * factor
        return out

    def _diagonals(self, numbers: np.ndarray, gap: int, starts: np.ndarray) -> np.ndarray:
        """Distinct (text, item, shift) that some seed hits; a word that is repeated hits a shift often, which counts once."""
        known = numbers > 0
        found: list[np.ndarray] = []
        for m, kept in enumerate(self.kept):
            ok = np.ones(len(known) - gap, bool)
            for offset in kept:
                ok &= known[offset : len(known) - gap + offset]
            at = np.flatnonzero(ok)
            if not len(at) or not len(self.hashes):
                continue
            h = self.hash(numbers, at, m)
            lo, hi = np.searchsorted(self.hashes, h, "left"), np.searchsorted(self.hashes, h, "right")
            hit = np.flatnonzero(hi > lo)
            n = (hi - lo)[hit]
            upto, done = np.cumsum(n), 0
            while done < len(hit):
                stop = max(done + 1, int(np.searchsorted(upto, (upto[done - 1] if done else 0) + AT_ONCE, "right")))
                k = n[done:stop]
                seed = np.repeat(lo[hit[done:stop]], k) + np.arange(k.sum()) - np.repeat(np.cumsum(k) - k, k)
                where = np.repeat(at[hit[done:stop]], k)
                done = stop
                text = np.searchsorted(starts, where, "right") - 1
                found.append(np.unique(np.stack([text, self.owner[seed], where - starts[text] - self.place[seed]], axis=1), axis=0))
                if sum(map(len, found)) > 4 * AT_ONCE:
                    found = [np.unique(np.concatenate(found), axis=0)]
        return np.unique(np.concatenate(found), axis=0) if found else np.zeros((0, 3), np.int64)

    def hits(self, texts: list[bytes | None]) -> list[list[tuple[int, int, int, int]]]:
        """Of each text (item id, first word of the best run in the text, words equal, words of the run), by item."""
        get, gap = self.number.get, max((len(m) for m, _ in self.masks), default=1)
        lists = [[get(w, 0) for w in tokens(t)] for t in texts]
        pad = max([gap, *map(len, self.items)])  # so that no alignment leaves the array
        starts = pad + np.cumsum([0] + [len(x) + pad for x in lists])
        numbers = np.zeros(starts[-1] + pad, dtype=np.int64)
        for s, x in zip(starts, lists, strict=False):
            numbers[s : s + len(x)] = x
        sizes = np.array([len(x) for x in lists])
        best: dict[tuple[int, int], tuple[int, int, int]] = {}
        diagonals = self._diagonals(numbers, gap, starts)
        diagonals = diagonals[np.lexsort((diagonals[:, 2], diagonals[:, 0], diagonals[:, 1]))]
        cuts = np.flatnonzero(diagonals[1:, 1] != diagonals[:-1, 1]) + 1
        for group in np.split(diagonals, cuts) if len(diagonals) else ():
            k, item = int(group[0, 1]), self.items[group[0, 1]]
            run, step = min(self.rule.window, len(item)), max(1, AT_ONCE // len(item))
            for lo in range(0, len(group), step):
                text, shift = group[lo : lo + step, 0], group[lo : lo + step, 2]
                same = numbers[(starts[text] + shift)[:, None] + np.arange(len(item))] == item
                sums = np.concatenate([np.zeros((len(same), 1), np.int64), np.cumsum(same, axis=1)], axis=1)
                equal = sums[:, run:] - sums[:, :-run]
                first = np.arange(equal.shape[1])
                inside = (shift[:, None] + first >= 0) & (shift[:, None] + first + run <= sizes[text][:, None])
                equal = np.where(inside, equal, -1)
                at = equal.argmax(axis=1)
                most = equal[np.arange(len(equal)), at]
                for i in np.flatnonzero(most >= self.rule.similarity * run - 1e-9).tolist():
                    place = (int(text[i]), k)
                    best[place] = max(best.get(place, (-1, 0, 0)), (int(most[i]), -int(shift[i] + at[i]), run))
        out: list[list[tuple[int, int, int, int]]] = [[] for _ in texts]
        for (text, k), (equal, at, run) in sorted(best.items()):
            out[text].append((int(self.ids[k]), -at, equal, run))
        return [sorted(x) for x in out]


def seed_blocks(items: DataFrame, rule: Rule, id_col: str = "item_id", text_col: str = "text") -> Iterator[list[tuple[int, bytes]]]:
    """The items in blocks of bounded size; items without id or text take no part."""
    picked = items.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").cast("binary").alias("text")).where("id IS NOT NULL AND text IS NOT NULL")
    size = picked.agg(F.sum(F.length("text"))).first()[0] or 0
    blocks = max(1, -(-size // BLOCK_BYTES))
    for b in range(blocks):
        rows = picked.where(F.pmod(F.xxhash64("id"), F.lit(blocks)) == b).collect()
        if rows:
            yield sorted((r["id"], bytes(r["text"])) for r in rows)


def _leaks(shared, rule: Rule):
    cached: list[Seeds] = []

    def leaks(texts: list) -> list:
        if not cached:
            cached.append(Seeds(shared.value, rule))
        return [[dict(zip(("item_id", "at", "matched", "words"), h, strict=True)) for h in x] for x in cached[0].hits(texts)]

    fields = [("item_id", pa.int64()), ("at", pa.int32()), ("matched", pa.int32()), ("words", pa.int32())]
    return text_function(leaks, HITS, pa.list_(pa.struct(fields)))


def find_leaks(docs: DataFrame, items: DataFrame, rule: Rule = Rule(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """A row for each item that leaks into a document: id, item_id, at (first word of the best run), matched, words.

    Every window of a text whose kept positions hash like an item's is a hit, and the item is compared along the hit's
    alignment, where substituted words are allowed. Every leak that the rule names is found: items shorter than its
    window have masks for whatever the common ones miss, and those of one to four words, in which none may differ, are
    seeds as a whole. Items without words leak nowhere. Seeds are broadcast in blocks of bounded size, one block at a
    time; with more than one block each block's leaks are written before the next is sent. Null and empty texts have no
    leaks; repeated rows give theirs as often; equal items leak each. Other columns are not read; empty tables give an
    empty result.
    """
    picked = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    out = docs.select(id_col).limit(0).selectExpr(id_col, "0L AS item_id", "0 AS at", "0 AS matched", "0 AS words")
    for block, last in _marked(seed_blocks(items, rule)):
        shared = docs.sparkSession.sparkContext.broadcast(block)
        found = picked.select(F.col("id").alias(id_col), F.explode(_leaks(shared, rule)(F.col("text"))).alias("leak")).select(id_col, "leak.*")
        if not last:
            found = materialize(found, "leaks")
            shared.destroy()
        out = out.unionAll(found)
    return out


def without_leaks(docs: DataFrame, items: DataFrame, rule: Rule = Rule(), text_col: str = "text") -> DataFrame:
    """The rows into which no item leaks, with all their columns."""
    for block, last in _marked(seed_blocks(items, rule)):
        shared = docs.sparkSession.sparkContext.broadcast(block)
        kept = docs.where(F.size(_leaks(shared, rule)(F.col(text_col))) == 0)
        if not last:
            docs, before = materialize(kept, "clean"), docs
            discard(before)
            shared.destroy()
        else:
            docs = kept
    return docs


def _marked(blocks: Iterator) -> Iterator[tuple[list, bool]]:
    """The blocks, with whether it is the last; one is held at a time, and the next."""
    now = next(blocks, None)
    while now is not None:
        after = next(blocks, None)
        yield now, after is None
        now = after
