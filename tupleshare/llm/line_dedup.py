"""Line dedup: exact set-similarity self-join of lines, and removal of later matches.

A line's set is its distinct words. Words are ordered by rarity over all lines; two sets whose Jaccard similarity
reaches the threshold t share a word among the first n - ceil(t n) + 1 of each (n: a set's size), and k words among the
first n - ceil(t n) + k. Frequent words are met in pairs or triples of words, so that no common word makes one long
list. Lists are joined under the length and the positional filter and the parity sketches of the sets (the sketch of a
symmetric difference is the exclusive or, and has at most as many bits as that has words); what survives is verified on
the words themselves. Equal sets are told by a 64-bit hash of the set, its size and its 128-bit sketch.

Rows between the steps are packed into binary blobs, one for each part of the lists, so the JVM moves few, large rows.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import discard, materialize, over_slices, release

#: Counters of word frequency: slices of 2^16. Words that share a counter share its count; the order stays total.
SLICES = 64
#: Rows of a side that may be broadcast (some 100 bytes each); a larger one is joined by shuffle.
BROADCAST_ROWS = 300_000
#: Bytes of text for each part of the lists.
PART_BYTES = 3_000_000
#: Lines and bytes of the blocks that arrays are made of; a line's number within its block takes 14 bits.
BLOCK_LINES, BLOCK_BYTES = 1 << 14, 1_000_000
#: Bytes that are hashed at once, so that a task's arrays of eight bytes for each stay small.
HASHED = 1 << 17
POSTING = np.dtype([("sig", "<u8"), ("key", "<u8"), ("doc", "<i8"), ("line", "<i4"), ("n", "<u4"), ("at", "<u4"), ("low", "<u8"), ("high", "<u8")])
COUNTED = pa.schema([("slice", pa.int32()), ("at", pa.binary()), ("n", pa.binary())])
POSTED = pa.schema([("part", pa.int32()), ("blob", pa.binary())])
MATCHED = pa.schema([("doc", pa.int64()), ("line", pa.int32()), ("key", pa.int64())])
HOME = np.uint32(1 << 31)  # in `at`: the first posting of its line
_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
_BASE = 0x9E3779B97F4A7C15
_BASE_BACK = pow(_BASE, -1, 1 << 64)


@dataclass(frozen=True)
class LineRule:
    """Lines of fewer than `least` distinct words are never compared; EVERY_LINE has no such floor. The rest has no effect on the result: words up to
    the count `alone` are met alone, up to `paired` in pairs, others in triples; of a line's earlier candidates
    `first_of_part` from each part and `first` in all are verified at once, and lines whose first ones all fail and that
    have more go the exact way for the rest."""

    threshold: float = 0.8
    least: int = 5
    alone: int = 3000
    paired: int = 30_000
    first_of_part: int = 4
    first: int = 16


#: Compares all lines that have words.
EVERY_LINE = LineRule(least=1)


def words_of(line: bytes) -> set[bytes]:
    """A-Z lower-cased, split at ASCII white space."""
    return set(line.lower().split())


class _Powers:
    """1, b, b^2, ... modulo 2^64, made once for a task."""

    def __init__(self, base: int):
        self.base, self.values = base, np.ones(1, np.uint64)

    def upto(self, n: int) -> np.ndarray:
        while len(self.values) < n:
            self.values = np.concatenate([self.values, self.values * np.uint64(pow(self.base, len(self.values), 1 << 64))])
        return self.values[:n]


class Hasher:
    """Hashes of all words of a buffer at once: polynomials in the bytes, modulo 2^64, mixed."""

    def __init__(self):
        self.up, self.down = _Powers(_BASE), _Powers(_BASE_BACK)

    def words(self, buffer: bytes) -> tuple[np.ndarray, np.ndarray]:
        """Starts and 50-bit hashes, in order. The buffer is lower-cased and ends in white space. Hashed in stretches of
        some HASHED bytes that end in white space; a word's hash does not depend on where it stands."""
        data = np.frombuffer(buffer, np.uint8)
        space = _SPACE[data]
        starts, hashes, at = [np.zeros(0, np.int64)], [np.zeros(0, np.uint64)], 0
        while at < len(data):
            end = min(len(data), at + HASHED)
            end += int(space[end - 1 :].argmax())
            own, h = self._stretch(data[at:end], space[at:end])
            starts.append(own + at)
            hashes.append(h)
            at = end
        return np.concatenate(starts), np.concatenate(hashes)

    def _stretch(self, data: np.ndarray, space: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        edge = np.flatnonzero(space[1:] != space[:-1]) + 1
        if not space[0]:
            edge = np.r_[0, edge]
        starts, ends = edge[::2], edge[1::2]
        sums = np.cumsum(data * self.up.upto(len(data)), dtype=np.uint64)
        before = np.where(starts > 0, sums[starts - 1], np.uint64(0))
        h = (sums[ends - 1] - before) * self.down.upto(len(data))[starts] + (ends - starts).astype(np.uint64)
        h = (h ^ h >> np.uint64(31)) * np.uint64(0xBF58476D1CE4E5B9)
        h = (h ^ h >> np.uint64(29)) * np.uint64(0x94D049BB133111EB)
        return starts, (h ^ h >> np.uint64(32)) >> np.uint64(14)


def blocks(batches: Iterator[tuple[list, list]], least: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """Blocks of the lines that are compared: (document, line number) of each, then line and hash of each of their
    distinct words, sorted by line and hash."""
    hasher = Hasher()

    def pieces(text: bytes) -> Iterator[tuple[int, bytes]]:
        """Number of the first line and text of the parts of a long text, cut at line ends."""
        number = at = 0
        while len(text) - at > BLOCK_BYTES and (end := text.rfind(b"\n", at, at + BLOCK_BYTES)) >= at or (at < len(text) - BLOCK_BYTES and (end := text.find(b"\n", at)) >= 0):
            part = text[at:end]
            yield number, part
            number += part.count(b"\n") + 1
            at = end + 1
        yield number, text[at:] if at else text

    def close(ids: list[int], texts: list[bytes], bases: list[int]) -> Iterator:
        buffer = b"\n".join(texts) + b"\n"
        ends = np.flatnonzero(np.frombuffer(buffer, np.uint8) == 10)  # of lines
        starts, h = hasher.words(buffer.lower())
        doc_starts, base = np.cumsum([0] + [len(t) + 1 for t in texts])[:-1], np.array(bases)
        first_line = np.searchsorted(ends, doc_starts)  # of each document
        owner = np.searchsorted(first_line, np.arange(len(ends)), "right") - 1
        line = np.searchsorted(ends, starts)
        for lo in range(0, len(ends), BLOCK_LINES):
            a, b = np.searchsorted(line, [lo, lo + BLOCK_LINES])
            packed = np.sort((line[a:b] - lo).astype(np.uint64) << np.uint64(50) | h[a:b])
            if len(packed):
                packed = packed[np.r_[True, packed[1:] != packed[:-1]]]
            of = (packed >> np.uint64(50)).astype(np.int64)
            n = np.bincount(of, minlength=min(BLOCK_LINES, len(ends) - lo))
            fit = n >= least
            if not fit.any():
                continue
            keep = fit[of]
            renumber = np.cumsum(fit) - 1
            chosen = np.flatnonzero(fit) + lo
            yield np.array(ids, np.int64)[owner[chosen]], (chosen - first_line[owner[chosen]] + base[owner[chosen]]).astype(np.int64), renumber[of[keep]], packed[keep] & np.uint64((1 << 50) - 1)

    ids, texts, bases, size = [], [], [], 0
    for some_ids, some_texts in batches:
        for i, t in zip(some_ids, some_texts, strict=True):
            for base_line, piece in pieces(t):
                ids.append(i)
                texts.append(piece)
                bases.append(base_line)
                size += len(piece)
                if size > BLOCK_BYTES:
                    yield from close(ids, texts, bases)
                    ids, texts, bases, size = [], [], [], 0
    if texts:
        yield from close(ids, texts, bases)


def set_key(hashes: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """Of each run of word hashes, in any order."""
    mixed = hashes * np.uint64(0x9E3779B97F4A7C15)
    mixed ^= mixed >> np.uint64(29)
    return np.add.reduceat(mixed * np.uint64(0xC2B2AE3D27D4EB4F), starts) ^ np.bitwise_xor.reduceat(mixed, starts)


_HASHER = Hasher()


def keys_of(lines: list[bytes]) -> np.ndarray:
    """Keys of the lines' sets, as signed numbers; 0 for lines without words."""
    out, lo = np.zeros(len(lines), np.int64), 0
    ends = np.cumsum([len(x) + 1 for x in lines])
    while lo < len(lines):
        hi = min(lo + BLOCK_LINES, max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + BLOCK_BYTES, "right"))))
        part = lines[lo:hi]
        starts, h = _HASHER.words(b"\n".join(part).lower() + b"\n")
        if len(h):
            line = np.searchsorted(ends[lo:hi] - (ends[lo - 1] if lo else 0), starts, "right").astype(np.uint64)
            packed = np.sort(line << np.uint64(50) | h)
            packed = packed[np.r_[True, packed[1:] != packed[:-1]]]
            of = (packed >> np.uint64(50)).astype(np.int64)
            heads = np.flatnonzero(np.r_[True, of[1:] != of[:-1]])
            out[lo + of[heads]] = set_key(packed & np.uint64((1 << 50) - 1), heads).view(np.int64)
        lo = hi
    return out


def _counting(rule: LineRule):
    def run(batches: Iterator[tuple[list, list]]) -> Iterator[pd.DataFrame]:
        counts = np.zeros(SLICES << 16, np.uint32)
        for _, _, _, h in blocks(batches, rule.least):
            np.add.at(counts, (h >> np.uint64(28)).astype(np.int64), np.uint32(1))
        parts = counts.reshape(SLICES, -1)
        at = [np.flatnonzero(p) for p in parts]
        yield pd.DataFrame({"slice": range(SLICES), "at": [a.astype("<u2").tobytes() for a in at], "n": [np.minimum(p[a], 65535).astype("<u2").tobytes() for p, a in zip(parts, at, strict=True)]})

    return run


def _adding(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
    total = np.zeros(1 << 16, np.uint64)
    for at, n in zip(rows["at"], rows["n"], strict=True):
        total[np.frombuffer(at, "<u2")] += np.frombuffer(n, "<u2")
    at = np.flatnonzero(total)
    return pd.DataFrame({"slice": [key[0]], "at": [at.astype("<u2").tobytes()], "n": [np.minimum(total[at], 65535).astype("<u2").tobytes()]})


#: Partial counts that one task adds up; more are merged in several steps.
MERGED = 64


def word_counts(docs: DataFrame, rule: LineRule) -> np.ndarray:
    """How many lines have a word of each counter, over all documents, up to 65535; 8 MB, whatever the input. Tasks'
    counts are merged as a tree, so none holds those of all tasks."""
    picked = docs.select("id", "text")
    parts = picked.mapInArrow(over_slices(_counting(rule), COUNTED), "slice int, at binary, n binary")
    left = picked.rdd.getNumPartitions()
    while left > MERGED:
        left = -(-left // MERGED)
        deal = F.pmod(F.xxhash64("at", "n"), F.lit(left)).cast("int")
        parts = parts.groupBy("slice", deal.alias("deal")).applyInPandas(_adding, "slice int, at binary, n binary")
    out = np.zeros((SLICES, 1 << 16), np.uint16)
    for r in parts.groupBy("slice").applyInPandas(_adding, "slice int, at binary, n binary").toLocalIterator():
        out[r["slice"], np.frombuffer(r["at"], "<u2")] = np.frombuffer(r["n"], "<u2")
    return out.reshape(-1)


def _code(count: np.ndarray) -> np.ndarray:
    """10 bits that rise with the count; exact up to 512, then in steps."""
    big = np.maximum(count.astype(np.int64), 1)
    return np.where(big <= 512, big, np.minimum(1023, 512 + (np.log2(big / 512) * 72).astype(np.int64))).astype(np.uint64)


def _mix(*words: np.ndarray) -> np.ndarray:
    out = np.full(len(words[0]), len(words), np.uint64)
    for w in words:
        out = (out ^ w) * np.uint64(0x9E3779B97F4A7C15)
        out ^= out >> np.uint64(31)
    return out


def signatures(tokens: np.ndarray, code: np.ndarray, n: np.ndarray, starts: np.ndarray, rule: LineRule) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(line, signature, position of its first word), lines being runs of `n` tokens in order of rarity from `starts`.

    If k words are wanted from a frequent first word, the others are later ones of the longer prefix: the rarest common
    word of two matching sets decides, and all their common words are as frequent or more. That takes k common words;
    sets that are too small to match any but an equal one have all their words as one signature."""
    least = np.ceil(rule.threshold * n - 1e-9).astype(np.int64)
    whole = (least == n) & (np.floor(n / rule.threshold + 1e-9).astype(np.int64) == n) & (n <= 3)
    first = n - least + 1  # words of the prefix
    line = np.repeat(np.arange(len(n)), n)
    place = np.arange(len(tokens)) - starts[line]
    within = np.flatnonzero((place < first[line]) & (code > 1) & ~whole[line])  # a word of one line meets no other
    alone, paired = (int(_code(np.array([c]))[0]) for c in (rule.alone, rule.paired))
    kind = np.searchsorted([alone, paired], code[within])
    lone = within[kind == 0]
    lines, sigs, at = [line[lone]], [_mix(tokens[lone])], [place[lone]]
    head = within[kind == 1]
    more = np.maximum(0, np.minimum(first + 1, n)[line[head]] - place[head] - 1)
    a = np.repeat(head, more)
    b = a + 1 + np.arange(len(a)) - np.repeat(np.cumsum(more) - more, more)
    lines.append(line[a])
    sigs.append(_mix(tokens[a], tokens[b]))
    at.append(place[a])
    head = within[kind == 2]
    if len(head):
        left = np.minimum(first + 2, n)[line[head]] - place[head]
        triples = [(h, h + i, h + j) for h, m in zip(head.tolist(), left.tolist(), strict=True) for i in range(1, m - 1) for j in range(i + 1, m)]
        if triples:
            a, b, c = np.array(triples).T
            lines.append(line[a])
            sigs.append(_mix(tokens[a], tokens[b], tokens[c]))
            at.append(place[a])
    for k in (1, 2, 3):
        of = np.flatnonzero(whole & (n == k))
        of = of[code[starts[of]] > 1] if len(of) else of
        lines.append(of)
        sigs.append(_mix(*(tokens[starts[of] + i] for i in range(k)), np.full(len(of), k, np.uint64)))
        at.append(np.zeros(len(of), np.int64))
    return np.concatenate(lines), np.concatenate(sigs), np.concatenate(at)


def _block_postings(doc: np.ndarray, number: np.ndarray, line: np.ndarray, h: np.ndarray, counts: np.ndarray, rule: LineRule) -> tuple[np.ndarray, np.ndarray]:
    """Postings of the sets of a block, each at its first place, and the places where the block itself repeats one."""
    n = np.bincount(line)
    starts = np.cumsum(n) - n
    key = set_key(h, starts)
    order = np.lexsort((number, doc, key))
    new = np.r_[True, key[order][1:] != key[order][:-1]]
    origin = order[new][np.cumsum(new) - 1]
    later = order[(doc[order] != doc[origin]) | (number[order] != number[origin])]
    keep = np.zeros(len(n), bool)
    keep[order[new]] = True

    bit = h & np.uint64(127)
    flip = np.uint64(1) << (bit & np.uint64(63))
    low = np.bitwise_xor.reduceat(np.where(bit < 64, flip, np.uint64(0)), starts)
    high = np.bitwise_xor.reduceat(np.where(bit < 64, np.uint64(0), flip), starts)
    code = _code(counts[(h >> np.uint64(28)).astype(np.int64)])
    packed = np.sort(line.astype(np.uint64) << np.uint64(50) | code << np.uint64(40) | (h & np.uint64((1 << 40) - 1)))
    token = packed & np.uint64((1 << 50) - 1)
    of, sig, at = signatures(token, (token >> np.uint64(40)).astype(np.int64), n, starts, rule)
    ok = keep[of]
    of, sig, at = of[ok], sig[ok], at[ok].astype(np.uint32)
    home = np.lexsort((sig, at, of))
    home = home[np.r_[True, of[home][1:] != of[home][:-1]]] if len(of) else home
    at[home] |= HOME
    out = np.empty(len(of), POSTING)
    for name, values in (("sig", sig), ("key", key[of]), ("doc", doc[of]), ("line", number[of]), ("n", n[of]), ("at", at), ("low", low[of]), ("high", high[of])):
        out[name] = values
    gone = np.zeros(len(later), POSTING)
    gone["doc"], gone["line"], gone["key"] = doc[later], number[later], key[later]
    return out, gone


def _posting(shared, rule: LineRule, parts: int):
    """Blobs of postings by part, and of the places of repeats within a block (part -1)."""

    def run(batches: Iterator[tuple[list, list]]) -> Iterator[pd.DataFrame]:
        for doc, number, line, h in blocks(batches, rule.least):
            out, gone = _block_postings(doc, number, line, h, shared.value, rule)
            part = (out["sig"] % np.uint64(parts)).astype(np.int64)
            order = np.argsort(part, kind="stable")
            out, part = out[order], part[order]
            heads = np.flatnonzero(np.r_[True, part[1:] != part[:-1]]) if len(part) else np.zeros(0, int)
            blobs = [out[s:e].tobytes() for s, e in zip(heads, np.r_[heads[1:], len(out)], strict=True)] if len(part) else []
            yield pd.DataFrame({"part": [*part[heads].tolist(), -1], "blob": [*blobs, gone.tobytes()]})

    return run


LINKS = "doc long, line int, key long, other_doc long, other_line int, other_key long, more boolean"
LINKED = pa.schema([("doc", pa.int64()), ("line", pa.int32()), ("key", pa.int64()), ("other_doc", pa.int64()), ("other_line", pa.int32()), ("other_key", pa.int64()), ("more", pa.bool_())])


def _links(doc, line, key, other_doc=None, other_line=None, other_key=None, more=None) -> pd.DataFrame:
    return pd.DataFrame(
        {
            "doc": doc, "line": line, "key": key.view(np.int64), "other_doc": doc if other_doc is None else other_doc, "other_line": line if other_line is None else other_line,
            "other_key": (key if other_key is None else other_key).view(np.int64), "more": np.zeros(len(doc), bool) if more is None else more,
        }
    )


def _earliest(pairs: np.ndarray, first: int) -> tuple[np.ndarray, np.ndarray]:
    """Of distinct (later, earlier) pairs, packed and sorted, the `first` of each later one, and which have more."""
    later = pairs >> np.uint64(32)
    start = np.flatnonzero(np.r_[True, later[1:] != later[:-1]]) if len(pairs) else np.zeros(0, int)
    size = np.diff(np.r_[start, len(pairs)])
    nth = np.arange(len(pairs)) - np.repeat(start, size)
    return pairs[nth < first], later[start[size > first]]


def join_postings(p: np.ndarray, threshold: float, first: int) -> tuple[np.ndarray, pd.DataFrame]:
    """Of a part's postings: those of repeated sets that aren't the first, and candidate links from a line to the
    `first` earliest others that pass the filters; `more` tells that there are others."""
    p = p[np.lexsort((p["line"], p["doc"], p["high"], p["low"], p["key"], p["n"], p["sig"]))]
    new = np.zeros(len(p), bool)
    new[:1] = True
    for name in ("sig", "key", "n", "low", "high"):  # a repeat has the key, the size and the sketch of its origin
        new[1:] |= p[name][1:] != p[name][:-1]
    firsts = np.flatnonzero(new)
    later = np.flatnonzero(~new & (p["at"] & HOME > 0))  # equal sets share all lists; one tells
    origin = firsts[np.cumsum(new)[later] - 1]
    repeats = p[later[(p["doc"][later] != p["doc"][origin]) | (p["line"][later] != p["line"][origin])]]
    sig = p["sig"][firsts]
    near = np.r_[sig[1:] == sig[:-1], False] | np.r_[False, sig[1:] == sig[:-1]]
    p, sig = p[firsts[near]], sig[near]
    n, at, low, high = p["n"].astype(np.int32), (p["at"] & ~HOME).astype(np.int32), np.ascontiguousarray(p["low"]), np.ascontiguousarray(p["high"])
    group = np.cumsum(np.r_[False, sig[1:] != sig[:-1]]) if len(p) else np.zeros(0, int)
    # Sizes rise within a list, so the partners of i that are not longer are those from the first long enough one.
    line_at = group * (1 << 32) + n
    lo = np.searchsorted(line_at, group * (1 << 32) + np.ceil(threshold * n - 1e-9).astype(np.int64))
    width = np.arange(len(p)) - lo
    place = np.lexsort((p["line"], p["doc"]))
    fresh = np.r_[True, (p["doc"][place][1:] != p["doc"][place][:-1]) | (p["line"][place][1:] != p["line"][place][:-1])] if len(p) else np.zeros(0, bool)
    rank = np.empty(len(p), np.uint64)  # of the line, whichever of its lists
    rank[place] = np.cumsum(fresh) - 1
    example = place[fresh]
    ratio, ends, done = threshold / (1 + threshold), np.cumsum(width), 0
    found, crowded = np.zeros(0, np.uint64), [np.zeros(0, np.uint64)]
    while done < len(p):
        stop = max(done + 1, int(np.searchsorted(ends, (ends[done - 1] if done else 0) + 400_000, side="right")))
        w = width[done:stop]
        i = np.repeat(np.arange(done, stop), w)
        j = np.repeat(lo[done:stop] - np.cumsum(w) + w, w) + np.arange(len(i))
        done = stop
        both = n[i] + n[j]
        slack = both - 2 * np.ceil(both * ratio - 1e-9).astype(np.int32)  # words that the sets may differ in
        ok = np.flatnonzero(np.bitwise_count(low[i] ^ low[j]) + np.bitwise_count(high[i] ^ high[j]) <= slack)
        i, j = i[ok], j[ok]
        ok = np.minimum(n[i] - at[i], n[j] - at[j]) * 2 >= both[ok] - slack[ok]
        i, j = rank[i[ok]], rank[j[ok]]
        i, j = i[i != j], j[i != j]
        if len(i):
            found = np.unique(np.concatenate([found, np.maximum(i, j) << np.uint64(32) | np.minimum(i, j)]))
            found, more = _earliest(found, first)
            crowded.append(more)
    later, earlier = example[(found >> np.uint64(32)).astype(np.int64)], example[(found & np.uint64(0xFFFFFFFF)).astype(np.int64)]
    a, b = p[later], p[earlier]
    return repeats, _links(a["doc"], a["line"], a["key"], b["doc"], b["line"], b["key"], np.isin(found >> np.uint64(32), np.concatenate(crowded)))


def records(blobs: pa.ChunkedArray) -> np.ndarray:
    """The postings of all blobs, where they stand if they are of one batch."""
    parts = [np.zeros(0, POSTING)]
    for c in blobs.chunks:
        if len(c):
            ends = np.frombuffer(c.buffers()[1], "<i8" if pa.types.is_large_binary(c.type) else "<i4")[c.offset : c.offset + len(c) + 1]
            if ends[-1] > ends[0]:
                parts.append(np.frombuffer(c.buffers()[2], POSTING, int(ends[-1] - ends[0]) // POSTING.itemsize, int(ends[0])))
    return parts[-1] if len(parts) < 3 else np.concatenate(parts)


def _joining(rule: LineRule):
    def run(key: tuple, rows: pa.Table) -> pa.Table:
        p = records(rows["blob"])
        if key[0].as_py() < 0:
            out = _links(p["doc"], p["line"], p["key"])
        else:
            repeats, links = join_postings(p, rule.threshold, rule.first_of_part)
            out = pd.concat([_links(repeats["doc"], repeats["line"], repeats["key"]), links])
        table = pa.Table.from_pandas(out, schema=LINKED, preserve_index=False)
        del out
        release()
        return table

    return run


def _fetching(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """The words of the asked lines of each document."""
    for b in batches:
        places, lines = [], []
        for doc, text, asked in zip(b["id"], b["text"], b["lines"], strict=True):
            own = text.split(b"\n")
            some = [k for k in asked if k < len(own)]  # rows may share an id
            places += [(doc, k) for k in some]
            lines += [own[k] for k in some]
        if lines:
            docs, numbers = zip(*places, strict=True)
            yield pd.DataFrame({"doc": docs, "line": numbers, "key": keys_of(lines), "words": [b" ".join(sorted(words_of(x))) for x in lines]})
    release()


def _similar(threshold: float):
    @F.pandas_udf("boolean")
    def similar(a: pd.Series, b: pd.Series) -> pd.Series:
        out = []
        for x, y in zip(a, b, strict=True):
            x, y = set(x.split()), set(y.split())
            common = len(x & y)
            out.append(common >= threshold * (len(x) + len(y) - common) - 1e-9)
        return pd.Series(out, dtype=bool)

    return similar


def _sided(left: DataFrame, right: DataFrame, on: list[str], rows: int, how: str = "inner") -> DataFrame:
    """Broadcasts the right side only if it is small."""
    return left.join(F.broadcast(right) if rows <= BROADCAST_ROWS else right, on, how)


def _against_all(shared, counts, rule: LineRule):
    """Hard lines, a block of bounded size, with every line of the corpus: those that have an earlier match."""

    def run(batches: Iterator[tuple[list, list]]) -> Iterator[pd.DataFrame]:
        hard = [(d, k, key, np.unique(_HASHER.words(bytes(words) + b"\n")[1])) for d, k, key, words in shared.value]
        index: dict[int, list[int]] = {}
        for m, (_, _, _, words) in enumerate(hard):
            rare = words[np.lexsort((words, counts.value[(words >> np.uint64(28)).astype(np.int64)]))]
            for w in rare[: len(words) - math.ceil(rule.threshold * len(words) - 1e-9) + 1].tolist():
                index.setdefault(w, []).append(m)
        probe, hit = np.array(sorted(index), np.uint64), set()
        for doc, number, line, h in blocks(batches, rule.least):
            at = np.minimum(np.searchsorted(probe, h), len(probe) - 1)
            starts = np.searchsorted(line, np.arange(len(doc) + 1))
            tokens = np.flatnonzero(probe[at] == h)
            for k, m in {(k, m) for k, w in zip(line[tokens].tolist(), h[tokens].tolist(), strict=True) for m in index[w]}:
                own, (d, no, _, words) = h[starts[k] : starts[k + 1]], hard[m]
                if m not in hit and min(len(own), len(words)) >= rule.threshold * max(len(own), len(words)) and (doc[k], number[k]) < (d, no):
                    common = len(np.intersect1d(own, words, assume_unique=True))
                    if common >= rule.threshold * (len(own) + len(words) - common) - 1e-9:
                        hit.add(m)
        yield pd.DataFrame([hard[m][:3] for m in sorted(hit)], columns=["doc", "line", "key"], dtype="int64")

    return run


def later_matches(docs: DataFrame, rule: LineRule = LineRule(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc, line, key) of every line that has an earlier match: a line at a lesser (id, line number) whose words reach
    the similarity. `key` names the set of words. May hold a line several times."""
    spark = docs.sparkSession
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").cast("binary").alias("text")).where("id IS NOT NULL AND text IS NOT NULL")
    size = rows.agg(F.sum(F.length("text").cast("double"))).first()[0] or 0
    parts = max(16, int(-(-size // PART_BYTES)))
    counts = spark.sparkContext.broadcast(word_counts(rows, rule))
    blobs = rows.mapInArrow(over_slices(_posting(counts, rule, parts), POSTED), "part int, blob binary")
    spread = F.when(F.col("part") < 0, (-1 - F.pmod(F.xxhash64("blob"), F.lit(parts))).cast("int")).otherwise(F.col("part"))
    found = materialize(blobs.withColumn("part", spread).groupBy("part").applyInArrow(_joining(rule), LINKS), "line-links")

    same = (F.col("doc") == F.col("other_doc")) & (F.col("line") == F.col("other_line"))
    repeats = found.where(same).select("doc", "line", "key")
    # A line's links come from several parts; the earliest of all are kept.
    place = F.struct("other_doc", "other_line", "other_key")
    links = (
        found.where(~same).groupBy("doc", "line", "key")
        .agg(F.slice(F.sort_array(F.collect_set(place)), 1, rule.first).alias("others"), (F.max("more") | (F.size(F.collect_set(place)) > rule.first)).alias("more"))
    )
    links = materialize(links, "line-candidates")
    pairs = links.select("doc", "line", "key", "more", F.explode("others").alias("o")).select("doc", "line", "key", "more", "o.*")
    asked = pairs.select("doc", "line").union(pairs.select(F.col("other_doc").alias("doc"), F.col("other_line").alias("line")))
    asked = materialize(asked.groupBy(F.col("doc").alias("id")).agg(F.collect_set("line").alias("lines")), "lines-asked")
    texts = _sided(rows, asked, ["id"], asked.count())
    words = materialize(texts.select("id", "text", "lines").mapInPandas(_fetching, "doc long, line int, key long, words binary").dropDuplicates(["doc", "line", "key"]), "line-words")
    others = words.select(F.col("doc").alias("other_doc"), F.col("line").alias("other_line"), F.col("key").alias("other_key"), F.col("words").alias("other_words"))
    both = pairs.join(words, ["doc", "line", "key"]).join(others, ["other_doc", "other_line", "other_key"])
    judged = both.withColumn("match", _similar(rule.threshold)("words", "other_words")).groupBy("doc", "line", "key").agg(F.max("match").alias("match"), F.max("more").alias("more"))
    judged = materialize(judged, "line-verdicts")
    repeats = materialize(repeats, "line-repeats")
    discard(found, links, asked)
    out = repeats.unionAll(judged.where("match").select("doc", "line", "key"))

    hard = judged.where("NOT match AND more").join(words, ["doc", "line", "key"])
    n_hard = hard.count()
    blocks = -(-n_hard // 20_000)
    for b in range(blocks):
        block = hard.where(F.pmod(F.xxhash64("doc", "line"), F.lit(blocks)) == b).collect()
        if block:
            shared = spark.sparkContext.broadcast([(r["doc"], r["line"], r["key"], bytes(r["words"])) for r in block])
            out = out.unionAll(rows.mapInArrow(over_slices(_against_all(shared, counts, rule), MATCHED), "doc long, line int, key long"))
    return out


def _keep_lines():
    @F.pandas_udf("text string, n_removed int")
    def keep(texts: pd.Series, lines: pd.Series, keys: pd.Series) -> pd.DataFrame:
        out, removed, asked = list(texts), [0] * len(texts), []
        for i, (text, gone, named) in enumerate(zip(texts, lines, keys, strict=True)):
            if text is not None and gone is not None:
                own = text.split("\n")
                asked += [(i, k, key, own[k].encode("utf-8", "surrogatepass")) for k, key in zip(gone.tolist(), named.tolist(), strict=True) if k < len(own)]
        drop: dict[int, set[int]] = {}
        for (i, k, key, _), now in zip(asked, keys_of([a[3] for a in asked]).tolist(), strict=True):
            if key == now:  # rows may share an id; a line that isn't the one that was found stays
                drop.setdefault(i, set()).add(k)
        for i, gone in drop.items():
            out[i] = "\n".join(x for k, x in enumerate(out[i].split("\n")) if k not in gone)
            removed[i] = len(gone)
        return pd.DataFrame({"text": out, "n_removed": removed})

    return keep


def dedup_lines(docs: DataFrame, rule: LineRule = LineRule(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The input rows with a struct `deduped` (an input column of that name is replaced): text without the lines that have an earlier match, and n_removed.

    Lines are what stands between line ends; the order is that of (id, line number). A line goes if any earlier line
    with at least `least` distinct words has Jaccard similarity `threshold` or more with it, whether that itself goes or
    not. The rest stands as it was. Rows without an id or text are left as they are. Rows that share an id have their
    places in common, so none of two equal lines at one place is later. An empty table gives an empty result.
    """
    gone = later_matches(docs, rule, id_col, text_col).distinct()
    gone = gone.groupBy(F.col("doc").alias("__id")).agg(F.sort_array(F.collect_list(F.struct("line", "key"))).alias("__gone"))
    gone = materialize(gone.select("__id", F.col("__gone.line").alias("__lines"), F.col("__gone.key").alias("__keys")), "lines-gone")
    joined = _sided(docs.withColumn("__id", F.col(id_col).cast("long")), gone, ["__id"], gone.count(), "left")
    text, some = F.col(text_col).cast("string"), F.col("__lines").isNotNull()
    kept = _keep_lines()(F.when(some, text), F.col("__lines"), F.col("__keys"))  # other texts stay in the JVM
    deduped = F.when(some, F.col("__kept")).otherwise(F.struct(text.alias("text"), F.lit(0).alias("n_removed")))
    return joined.withColumn("__kept", kept).select(*(docs[c] for c in docs.columns if c.lower() != "deduped"), deduped.alias("deduped"))
