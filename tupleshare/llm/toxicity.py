"""Toxicity: a weighted lexicon, matched by Aho-Corasick in folded text."""

from __future__ import annotations

import math
import re
import unicodedata
from collections import Counter, defaultdict
from collections.abc import Iterator
from dataclasses import dataclass

import ahocorasick
import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import held_out, materialize
from .labelled import FIT_ROWS, labelled_sample

#: Letters of other scripts by the Latin letters they look like, and digits and signs by the letters they stand for
#: (fixed values). i, l and what looks like either fold to one letter.
LOOKALIKES = {
    "a": "аɑαаä4@", "b": "Ьвβь8", "c": "сϲ", "d": "ԁ", "e": "еєεё3", "g": "ɡ9", "h": "һ", "i": "іιїı1l|!", "j": "јϳ", "k": "кκ",
    "m": "м", "n": "пη", "o": "оοσ0", "p": "рρ", "q": "ԛ", "s": "ѕ5$", "t": "тτ7", "u": "υս", "v": "ѵν", "w": "ԝωш", "x": "хχ", "y": "уγү", "z": "2",
}
_SIGNS = "@$|!"
#: Letters with a mark stay apart from those without, but for the few in the table.
_FOLD = {ord(c): to for to, many in LOOKALIKES.items() for c in many if c not in _SIGNS}
_SIGN_FOLD = {c: to for to, many in LOOKALIKES.items() for c in many if c in _SIGNS}
_SIGN_IN_WORD = re.compile(r"(?<=[^\W_])[@$|!](?=[^\W_])|(?<![^\W_@$|!])[@$](?=[^\W_])")
_NO_LETTER = re.compile(r"[\W_]+")
_HIDDEN = dict.fromkeys([0xAD, 0x200B, 0x200C, 0x200D, 0x2060, 0xFEFF])
#: Harmless phrases that hold a term (fixed values); more are learnt.
EXCEPTIONS = ("trash can", "trash bin", "trash bag", "class clown", "clown fish", "stupid easy", "dick van", "pathetic fallacy")
STEM = range(4, 8)


def fold(text: str | None) -> str:
    """Lower case, compatibility forms (only where the text isn't ASCII), look-alikes and digits as letters, hidden
    characters dropped; words between single spaces, with one before the first and after the last."""
    text = text or ""
    if not text.isascii():
        text = unicodedata.normalize("NFKC", text).translate(_HIDDEN)
    text = text.lower()
    if any(c in text for c in _SIGNS):
        text = _SIGN_IN_WORD.sub(lambda m: _SIGN_FOLD[m[0]], text)
    return f" {_NO_LETTER.sub(' ', text.translate(_FOLD)).strip()} "


@dataclass(frozen=True)
class Lexicon:
    """terms: folded " word " or " stem" (the start of words), with weights. exceptions: folded phrases within which
    terms don't count. The score is a logistic function of the length-normalised weight."""

    terms: dict[str, float]
    exceptions: tuple[str, ...]
    slope: float
    offset: float

    def automaton(self) -> ahocorasick.Automaton:
        found = ahocorasick.Automaton()
        for e in self.exceptions:
            found.add_word(e, (len(e), None))
        for t, w in self.terms.items():
            if t not in self.exceptions:
                found.add_word(t, (len(t), w))
        found.make_automaton()
        return found


def weigh(folded: str, automaton: ahocorasick.Automaton) -> float:
    """The greatest weight at each word that starts a term and isn't within an exception, summed, over the square root
    of one plus the thousands of characters."""
    if not len(automaton):
        return 0.0
    hits: dict[int, float] = {}
    excused: list[tuple[int, int]] = []
    for end, (size, weight) in automaton.iter(folded):
        start = end - size + 1
        if weight is None:
            excused.append((start, end))
        else:
            hits[start] = max(weight, hits.get(start, 0.0))
    if excused and hits:
        hits = {s: w for s, w in hits.items() if not any(a <= s < b for a, b in excused)}
    return sum(hits.values()) / math.sqrt(1 + len(folded) / 1000)


def _terms(folded: str) -> set[str]:
    words = set(folded.split())
    out = {f" {w} " for w in words}
    for k in STEM:
        out.update([f" {w[:k]}" for w in words if len(w) >= k])
    return out


def _counting(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """Of a task's texts: how many of either label have each term."""
    counts = (Counter(), Counter())
    for b in batches:
        for text, label in zip(b["text"], b["label"], strict=True):
            counts[int(label > 0)].update(_terms(fold(text)))
    keys = list(counts[0].keys() | counts[1].keys())
    for at in range(0, len(keys), 50_000):
        part = keys[at : at + 50_000]
        yield pd.DataFrame({"term": part, "toxic": [counts[1][k] for k in part], "other": [counts[0][k] for k in part]})


def _crediting(support: dict[str, int]):
    """Counts each toxic text for one term it has, that with most support: how often a term is needed."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        automaton = ahocorasick.Automaton()
        for t, n in support.items():
            automaton.add_word(t, (n, t))
        automaton.make_automaton()
        counts: Counter = Counter()
        for b in batches:
            for text in b["text"]:
                hits = [hit for _, hit in automaton.iter(fold(text))] if support else []
                if hits:
                    counts[max(hits)[1]] += 1
        if counts:  # a frame without rows has no type that Arrow could read from its strings
            yield pd.DataFrame({"term": list(counts), "n": list(counts.values())})

    return run


def _logistic(x: np.ndarray, y: np.ndarray, ridge: float = 0.05) -> tuple[float, float]:
    """Slope and offset by Newton's method, the slope held to 0 or more."""
    beta = np.array([0.0, float(np.log((y.sum() + 0.5) / (len(y) - y.sum() + 0.5)))])
    z = np.stack([x, np.ones(len(x))], axis=1)
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(z @ beta, -30, 30)))
        step = np.linalg.solve((z * (p * (1 - p))[:, None]).T @ z + ridge * np.eye(2), z.T @ (y - p) - ridge * beta * [1, 0])
        beta += np.clip(step, -5, 5)
        if np.abs(step).max() < 1e-9:
            break
    return max(0.0, float(beta[0])), float(beta[1])


def fit_lexicon(docs: DataFrame, labels: DataFrame, label_col: str = "toxic", rows: int = FIT_ROWS, least: int = 4, purity: float = 0.75, **names: str) -> Lexicon:
    """Words and stems that texts labelled toxic have far more often than others, weighted by their log odds.

    Fitted on a sample of about `rows` labelled documents that aren't held out, each distinct text once. A stem takes
    the place of the words that begin with it unless these are clearer; a word that begins with a stem and stands mostly
    in other texts becomes an exception. Without labels of both kinds the lexicon is empty and scores are the share of
    toxic ones. The lexicon has no other bound than what the sample holds.
    """
    sample = materialize(labelled_sample(docs, labels, label_col, rows, **names), "toxicity-sample")
    sizes = {r["t"]: r["count"] for r in sample.groupBy((F.col("label") > 0).alias("t")).count().collect()}
    n_toxic, n_other = sizes.get(True, 0), sizes.get(False, 0)
    if not n_toxic or not n_other:
        return Lexicon({}, (), 0.0, float(np.log((n_toxic + 0.5) / (n_other + 0.5)) if n_toxic + n_other else -math.log(99)))
    counts = sample.mapInPandas(_counting, "term string, toxic long, other long").groupBy("term").agg(F.sum("toxic").alias("toxic"), F.sum("other").alias("other"))
    counts = materialize(counts.where(F.col("toxic") + F.col("other") >= least), "toxicity-terms")
    odds = F.log((F.col("toxic") + 0.1) / (n_toxic + 0.2)) - F.log((F.col("other") + 0.1) / (n_other + 0.2))
    base = n_toxic / (n_toxic + n_other)
    bar = max(purity, base + 0.5 * (1 - base))
    floor = max(least, int(0.002 * n_toxic))
    strong = counts.where((F.col("toxic") >= floor) & (F.col("toxic") >= bar * (F.col("toxic") + F.col("other"))))
    top = strong.withColumn("weight", odds).collect()
    terms: dict[str, tuple[float, int]] = {r["term"]: (r["weight"], r["toxic"]) for r in top}
    under: dict[str, list[str]] = defaultdict(list)  # by stem the terms that begin with it
    for t in terms:
        for k in range(2, len(t) + 1):
            if t[:k] in terms and not t[:k].endswith(" "):
                under[t[:k]].append(t)
    chosen: dict[str, float] = {}
    for t in sorted(terms, key=lambda t: (len(t.rstrip()), t)):
        weight, n = terms[t]
        covers = [t[:k] for k in range(2, len(t)) if t[:k] in chosen]  # stems; a word ends in a space, which only whole words hold
        if not any(chosen[c] >= weight - 0.7 for c in covers):
            chosen[t] = weight
    # A stem must speak for more than the one word it was cut from; else the word itself stands.
    for t in [t for t in chosen if not t.endswith(" ")]:
        whole = [w for w in under[t] if w.endswith(" ")]
        if any(terms[w][1] >= 0.95 * terms[t][1] for w in whole):
            del chosen[t]
            chosen.update({w: terms[w][0] for w in whole})
    # Of stems that speak for much the same texts the longest is the most exact.
    for t in [t for t in chosen if not t.endswith(" ")]:
        longest = max((s for s in under[t] if not s.endswith(" ") and terms[s][1] >= 0.95 * terms[t][1]), key=lambda s: (len(s), s))
        if longest != t:
            del chosen[t]
            chosen[longest] = terms[longest][0]
    # Rare words of texts that a stronger term marks already are but company; else a cluster of near copies would fill the lexicon.
    needed = sample.where("label > 0").select("text").mapInPandas(_crediting({t: terms[t][1] for t in chosen}), "term string, n long")
    alone = {r["term"] for r in needed.groupBy("term").agg(F.sum("n").alias("n")).where(F.col("n") >= least).collect()}
    chosen = {t: w for t, w in chosen.items() if t in alone or terms[t][1] >= 0.03 * n_toxic}
    stems = [t for t in chosen if not t.endswith(" ")]
    clean: list[str] = []
    if stems:
        starts = F.lit(False)
        for at in range(0, len(stems), 200):
            starts = starts | F.col("term").rlike("^(?:" + "|".join(map(re.escape, stems[at : at + 200])) + ")")
        harmless = counts.where(F.col("term").endswith(" ") & (F.col("other") >= least) & (F.col("other") > 3 * F.col("toxic")) & starts)
        clean = [r["term"] for r in harmless.orderBy(F.desc("other"), "term").collect()]
    exceptions = tuple(dict.fromkeys([fold(e) for e in EXCEPTIONS] + clean))
    raw = Lexicon(chosen, exceptions, 1.0, 0.0)
    seen = sample.select((F.col("label") > 0).cast("int").alias("label"), _weights(F.col("text"), raw).alias("x")).toPandas()
    order = np.lexsort((seen["label"], seen["x"]))
    slope, offset = _logistic(seen["x"].to_numpy()[order], seen["label"].to_numpy()[order])
    return Lexicon(chosen, exceptions, slope, offset)


def _weights(text: Column, lexicon: Lexicon) -> Column:
    cached: list[ahocorasick.Automaton] = []

    @F.pandas_udf("double")
    def weights(texts: pd.Series) -> pd.Series:
        if not cached:
            cached.append(lexicon.automaton())
        return pd.Series([weigh(fold(t), cached[0]) for t in texts], dtype=float)

    return weights(text.cast("string"))


def toxicity_score(text: Column, lexicon: Lexicon) -> Column:
    return 1 / (1 + F.exp(-(F.lit(lexicon.slope) * _weights(text, lexicon) + F.lit(lexicon.offset))))


def score_toxicity(docs: DataFrame, lexicon: Lexicon, threshold: float = 0.3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: id, held_out, score, predicted.

    The score depends on the whole text alone. Null and empty texts have no hits and the score of such; repeated rows
    come back as often; other columns are not read; an empty table gives an empty result. No shuffle.
    """
    scored = docs.select(F.col(id_col).alias("id"), toxicity_score(F.col(text_col), lexicon).alias("score"))
    return scored.select(F.col("id").alias(id_col), held_out(F.col("id")).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))
