"""Mixing sources to target weights: token weights raked to source, language and topic, then documents sampled."""

from __future__ import annotations

from collections.abc import Mapping
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialize

DIMENSIONS = ("source", "lang", "topic")
#: Cells (combinations of source, language and topic) that are raked in the driver and broadcast; more are raked by joins.
MAX_CELLS = 200_000


@dataclass(frozen=True)
class Mix:
    """share: of all tokens to keep. targets: by dimension the shares of its values; a dimension without targets has
    those of its values in the corpus to the power `temper`, which lifts small ones. Values without a target get 0."""

    share: float = 0.5
    temper: float = 0.7
    targets: Mapping[str, Mapping[str, float]] = field(default_factory=dict)
    seed: int = 9
    rounds: int = 500
    error: float = 1e-9


def topic_of(text: Column) -> Column:
    """By what the text shows of its kind: a table, terms of use, contact data, or prose."""
    return (
        F.when(text.contains(" | "), "table").when(text.rlike("(?i)licen[sc]e|all rights reserved|copyright"), "terms")
        .when(text.rlike("[A-Za-z0-9]@[A-Za-z0-9]"), "contact").otherwise("prose")
    )


def n_tokens(text: Column) -> Column:
    """Words between white space."""
    return F.size(F.filter(F.split(text, r"\s+"), lambda w: w != "")).cast("long")


def rake(tokens: np.ndarray, codes: list[np.ndarray], goals: list[np.ndarray], rounds: int, error: float) -> np.ndarray:
    """Probabilities of the cells, at most 1, under which the expected tokens of every value of every dimension are its
    goal: iterative proportional fitting, cut off at 1. Where goals can't all be met the last round counts."""
    p = np.full(len(tokens), min(1.0, goals[0].sum() / max(1.0, tokens.sum())))
    for _ in range(rounds):
        worst = 0.0
        for code, goal in zip(codes, goals, strict=True):
            now = np.bincount(code, tokens * p, len(goal))
            factor = np.divide(goal, now, out=np.zeros(len(goal)), where=now > 0)
            worst = max(worst, float(np.abs(factor[now > 0] - 1).max(initial=0)))
            p = np.minimum(1.0, p * factor[code])
        if worst < error:
            break
    return p


def _shares(d: str, values: list[str], tokens: np.ndarray, mix: Mix) -> np.ndarray:
    if d in mix.targets:
        return np.array([float(mix.targets[d].get(v, 0.0)) for v in values])
    return tokens**mix.temper


def probabilities(cells: DataFrame, mix: Mix, most: int = MAX_CELLS) -> tuple[DataFrame, bool]:
    """The cells (source, lang, topic) with the probability of each, and whether they are few enough to be broadcast."""
    rows = cells.limit(most + 1).collect()  # of an aggregate: one scan of the texts
    if len(rows) > most:
        return _raked_by_joins(cells, mix), False
    rows = sorted(rows, key=lambda r: tuple(r[d] for d in DIMENSIONS))
    tokens = np.array([r["tokens"] for r in rows], dtype=float)
    codes, goals = [], []
    for d in DIMENSIONS:
        values = sorted({r[d] for r in rows})
        at = {v: k for k, v in enumerate(values)}
        code = np.array([at[r[d]] for r in rows], dtype=int)
        share = _shares(d, values, np.bincount(code, tokens, len(values)), mix)
        codes.append(code)
        goals.append(share / max(share.sum(), 1e-300) * mix.share * tokens.sum())
    p = rake(tokens, codes, goals, mix.rounds, mix.error) if rows else np.zeros(0)
    return cells.sparkSession.createDataFrame([(*(r[d] for d in DIMENSIONS), float(x)) for r, x in zip(rows, p, strict=True)], "source string, lang string, topic string, probability double"), True


def _raked_by_joins(cells: DataFrame, mix: Mix) -> DataFrame:
    """The same rounds on tables: a sum and a join by each dimension in turn, written to the shared folder after each round."""
    cells = materialize(cells, "cells")
    total = float(cells.agg(F.sum("tokens")).first()[0] or 0)
    goals = {}
    for d in DIMENSIONS:
        by = cells.groupBy(d).agg(F.sum("tokens").cast("double").alias("t"))
        if d in mix.targets:
            given = cells.sparkSession.createDataFrame([(k, float(v)) for k, v in mix.targets[d].items()], f"{d} string, share double")
            by = by.join(given, d, "left").withColumn("share", F.coalesce("share", F.lit(0.0)))
        else:
            by = by.withColumn("share", F.pow("t", F.lit(mix.temper)))
        whole = by.agg(F.sum("share")).first()[0] or 1.0
        goals[d] = materialize(by.select(d, (F.col("share") / F.lit(whole) * F.lit(mix.share * total)).alias("goal")), "goals")
    now = cells.withColumn("p", F.lit(min(1.0, mix.share * total / max(1.0, total))))
    for _ in range(mix.rounds):
        worst = 0.0
        for d in DIMENSIONS:
            sums = now.groupBy(d).agg(F.sum(F.col("tokens") * F.col("p")).alias("now")).join(goals[d], d)
            factors = materialize(sums.select(d, F.when(F.col("now") > 0, F.col("goal") / F.col("now")).otherwise(0.0).alias("factor"), (F.col("now") > 0).alias("any")), "factors")
            worst = max(worst, factors.where("any").agg(F.max(F.abs(F.col("factor") - 1))).first()[0] or 0.0)
            now = now.join(factors.drop("any"), d).withColumn("p", F.least(F.lit(1.0), F.col("p") * F.col("factor"))).drop("factor")
        now = materialize(now, "raked")
        if worst < mix.error:
            break
    return now.select(*DIMENSIONS, F.col("p").alias("probability"))


def sample(docs: DataFrame, mix: Mix = Mix(), topic: Column | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The sampled rows, with all their columns and a struct `mix`: topic, tokens, probability.

    Tokens are counted by cell over all documents; the cells are raked; a row is kept if a hash of its id, read as a
    number from 0 to 1, is below its cell's probability. So a row is kept or not whatever its partition, and repeated
    rows fare alike. Null texts have no tokens, null sources, languages and topics are the value "". A column `mix` of
    the input is replaced. An empty table gives an empty result.
    """
    named = lambda c: F.coalesce(c.cast("string"), F.lit(""))
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    traits = {"__source": named(F.col("source")), "__lang": named(F.col("lang")), "__topic": named(topic if topic is not None else topic_of(text))}
    cells = docs.select(*(v.alias(k[2:]) for k, v in traits.items()), n_tokens(text).alias("tokens")).groupBy(*DIMENSIONS).agg(F.sum("tokens").alias("tokens"))
    fitted, small = probabilities(cells, mix)
    fitted = fitted.select(*(F.col(d).alias(f"__{d}") for d in DIMENSIONS), F.col("probability").alias("__p"))
    draw = F.pmod(F.xxhash64(F.col(id_col), F.lit(mix.seed)), F.lit(1 << 52)) / float(1 << 52)
    joined = docs.withColumns(traits).join(F.broadcast(fitted) if small else fitted, list(traits)).where(draw < F.col("__p"))
    return joined.select(*(docs[c] for c in docs.columns if c.lower() != "mix"), F.struct(F.col("__topic").alias("topic"), n_tokens(text).alias("tokens"), F.col("__p").alias("probability")).alias("mix"))
