"""Quality of documents: boosted trees over statistics of the text."""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import boosting
from .common import held_out, text_function
from .labelled import FIT_ROWS, labelled_sample

STATISTICS = (
    "words", "bytes a word", "longest word", "distinct words", "commonest word", "distinct pairs", "lines", "words a line", "distinct lines", "commonest line",
    "letters", "capitals", "digits", "points and commas", "bars", "shouts", "signs", "beyond ASCII", "lines that begin small", "capital words",
)
_CLASSES = np.zeros((256, 8))
for _k, _chars in enumerate((b"abcdefghijklmnopqrstuvwxyz", b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"0123456789", b".,;:", b"|", b"!?", b"#$%&*@<>{}[]()=+_^~/\\")):
    _CLASSES[list(_chars), _k] = 1
_CLASSES[128:, 7] = 1


def statistics(text: bytes | None) -> list[float]:
    """Of a UTF-8 text; all 0 without words."""
    text = text or b""
    words = text.split()
    if not words:
        return [0.0] * len(STATISTICS)
    n, size = len(words), len(text)
    lines = [x for x in text.split(b"\n") if x.strip()]
    shares = np.bincount(np.frombuffer(text, np.uint8), minlength=256) @ _CLASSES / size
    small, upper, digits, points, bars, shouts, signs, beyond = shares.tolist()
    top_word = max(Counter(words).values()) / n
    line_counts = Counter(lines)
    lengths = list(map(len, words))
    return [
        float(np.log1p(n)), sum(lengths) / n, float(np.log1p(max(lengths))), len(set(words)) / n, top_word, len(set(zip(words, words[1:], strict=False))) / n,
        float(np.log1p(len(lines))), float(np.log1p(n / len(lines))), len(line_counts) / len(lines), max(line_counts.values()) / len(lines),
        small + upper, upper / (small + upper + 1e-9), digits, points, bars, shouts, signs, beyond,
        sum(x[:1].islower() for x in lines) / len(lines), sum(map(bytes.isupper, words)) / n,
    ]


def _measuring(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    for b in batches:
        yield pd.DataFrame({"x": [statistics(t) for t in b["text"]], "label": b["label"]})


def fit_quality(docs: DataFrame, labels: DataFrame, label_col: str = "quality", rows: int = FIT_ROWS, **names: str) -> boosting.Forest:
    """On a sample of at most about `rows` labelled documents that aren't held out; only their statistics reach the driver."""
    sample = labelled_sample(docs, labels, label_col, rows, **names).select(F.col("text").cast("binary").alias("text"), "label")
    seen = sample.mapInPandas(_measuring, "x array<double>, label int").toPandas()
    x = np.stack(seen["x"].to_numpy()) if len(seen) else np.zeros((0, len(STATISTICS)))
    order = np.lexsort(x.T[::-1])  # rows come in any order; sums of doubles must not depend on it
    return boosting.fit(x[order], seen["label"].to_numpy(dtype=np.int64)[order])


def quality_score(text: Column, forest: boosting.Forest) -> Column:
    """The score as a column; only the text goes to Python."""

    def score(texts: list) -> list:
        return forest.score(np.array([statistics(t) for t in texts]).reshape(-1, len(STATISTICS))).tolist()

    return text_function(score, "double", pa.float64())(text)


def score_quality(docs: DataFrame, forest: boosting.Forest, threshold: float = 0.7, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: id, held_out, score, predicted.

    The score depends on the text alone. Null and empty texts have all statistics 0 and are scored; repeated rows come
    back as often; other columns are not read; an empty table gives an empty result. No shuffle.
    """
    scored = docs.select(F.col(id_col).alias("id"), quality_score(F.col(text_col), forest).alias("score"))
    return scored.select(F.col("id").alias(id_col), held_out(F.col("id")).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def keep_good(docs: DataFrame, forest: boosting.Forest, threshold: float = 0.7, text_col: str = "text") -> DataFrame:
    """The rows whose score reaches the threshold, with all their columns."""
    return docs.where(quality_score(F.col(text_col), forest) >= threshold)
