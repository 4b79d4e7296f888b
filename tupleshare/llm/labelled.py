"""A bounded sample of labelled documents to fit on."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import held_out

#: Labelled documents, about, that a model is fitted on; the only bound of its kind.
FIT_ROWS = 20_000


def labelled_sample(docs: DataFrame, labels: DataFrame, label_col: str, rows: int = FIT_ROWS, seed: int = 5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(text, label) of about `rows` labelled documents that aren't held out, chosen by a hash of the id.

    Null ids and labels are left out; an id with several labels has the greatest. Null texts are empty. The chosen
    labels, at most some more than `rows`, are broadcast to the scan of the documents. Texts that occur several times
    count once.
    """
    known = labels.select(F.col(id_col).alias("id"), F.col(label_col).cast("int").alias("label")).where("id IS NOT NULL AND label IS NOT NULL")
    known = known.where(~held_out(F.col("id"))).groupBy("id").agg(F.max("label").alias("label"))
    share = min(1.0, rows / max(1, known.count()))
    picked = known.where(F.pmod(F.xxhash64("id", F.lit(seed)), F.lit(1 << 30)) < int(share * (1 << 30)) + 1)
    texts = docs.select(F.col(id_col).alias("id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    return texts.join(F.broadcast(picked), "id").groupBy(F.xxhash64("text").alias("h"), F.length("text").alias("n")).agg(F.min_by("text", "id").alias("text"), F.max("label").alias("label")).select("text", "label")
