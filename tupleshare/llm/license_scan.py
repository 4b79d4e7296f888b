"""License scan: exact containment join of text blocks with license templates, in DataFrame functions only."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import ascii_lower

#: Phrases whose places are counted exactly, with the label of each (fixed values).
PHRASES = [("cc by", "cc-by"), ("general public license", "gpl"), ("all rights reserved", "reserved")]
#: Short notices of public licenses, by label (fixed values).
TEMPLATES = [
    ("agpl", "licensed under the gnu affero general public license"),
    ("apache-2.0", "licensed under the apache license version 2 0"),
    ("bsd", "redistribution and use in source and binary forms with or without modification are permitted"),
    ("cc-by-nc", "licensed under cc by nc 4 0"),
    ("cc-by-sa", "licensed under the creative commons attribution sharealike license"),
    ("gpl-3.0", "this work is licensed under the gnu general public license version 3"),
    ("isc", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted"),
    ("lgpl", "licensed under the gnu lesser general public license"),
    ("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software"),
    ("mit", "released under the mit license"),
    ("mpl-2.0", "this source code form is subject to the terms of the mozilla public license"),
    ("proprietary", "unauthorized copying of this file via any medium is strictly prohibited proprietary and confidential"),
    ("public-domain", "this is free and unencumbered software released into the public domain"),
]
#: Words without which a block does not meet the templates of a label: they alone tell it from a longer known license.
TELLING = {"agpl": "affero", "lgpl": "lesser"}
#: Neighbouring lines over which a notice may be wrapped.
SPAN = 4
NO_WORD = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
NO_WORD_IN_LINE = r"[\x00-\x09\x0B-\x2F\x3A-\x60\x7B-\x7F]+"
#: The template index is broadcast; more words than this in all templates together are refused.
MAX_TEMPLATE_WORDS = 200_000


def _words(line: Column) -> Column:
    return F.filter(F.split(line, " "), lambda w: w != "")


def _places(words: Column, phrase: str) -> Column:
    """Starts of the phrase in the array of words."""
    parts = phrase.split(" ")
    last = F.size(words) - len(parts)
    starts = F.when(last >= 0, F.sequence(F.lit(0), F.greatest(last, F.lit(0)))).otherwise(F.array().cast("array<int>"))

    def at(i: Column) -> Column:
        hit = F.get(words, i) == parts[0]
        for k, p in enumerate(parts[1:], 1):
            hit = hit & (F.get(words, i + k) == p)
        return hit

    return F.filter(starts, at)


def scan_licenses(docs: DataFrame, threshold: float = 0.8, templates: list[tuple[str, str]] | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: id, n_words, n_base, first_word, last_word, base_labels, labels, score.

    A block is a window of SPAN neighbouring lines of one paragraph (all of a shorter one), so wrapped notices are whole
    in some block. It meets a template if it holds at least `threshold` of the template's distinct words, and the word
    that tells the license where TELLING has one. Words are ordered by how many blocks have them, rarest first. A template's prefix is its rarest words, of
    which a block that meets it must hold one; the index has the prefixes, and a block's words probe it. The length
    filter asks for enough template words in the block, the positional filter for enough left behind the common word
    in both orders; survivors are verified. The score is the best containment met, 1 where a phrase stands.

    Null and empty texts have no words, no labels and score 0. Repeated rows are scanned one by one; other columns are
    not read; an empty table gives an empty result.
    """
    kept = [(label, list(dict.fromkeys(text.split(" ")))) for label, text in (TEMPLATES if templates is None else templates)]
    if sum(len(w) for _, w in kept) > MAX_TEMPLATE_WORDS:
        raise ValueError(f"the templates hold over {MAX_TEMPLATE_WORDS} words; their index is broadcast")
    spark = docs.sparkSession
    need = [math.ceil(threshold * len(w) - 1e-9) for _, w in kept]
    least = min(need, default=1)
    vocabulary = sorted({w for _, words in kept for w in words})
    array = lambda words: F.array(*map(F.lit, words)) if words else F.array().cast("array<string>")

    plain = F.regexp_replace(ascii_lower(F.coalesce(F.col("text"), F.lit(""))), NO_WORD_IN_LINE, " ")
    lines = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text")).select("id", F.transform(F.split(plain, "\n"), _words).alias("lines"))

    # Of the blocks' words only those of a template can meet one, and fewer than `least` of them are too few for any.
    cut = F.transform("lines", lambda ws: F.struct((F.size(ws) > 0).alias("some"), F.array_intersect(array(vocabulary), ws).alias("words")))
    lines = lines.withColumn("cut", cut)

    def window(i: Column) -> Column:
        """Template words of the lines from i on, up to SPAN of them and to the end of the paragraph."""

        def add(have: Column, x: Column) -> Column:
            going = have["some"] & x["some"]
            return F.struct(going.alias("some"), F.when(going, F.array_union(have["words"], x["words"])).otherwise(have["words"]).alias("words"))

        start = F.struct(F.lit(True).alias("some"), F.array().cast("array<string>").alias("words"))
        return F.aggregate(F.slice("cut", i + 1, F.lit(SPAN)), start, add, lambda have: have["words"])

    def in_order(order: list[str]) -> Column:
        blocks = F.filter(F.transform("cut", lambda x, i: F.when(x["some"], window(i))), lambda ws: F.size(ws) >= least)
        return F.array_distinct(F.transform(blocks, lambda ws: F.array_intersect(array(order), ws)))

    met = lines.select(F.explode(in_order(vocabulary)).alias("block")).select(F.explode("block").alias("word"))
    counts = dict(met.groupBy("word").count().collect()) if vocabulary else {}  # as many rows as the templates have words
    order = sorted(vocabulary, key=lambda w: (counts.get(w, 0), w))
    rank = {w: i for i, w in enumerate(order)}
    index_rows = []
    for (label, words), k in zip(kept, need, strict=True):
        words = sorted(words, key=rank.get)
        telling = TELLING.get(label) if TELLING.get(label) in words else None
        index_rows += [(w, i, label, len(words), k, words, telling) for i, w in enumerate(words[: len(words) - k + 1])]
    schema = T.StructType(
        [T.StructField("word", T.StringType()), T.StructField("place", T.IntegerType()), T.StructField("label", T.StringType()), T.StructField("size", T.IntegerType()), T.StructField("need", T.IntegerType()), T.StructField("words", T.ArrayType(T.StringType())), T.StructField("telling", T.StringType())]
    )
    index = spark.createDataFrame(index_rows, schema)
    prefix_words = sorted({r[0] for r in index_rows})

    words = F.flatten("lines")
    scanned = lines.select(F.monotonically_increasing_id().alias("row"), "id", words.alias("words"), in_order(order).alias("blocks"))
    places = F.array(*(_places(F.col("words"), p) for p, _ in PHRASES))
    scanned = scanned.withColumn("has", F.arrays_overlap("words", F.array(F.lit("cc"), F.lit("general"), F.lit("rights"))))
    scanned = scanned.withColumn("places", F.when(F.col("has"), places).otherwise(F.array_repeat(F.array().cast("array<int>"), len(PHRASES))))
    base_labels = F.array_compact(F.array(*(F.when(F.size(F.col("places")[i]) > 0, label) for i, (_, label) in enumerate(PHRASES))))
    per_doc = scanned.select(
        "row", "id", F.size("words").cast("long").alias("n_words"), F.size(F.flatten("places")).cast("long").alias("n_base"),
        F.array_min(F.flatten("places")).cast("long").alias("first_word"), F.array_max(F.flatten("places")).cast("long").alias("last_word"),
        base_labels.alias("base"), F.explode_outer("blocks").alias("block"),
    )
    probing = F.filter(F.transform(F.col("block"), lambda w, j: F.struct(w.alias("word"), j.alias("at"))), lambda s: F.array_contains(array(prefix_words), s["word"]))
    probes = per_doc.select("*", F.explode_outer(probing).alias("probe")).withColumn("word", F.col("probe.word")).drop("probe").withColumn("at", F.array_position("block", F.col("word")) - 1)
    enough = F.size("block") >= F.col("need")
    reach = 1 + F.least(F.col("size") - F.col("place") - 1, F.size("block") - F.col("at") - 1) >= F.col("need")
    common = F.size(F.array_intersect("block", "words"))
    told = F.col("telling").isNull() | F.array_contains("block", F.col("telling"))
    meets = F.when(enough & reach & told, common >= F.col("need"))
    joined = probes.join(F.broadcast(index), "word", "left")
    one = joined.groupBy("row").agg(
        *(F.first(c).alias(c) for c in ("id", "n_words", "n_base", "first_word", "last_word", "base")),
        F.collect_set(F.when(meets, F.col("label"))).alias("more"),
        F.max(F.when(meets, common / F.col("size"))).alias("best"),
    )
    return one.select(
        F.col("id").alias(id_col), "n_words", "n_base", "first_word", "last_word",
        F.concat_ws(",", F.array_sort("base")).alias("base_labels"),
        F.concat_ws(",", F.array_sort(F.array_union("base", "more"))).alias("labels"),
        F.when(F.col("n_base") > 0, 1.0).otherwise(F.coalesce("best", F.lit(0.0))).alias("score"),
    )
