"""Toxicity, quality, decontamination and mixing."""

import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from tupleshare.llm import boosting, decontam, mixing, quality, toxicity

SF = "/root/testdata/sf0.01"


def labelled(spark, n=600):
    """Toxic texts hold one of two words or a word of one stem; bad ones shout."""
    rng = np.random.default_rng(0)
    words = [f"word{chr(97 + i // 26)}{chr(97 + i % 26)}" for i in range(200)]
    rows = []
    for i in range(n):
        toxic, bad = i % 3 == 0, i % 5 == 0
        w = list(rng.choice(words, 40))
        if toxic:
            w[7] = ["nasty", "V1le", "grumbo" + "abcdefghij"[i % 10]][i // 3 % 3]
        text = " ".join(w)
        rows.append((i, text.upper().replace(" ", "!! ") if bad else text, int(not bad), int(toxic)))
    return spark.createDataFrame(rows, "doc_id long, text string, quality int, toxic int").cache()


def test_fold():
    assert toxicity.fold("M0R0N, idi\u0456ot 1d1ot!! cl@ss \uff26ull") == " moron idiiot idiot ciass fuii "
    assert toxicity.fold(None) == toxicity.fold("") == "  "


def test_toxicity_learns_words_and_stems(spark):
    df = labelled(spark)
    lexicon = toxicity.fit_lexicon(df.select("doc_id", "text"), df.select("doc_id", "toxic"))
    got = toxicity.score_toxicity(df, lexicon).join(df.select("doc_id", "toxic"), "doc_id").collect()
    assert all(r.predicted == r.toxic for r in got)
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 4 == 2) for r in got)
    new = spark.createDataFrame([(1, "so n4sty a thing"), (2, "grumbozz again"), (3, None), (4, ""), (5, "worthy words"), (5, "worthy words"), (None, "nasty " * 20000)], "doc_id long, text string").withColumn("score", F.lit("x"))
    assert sorted((r.doc_id or 0, r.predicted) for r in toxicity.score_toxicity(new, lexicon).collect()) == [(0, 1), (1, 1), (2, 1), (3, 0), (4, 0), (5, 0), (5, 0)]
    assert toxicity.score_toxicity(new.limit(0), lexicon).count() == 0


def test_exceptions_excuse():
    lexicon = toxicity.Lexicon({" trash ": 5.0}, (" trash can ",), 1.0, 0.0)
    a = lexicon.automaton()
    assert toxicity.weigh(toxicity.fold("a trash can here"), a) == 0 and toxicity.weigh(toxicity.fold("trash talk"), a) > 0


def test_no_labels(spark):
    df = labelled(spark, 10)
    none = df.limit(0)
    lexicon = toxicity.fit_lexicon(df, none.select("doc_id", "toxic"))
    assert {r.predicted for r in toxicity.score_toxicity(df, lexicon).collect()} == {0}
    forest = quality.fit_quality(df, none.select("doc_id", "quality"))
    assert {r.score for r in quality.score_quality(df, forest).collect()} == {0.5}


def test_labels_held_out_have_no_effect(spark):
    df = labelled(spark)
    flipped = df.withColumn("quality", F.when(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4 == 2, 1 - F.col("quality")).otherwise(F.col("quality")))
    a, b = (quality.fit_quality(df, x.select("doc_id", "quality")) for x in (df, flipped))
    assert (a.leaf == b.leaf).all() and (a.bound == b.bound).all()


def test_quality_held_out_accuracy(spark):
    docs, labels = spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/labels.parquet")
    forest = quality.fit_quality(docs, labels)
    got = quality.score_quality(docs, forest).where("held_out").join(labels, "doc_id").collect()
    assert sum(r.predicted == r.quality for r in got) / len(got) > 0.95
    odd = spark.createDataFrame([(1, None), (2, ""), (3, "a " * 50000), (None, "x"), (3, "y")], "doc_id long, text string").withColumn("held_out", F.lit(1))
    assert all(0 <= r.score <= 1 for r in quality.score_quality(odd, forest).collect())
    assert quality.keep_good(odd, forest).columns == odd.columns


def test_forest_equals_slow_traversal():
    rng = np.random.default_rng(3)
    x = rng.standard_normal((500, 4))
    y = ((x[:, 0] > 0.3) ^ (x[:, 1] > 0)).astype(int)
    f = boosting.fit(x, y, trees=20)

    def slow(row):
        total = f.base
        for feature, bound, leaf in zip(f.feature, f.bound, f.leaf, strict=True):
            n = 0
            while n < len(feature):
                n = 2 * n + 1 + int(row[feature[n]] > bound[n])
            total += leaf[n - len(feature)]
        return total

    assert np.allclose(f.margin(x), [slow(r) for r in x])
    assert ((f.score(x) > 0.5) == y).mean() > 0.9


def items_of(rng, n=6, size=30):
    return [(i, " ".join(f"b{rng.integers(300)}" for _ in range(size))) for i in range(n)]


def test_decontamination_finds_what_is_planted_and_nothing_else(spark):
    rng = np.random.default_rng(4)
    items = items_of(rng)
    docs, want = [], set()
    for d in range(200):
        words = [f"b{rng.integers(300)}" if rng.random() < 0.5 else f"x{rng.integers(5000)}" for _ in range(150)]
        if d % 4 == 0:
            i = d // 4 % 6
            part = items[i][1].split()
            for k in rng.choice(len(part), d % 3, replace=False):
                part[k] = "other"
            at = rng.integers(0, 120)
            words[at:at] = [p.upper() + "," for p in part]
            want.add((d, i))
        docs.append((d, " ".join(words)))
    df = spark.createDataFrame(docs, "doc_id long, text string").withColumn("at", F.lit("x"))
    table = spark.createDataFrame([*items, (7, None), (8, ""), (9, "too short"), (None, "b1 b2 b3 b4 b5 b6 b7 b8")], "item_id long, text string")
    got = {(r.doc_id, r.item_id) for r in decontam.find_leaks(df, table).collect()}
    assert got == want
    kept = {r.doc_id for r in decontam.without_leaks(df, table).collect()}
    assert kept == {d for d, _ in docs} - {d for d, _ in want}
    odd = spark.createDataFrame([(1, None), (2, ""), (3, items[0][1]), (3, items[0][1]), (None, items[1][1])], "doc_id long, text string")
    assert sorted((r.doc_id or 0, r.item_id) for r in decontam.find_leaks(odd, table).collect()) == [(0, 1), (3, 0), (3, 0)]
    assert decontam.find_leaks(odd, table.limit(0)).count() == 0 and decontam.find_leaks(odd.limit(0), table).count() == 0


def test_part_of_a_long_item(spark):
    rng = np.random.default_rng(5)
    items = items_of(rng, 2, 60)
    part = " ".join(items[1][1].split()[20:42])
    df = spark.createDataFrame([(1, f"start here {part} and end"), (2, " ".join(items[1][1].split()[20:30]))], "doc_id long, text string")
    got = decontam.find_leaks(df, spark.createDataFrame(items, "item_id long, text string")).collect()
    assert [(r.doc_id, r.item_id, r.at, r.matched, r.words) for r in got] == [(1, 1, 2, 20, 20)]


def test_rake_meets_marginals():
    rng = np.random.default_rng(6)
    tokens = rng.integers(100, 1000, 60).astype(float)
    codes = [np.arange(60) % 3, np.arange(60) // 3 % 4, np.arange(60) // 12]
    goals = [np.array([0.5, 0.3, 0.2]), np.full(4, 0.25), np.array([0.3, 0.1, 0.2, 0.2, 0.2])]
    goals = [g * 0.3 * tokens.sum() for g in goals]
    p = mixing.rake(tokens, codes, goals, 1000, 1e-12)
    assert (p <= 1).all() and (p >= 0).all()
    for code, goal in zip(codes, goals, strict=True):
        assert np.bincount(code, tokens * p) == pytest.approx(goal, rel=1e-6)


def test_sample_by_hash(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    mix = mixing.Mix(0.4, targets={"lang": {"en": 0.25, "de": 0.25, "fr": 0.25, "es": 0.25}})
    got = mixing.sample(docs, mix)
    again = mixing.sample(docs.repartition(7), mix)
    assert sorted(r.doc_id for r in got.collect()) == sorted(r.doc_id for r in again.collect())
    assert got.columns == [*docs.columns, "mix"]
    by_lang = {r.lang: r.t for r in got.groupBy("lang").agg(F.sum(F.col("mix.tokens")).alias("t")).collect()}
    total = sum(by_lang.values())
    assert all(abs(t / total - 0.25) < 0.1 for t in by_lang.values())
    odd = spark.createDataFrame([(None, None, None, None, None), (1, "", "en", "s", 0), (2, "a b", "en", "s", 3), (2, "a b", "en", "s", 3)], "doc_id long, text string, lang string, source string, n_chars long")
    rows = mixing.sample(odd, mixing.Mix(1.0)).collect()
    assert sorted(r.mix.tokens for r in rows if r.doc_id == 2) in ([], [2, 2])
    assert mixing.sample(odd.limit(0)).count() == 0


def plain_leaks(docs, items, window=20, similarity=0.8):
    """All alignments of all items with all texts."""
    out = set()
    for d, text in docs:
        own = decontam.tokens((text or "").encode())
        for k, item in items:
            words = decontam.tokens((item or "").encode())
            run = min(window, len(words))
            if run and any(
                sum(words[i + x] == own[j + x] for x in range(run)) >= similarity * run - 1e-9 for i in range(len(words) - run + 1) for j in range(len(own) - run + 1)
            ):
                out.add((d, k))
    return out


def test_decontamination_against_all_alignments(spark, monkeypatch):
    rng = np.random.default_rng(11)
    words = [f"w{i}" for i in range(200)]
    items = [(k, " ".join(rng.choice(words, n))) for k, n in enumerate([*range(1, 26), 40, 60])] + [(90, "the the the the the the the"), (91, "what is the capital of france")]
    docs = []
    for d in range(400):
        item = items[rng.integers(len(items))][1].split()
        for at in rng.choice(len(item), rng.integers(0, 1 + max(1, len(item) // 4)), replace=False):
            item[at] = "zz"
        lo = rng.integers(0, 3)
        docs.append((d, " ".join([*rng.choice(words, rng.integers(0, 9)), *item[lo if len(item) > 20 else 0 :], *rng.choice(words, rng.integers(0, 9))])))
    docs += [(900, "the " * 50), (901, "And what is the capital of France?"), (902, None), (903, "")]
    df = spark.createDataFrame(docs, "doc_id long, text string")
    table = spark.createDataFrame([*items, (95, None), (96, "")], "item_id long, text string")
    expected = plain_leaks(docs, items)
    assert {(r.doc_id, r.item_id) for r in decontam.find_leaks(df, table).collect()} == expected
    monkeypatch.setattr(decontam, "BLOCK_BYTES", 700)  # several blocks of items
    assert {(r.doc_id, r.item_id) for r in decontam.find_leaks(df, table).collect()} == expected
    assert {r.doc_id for r in decontam.without_leaks(df, table).collect()} == {d for d, _ in docs} - {d for d, _ in expected}


def test_one_word_repeated_many_times():
    found = decontam.Seeds([(1, b"buy " * 30), (2, b"buy " * 6)], decontam.Rule()).hits([b"buy " * 200_000])
    assert found == [[(1, 0, 20, 20), (2, 0, 6, 6)]]


def test_raking_by_joins_is_the_same(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    cells = docs.groupBy("source", "lang").agg(F.sum("n_chars").alias("tokens")).selectExpr("source", "lang", "substr(source, 1, 1) AS topic", "tokens")
    mix = mixing.Mix(rounds=6)
    one, few = mixing.probabilities(cells, mix)
    other, some = mixing.probabilities(cells, mix, most=1)
    assert few and not some
    a, b = ({(r.source, r.lang, r.topic): r.probability for r in x.collect()} for x in (one, other))
    assert a.keys() == b.keys() and all(abs(a[k] - b[k]) < 1e-9 for k in a)


def test_columns_that_clash_are_replaced(spark):
    from tupleshare.llm import line_dedup

    docs = spark.createDataFrame([(1, "a b\na b", "s", "en", 5, 6)], "doc_id long, text string, source string, lang string, mix int, Deduped int")
    assert mixing.sample(docs, mixing.Mix(share=1.0)).select("mix.topic").count() <= 1
    assert line_dedup.dedup_lines(docs, line_dedup.EVERY_LINE).select("deduped.text").first()[0] == "a b"


def plain_weight(folded, lexicon):
    """Every term at every place, and every phrase (the blank that ends it begins the next word), without an automaton."""
    excused = [(i, i + len(e) - 1) for e in lexicon.exceptions for i in range(len(folded)) if folded.startswith(e, i)]
    total = 0.0
    for i in range(len(folded)):
        here = [w for t, w in lexicon.terms.items() if t not in lexicon.exceptions and folded.startswith(t, i)]
        if here and not any(a <= i < b for a, b in excused):
            total += max(max(here), 0.0)
    return total / (1 + len(folded) / 1000) ** 0.5


def test_weights_against_a_plain_matcher():
    rng = np.random.default_rng(4)
    parts = ["bad", "badly", "ba", "trash", "trash can", "clown", "class clown", "good", "b4d", "fine", "sand"]
    lexicon = toxicity.Lexicon({" bad": 2.0, " bad ": 2.5, " trash": 1.5, " clown ": 1.0, " ba": 0.4}, tuple(map(toxicity.fold, ("trash can", "class clown"))), 1.0, 0.0)
    for _ in range(300):
        folded = toxicity.fold(" ".join(rng.choice(parts, rng.integers(0, 12))))
        assert toxicity.weigh(folded, lexicon.automaton()) == pytest.approx(plain_weight(folded, lexicon))
