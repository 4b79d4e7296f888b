"""Lines of one to four words in line dedup."""

import numpy as np
import pytest

from tests.llm.test_line_dedup import plain_removed
from tupleshare.llm import line_dedup as ld
from tupleshare.llm import queries


def short_docs(rng, n, vocabulary):
    line = lambda: " ".join(f"w{i}" for i in rng.integers(0, vocabulary, rng.integers(1, 8)))
    return [(d, "\n".join(line() for _ in range(rng.integers(0, 6)))) for d in range(n)]


@pytest.mark.parametrize("alone, paired, vocabulary", [(400, 20000, 12), (3, 10, 12), (1, 2, 9), (2, 4000, 9)])
def test_equals_brute_force(spark, alone, paired, vocabulary):
    rows = short_docs(np.random.default_rng(vocabulary + alone), 150, vocabulary)
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    got = {(r.doc, r.line) for r in ld.later_matches(df, ld.LineRule(least=1, alone=alone, paired=paired)).collect()}
    assert got == plain_removed(rows, least=1)


def test_query_drops_short_repeats(spark, tmp_path):
    rows = [(1, "All rights reserved.\nsee\na b c d"), (2, "all rights reserved.\n\nnew"), (3, "d c b a e\nsee\nsee also\n")]
    spark.createDataFrame(rows, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = sorted(tuple(r) for r in queries.op8_line_dedup(spark, str(tmp_path)).collect())
    assert got == [(1, rows[0][1], 0), (2, "\nnew", 1), (3, "see also\n", 2)]
