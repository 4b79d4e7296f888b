import math

import numpy as np
import pytest

from tupleshare.llm import line_dedup as ld


def low(text):
    return "".join(c.lower() if "A" <= c <= "Z" else c for c in text)


def plain_removed(rows, threshold=0.8, least=5):
    """(id, line number) of lines with an earlier match."""
    lines = []
    for doc, text in rows:
        if doc is None or text is None:
            continue
        for k, line in enumerate(text.split("\n")):
            s = frozenset(low(line).encode().split())
            if len(s) >= least:
                lines.append((doc, k, s))
    out = set()
    for d, k, s in lines:
        for e, m, o in lines:
            if (e, m) < (d, k) and min(len(s), len(o)) >= threshold * max(len(s), len(o)) - 1e-9 and len(s & o) >= threshold * len(s | o) - 1e-9:
                out.add((d, k))
                break
    return out


def random_docs(rng, n, vocabulary=400, copies=0.3):
    words = [f"w{i}" for i in range(vocabulary)]
    weights = 1 / np.arange(1, vocabulary + 1)
    weights /= weights.sum()
    pool, docs = [], []
    for d in range(n):
        lines = []
        for _ in range(rng.integers(0, 6)):
            if pool and rng.random() < copies:
                line = pool[rng.integers(len(pool))].split()
                for _ in range(rng.integers(0, 4)):
                    line[rng.integers(len(line))] = words[rng.integers(vocabulary)]
                line = " ".join(line)
            else:
                line = " ".join(rng.choice(words, rng.integers(1, 40), p=weights))
                pool.append(line)
            lines.append(line)
        docs.append((d, "\n".join(lines)))
    return docs


@pytest.mark.parametrize("seed, alone, paired, first", [(1, 400, 20000, 16), (2, 3, 10, 16), (3, 2, 4, 1), (4, 1, 2, 2)])
def test_equals_brute_force(spark, seed, alone, paired, first):
    rows = random_docs(np.random.default_rng(seed), 150, 60 if seed == 4 else 400)
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    got = {(r.doc, r.line) for r in ld.later_matches(df, ld.LineRule(alone=alone, paired=paired, first=first, first_of_part=first)).collect()}
    assert got == plain_removed(rows)


def test_dedup_edges(spark):
    line, near = "one two three four five six seven eight nine ten", "ONE two three four five six seven eight nine other"
    rows = [
        (4, f"{line}\nshort\n\n{near}\nshort"), (2, line), (None, line), (7, None), (8, ""), (9, f"x\n{line}"), (9, f"{line}\ny"), (9, f"x\n{line}"),
        (11, "a b c d\na b c d"), (12, f"{line} eleven twelve thirteen"), (13, line),
    ]
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "'k' AS key", "5 AS line", "'d' AS doc", "'t' AS words")
    got = sorted(((r.doc_id, r.deduped.text, r.deduped.n_removed, r.key) for r in ld.dedup_lines(df).collect()), key=repr)
    want = [
        (4, "short\n\nshort", 2, "k"), (2, line, 0, "k"), (None, line, 0, "k"), (7, None, 0, "k"), (8, "", 0, "k"), (9, "x", 1, "k"), (9, "y", 1, "k"), (9, "x", 1, "k"),
        (11, "a b c d\na b c d", 0, "k"), (12, f"{line} eleven twelve thirteen", 0, "k"), (13, "", 1, "k"),
    ]
    assert got == sorted(want, key=repr)
    assert ld.dedup_lines(df.limit(0)).count() == 0


def test_shuffled_sides(spark, monkeypatch):
    monkeypatch.setattr(ld, "BROADCAST_ROWS", 0)
    rows = random_docs(np.random.default_rng(9), 80)
    df = spark.createDataFrame(rows, "doc_id long, text string")
    gone = plain_removed(rows)
    got = {r.doc_id: r.deduped.text for r in ld.dedup_lines(df).collect()}
    assert got == {d: "\n".join(x for k, x in enumerate(t.split("\n")) if (d, k) not in gone) for d, t in rows}


def test_prefix_of_small_sets():
    for n in range(5, 60):
        assert n - math.ceil(0.8 * n) + 3 <= n


def test_tasks_hold_little_at_once():
    """Hashing a block and joining a part take little more memory than their input; hashes don't depend on the stretches."""
    import tracemalloc

    import numpy as np

    from tupleshare.llm import line_dedup as ld

    def peak(work):
        tracemalloc.start()
        work()
        most = tracemalloc.get_traced_memory()[1]
        tracemalloc.stop()
        return most

    text = b"lorem ipsum dolor sit amet\n" * 40_000
    assert peak(lambda: ld.Hasher().words(text)) < 12 * len(text)
    starts, h = ld.Hasher().words(text)
    assert len(starts) == 200_000 and len(set(h.tolist())) == 5 and (np.diff(starts) > 0).all()
    p = np.zeros(200_000, ld.POSTING)
    p["sig"], p["key"], p["n"] = np.arange(len(p)) // 2, np.arange(len(p)), 5
    assert peak(lambda: ld.join_postings(p, 0.8, 4)) < 3.9 * p.nbytes
