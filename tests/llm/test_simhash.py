import numpy as np
import xxhash

from tupleshare.llm import simhash
from tupleshare.llm.components import components


def plain_fingerprint(text):
    words = "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "").encode().split()
    if not words:
        return 0
    shingles = [b" ".join(words[i : i + 3]) for i in range(len(words) - 2)] or [b" ".join(words)]
    hashes = [xxhash.xxh64(s, seed=42).intdigest() for s in shingles]
    return sum(1 << k for k in range(64) if 2 * sum(h >> k & 1 for h in hashes) > len(hashes))


def plain_components(fps):
    root = list(range(len(fps)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(fps)):
        for j in range(i):
            if (fps[i] ^ fps[j]).bit_count() <= 2:
                root[find(i)] = find(j)
    return [find(i) for i in range(len(fps))]


def test_fingerprint_matches_plain():
    for t in [None, "", " \n\t", "One", "one two", "A b c", "É x y z É", "the THE the the the", "w " * 5000, "a b c d e f g"]:
        assert simhash.fingerprint(None if t is None else t.encode()) == plain_fingerprint(t)


def clusters(rng, n=60, size=30):
    base = rng.integers(0, 2**64, n, dtype=np.uint64)
    out = [base]
    for b in base:
        walk = b
        for _ in range(rng.integers(0, size)):
            walk ^= np.uint64(sum(1 << int(k) for k in rng.choice(64, rng.integers(1, 4), replace=False)))
            out.append(np.array([walk]))
    return np.unique(np.concatenate(out))


def same_partition(a, b):
    return len(set(zip(a, b, strict=True))) == len(set(a)) == len(set(b))


def test_links_connect_what_brute_force_connects(spark):
    fps = clusters(np.random.default_rng(3))
    df = spark.createDataFrame([(int(x),) for x in fps.view(np.int64)], "fp long").repartition(5)
    label = {r.node: r.label for r in components(simhash.fingerprint_links(df)).collect()}
    got = [label.get(int(x), int(x)) for x in fps.view(np.int64)]
    assert same_partition(got, plain_components([int(x) for x in fps]))


def test_large_cell_by_flips_equals_pairs(monkeypatch):
    fps = clusters(np.random.default_rng(5), 3, 60)
    pivots = simhash.PivotTables()
    pairs = simhash.cell_links(fps, pivots)
    monkeypatch.setattr(simhash, "TOGETHER", 4)
    flips = simhash.cell_links(fps, pivots)
    assert sorted(zip(*pairs, strict=True)) == sorted(zip(*flips, strict=True))


def test_cells_across_batches():
    meet = simhash._meet(simhash.PivotTables())
    import pandas as pd

    frames = [pd.DataFrame({"cell": c, "fp": f}) for c, f in [([1, 2, 2], [5, 8, 9]), ([2, 2], [10, 11]), ([2, 3], [12, 7]), ([4], [1]), ([4], [3])]]
    out = pd.concat(meet(iter(frames)))
    assert sorted(map(tuple, out.values.tolist())) == [(3, 1), (9, 8), (10, 8), (11, 8), (12, 8)]


def test_near_duplicates_edges(spark):
    rows = [(5, "the cat sat on the mat"), (3, "The CAT sat on the mat"), (None, "the cat sat on the mat"), (9, None), (7, ""), (8, "other words entirely here now"), (8, "other words entirely here now")]
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "'x' AS fp", "1 AS label", "2 AS first")
    got = sorted(((r.doc_id, r.fingerprint, r.component_id) for r in simhash.near_duplicates(df).collect()), key=repr)
    hexes = {t: f"{plain_fingerprint(t):016x}" for _, t in rows}
    assert got == sorted(((d, hexes[t], 3 if t and "mat" in t else 7 if not t else 8) for d, t in rows), key=repr)
    assert simhash.near_duplicates(df.limit(0)).count() == 0
