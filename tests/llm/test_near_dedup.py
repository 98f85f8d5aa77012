import random

import numpy as np

from cadenza.llm import near_dedup, queries
from cadenza.llm.words import shingle_units, weighted_jaccard, word_list


def test_signatures_estimate_weighted_jaccard():
    rng = random.Random(1)
    a = [b"%d" % rng.randrange(40) for _ in range(400)]
    b = a[:300] + [b"%d" % rng.randrange(40) for _ in range(100)]
    ua, ub = shingle_units(a, 1), shingle_units(b, 1)
    s = near_dedup.signatures([ua, ub], 2000)
    assert abs((s[0] == s[1]).mean() - weighted_jaccard(ua, ub)) < 0.04
    # a signature doesn't depend on what else is in the batch
    assert (near_dedup.signatures([ub], 2000)[0] == s[1]).all()
    # one unit fills all coordinates
    assert (near_dedup.signatures([ua[:1]], 50) != 0).all()


def test_weighted_jaccard_is_of_multisets():
    u = lambda s: shingle_units(s.encode().split(), 1)
    assert weighted_jaccard(u("a a a b"), u("a b b c")) == 2 / 6
    assert weighted_jaccard(u(""), u("")) == 0


def brute(docs):
    """Class by root over rows; None stands alone."""
    units = [shingle_units(word_list((t or "").encode())) for _, t in docs]
    root = list(range(len(docs)))

    def top(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(docs)):
        for j in range(i):
            if len(units[i]) and weighted_jaccard(units[i], units[j]) >= 0.8:
                root[top(i)] = top(j)
    low = {}
    for i, (d, _) in enumerate(docs):
        if len(units[i]) and d is not None:
            low[top(i)] = min(d, low.get(top(i), d))
    return [low.get(top(i)) if len(units[i]) else d for i, (d, _) in enumerate(docs)]


def varied(seed=5, n=60):
    rng = random.Random(seed)
    word = lambda: f"w{rng.randrange(2000)}"
    docs = []
    for _ in range(n):
        base = [word() for _ in range(rng.choice([1, 3, 8, 60, 200]))]
        for _ in range(rng.choice([1, 1, 2, 6])):
            docs.append((len(docs), " ".join(base)))
            base = list(base)
            for _ in range(rng.randrange(3)):
                base[rng.randrange(len(base))] = word()
    return docs


def test_equals_brute_force(spark):
    docs = varied() + [(900, None), (901, ""), (902, "?!"), (903, None), (None, "w1 w2 w3 w4 w5 w6"), (904, "w1 W2, w3 w4 w5 w6."), (905, "same"), (905, "same"), (None, None)]
    df = spark.createDataFrame([(*d, "x") for d in docs], "doc_id long, text string, root string")
    got = near_dedup.near_duplicates(df).select("doc_id", "class_id").collect()
    want = [(d, c) for (d, _), c in zip(docs, brute(docs))]
    assert sorted(map(repr, map(tuple, got))) == sorted(map(repr, want))
    kept = near_dedup.keep_one(df).collect()
    ids = sorted(r.doc_id for r in kept if r.doc_id is not None)
    assert ids == sorted({c for (d, _), c in zip(docs, brute(docs)) if c is not None} )
    assert len(kept) == len(ids) + 1
    assert near_dedup.near_duplicates(df.limit(0)).count() == 0


def test_chains_and_mixed_buckets(spark):
    """A leader that differs from a pair in its bucket must not part the pair; a chain is one class."""
    rng = random.Random(2)
    base = [f"v{i}" for i in range(300)]
    docs, step = [], list(base)
    for i in range(8):
        docs.append((i, " ".join(step)))
        step = step[9:] + [f"n{i}x{j}" for j in range(9)]
    rng.shuffle(docs)
    df = spark.createDataFrame(docs, "doc_id long, text string")
    want = dict(zip([d for d, _ in docs], brute(docs)))
    for block in (512, 2):
        got = near_dedup.near_duplicates(df, bands=30, band_rows=2, block=block).collect()
        assert {r.doc_id: r.class_id for r in got} == want


def test_query_equals_brute_force_on_small_table(spark, sf_small):
    docs = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf_small}/documents.parquet").collect()]
    got = {r.doc_id: r.class_id for r in queries.op6_near_duplicates(spark, sf_small).collect()}
    assert got == dict(zip([d for d, _ in docs], brute(docs)))
    assert np.mean([d != c for d, c in got.items()]) > 0
