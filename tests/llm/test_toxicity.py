import numpy as np
from pyspark.sql import functions as F

from cadenza.llm import linear, queries, toxicity
from cadenza.llm.common import table
from cadenza.llm.words import word_list


def test_fit_separates_and_takes_soft_targets():
    rows = [np.array([0, 2]), np.array([1, 2])] * 20
    y = np.array([1.0, 0.0] * 20)
    m = linear.fit(rows, np.zeros((40, 0)), y, np.ones(40), 3)
    p = m.probability(rows, np.zeros((40, 0)))
    assert (p[::2] > 0.9).all() and (p[1::2] < 0.1).all()
    soft = linear.fit(rows, np.zeros((40, 0)), np.where(y == 1, 0.7, 0.3), np.ones(40), 3, l2=1e-6)
    assert np.allclose(soft.probability(rows, np.zeros((40, 0))), np.where(y == 1, 0.7, 0.3), atol=1e-3)
    assert linear.fit([], np.zeros((0, 1)), np.zeros(0), np.zeros(0), 3).probability([np.array([1])], np.zeros((1, 1)))[0] < 1e-9


def test_chain_feeds_earlier_probabilities():
    """The second category is the first one's; its own features say nothing."""
    rng = np.random.default_rng(0)
    first = rng.random(400) < 0.5
    rows = [np.array([0 if f else 1]) if rng.random() < 0.95 else np.array([2]) for f in first]
    models = toxicity.fit_models(rows, np.column_stack([first, first]).astype(float), np.ones(400), 3)
    assert models[1].dense.shape == (1,) and models[1].dense[0] > 0.5


def test_held_out_accuracy(spark, sf):
    docs, labels = table(spark, sf, "documents"), table(spark, sf, "labels")
    chain = toxicity.train(docs, labels.where("doc_id % 4 <> 0"), queries.TOXICITY_CATEGORIES)
    judged = toxicity.score(docs, chain).join(labels.where("doc_id % 4 = 0"), "doc_id").collect()
    assert sum(r.rejected for r in judged if not r.toxic) <= 0.02 * sum(not r.toxic for r in judged)
    assert sum(r.rejected for r in judged if r.toxic) >= 0.6 * sum(r.toxic for r in judged)


def test_query_rows_and_edges(spark, sf):
    got = queries.op1_toxicity(spark, sf)
    assert got.columns == ["doc_id", "p_unfit", "p_toxic", "toxic"] and got.count() == 1000
    docs, labels = table(spark, sf, "documents"), table(spark, sf, "labels")
    chain = toxicity.train(docs, labels, queries.TOXICITY_CATEGORIES)
    odd = spark.createDataFrame([(1, None, "x"), (2, "", "x"), (None, "you idiot moron scum trash loser clown", "x"), (3, "fine", "x"), (3, "fine", "x")], "doc_id long, text string, rejected string")
    rows = toxicity.score(odd, chain, keep=("rejected",)).collect()
    assert len(rows) == 5 and [r[-1] for r in rows] == ["x"] * 5
    kept = toxicity.keep_clean(odd, chain)
    assert kept.columns == odd.columns and sorted(str(r.doc_id) for r in kept.collect()) == ["1", "2", "3", "3"]
    assert toxicity.score(odd.limit(0), chain).count() == 0
    none = toxicity.train(docs, labels.limit(0), queries.TOXICITY_CATEGORIES)
    assert toxicity.score(docs, none).where("rejected or p_toxic > 1e-6").count() == 0


def test_held_out_rows_have_no_part_in_choosing_what_judges_them(spark):
    """Labels are drawn at random and each is told by a word that its group of rows has alone: in fold, chosen features would know it."""
    rng = np.random.default_rng(2)
    rows = [(i, f"word{i // 4} filler text here", int(rng.random() < 0.5)) for i in range(400)]
    docs = spark.createDataFrame([(i, t) for i, t, _ in rows], "doc_id long, text string")
    seen = docs.withColumn("target", F.when(F.col("doc_id") % 2 == 0, 1.0).otherwise(0.0)).withColumn("fold", (F.col("doc_id") % 4).cast("int"))
    every, *without = linear.choose_by_fold(seen, ["target"], "text", 64, "fold", 4, least=1, significant=0.0)
    for k, chosen in enumerate(without):
        own = linear.choose(seen.where(F.col("fold") != k), ["target"], "text", 64, least=1, significant=0.0)
        assert (chosen == own).all()
    assert (every == linear.choose(seen, ["target"], "text", 64, least=1, significant=0.0)).all()


def test_features_left_out_for_a_fold_have_no_weight_there():
    rows = [np.array([0, 1]), np.array([1])] * 50
    y = np.array([1.0, 0.0] * 50)
    fold = np.repeat(np.arange(4), 25)
    none = [np.array([True, True]), *[np.array([False, True])] * 4]
    told = toxicity.fit_models(rows, np.column_stack([y, y]), np.ones(100), 2, 4, fold)
    blind = toxicity.fit_models(rows, np.column_stack([y, y]), np.ones(100), 2, 4, fold, none)
    # without feature 0 the out-of-fold probabilities say nothing, so the second model has its own features only
    assert abs(blind[1].dense[0]) < 0.2 < told[1].dense[0]


def test_clashing_labels_and_repeated_ids(spark):
    docs = spark.createDataFrame([(i % 40, f"{'bad nasty' if i % 40 < 20 else 'good kind'} text number {i}", "x") for i in range(4000)], "doc_id long, text string, toxic string")
    labels = spark.createDataFrame([(i, 1, 0) for i in range(40)] + [(i, 0, 1) for i in range(20)] + [(None, 1, 0), (5, None, 1)], "doc_id long, quality int, toxic int")
    chain = toxicity.train(docs, labels, queries.TOXICITY_CATEGORIES)
    again = toxicity.train(docs.repartition(7), labels.repartition(5), queries.TOXICITY_CATEGORIES)
    assert (chain.buckets == again.buckets).all() and np.allclose(chain.models[-1].sparse, again.models[-1].sparse)
    got = {r.doc_id: r.rejected for r in toxicity.score(docs, chain).collect()}
    assert all(got[i] == (i < 20) for i in got)


def test_query_equals_brute_force(spark, sf_small):
    """Text by text and feature by feature, from the chain's weights."""
    docs, labels = table(spark, sf_small, "documents"), table(spark, sf_small, "labels")
    chain = toxicity.train(docs, labels, queries.TOXICITY_CATEGORIES)
    place = {int(b): i for i, b in enumerate(chain.buckets)}
    want = {}
    for r in docs.collect():
        words = word_list((r.text or "").encode())
        features = {place[b] for w in words for b in linear.WordFeatures().of(w) if b in place}
        p = []
        for m in chain.models:
            z = m.bias + sum(m.sparse[i] for i in features) + sum(w * x for w, x in zip(m.dense, p))
            p.append(1 / (1 + np.exp(-np.clip(z, -30, 30))))
        want[r.doc_id] = p if words else [0.0, 0.0]
    got = queries.op1_toxicity(spark, sf_small).collect()
    assert len(got) == len(want)
    for r in got:
        assert np.allclose([r.p_unfit, r.p_toxic], want[r.doc_id], atol=1e-9) and r.toxic == (want[r.doc_id][1] >= 0.5)


def test_empty_tables_and_long_texts(spark):
    empty = spark.createDataFrame([], "doc_id long, text string, __id string")
    labels = spark.createDataFrame([(1, 1, 0)], "doc_id long, quality int, toxic int")
    chain = toxicity.train(empty, labels, queries.TOXICITY_CATEGORIES)
    long = spark.createDataFrame([(1, "word " * 300_000, "a"), (2, None, "b")], "doc_id long, text string, extra string")
    assert toxicity.score(long, chain).count() == 2 and toxicity.keep_clean(long, chain).count() == 2
