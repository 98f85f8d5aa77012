import zlib
from collections import Counter

import numpy as np
from pyspark.sql import functions as F

from cadenza.llm import language, linear, quality, queries
from cadenza.llm.common import table
from cadenza.llm.words import word_list


def test_held_out_languages(spark, sf):
    docs = {r.doc_id: r for r in table(spark, sf, "documents").collect()}
    got = queries.op5_language(spark, sf).collect()
    assert len(got) == len(docs)
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 3 == 1) and 0 <= r.score <= 1 for r in got)
    held = [r for r in got if r.held_out]
    assert np.mean([r.lang_pred == docs[r.doc_id].lang for r in held]) > 0.98


def test_viterbi_equals_brute_force():
    rng = np.random.default_rng(1)
    from itertools import product

    seqs = [rng.normal(size=(n, 3)) * 3 for n in (1, 4, 6, 6)] + [np.zeros((0, 3))]
    for s, label in zip(seqs, language.viterbi(seqs, 2.0, room=20)):
        cost = lambda path: sum(s[t, x] for t, x in enumerate(path)) - 2.0 * sum(a != b for a, b in zip(path, path[1:]))
        if len(s):
            assert np.isclose(cost(label), max(map(cost, product(range(3), repeat=len(s)))))
        else:
            assert len(label) == 0


def test_viterbi_in_stretches_equals_one_pass():
    rng = np.random.default_rng(4)
    seqs = [rng.normal(size=(n, 4)) * 3 for n in (300, 1, 77, 78, 2)]
    whole = language.viterbi(seqs, 2.0)
    for room in (1, 4, 29, 400, 3000):
        assert all((a == b).all() for a, b in zip(whole, language.viterbi(seqs, 2.0, room=room)))


def test_grams_are_of_the_word_alone():
    words = ["a", "ab", "wörd", "日本", "abcdefgh" * 40, "abc"]
    places, starts = language.grams(words, 1 << 20)
    for w, at, end in zip(words, starts, [*starts[1:], len(places)]):
        own, _ = language.grams([w], 1 << 20)
        n = len(w.encode()) + 2
        assert (places[at:end] == own).all() and len(own) == n
        assert [(own[:, k] < 1 << 20).sum() for k in (0, 1, 2)] == [n - 2, max(0, n - 3), int(n > 4)]
    assert len({tuple(x) for x in language.grams(["abcx", "bcxa", "cxab"], 1 << 20)[0]}) > 9


def test_query_equals_brute_force(spark, sf_small):
    """Word by word, in dictionaries; labels by the full table of transitions."""
    rows = table(spark, sf_small, "documents").collect()
    words = lambda text: language._WORD.findall((text or "").lower())
    of = lambda w: [b for b in language.grams([w], language.BUCKETS)[0].ravel().tolist() if b < language.BUCKETS]
    learned = [r for r in rows if zlib.crc32(str(r.doc_id).encode()) % 3 != 1 and r.lang is not None and r.text is not None]
    langs = sorted({r.lang for r in learned})
    counts, script = {x: Counter() for x in langs}, {x: Counter() for x in langs}
    known = {w: (of(w), int(language.scripts_of([language.first_letter(w)])[0])) for r in rows for w in set(words(r.text)) if language.first_letter(w)}
    for r in learned:
        for w in filter(known.__contains__, words(r.text)):
            counts[r.lang].update(known[w][0])
            script[r.lang][known[w][1]] += 1
    total = {x: sum(c.values()) + 0.5 * language.BUCKETS for x, c in counts.items()}

    def score(w, x):
        if w not in known:
            return 0.0
        grams, s = known[w]
        uses = lambda y: script[y][s] >= language.SCRIPT_SHARE * max(sum(script[y].values()), 1)
        return sum(np.log((counts[x][g] + 0.5) / total[x]) for g in grams) / 2 if uses(x) or not any(map(uses, langs)) else -1e4

    got = {r.doc_id: r for r in queries.op5_language(spark, sf_small).collect()}
    assert len(got) == len(rows)
    for r in rows:
        ws, value, back = words(r.text), [0.0] * len(langs), []
        for w in ws:
            come = [max(range(len(langs)), key=lambda y: value[y] - language.SWITCH_PENALTY * (x != y)) for x in range(len(langs))] if back else list(range(len(langs)))
            value = [value[come[x]] - language.SWITCH_PENALTY * (x != come[x]) + score(w, langs[x]) for x in range(len(langs))]
            back.append(come)
        letters, x = Counter(), max(range(len(langs)), key=value.__getitem__)
        for w, come in zip(reversed(ws), reversed(back)):
            letters[langs[x]] += len(w) * (w in known)
            x = come[x]
        if not sum(letters.values()):
            assert (got[r.doc_id].lang_pred, got[r.doc_id].score) == ("und", 0.0)
            continue
        assert got[r.doc_id].lang_pred == max(langs, key=lambda x: letters[x])
        assert abs(got[r.doc_id].score - max(letters.values()) / sum(letters.values())) < 1e-9


def test_rare_languages_are_not_learned_and_nothing_breaks(spark):
    docs = spark.createDataFrame([(i, f"text number {i} of many", f"l{i % 5}") for i in range(23)], "doc_id long, text string, lang string")
    assert language.train(docs, most_languages=3).languages == ["l0", "l1", "l2"]


def test_spans_scripts_and_edges(spark):
    en = "the cat sat on the mat and the dog ran over the hill with all of them "
    ru = "мама мыла раму и потом они все пошли гулять в большой старый парк "
    de = "der hund und die katze sind nicht auf dem tisch sondern unter der bank "
    docs = spark.createDataFrame([(1, en * 3, "en"), (2, ru * 3, "ru"), (3, de * 3, "de"), (4, None, "en"), (5, en, None)], "doc_id long, text string, lang string")
    model = language.train(docs)
    assert model.languages == ["de", "en", "ru"]
    mixed = "🙂 " + en * 2 + de * 3 + "парк " + de
    rows = [(1, mixed, "x"), (2, None, "x"), (3, "", "x"), (4, "123 !? ½", "x"), (None, "парк", "x"), (6, "日本", "x"), (6, "日本", "x"), (7, "a" * 100_000, "x")]
    got = language.identify(spark.createDataFrame(rows, "doc_id long, text string, score string"), model).collect()
    by = {r.doc_id: r for r in got}
    assert len(got) == len(rows) and [by[i].lang_pred for i in (2, 3, 4)] == ["und"] * 3
    assert by[None].lang_pred == "ru" and by[6].lang_pred in model.languages
    spans = by[1].spans
    assert [s.lang for s in spans][:2] == ["en", "de"] and by[1].lang_pred == "de"
    assert mixed[spans[0].start :].startswith("the cat") and mixed[spans[1].start :].startswith("der hund")
    # a script of its own allows no other language, whatever the penalty
    assert mixed[spans[2].start : spans[2].end] == "парк" and spans[2].lang == "ru"
    assert language.identify(docs.limit(0), model).count() == 0
    none = language.identify(docs, language.train(docs.limit(0))).collect()
    assert {r.lang_pred for r in none} == {"und"}


def test_label_model_finds_accuracies():
    rng = np.random.default_rng(0)
    y = rng.random(20_000) < 0.8
    rates = [(0.9, 0.7), (0.8, 0.8), (0.7, 0.6), (0.85, 0.9)]  # right when it votes, part of texts it votes on
    v = np.stack([np.where(rng.random(len(y)) < cover, np.where(rng.random(len(y)) < acc, y, ~y), quality.ABSTAIN) for acc, cover in rates], axis=1).astype(int)
    patterns, counts = np.unique(v, axis=0, return_counts=True)
    model = quality.expectation_maximisation(patterns, counts.astype(float))
    assert abs(model.prior - 0.8) < 0.05
    assert np.allclose(model.accuracy(), [a for a, _ in rates], atol=0.05)


def test_quality_agrees_with_gold_labels_it_never_saw(spark, sf):
    got = queries.op10_quality(spark, sf)
    assert got.count() == 1000
    judged = got.select("doc_id", "good", F.col("quality").alias("p")).join(table(spark, sf, "labels"), "doc_id").collect()
    assert np.mean([r.good for r in judged if r.quality == 1]) > 0.97
    assert np.mean([r.good for r in judged if r.quality == 0]) < 0.1


def test_quality_edges(spark, sf_small):
    scorer = quality.train(table(spark, sf_small, "documents"))
    rows = [(1, None, "x"), (2, "", "x"), (3, "!!!", "x"), (None, "spam " * 500, "x"), (4, "spam " * 500, "x"), (4, "spam " * 500, "x")]
    df = spark.createDataFrame(rows, "doc_id long, text string, quality string")
    got = quality.score(df, scorer).collect()
    assert len(got) == 6 and not any(r.good for r in got)
    assert all(r.quality == 0 == r.weak_label for r in got if r.doc_id in (1, 2, 3))
    assert quality.score(df.limit(0), scorer).count() == 0
    assert quality.score(df, quality.train(df.limit(0))).count() == 6


def test_quality_query_equals_brute_force(spark, sf_small):
    """Text by text, from the label model's rates and the scorer's weights."""
    docs = table(spark, sf_small, "documents")
    scorer = quality.train(docs)
    known = linear.Chosen(scorer.buckets)
    rows = docs.collect()
    texts = {r.doc_id: (r.text or "").encode() for r in rows}
    # the label model: maximum likelihood over all worded texts, from counted patterns
    worded = [t for t in texts.values() if word_list(t)]
    patterns = Counter(tuple(quality.votes(quality.measures(t))) for t in worded)
    again = quality.expectation_maximisation(np.array(sorted(patterns)), np.array([float(patterns[p]) for p in sorted(patterns)]))
    assert np.isclose(again.prior, scorer.labels.prior, atol=1e-6) and np.allclose(again.on_good, scorer.labels.on_good, atol=1e-5)
    for r in quality.score(docs, scorer).collect():
        t = texts[r.doc_id]
        if not word_list(t):
            assert (r.weak_label, r.quality, r.good) == (0.0, 0.0, False)
            continue
        style = quality.measures(t)
        odds = np.log(scorer.labels.prior / (1 - scorer.labels.prior)) + sum(np.log(g[v] / b[v]) for g, b, v in zip(scorer.labels.on_good, scorer.labels.on_bad, quality.votes(style)))
        assert np.isclose(r.weak_label, 1 / (1 + np.exp(-np.clip(odds, -50, 50))))
        z = scorer.model.bias + sum(scorer.model.sparse[i] for i in known.row(t)) + sum(scorer.model.sparse[i] for i in quality.style_features(style, len(scorer.buckets)))
        assert np.isclose(r.quality, 1 / (1 + np.exp(-np.clip(z, -30, 30)))) and r.good == (r.quality >= 0.5)


def test_quality_of_long_texts_repeats_and_no_rows(spark):
    rows = [(1, "word " * 300_000, "x"), (1, "word " * 300_000, "x"), (None, "a b c", "x"), (2, None, None), (3, "", "x")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, quality string")
    got = quality.score(docs, quality.train(docs)).collect()
    assert len(got) == 5 and len({r.quality for r in got if r.doc_id == 1}) == 1
    assert quality.score(docs.limit(0), quality.train(docs.limit(0))).count() == 0
