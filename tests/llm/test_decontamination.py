import random

from cadenza.llm import decontamination, queries
from cadenza.llm.common import table
from tests.llm.oracle import rows, sql_rows


def test_query_equals_sql(spark, sf):
    names, want = sql_rows(queries.oracle_sql()["op2_decontamination"], sf)
    got = queries.op2_decontamination(spark, sf)
    assert sorted(got.columns) == names and rows(got) == want
    assert any(r[names.index("contaminated")] for r in want)


def brute(words, windows):
    hit, items = set(), set()
    for w, item in windows:
        for i in range(len(words) - len(w) + 1):
            if words[i : i + len(w)] == w:
                hit |= set(range(i, i + len(w)))
                items.add(item)
    return len(hit), sorted(items)


def test_both_ways_equal_brute_force(spark):
    rng = random.Random(3)
    text = lambda n: " ".join(rng.choice("ab") for _ in range(n))
    docs = [(i, text(rng.randrange(60))) for i in range(40)] + [(100, None), (101, ""), (102, "!?"), (None, text(30)), (3, text(30)), (3, "a")]
    items = [(i, text(n)) for i, n in enumerate([4, 12, 13, 11, 2])] + [(7, None), (8, "..."), (9, "zzz a b"), (None, "a b"), (10, docs[5][1]), (11, docs[5][1])]
    windows = []
    for item, t in items:
        w = (t or "").replace(".", " ").split()
        if item is not None:
            windows += [(w[i : i + 10], str(item)) for i in range(max(1, len(w) - 9)) if w]
    want = sorted(((d, len(w := (t or "").replace("!?", "").split()), *brute(w, windows)) for d, t in docs), key=repr)
    d = spark.createDataFrame([(*x, 1) for x in docs], "doc_id long, text string, n_hit int")
    b = spark.createDataFrame(items, "item_id long, text string")
    for bound in (10**6, 0):
        got = decontamination.decontaminate(d, b, broadcast_words=bound)
        assert sorted(((r.doc_id, r.n_words, r.n_hit, r["items"]) for r in got.collect()), key=repr) == want, bound
    clean = {x[0] for x in want if not x[2]}
    left = decontamination.remove_contaminated(d, b)
    assert left.columns == d.columns and {r.doc_id for r in left.collect()} == {x[0] for x in want if not x[2]} == clean
    assert decontamination.decontaminate(d.limit(0), b).count() == 0
    assert decontamination.decontaminate(d, b.limit(0)).where("contaminated").count() == 0


def test_both_ways_agree_on_the_tables(spark, sf_small):
    docs, items = table(spark, sf_small, "documents"), table(spark, sf_small, "benchmark")
    assert rows(decontamination.decontaminate(docs, items)) == rows(decontamination.decontaminate(docs, items, broadcast_words=0))


def test_a_very_long_text_both_ways(spark):
    items = spark.createDataFrame([(1, "needle in the hay of ten words or a few more"), (2, None), (None, "no id")], "item_id long, text string")
    long = "filler words without end " * 100_000 + "needle in the hay of ten words or a few more " + "and on " * 50_000
    docs = spark.createDataFrame([(1, long, "x"), (2, "needle in the hay", "x"), (None, None, None)], "doc_id long, text string, n_hit string")
    for bound in (10**6, 0):
        got = {r.doc_id: (r.n_hit, r.contaminated) for r in decontamination.decontaminate(docs, items, broadcast_words=bound).collect()}
        assert got == {1: (11, True), 2: (0, False), None: (0, False)}
