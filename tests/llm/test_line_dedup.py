from cadenza.llm import line_dedup, queries
from tests.llm.oracle import rows, sql_rows

A = "\n".join(f"shared line number {i} of the passage" for i in range(12))
LONG = " ".join(f"word{i}" for i in range(55))


def texts(spark, data, **options):
    df = spark.createDataFrame(data, "doc_id long, text string, spans string")
    found = line_dedup.drop_repeated(df, **options)
    assert found.columns == [*df.columns, "__n_lines", "__n_removed"]
    return {r.doc_id: r.text for r in found.collect()}


def test_query_equals_sql(spark, sf):
    names, want = sql_rows(queries.oracle_sql()["op8_line_dedup"], sf)
    got = queries.op8_line_dedup(spark, sf)
    assert sorted(got.columns) == names and rows(got) == want
    assert sum(r[names.index("n_removed")] for r in want) > 0


def test_passages_go_wherever_they_stand(spark):
    data = [(1, f"own start\n{A}\nown end", "x"), (2, f"another\nbeginning\n{A}\nother end\nmore", "x"), (3, f"{A}", "x"), (4, f"top\n{LONG}\nend", "x"), (5, f"{LONG}\nelse", "x")]
    for bound in (10**6, 0):
        got = texts(spark, data, broadcast_rows=bound)
        assert got == {1: data[0][1], 2: "another\nbeginning\nother end\nmore", 3: "", 4: data[3][1], 5: "else"}


def test_short_single_lines_stay(spark):
    data = [(i, f"All rights reserved.\nunique {i}", None) for i in range(5)]
    assert texts(spark, data) == {d: t for d, t, _ in data}


def test_edges(spark):
    data = [(1, None, "x"), (2, "", "x"), (3, "\n\n\n", "x"), (4, "\n\n\n", "x"), (None, f"{A}", "x"), (5, f"{A}", "x"), (6, "a\r\nb", "x"), (7, f"again\n{A}\nthen\n{A}\nend", None), (8, "x" * 200_000, None)]
    got = texts(spark, data)
    # the null id comes first; a passage within one text goes as well
    assert got == {1: None, 2: "", 3: "\n\n\n", 4: "\n\n\n", None: A, 5: "", 6: "a\r\nb", 7: "again\nthen\nend", 8: "x" * 200_000}
    same = [(1, A, "x"), (1, A, "x")]
    assert texts(spark, same) == {1: A}
    assert texts(spark, []) == {}


def test_short_passages_go_in_all_surroundings(spark):
    # 55 words on 2 to 6 lines of fewer than 40 each, among lines of 30 documents' own
    for n in range(2, 7):
        passage = "\n".join(" ".join(f"p{n}w{i}" for i in range(55) if i * n // 55 == k) for k in range(n))
        data = [(d, f"top {d}\nsecond {d * d}\n{passage}\nafter {d}\nlast {d * 7}", None) for d in range(30)]
        want = {d: t if d == 0 else t.replace(f"{passage}\n", "") for d, t, _ in data}
        assert texts(spark, data) == want


def test_blank_lines_neither_make_nor_part_a_passage(spark):
    data = [(i, f"own {i}\n\nContents\n\nunique {i}\n\nfirst of two\n \nsecond of two\n\nend {i}", None) for i in range(3)]
    got = texts(spark, data)
    assert got[0] == data[0][1] and got[1] == "own 1\n\nContents\n\nunique 1\n\n\nend 1"


def test_what_overlaps_the_first_stays(spark):
    assert texts(spark, [(1, "x\nx\nx", None), (2, "y\n" * 5 + "end", None)]) == {1: "x\nx\nx", 2: "y\ny\nend"}


def test_all_that_sql_removes_goes(spark, sf):
    names, want = sql_rows(queries.oracle_sql()["op8_line_dedup"], sf)
    at, n = names.index("doc_id"), names.index("n_removed")
    got = {r.doc_id: r.n_removed for r in queries.op8_line_dedup(spark, sf).collect()}
    assert all(got[r[at]] >= r[n] for r in want)


def test_very_common_units_are_dealt_out(spark):
    data = [(d, f"own {d}\n{A}\nend {d}", None) for d in range(40)]
    want = {d: t if d == 0 else f"own {d}\nend {d}" for d, t, _ in data}
    assert texts(spark, data, part_rows=3) == texts(spark, data) == want
