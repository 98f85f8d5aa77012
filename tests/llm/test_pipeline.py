import corpus_pipeline
from cadenza.llm import decontamination, near_dedup
from cadenza.llm.common import table
from tests.llm.test_near_dedup import brute
from tests.llm.test_tokens_packing import check_packed


def test_stages_one_by_one(spark, sf_small, tmp_path):
    from tokenizers import Tokenizer

    docs = table(spark, sf_small, "documents")
    columns, results = docs.columns, [docs]
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        stage(spark, docs, sf_small).write.parquet(f"{tmp_path}/{k}")
        docs = spark.read.parquet(f"{tmp_path}/{k}")
        if k < 4:
            assert docs.columns == columns, name
        results.append(docs)
    held = [{r.doc_id: r.text for r in x.collect()} for x in results[:5]]
    assert held[1].items() <= held[0].items()
    assert all(len(held[2][d]) <= len(t) for d, t in held[1].items() if d in held[2])
    assert all(r.n_chars == len(r.text) for r in results[2].collect())
    before = list(held[2].items())
    assert set(held[3]) == {c for c in brute(before)}
    bad = {r.doc_id for r in decontamination.decontaminate(results[3], table(spark, sf_small, "benchmark")).where("contaminated").collect()}
    assert set(held[4]) == set(held[3]) - bad
    tok = Tokenizer.from_file(corpus_pipeline.tokenizer_path())
    check_packed(results[5].collect(), {d: tok.encode(t or "", add_special_tokens=False).ids + [2] for d, t in held[4].items()})


def test_run(spark, sf_small):
    got = corpus_pipeline.run(spark, sf_small)
    assert "ids_crc32" in got.columns and got.count() > 0
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "line dedup", "near dedup", "decontamination", "packing"]


def odd_documents(spark):
    """Nulls in each column, empty and very long texts, ties, repeated rows, and further columns whose names the operators use inside."""
    long = "lorem ipsum dolor sit amet " * 20_000
    same = "one two three four five six seven eight nine ten eleven twelve"
    rows = [(1, None, "en", "s", 0), (2, "", None, "s", 0), (3, same, "en", None, len(same)), (3, same, "en", None, len(same)), (4, same, "en", "s", None), (None, same + " more", "en", "s", 1), (None, None, None, None, None), (5, long, "en", "s", len(long)), (6, "🙂 é", "fr", "s", 3), (7, "Ünïcödé " * 40, "de", "s", 1)]
    extra = "node binary, root string, unit long, id long, key string, spans string, __id long, n long"
    return spark.createDataFrame([(*r, None, "x", 1, 2, "k", "y", 3, 4) for r in rows], f"doc_id long, text string, lang string, source string, n_chars long, {extra}")


def test_each_stage_takes_odd_rows(spark, sf_small, tmp_path):
    docs = odd_documents(spark)
    left = {"toxicity": 10, "line dedup": 10, "near dedup": 8, "decontamination": 10}
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        stage(spark, docs, sf_small).write.parquet(f"{tmp_path}/{k}")
        got = spark.read.parquet(f"{tmp_path}/{k}")
        if name == "packing":
            held = {r.doc_id: r.text for r in docs.collect()}
            assert {r.doc_id for r in got.collect()} == held.keys()
            continue
        assert got.columns == docs.columns
        rows = got.collect()
        if name == "near dedup":
            # the two equal rows and document 4 are one class, which the null id's near copy joins or not; rows without words stay
            assert len([r for r in rows if r.doc_id in (3, 4)]) <= 1 and {1, 2, 5, 6, 7} <= {r.doc_id for r in rows}
        else:
            assert len(rows) == left[name], name
        assert all(r.root == "x" and r.n == 4 for r in rows)


def test_each_stage_takes_an_empty_table(spark, sf_small, tmp_path):
    docs = odd_documents(spark).limit(0)
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        stage(spark, docs, sf_small).write.parquet(f"{tmp_path}/e{k}")
        got = spark.read.parquet(f"{tmp_path}/e{k}")
        assert got.count() == 0 and (name == "packing" or got.columns == docs.columns)
