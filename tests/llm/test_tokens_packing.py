import random
import zlib
from collections import defaultdict

import numpy as np
import pytest

from cadenza.llm import packing, queries, tokens


@pytest.fixture(scope="module")
def library():
    from tokenizers import Tokenizer

    return Tokenizer.from_file(queries.tokenizer_path())


ODD = [
    None, "", " ", "\n\n", "a", "It's we'll 'tis", "The. the, THE!! ...!?", "x" * 5000, "wörd " * 4000, "no break space",
    "<|endoftext|> <|ENDOFTEXT|> a<|startoftext|>b", "éte ́a", "ΣΑΣ ΟΔΟΣ.", "İstanbul 123 4.5", "日本語 テキスト", "a\x1cb !\x1c! \x85 c", "tab\tand\r\nnew", "🙂🙂 ok", "ǅ Ǆ ſ K",
]


def test_counts_equal_the_library(spark, library):
    rows = [(i, t) for i, t in enumerate(ODD)] + [(3, "again"), (None, "null id")]
    got = tokens.count_tokens(spark.createDataFrame(rows, "doc_id long, text string"), queries.tokenizer_path()).collect()
    want = [(i, len((t or "").encode()), len(library.encode(t or "", add_special_tokens=False).ids)) for i, t in rows]
    key = lambda x: (x[0] is None, x[0] or 0, x[1])
    assert sorted(((r.doc_id, r.n_bytes, r.n_tokens) for r in got), key=key) == sorted(want, key=key)


def test_splices_at_any_chunk_size(library):
    speller = tokens.Speller(queries.tokenizer_path(), remembered=50)
    texts = [t for t in ODD if t] + ["abc" * 300 + " d e f" + "g" * 700 + "\nh i"]
    for text in texts:
        want = np.array(library.encode(text, add_special_tokens=False).ids, "<u4").tobytes()
        for chunk, overlap in ((1, 1), (7, 2), (64, 8), (1000, 16)):
            assert tokens.encode_all([text], speller, chunk, overlap)[0][0] == want, (text[:30], chunk)


def all_json():
    import public_tokenizers

    return sorted(str(p) for p in __import__("pathlib").Path(public_tokenizers.path("word_bpe_49k.json")).parent.glob("*.json"))


@pytest.mark.parametrize("path", all_json())
def test_each_tokenizer_file_at_any_chunk_size(path):
    from tokenizers import Tokenizer

    library, speller = Tokenizer.from_file(path), tokens.Speller(path, remembered=100)
    rng = random.Random(7)
    parts = ["a", "b", "é", "É", " ", "  ", "\n", "'", "s", "t", "<|endoftext|>", "<|end", "!", "#", "1", "日", "\u0301", "ß", "ſ", "-", '"', "\t", "\xa0", "A", "word", "🙂"]
    texts = [t for t in ODD if t] + ["a  b\n c"] + ["".join(rng.choices(parts, k=rng.randint(1, 200))) for _ in range(150)]
    chunks = 0
    for text in texts:
        want = np.array(library.encode(text, add_special_tokens=False).ids, "<u4").tobytes()
        for chunk, overlap in ((16, 4), (64, 8), (10**6, 8)):
            ids, n = tokens.encode_all([text], speller, chunk, overlap)[0]
            chunks += n
            assert ids == want, (text[:50], chunk)
    assert chunks > 6 * len(texts)


def test_a_huge_text_is_spliced_and_one_without_blanks_too(library):
    speller = tokens.Speller(queries.tokenizer_path())
    rng = random.Random(3)
    words = ["".join(rng.choices("abcdefghi", k=rng.randint(1, 9))) for _ in range(5000)]
    plain = " ".join(rng.choices(words, k=60_000))
    for text, least in ((plain, 4), (plain.replace(" ", "-"), 4), ("q" * 200_000, 1)):
        ids, n = tokens.encode_all([text], speller)[0]
        assert ids == np.array(library.encode(text, add_special_tokens=False).ids, "<u4").tobytes() and n >= least


def test_overlaps_widen_and_what_has_no_boundary_is_one_chunk():
    speller = tokens.Speller(queries.tokenizer_path())
    long_word = "one two three four five " + "x" * 90 + " six seven eight nine ten " * 20
    assert tokens.encode_all([long_word], speller, 60, 4)[0][1] > 2
    assert tokens.encode_all(["x" * 1000], speller, 60, 4)[0][1] == 1
    # of two chunks, the words that agree begin after the right one's start and end before the left one's end
    left, right = [(0, 2, b"a"), (3, 5, b"b"), (6, 8, b"c"), (9, 10, b"d")], [(4, 5, b"x"), (6, 8, b"c"), (9, 10, b"d"), (11, 12, b"e")]
    assert tokens.common_boundary(left, 0, right, 4, 11, 2) == (2, 1)
    assert tokens.common_boundary(left, 0, right, 4, 10, 2) is None
    assert tokens.common_boundary(left, 0, right, 4, 11, 3) is None


def test_stability_is_read_from_the_file():
    bare = {"normalizer": None, "pre_tokenizer": {"type": "Whitespace"}, "model": {"type": "BPE", "dropout": None}, "added_tokens": []}
    assert tokens.scans_forward(bare)
    assert not tokens.scans_forward(bare | {"pre_tokenizer": None})
    assert not tokens.scans_forward(bare | {"pre_tokenizer": {"type": "Metaspace"}})
    assert not tokens.scans_forward(bare | {"normalizer": {"type": "Strip"}})
    assert not tokens.scans_forward(bare | {"model": {"type": "Unigram"}})
    split = lambda pattern: bare | {"pre_tokenizer": {"type": "Split", "pattern": {"Regex": pattern}, "behavior": "Isolated", "invert": False}}
    assert tokens.scans_forward(split(r"\s+(?!\S)|\s+|[^\s]+"))
    assert not tokens.scans_forward(split(r"(?<=a)b")) and not tokens.scans_forward(split(r"a(?=.*b)")) and not tokens.scans_forward(split(r"a$"))


def test_count_edges(spark):
    empty = spark.createDataFrame([], "doc_id long, text string, n_tokens string")
    assert tokens.count_tokens(empty, queries.tokenizer_path()).collect() == []
    clash = spark.createDataFrame([(1, "a b", "x"), (1, "a b", "x"), (None, None, None)], "doc_id long, text string, n_tokens string")
    assert sorted((r.doc_id or 0, r.n_tokens, r.n_chunks) for r in tokens.count_tokens(clash, queries.tokenizer_path()).collect()) == [(0, 0, 1), (1, 2, 1), (1, 2, 1)]


def test_query_counts(spark, sf, library):
    docs = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    got = queries.op7_token_counts(spark, sf).collect()
    assert len(got) == len(docs)
    for r in got:
        n = len(library.encode(docs[r.doc_id] or "", add_special_tokens=False).ids)
        assert (r.n_tokens, r.over_limit, r.n_bytes) == (n, n > 2048, len((docs[r.doc_id] or "").encode()))


def check_packed(rows, ids_of, window=4096):
    by_doc, by_seq = defaultdict(list), defaultdict(list)
    for r in rows:
        by_doc[r.doc_id].append(r)
        by_seq[r.sequence_id].append(r)
    assert by_doc.keys() == ids_of.keys()
    for d, pieces in by_doc.items():
        at, ids = 0, ids_of[d]
        for r in sorted(pieces, key=lambda r: r.start):
            assert r.start == at and r.doc_tokens == len(ids) and r.length > 0
            assert r.ids_crc32 == zlib.crc32(np.array(ids[at : at + r.length], "<u4").tobytes())
            at += r.length
        assert at == len(ids)
    padding = 0
    for pieces in by_seq.values():
        at = 0
        for r in sorted(pieces, key=lambda r: r.offset):
            assert r.offset == at
            at += r.length
        assert at <= window
        padding += 0 if at & (at - 1) == 0 else window - at
    return padding


def test_query_packing(spark, sf, library):
    ids = {r.doc_id: library.encode(r.text or "", add_special_tokens=False).ids + [2] for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    padding = check_packed(queries.op9_packing(spark, sf).collect(), ids)
    assert padding <= 0.01 * sum(map(len, ids.values()))


def test_packing_edges(spark, library):
    rows = [(1, None), (2, ""), (3, "a b c"), (4, "word " * 9000), (None, "x")]
    docs = spark.createDataFrame([(*r, "clash") for r in rows], "doc_id long, text string, offset string")
    ids = {d: library.encode(t or "", add_special_tokens=False).ids + [2] for d, t in rows}
    check_packed(packing.pack(docs, queries.tokenizer_path()).collect(), ids)
    assert packing.pack(docs.limit(0), queries.tokenizer_path()).count() == 0


def test_sum_of_squares_choice():
    p = packing.SumOfSquares(window=10)
    for n in (6, 6, 3):
        p.add(n, b"\0" * 4 * n)
    # the 3 went from 6 to 9, as that left fewer equal windows than a second fresh one: one window each at 6 and 9
    assert p.count[6] == p.count[9] == 1
    assert p.choose(4) == 6  # fills a window up
    assert p.choose(3) == 0  # 6 to 9 would make two at 9; a fresh window costs less
    p.flush()
    assert sum(r[2] for r in p.packed()) == 15


def test_many_open_windows_and_fine_levels():
    for levels in (4, 64):
        p = packing.SumOfSquares(window=64, levels=levels, open_windows=3)
        for n in range(1, 63):
            p.add(n, bytes(4 * n))
            assert p.n_open <= 4
        p.flush()
        assert sum(r[2] for r in p.packed()) == sum(range(1, 63)) == p.placed + p.cut


def test_most_ids_stay_where_the_rule_put_them():
    rng = np.random.default_rng(5)
    placed = every = 0
    for _ in range(32):
        p = packing.SumOfSquares()
        sizes = np.minimum(rng.lognormal(6.3, 0.9, 300).astype(int) + 1, 40_000)
        for i, n in enumerate(sizes):
            p.add(i, bytes(4 * int(n)))
        p.flush()
        held = defaultdict(int)
        for r in p.packed():
            assert r[6] == held[r[5]]
            held[r[5]] += r[2]
        assert all(n == 4096 or n & (n - 1) == 0 for n in held.values())
        placed, every = placed + p.placed, every + int(sizes.sum())
    assert placed > 0.95 * every
