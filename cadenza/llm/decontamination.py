"""Benchmark decontamination by a prefix-filtered containment join.

An item is cut into windows of ten consecutive words (a shorter item is one window). A window
must occur as a whole, so the set join asks for a containment of 1, for which a prefix of one
token is necessary: of its words, ordered by the number of documents that hold them, the rarest
one. Positions of documents that hold such a word are joined with its windows; the length bound
and the place of the word in the window give where the window would lie, and the words there are
compared exactly.

Items up to a fixed number of window words travel to all tasks and the join is done where the
documents lie, with no shuffle. Beyond it the same join is a shuffle join (joined_hits()).
"""

from __future__ import annotations

from collections import Counter, defaultdict
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cadenza.llm.common import LOWER, UPPER, WORD_PATTERN, cut, in_small_batches, tidy
from cadenza.llm.words import word_list

WINDOW_WORDS = 10
#: Words in all different windows, up to which they are sent to all tasks (about 10 bytes each, 100 in a worker).
BROADCAST_WORDS = 2_000_000


def column_words(text: str):
    """Words of a text column, A-Z lower-cased."""
    return F.regexp_extract_all(F.translate(F.col(text), UPPER, LOWER), F.lit(WORD_PATTERN), F.lit(0))


def item_windows(items: DataFrame, window: int, item_col: str, text_col: str) -> DataFrame:
    """(window array<string>, item string), each once; items without words have none."""
    words = items.where(F.col(item_col).isNotNull()).select(F.col(item_col).cast("string").alias("item"), column_words(text_col).alias("words")).where("size(words) > 0")
    spans = F.transform(F.sequence(F.lit(1), F.greatest(F.lit(1), F.size("words") - window + 1)), lambda i: F.slice("words", i, window))
    return words.select("item", F.explode(spans).alias("window")).distinct()


def document_frequencies(docs: DataFrame, vocabulary: DataFrame | set[bytes], text_col: str) -> DataFrame:
    """(word, n) for the words of a vocabulary: the number of rows of docs that hold it."""
    if isinstance(vocabulary, DataFrame):
        held = docs.select(F.explode(F.array_distinct(column_words(text_col))).alias("word"))
        return held.groupBy("word").agg(F.count(F.lit(1)).alias("n")).join(vocabulary, "word", "left_semi")
    shared = docs.sparkSession.sparkContext.broadcast(vocabulary)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, counts = shared.value, Counter()
        for batch in batches:
            for text in batch.column(0).cast(pa.binary()):
                counts.update(known.intersection(word_list(text.as_py())))
        if counts:
            yield pa.RecordBatch.from_arrays([pa.array([w.decode() for w in counts], pa.string()), pa.array(counts.values(), pa.int64())], ["word", "n"])

    return in_small_batches(docs.select(text_col)).mapInArrow(tidy(run), "word string, n bigint").groupBy("word").agg(F.sum("n").alias("n"))


def _index(windows: list[tuple[list[bytes], list[str]]], frequency: dict[bytes, int]) -> dict[bytes, list[tuple]]:
    """By rarest word: (its place, words of the window, items)."""
    index = defaultdict(list)
    for words, items in windows:
        rare = min(words, key=lambda w: (frequency.get(w, 0), w))
        index[rare].append((words.index(rare), words, items))
    return dict(index)


def find(words: list[bytes], index: dict[bytes, list[tuple]]) -> tuple[int, list[str]]:
    """Number of words hit and the items found, sorted."""
    if index.keys().isdisjoint(words):
        return 0, []
    hit, found = bytearray(len(words)), set()
    for i, word in enumerate(words):
        for place, window, items in index.get(word, ()):
            start, n = i - place, len(window)
            if start >= 0 and start + n <= len(words) and words[start : start + n] == window:
                hit[start : start + n] = b"\1" * n
                found.update(items)
    return sum(hit), sorted(found)


def local_hits(docs: DataFrame, windows: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(id, n_words, n_hit, items) where the documents lie; the windows' bound has been checked."""
    sc = docs.sparkSession.sparkContext
    held = [([w.encode() for w in r.window], r.items) for r in windows.groupBy("window").agg(F.collect_set("item").alias("items")).toLocalIterator()]
    frequency = {r.word.encode(): r.n for r in document_frequencies(docs, {w for words, _ in held for w in words}, text_col).toLocalIterator()}
    # a window with a word that no document holds can't occur
    index = sc.broadcast(_index([x for x in held if all(w in frequency for w in x[0])], frequency))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        by_word = index.value
        for batch in batches:
            n_words, found = [], []
            for text in batch.column(1).cast(pa.binary()):
                words = word_list(text.as_py())
                n_words.append(len(words))
                found.append(find(words, by_word))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n_words, pa.int64()), pa.array([n for n, _ in found], pa.int64()), pa.array([x for _, x in found], pa.list_(pa.string()))], ["id", "n_words", "n_hit", "items"])

    return in_small_batches(docs.select(id_col, text_col)).mapInArrow(tidy(run), f"id {dict(docs.dtypes)[id_col]}, n_words bigint, n_hit bigint, items array<string>")


def joined_hits(docs: DataFrame, windows: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """The same by shuffle joins, for items of any size."""
    texts = docs.select(F.col(id_col).alias("id"), column_words(text_col).alias("words"), F.md5(text_col).alias("text_key"))
    vocabulary = windows.select(F.explode("window").alias("word")).distinct()
    frequency = document_frequencies(docs, vocabulary, text_col)
    numbered = cut(windows.groupBy("window").agg(F.collect_set("item").alias("items")).withColumn("key", F.md5(F.concat_ws(" ", "window"))))
    ranked = numbered.select("key", "window", F.posexplode("window").alias("place", "word")).join(frequency, "word")
    prefix = ranked.groupBy("key").agg(F.min_by(F.struct("word", "place"), F.struct("n", "word", "place")).alias("rare"), F.count(F.lit(1)).alias("known")).select("key", "known", "rare.*")
    prefix = prefix.join(numbered, "key").where("known = size(window)")
    bodies = texts.where("size(words) > 0").select("text_key", "words").dropDuplicates(["text_key"])
    places = bodies.select("text_key", F.size("words").alias("n_words"), F.posexplode("words").alias("at", "word"))
    possible = places.join(prefix, "word").where("at >= place and at - place + size(window) <= n_words").select("text_key", (F.col("at") - F.col("place")).alias("start"), "window", "items")
    sure = possible.join(bodies, "text_key").where("slice(words, start + 1, size(window)) = window")
    hits = sure.select("text_key", "items", F.explode(F.sequence("start", F.col("start") + F.size("window") - 1)).alias("at"))
    n_hit = hits.groupBy("text_key").agg(F.countDistinct("at").alias("n_hit"))
    items = hits.select("text_key", F.explode("items").alias("item")).distinct().groupBy("text_key").agg(F.array_sort(F.collect_list("item")).alias("items"))
    return texts.join(n_hit.join(items, "text_key"), "text_key", "left").select(
        "id", F.greatest(F.coalesce(F.size("words"), F.lit(0)), F.lit(0)).cast("long").alias("n_words"),
        F.coalesce("n_hit", F.lit(0)).cast("long").alias("n_hit"), F.coalesce("items", F.array().cast("array<string>")).alias("items"),
    )


def decontaminate(docs: DataFrame, items: DataFrame, window: int = WINDOW_WORDS, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", broadcast_words: int = BROADCAST_WORDS) -> DataFrame:
    """One row for each row of docs: id, n_words, n_hit, items (of windows that occur, sorted as strings), contaminated.

    Null texts and texts without words have no words and no hits; items without words, or without
    an id, find nothing. Items of one text are all reported. Repeated rows and null ids are kept;
    further columns are ignored; empty tables give no rows or no hits.
    """
    windows = cut(item_windows(items, window, item_col, item_text_col))
    size = windows.agg(F.sum(F.size("window"))).first()[0] or 0
    way = local_hits if size <= broadcast_words else joined_hits
    return way(docs, windows, id_col, text_col).withColumnRenamed("id", id_col).withColumn("contaminated", F.col("n_hit") > 0)


def remove_contaminated(docs: DataFrame, items: DataFrame, text_col: str = "text", broadcast_words: int = BROADCAST_WORDS, **options) -> DataFrame:
    """docs without contaminated rows; all columns stay as they are."""
    key = "__row_text"
    judged = decontaminate(docs.select(F.md5(text_col).alias(key), text_col), items, id_col=key, text_col=text_col, broadcast_words=broadcast_words, **options)
    bad = cut(judged.where("contaminated").select(key).distinct())
    bad = F.broadcast(bad) if bad.limit(300_001).count() <= 300_000 else bad
    return docs.join(bad, F.md5(docs[text_col]) == bad[key], "left_anti")
