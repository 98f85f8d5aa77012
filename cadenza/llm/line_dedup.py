"""Removal of passages that repeat anywhere in the corpus, by content-defined chunks of lines.

A rolling hash runs over the hashes of each two successive lines that aren't blank (with the blank ones
between them), and over each line of many words. Where the rolling hash is one that the corpus has
several times a chunk goes on, where it isn't a boundary stands. So boundaries depend on content alone
and not on positions, and a repeated passage is a chunk whatever its length and whatever stands around it. (Boundaries at some
fixed values of the hash would miss passages of a few lines, which need not hold two such values.)
Before anything goes, the lines themselves are compared byte by byte; all but the first occurrence are removed.

DataFrame functions only.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cadenza.llm.common import cut, numbered

#: A line of so many words is a unit of its own.
LONG_LINE_WORDS = 40
#: Occurrences of a unit that are joined with its first one together.
PART_ROWS = 1000
#: Repeated units, or rows with removed lines, up to which they are broadcast (some 100 bytes each).
BROADCAST_ROWS = 300_000


def _words(line: Column) -> Column:
    """Blanks between words, and one."""
    return F.length(line) - F.length(F.replace(line, F.lit(" "), F.lit(""))) + 1


def units(docs: DataFrame, id_col: str, text_col: str, long_line: int, with_body: bool = True) -> DataFrame:
    """A row for each unit: id, key (md5 of the text), s and e (first line, line after the last; from 0), unit (hash), body if asked for."""
    rows = docs.where(F.col(text_col).isNotNull()).select(F.col(id_col).alias("id"), F.unhex(F.md5(text_col)).alias("key"), F.split(text_col, "\n", -1).alias("lines"))
    rows = rows.withColumn("full", F.filter(F.transform("lines", lambda x, i: F.when(x.rlike(r"\S"), i)), lambda i: i.isNotNull()))
    part = lambda s, e: F.slice("lines", s + 1, e - s)

    def unit(s: Column, e: Column) -> Column:
        body = [F.array_join(part(s, e), "\n").alias("body")] if with_body else []
        return F.struct(s.alias("s"), e.alias("e"), F.xxhash64(part(s, e)).alias("unit"), *body)

    pairs = F.transform(F.slice("full", 1, F.greatest(F.size("full") - 1, F.lit(0))), lambda s, k: unit(s, F.get("full", k + 1) + 1))
    long = F.transform(F.filter("full", lambda i: _words(F.get("lines", i)) >= long_line), lambda s: unit(s, s + 1))
    return rows.select("id", "key", F.explode(F.concat(pairs, long)).alias("u")).select("id", "key", "u.*")


def _merged(spans: Column) -> Column:
    """Sorted array<struct<s, e>> with those that meet made one, so texts aren't searched unit by unit."""
    one = lambda a: F.when(a["e"] > a["s"], F.array(F.struct(a["s"].alias("s"), a["e"].alias("e")))).otherwise(F.array().cast("array<struct<s:int,e:int>>"))
    start = F.struct(F.array().cast("array<struct<s:int,e:int>>").alias("done"), F.lit(0).alias("s"), F.lit(0).alias("e"))

    def step(a, x):
        longer = F.struct(a["done"].alias("done"), a["s"].alias("s"), F.greatest(a["e"], x["e"]).alias("e"))
        return F.when(x["s"] <= a["e"], longer).otherwise(F.struct(F.concat(a["done"], one(a)).alias("done"), x["s"].alias("s"), x["e"].alias("e")))

    return F.aggregate(spans, start, step, lambda a: F.concat(a["done"], one(a)))


def repeated_spans(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", long_line: int = LONG_LINE_WORDS, broadcast_rows: int = BROADCAST_ROWS, part_rows: int = PART_ROWS) -> DataFrame:
    """(id, key, spans array<struct<s, e>>) for each text that loses lines s to e-1; kept already."""
    every = units(docs, id_col, text_col, long_line, with_body=False)
    seen = cut(every.groupBy("unit").agg(F.count(F.lit(1)).alias("n")).where("n > 1"))
    seen = F.broadcast(seen) if seen.limit(broadcast_rows + 1).count() <= broadcast_rows else seen
    # a unit that occurs very often is dealt out in parts, and its first occurrence goes to each part
    parts = F.ceil(F.col("n") / part_rows)
    again = cut(units(docs, id_col, text_col, long_line).join(seen, "unit").withColumn("part", F.pmod(F.xxhash64("id", "key", "s"), parts)))
    # bytes are compared here: a body, not its hash, is the group
    first = again.groupBy("unit", "body").agg(F.any_value("n").alias("n"), F.count(F.lit(1)).alias("copies"), F.min(F.struct("id", "key", "s", "e")).alias("first")).where("copies > 1")
    first = cut(first.select(F.col("unit").alias("first_unit"), F.col("body").alias("first_body"), "first", F.explode(F.sequence(F.lit(0).cast("long"), parts - 1)).alias("first_part")))
    # the first itself stays, and what overlaps it in one text
    of_first = F.col("id").eqNullSafe(F.col("first.id")) & (F.col("key") == F.col("first.key")) & (F.col("s") < F.col("first.e"))
    later = again.join(first, (F.col("unit") == F.col("first_unit")) & (F.col("part") == F.col("first_part"))).where((F.col("body") == F.col("first_body")) & ~of_first)
    return cut(later.groupBy("id", "key").agg(_merged(F.array_sort(F.collect_set(F.struct("s", "e")))).alias("spans")))


def drop_repeated(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", long_line: int = LONG_LINE_WORDS, broadcast_rows: int = BROADCAST_ROWS, part_rows: int = PART_ROWS) -> DataFrame:
    """docs with all their columns, the text without repeated passages, then __n_lines and __n_removed.

    Of a repeated unit the occurrence with the smallest (id, md5 of the text, line) stays, nulls first.
    Rows that agree in id and text are one document and keep the same text. A null text stays null and
    has no lines; an empty one has one line. An empty table gives no rows; other columns pass unchanged.
    """
    names = docs.columns
    docs, (id_col, text_col) = numbered(docs, id_col, text_col)
    spans = repeated_spans(docs, id_col, text_col, long_line, broadcast_rows, part_rows).select(F.col("id").alias("__id"), F.col("key").alias("__key"), F.col("spans").alias("__spans"))
    spans = F.broadcast(spans) if spans.limit(broadcast_rows + 1).count() <= broadcast_rows else spans
    joined = docs.join(spans, docs[id_col].eqNullSafe(F.col("__id")) & (F.unhex(F.md5(docs[text_col])) == F.col("__key")), "left")
    lines = F.split(text_col, "\n", -1)
    kept = F.filter(lines, lambda _, i: ~F.exists("__spans", lambda x: (x["s"] <= i) & (i < x["e"])))
    joined = joined.withColumn("__n_lines", F.coalesce(F.size(lines), F.lit(0))).withColumn("__n_lines", F.greatest(F.col("__n_lines"), F.lit(0)).cast("long"))
    joined = joined.withColumn("__kept", F.when(F.col("__spans").isNotNull(), kept))
    removed = F.when(F.col("__kept").isNull(), F.lit(0)).otherwise(F.col("__n_lines") - F.size("__kept")).cast("long")
    text = F.when(F.col("__kept").isNull(), F.col(text_col)).otherwise(F.array_join("__kept", "\n"))
    return joined.select(*((text if c == text_col else F.col(c)).alias(name) for c, name in zip(docs.columns, names)), "__n_lines", removed.alias("__n_removed"))
