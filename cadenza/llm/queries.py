"""The registered queries of the text operators, each over its whole table with production parameters."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cadenza.llm import decontamination, language, line_dedup, near_dedup, nearest, packing, pii, quality, tokens, toxicity
from cadenza.llm.common import table


def tokenizer_path(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return str(public_tokenizers.path(name))


#: In order: a text that isn't fit to train on at all, then a toxic one.
TOXICITY_CATEGORIES = {"unfit": "quality = 0", "toxic": "toxic = 1"}


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    chain = toxicity.train(docs, table(spark, sf_dir, "labels"), TOXICITY_CATEGORIES)
    return toxicity.score(docs, chain).select("doc_id", "p_unfit", "p_toxic", F.col("rejected").alias("toxic"))


def op2_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = decontamination.decontaminate(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return found.select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.concat_ws(",", "items"), 256).alias("items_sha256"), "contaminated")


def op3_nearest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nearest.nearest(table(spark, sf_dir, "embeddings"))


def op4_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = pii.find_personal(table(spark, sf_dir, "documents"))
    of = {k: F.filter("__spans", _has_rank(r)) for r, k in enumerate(pii.KINDS)}
    base = F.filter("__spans", lambda x: x["rank"] < len(pii.PATTERNS))
    counts = [F.size(of[k]).cast("long").alias(f"n_{k}") for k in pii.KINDS]
    return found.select("doc_id", *counts, F.sha2(pii.listed(base), 256).alias("base_sha256"), pii.listed(F.col("__spans")).alias("spans"), (F.size("__spans") > 0).alias("personal"))


def op5_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").withColumn("held_out", F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 3 == 1, F.lit(False)))
    model = language.train(docs.where(~F.col("held_out")))
    found = language.identify(docs, model, with_spans=False)
    return found.select("doc_id", F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 3 == 1, F.lit(False)).alias("held_out"), "lang_pred", "score")


def op10_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return quality.score(docs, quality.train(docs))


def _has_rank(rank: int):
    return lambda x: x["rank"] == rank


def op6_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dedup.near_duplicates(table(spark, sf_dir, "documents")).select("doc_id", "class_id", (F.col("doc_id") == F.col("class_id")).alias("representative"))


def op7_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokens.count_tokens(table(spark, sf_dir, "documents"), tokenizer_path())


def op8_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = line_dedup.drop_repeated(table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.col("__n_lines").alias("n_lines"), F.col("__n_removed").alias("n_removed"), F.sha2("text", 256).alias("text_sha256"))


def op9_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"), tokenizer_path())


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_toxicity": op1_toxicity,
        "op2_decontamination": op2_decontamination,
        "op3_nearest": op3_nearest,
        "op4_personal_data": op4_personal_data,
        "op5_language": op5_language,
        "op6_near_duplicates": op6_near_duplicates,
        "op7_token_counts": op7_token_counts,
        "op8_line_dedup": op8_line_dedup,
        "op9_packing": op9_packing,
        "op10_quality": op10_quality,
    }


#: The windows of items and all windows of documents of the same lengths, joined.
DECONTAMINATION_SQL = r"""
WITH w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS words FROM documents),
b AS (SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS words FROM benchmark),
bw AS (SELECT DISTINCT item_id, least(10, len(words)) AS n, array_to_string(list_slice(words, i, i + least(10, len(words)) - 1), ' ') AS win
       FROM (SELECT item_id, words, unnest(range(1, greatest(len(words) - 9, 1) + 1)) AS i FROM b WHERE len(words) > 0)),
lens AS (SELECT DISTINCT n FROM bw),
dw AS (SELECT doc_id, i, n, array_to_string(list_slice(words, i, i + n - 1), ' ') AS win
       FROM (SELECT doc_id, words, n, unnest(range(1, len(words) - n + 2)) AS i FROM w, lens WHERE len(words) >= n)),
h AS (SELECT DISTINCT doc_id, i, n, item_id FROM dw JOIN bw USING (n, win)),
hits AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + n)) AS p FROM h) GROUP BY doc_id),
its AS (SELECT doc_id, count(*) AS n_items, string_agg(CAST(item_id AS VARCHAR), ',' ORDER BY CAST(item_id AS VARCHAR)) AS items FROM (SELECT DISTINCT doc_id, item_id FROM h) GROUP BY doc_id)
SELECT w.doc_id, CAST(len(words) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items,
       sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM w LEFT JOIN hits USING (doc_id) LEFT JOIN its USING (doc_id)
"""


#: By definition: of each two successive lines that aren't blank, and of each long line, all occurrences but the first go, bodies being compared as they are.
LINE_DEDUP_SQL = r"""
WITH t AS (SELECT doc_id, md5(text) AS key, string_split(text, chr(10)) AS lines FROM documents WHERE text IS NOT NULL),
f AS (SELECT *, list_filter(range(1, len(lines) + 1), lambda i: regexp_matches(lines[i], '\S')) AS solid FROM t),
u AS (SELECT doc_id, key, lines, solid[k] AS s, solid[k + 1] AS e FROM (SELECT *, unnest(range(1, len(solid))) AS k FROM f WHERE len(solid) > 1)
      UNION ALL SELECT doc_id, key, lines, i, i FROM (SELECT *, unnest(solid) AS i FROM f) WHERE length(lines[i]) - length(replace(lines[i], ' ', '')) + 1 >= 40),
b AS (SELECT doc_id, key, s, e, array_to_string(list_slice(lines, s, e), chr(10)) AS body FROM u),
o AS (SELECT *, first_value(doc_id) OVER w AS doc_0, first_value(key) OVER w AS key_0, first_value(e) OVER w AS e_0 FROM b WINDOW w AS (PARTITION BY body ORDER BY doc_id NULLS FIRST, key, s)),
g AS (SELECT DISTINCT doc_id, unnest(range(s, e + 1)) AS i FROM o WHERE NOT (doc_id IS NOT DISTINCT FROM doc_0 AND key = key_0 AND s <= e_0)),
r AS (SELECT doc_id, list(i) AS gone FROM g GROUP BY doc_id),
k AS (SELECT t.doc_id, len(lines) AS n_lines, coalesce(len(gone), 0) AS n_removed, array_to_string(list_filter(lines, lambda x, i: gone IS NULL OR NOT list_contains(gone, i)), chr(10)) AS text FROM t LEFT JOIN r ON t.doc_id = r.doc_id)
SELECT d.doc_id, CAST(coalesce(n_lines, 0) AS BIGINT) AS n_lines, CAST(coalesce(n_removed, 0) AS BIGINT) AS n_removed, sha256(k.text) AS text_sha256 FROM documents d LEFT JOIN k ON d.doc_id = k.doc_id
"""


def _matches(source: str, text: str, pattern: str, more: str) -> str:
    """Rows of source with each match of a pattern in a column: value and start (code points), from the gaps between matches."""
    base = f"(SELECT {more}, regexp_extract_all({text}, '{pattern}') AS vs, string_split_regex({text}, '{pattern}') AS gs FROM {source})"
    start = "list_sum(list_transform(list_slice(gs, 1, i), lambda x: length(x))) + coalesce(list_sum(list_transform(list_slice(vs, 1, i - 1), lambda x: length(x))), 0)"
    names = ", ".join(x.split(" AS ")[-1] for x in more.split(", "))
    return f"SELECT {names}, vs[i] AS value, CAST({start} AS BIGINT) AS start FROM (SELECT *, unnest(range(1, len(vs) + 1)) AS i FROM {base} WHERE len(vs) > 0)"


def _personal_sql() -> str:
    """By definition: patterns as they are stated, all words near each value, and the information of all pairs from plain counts of texts."""
    stated = [r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", r"[0-9]([\x20-]?[0-9])+", r"\+[0-9][\x20().0-9-]+[0-9]", r"[A-Za-z0-9]{32,}"]
    digits = "regexp_replace(value, '[^0-9]', '', 'g')"
    small = "len(list_filter(string_split(value, '.'), lambda x: length(ltrim(x, '0')) > 3 OR coalesce(TRY_CAST(x AS HUGEINT), 0) > 255)) = 0"
    luhn = "list_sum(list_transform(range(1, length(g) + 1), lambda j: CAST(g[length(g) + 1 - j] AS INT) * (1 + (j - 1) % 2) - CASE WHEN CAST(g[length(g) + 1 - j] AS INT) * (1 + (j - 1) % 2) > 9 THEN 9 ELSE 0 END)) % 10 = 0"
    sound = ["true", small, f"length(g) BETWEEN 14 AND 19 AND {luhn}", "length(g) BETWEEN 10 AND 15", "regexp_matches(value, '[0-9]') AND regexp_matches(value, '[A-Za-z]')"]
    found = " UNION ALL ".join(f"SELECT * FROM (SELECT *, {r} AS rank, {digits} AS g FROM ({_matches('d', 'text', x, 'doc_id, key, text')})) WHERE {ok}" for r, (x, ok) in enumerate(zip(stated, sound)))
    sides = "SELECT doc_id, key, rank, value AS named, greatest(start - 81, 0) AS origin, substring(text, greatest(start - 81, 0) + 1, start - greatest(start - 81, 0)) AS side, CASE WHEN start - 81 <= 0 THEN 0 ELSE 1 END AS low, 81 AS high FROM p UNION ALL SELECT doc_id, key, rank, value, stop, substring(text, stop + 1, 81), 0, 80 FROM p"
    words = _matches("sides", "side", r"\p{L}{3,}", "doc_id, key, rank, named, origin, low, high")
    told = "log2(n_both * CAST(total AS DOUBLE) / (of_term * of_entity)) / greatest(log2(CAST(total AS DOUBLE) / of_entity), 1e-9)"
    kinds = "['email', 'ip', 'card', 'phone', 'secret', 'term']"
    counts = ", ".join(f"count(*) FILTER (rank = {r}) AS n_{k}" for r, k in enumerate(pii.KINDS))
    return rf"""
WITH d AS MATERIALIZED (SELECT doc_id, md5(text) AS key, text FROM documents WHERE text IS NOT NULL),
p AS MATERIALIZED (SELECT doc_id, key, text, rank, value, start, start + length(value) AS stop FROM ({found})),
sides AS ({sides}), w AS ({words}),
near AS MATERIALIZED (SELECT doc_id, key, unnest([rank || ':', rank || ':' || named]) AS entity, lower(value) AS term, origin + start AS start, origin + start + length(value) AS stop FROM w WHERE start >= low AND start + length(value) <= high),
m AS (SELECT DISTINCT entity, term, key FROM near), n AS (SELECT count(DISTINCT key) AS total FROM d),
e AS (SELECT entity, count(DISTINCT key) AS of_entity FROM m GROUP BY 1), b AS (SELECT entity, term, count(*) AS n_both FROM m GROUP BY 1, 2 HAVING count(*) >= 3),
v AS (SELECT term, count(*) AS of_term FROM (SELECT DISTINCT key, unnest(regexp_extract_all(lower(text), '\p{{L}}{{3,}}')) AS term FROM d) GROUP BY 1),
k AS (SELECT entity, term FROM b JOIN e USING (entity) JOIN v USING (term), n WHERE {told} >= 0.8),
t AS (SELECT DISTINCT doc_id, start, stop FROM near JOIN k USING (entity, term)),
a AS (SELECT doc_id, start, stop, rank FROM p UNION ALL SELECT doc_id, start, stop, 5 FROM t WHERE NOT EXISTS (SELECT 1 FROM p WHERE p.doc_id = t.doc_id AND p.start < t.stop AND t.start < p.stop)),
s AS (SELECT *, {kinds}[rank + 1] || ':' || start || ':' || stop AS said FROM a),
g AS (SELECT doc_id, {counts}, string_agg(said, ',' ORDER BY start, rank, stop) FILTER (rank < 4) AS base, string_agg(said, ',' ORDER BY start, rank, stop) AS spans FROM s GROUP BY 1)
SELECT d0.doc_id, {", ".join(f"coalesce(n_{k}, 0) AS n_{k}" for k in pii.KINDS)}, sha256(coalesce(base, '')) AS base_sha256, coalesce(spans, '') AS spans, spans IS NOT NULL AS personal FROM documents d0 LEFT JOIN g ON g.doc_id = d0.doc_id
"""


def oracle_sql() -> dict[str, str]:
    return {"op4_personal_data": _personal_sql(), "op8_line_dedup": LINE_DEDUP_SQL, "op2_decontamination": DECONTAMINATION_SQL}
