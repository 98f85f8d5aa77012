"""Near-duplicate classes by dart-throwing weighted MinHash and banded joining.

A document is the multiset of its shingles of five words. Darts fall as a Poisson process of
density one on the strip (weight of an element) x (rank); the darts of an occurrence of a
shingle come from hashes of that shingle alone, so two documents share the darts of what
they share. A document needs its darts of low rank only: each falls to one of the coordinates of
the signature, and the earliest of a coordinate is its value. Two signatures agree in a
coordinate with a probability equal to the weighted Jaccard similarity.

Exact copies are one node. In each bucket of a band all nodes are first compared with the
bucket's leader. Buckets that then hold several components are looked through once more, in
blocks of bounded size, where nodes of different components are compared and only links that
join components leave the task. So each pair that shares a bucket is compared or is connected
already, a bucket of n copies makes n pairs, not n^2, and no list of all pairs of a bucket is ever
made. Comparison is exact, over whole texts.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cadenza.llm.common import cut, in_small_batches, numbered, tidy
from cadenza.llm.components import components
from cadenza.llm.words import SHINGLE_WORDS, mix, shingle_units, weighted_jaccard, word_list

THRESHOLD = 0.8
#: 20 bands of 5 coordinates: a pair at 0.8 is missed with probability 0.0004.
BANDS, BAND_ROWS = 20, 5
#: Nodes in buckets of several; up to here their keys are broadcast (16 bytes each), beyond they are joined by a shuffle.
BROADCAST_KEYS = 300_000

#: Nodes in a block of a bucket that is looked through once more, and their shingles; pairs of a leader that are compared together.
BLOCK, BLOCK_UNITS = 512, 1_000_000
PAIRS_TOGETHER = 1000

_U = np.uint64
_SALTS = mix(np.arange(1, 1001, dtype=np.uint64) * _U(0xD1342543DE82EF95))


def signatures(units: list[np.ndarray], k: int) -> np.ndarray:
    """A row of k 64-bit values for each array of unit keys, none of which is empty."""
    sizes = np.array([len(u) for u in units])
    signs = np.zeros((len(units), k), np.uint64)
    reach = (k * np.log(k) + 2 * k) / sizes  # ranks up to here leave few coordinates empty
    todo = np.arange(len(units))
    while len(todo):
        keys = np.concatenate([units[i] for i in todo])
        doc = np.repeat(np.arange(len(todo)), sizes[todo])
        far = np.repeat(reach[todo], sizes[todo])
        rank = np.zeros(len(keys))
        darts, ranks, slots = [], [], []
        nth = 0
        while len(keys):
            dart = mix(keys + _SALTS[nth % 1000 : nth % 1000 + 1] * _U(2 * (nth // 1000) + 1))
            u = (mix(dart ^ _SALTS[7]) >> _U(11)).astype(np.float64) * 2.0**-53
            rank = rank - np.log1p(-u)  # the next arrival on this unit's strip
            near = rank <= far
            keys, doc, far, rank, dart = keys[near], doc[near], far[near], rank[near], dart[near]
            darts.append(dart)
            ranks.append(rank)
            slots.append(doc * k + (mix(dart ^ _SALTS[11]) % _U(k)).astype(np.int64))
            nth += 1
        dart, rank, slot = map(np.concatenate, (darts, ranks, slots))
        least = np.full(len(todo) * k, np.inf)
        np.minimum.at(least, slot, rank)
        first = rank == least[slot]
        own = np.zeros(len(todo) * k, np.uint64)
        own[slot[first]] = dart[first]
        full = np.isfinite(least).reshape(len(todo), k).all(axis=1)
        signs[todo[full]] = own.reshape(len(todo), k)[full]
        todo = todo[~full]
        reach[todo] *= 2
    return signs


def band_keys(signs: np.ndarray, bands: int, rows: int) -> np.ndarray:
    keys = np.empty((len(signs), bands), np.int64)
    for b in range(bands):
        h = np.full(len(signs), b + 1, np.uint64)
        for r in range(rows):
            h = mix(h + signs[:, b * rows + r])
        keys[:, b] = h.view(np.int64)
    return keys


def _sign(bands: int, rows: int, shingle: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column(1).cast(pa.binary())
            at, units, held = [], [], 0

            def out():
                keys = band_keys(signatures(units, bands * rows), bands, rows)
                column = pa.ListArray.from_arrays(pa.array(np.arange(0, keys.size + 1, bands), pa.int32()), pa.array(keys.ravel()))
                return pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(at)), pa.array([len(u) for u in units], pa.int64()), column], ["node", "units", "bands"])

            for i, text in enumerate(texts):
                if len(u := shingle_units(word_list(text.as_py()), shingle)):
                    at.append(i)
                    units.append(u)
                    held += max(len(u), 500)
                if held > 100_000:
                    yield out()
                    at, units, held = [], [], 0
            if at:
                yield out()

    return run


def _compare(threshold: float, shingle: int):
    """Rows (b, part, a, text), those of (b, part) together and the one without a first, which has b's own text: the pairs (a, b) within the threshold."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        leader = np.empty(0, np.uint64)
        for batch in batches:
            good = []
            for a, text in zip(batch.column(2), batch.column(3).cast(pa.binary())):
                units = shingle_units(word_list(text.as_py()), shingle)
                if not a.is_valid:
                    leader = units
                good.append(a.is_valid and weighted_jaccard(units, leader) >= threshold)
            yield pa.RecordBatch.from_arrays([batch.column(2), batch.column(0)], ["a", "b"]).filter(pa.array(good, pa.bool_()))

    return run


def _join_components(threshold: float, shingle: int):
    """Rows (bucket, low, high, block, node, root, text), those of (bucket, low, high) together: links between the blocks low and high, or within one, that join components."""

    def links(low: int, high: int, items: list[tuple]) -> list[tuple[bytes, bytes]]:
        if len({root for _, _, root, _ in items}) < 2:
            return []
        up: dict[bytes, bytes] = {}

        def top(x: bytes) -> bytes:
            while (y := up.get(x, x)) != x:
                x = y
            return x

        found = []
        items.sort(key=lambda x: (len(x[3]), x[1]))
        sizes = np.array([len(x[3]) for x in items])
        reach = np.searchsorted(sizes, sizes / threshold * (1 + 1e-12), "right")
        for i, (block, node, root, units) in enumerate(items):
            for other_block, other, other_root, other_units in items[i + 1 : reach[i]]:
                if (low == high or block != other_block) and (a := top(root)) != (b := top(other_root)) and weighted_jaccard(units, other_units) >= threshold:
                    up[a] = b
                    found.append((node, other))
        return found

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, items = None, []
        for batch in batches:
            found = []
            texts = batch.column(6).cast(pa.binary())
            for i, (bucket, low, high, block, node, root) in enumerate(zip(*(batch.column(j).to_pylist() for j in range(6)))):
                if (bucket, low, high) != key:
                    found += links(*key[1:], items) if key else []
                    key, items = (bucket, low, high), []
                # of a text only its keys are held
                items.append((block, node, root, shingle_units(word_list(texts[i].as_py()), shingle)))
            yield out(found)
        if key:
            yield out(links(*key[1:], items))

    def out(found: list[tuple[bytes, bytes]]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array([x for x, _ in found], pa.binary()), pa.array([y for _, y in found], pa.binary())], ["a", "b"])

    return run


def _small(df: DataFrame, bound: int) -> DataFrame:
    """df, to be broadcast if it has no more rows than bound; df is kept already."""
    return F.broadcast(df) if df.limit(bound + 1).count() <= bound else df


def near_duplicates(docs: DataFrame, threshold: float = THRESHOLD, bands: int = BANDS, band_rows: int = BAND_ROWS, shingle: int = SHINGLE_WORDS, id_col: str = "doc_id", text_col: str = "text", broadcast_keys: int = BROADCAST_KEYS, block: int = BLOCK, block_units: int = BLOCK_UNITS, pairs_together: int = PAIRS_TOGETHER) -> DataFrame:
    """One row for each row of docs: id, content (md5 of the text, binary), class_id, root.

    class_id is the smallest id of all rows whose texts are connected by a weighted Jaccard
    similarity of shingles of at least the threshold. root is the same for the rows of a class and
    null for a row that stands alone in any case: its text is null or has no word; its class_id
    is its own id. A text of fewer words than a shingle has one shingle of them all. Repeated rows
    are in one class. Null ids are kept; a class that has null ids only has a null class_id.
    Further columns are ignored; an empty table gives an empty result.
    """
    rows = docs.select(F.col(id_col).alias("id"), F.unhex(F.md5(text_col)).alias("node"), F.col(text_col).alias("text"))
    texts = rows.select("node", "text").where(F.col("text").isNotNull())
    # copies are signed where they lie, once for each; one row of each content goes on
    signed = in_small_batches(texts).mapInArrow(tidy(_sign(bands, band_rows, shingle)), "node binary, units bigint, bands array<bigint>")
    nodes = cut(signed.groupBy("node").agg(F.any_value("units").alias("units"), F.any_value("bands").alias("bands")))
    buckets = nodes.select("node", "units", F.explode("bands").alias("bucket"))
    leaders = buckets.groupBy("bucket").agg(F.min("node").alias("leader"), F.count(F.lit(1)).alias("n")).where("n > 1").select("bucket", "leader")
    members = cut(buckets.join(leaders, "bucket"))
    size_fits = f"least(units_a, units_b) >= {threshold} * greatest(units_a, units_b)"

    involved = cut(members.select("node").distinct())
    some = texts.join(_small(involved, broadcast_keys), "node", "left_semi")
    bodies = cut(some.groupBy("node").agg(F.any_value("text").alias("text")))

    def verified(pairs: DataFrame) -> DataFrame:
        # a leader's text goes once to each part of its pairs, and parts are bounded
        parts = cut(pairs.groupBy("b").agg(F.ceil(F.count(F.lit(1)) / pairs_together).alias("parts")))
        placed = pairs.join(parts, "b").select("b", F.pmod(F.xxhash64("a"), "parts").alias("part"), "a").join(bodies.withColumnRenamed("node", "a"), "a").select("b", "part", "a", "text")
        leaders = parts.select("b", F.explode(F.sequence(F.lit(0).cast("long"), F.col("parts") - 1)).alias("part")).join(bodies.withColumnRenamed("node", "b"), "b").select("b", "part", F.lit(None).cast("binary").alias("a"), "text")
        rows = placed.unionByName(leaders).repartition("b", "part").sortWithinPartitions("b", "part", F.col("a").asc_nulls_first())
        return cut(in_small_batches(rows).mapInArrow(tidy(_compare(threshold, shingle)), "a binary, b binary"))

    with_leader = cut(
        members.where("node <> leader").select(F.col("node").alias("a"), F.col("leader").alias("b"), F.col("units").alias("units_a")).distinct()
        .join(nodes.select(F.col("node").alias("b"), F.col("units").alias("units_b")), "b").where(size_fits).select("a", "b")
    )
    links = verified(with_leader)
    found = cut(components(links))

    # buckets that still hold several components
    placed = members.join(found, "node", "left").select("bucket", "node", "units", F.coalesce("root", "node").alias("root"))
    mixed = placed.groupBy("bucket").agg(F.min("root").alias("low"), F.max("root").alias("high"), F.greatest(F.ceil(F.count(F.lit(1)) / block), F.ceil(F.sum("units") / block_units)).alias("blocks")).where("low <> high").select("bucket", "blocks")
    placed = placed.join(mixed, "bucket").withColumn("block", F.pmod(F.xxhash64("node"), "blocks")).withColumn("with", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)))
    keys = ["bucket", "low", "high"]
    blocks = placed.select("bucket", F.least("block", "with").alias("low"), F.greatest("block", "with").alias("high"), "block", "node", "root")
    more = blocks.join(bodies, "node").select(*keys, "block", "node", "root", "text").repartition(*keys).sortWithinPartitions(*keys)
    more = cut(in_small_batches(more).mapInArrow(tidy(_join_components(threshold, shingle)), "a binary, b binary"))
    if not more.isEmpty():
        found = cut(components(links.union(more)))

    worded = nodes.select("node").join(found, "node", "left").select("node", F.coalesce("root", "node").alias("root"))
    placed_rows = rows.select("id", "node").join(worded, "node", "left")
    # a class of one row needs no join; those of several are kept first, so the join can split a large class
    classes = cut(placed_rows.where("root is not null").groupBy("root").agg(F.min("id").alias("class_id"), F.count(F.lit(1)).alias("n")).where("n > 1"))
    joined = placed_rows.join(_small(classes, broadcast_keys), "root", "left")
    return joined.select(F.col("id").alias(id_col), F.col("node").alias("content"), F.when(F.col("n").isNull(), F.col("id")).otherwise(F.col("class_id")).alias("class_id"), "root")


def keep_one(docs: DataFrame, broadcast_keys: int = BROADCAST_KEYS, **options) -> DataFrame:
    """docs without the rows that near_duplicates() puts in a class with a row kept: of each class the row with the smallest id stays (of equal rows, one). All columns stay as they are."""
    names = docs.columns
    docs, (id_col, text_col) = numbered(docs, options.pop("id_col", "doc_id"), options.pop("text_col", "text"))
    found = cut(near_duplicates(docs, id_col=id_col, text_col=text_col, **options).where("root is not null"))
    content = F.unhex(F.md5(text_col))
    counted = found.groupBy(id_col, "content").agg(F.count(F.lit(1)).alias("n"), F.any_value("class_id").alias("class_id"), F.any_value("root").alias("root"))
    # of the texts under the class's id one is chosen; a class without ids keeps its first content
    chosen = counted.where(F.col(id_col).eqNullSafe(F.col("class_id"))).groupBy("root").agg(F.min("content").alias("kept"))
    judged = cut(
        counted.join(chosen, "root", "left")
        .select(F.col(id_col).alias("__id"), F.col("content").alias("__content"), (F.col(id_col).eqNullSafe(F.col("class_id")) & (F.col("content") == F.col("kept"))).alias("__kept"), "n")
        .where("n > 1 or not __kept")
    )
    same = docs[id_col].eqNullSafe(F.col("__id")) & (content == F.col("__content"))
    plain = docs.join(_small(judged.select("__id", "__content"), broadcast_keys), same, "left_anti")
    repeated = judged.where("__kept and n > 1").select("__id", "__content")
    # rows that repeat under the id kept are few: one of each content stays
    once = docs.join(_small(repeated, broadcast_keys), same, "left_semi").dropDuplicates([id_col, text_col])
    return plain.select(docs.columns).union(once.select(docs.columns)).toDF(*names)
