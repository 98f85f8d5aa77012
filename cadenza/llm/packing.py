"""Packing of token ids into windows of fixed size, online, by the sum-of-squares rule.

Each task packs its own documents as they come. A level array counts the partially filled
windows of each fill level, a level being a fixed part of a window. A document goes whole to the
level (or an empty window) for which the sum of the squared counts is then smallest. A
document longer than a window first fills whole windows. A window with less room than one level
is filled up with the first ids of the next document, so it has no padding; beyond a
number of open windows the fullest one is filled up like that. At the end of a task the emptiest windows
are taken apart to fill up the fullest ones; the last is cut into windows whose lengths are powers of
two, which need no padding. All other ids stay where the rule has put them.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame

from cadenza.llm.common import in_small_batches, tidy
from cadenza.llm.tokens import Speller, batches_of

WINDOW = 4096
#: Fill levels of a window, and open windows that a task holds at most.
LEVELS = 64
OPEN_WINDOWS = 1024
END_ID = 2

FIELDS = "start bigint, length bigint, ids_crc32 bigint, doc_tokens bigint, sequence_id bigint, offset bigint"


class SumOfSquares:
    """Pieces are (document, start, bytes of ids, tokens of the document); packed() rows are (document, start, length, crc32, tokens, sequence, offset).

    placed and cut count the ids that the rule has put (whole windows of long documents among them) and those that were used to fill up.
    """

    def __init__(self, window: int = WINDOW, levels: int = LEVELS, open_windows: int = OPEN_WINDOWS, first_sequence: int = 0):
        self.window, self.open_windows, self.sequence = window, open_windows, first_sequence
        self.grain = max(1, window // levels)
        self.count = [0] * (window // self.grain + 1)
        self.at_level: list[list[tuple[int, list[tuple]]]] = [[] for _ in self.count]  # (ids held, pieces)
        self.almost: list[tuple[int, list[tuple]]] = []  # with less room than one level
        self.n_open = 0
        self.placed = self.cut = 0
        self.rows: list[tuple] = []

    def close(self, pieces: list[tuple]) -> None:
        offset = 0
        for doc, start, ids, total in pieces:
            self.rows.append((doc, start, n := len(ids) // 4, zlib.crc32(ids), total, self.sequence, offset))
            offset += n
        self.sequence += 1

    def level(self, held: int) -> int:
        return -(-held // self.grain)

    def choose(self, size: int) -> int:
        """The fill level of the window to use; 0: a new one. Ties go to the fullest.

        Taking a window off a level of c saves 2c - 1, putting one on a level of c costs 2c + 1; filling a window up costs nothing.
        """
        count = self.count
        ends = lambda held: 2 * count[self.level(held)] + 1 if self.window - held >= self.grain else 0
        best, least = 0, ends(size)
        for level in range(1, len(count)):
            if count[level]:
                held = self.at_level[level][-1][0]
                if held + size > self.window:
                    break
                cost = 0 if self.level(held + size) == level else ends(held + size) - 2 * count[level] + 1
                if cost <= least:
                    best, least = level, cost
        return best

    def _put(self, held: int, pieces: list[tuple]) -> None:
        if held == self.window:
            self.close(pieces)
        elif self.window - held < self.grain:
            self.almost.append((held, pieces))
        else:
            self.count[self.level(held)] += 1
            self.at_level[self.level(held)].append((held, pieces))
            self.n_open += 1

    def _take(self, level: int) -> tuple[int, list[tuple]]:
        self.count[level] -= 1
        self.n_open -= 1
        return self.at_level[level].pop()

    def add(self, doc, ids: bytes) -> None:
        total, at = len(ids) // 4, 0
        while total - at >= self.window:
            self.close([(doc, at, ids[4 * at : 4 * (at + self.window)], total)])
            self.placed += self.window
            at += self.window
        while at < total and (self.almost or self.n_open >= self.open_windows):
            held, pieces = self.almost.pop() if self.almost else self._take(max(k for k, c in enumerate(self.count) if c))
            n = min(self.window - held, total - at)
            self._put(held + n, [*pieces, (doc, at, ids[4 * at : 4 * (at + n)], total)])
            self.cut += n
            at += n
        if at == total:
            return
        n = total - at
        level = self.choose(n)
        held, pieces = self._take(level) if level else (0, [])
        pieces.append((doc, at, ids[4 * at :], total))
        self.placed += n
        self._put(held + n, pieces)

    def flush(self) -> None:
        """All windows that are open: the emptiest fill up the fullest, the last is cut into windows of 2^k ids."""
        windows = sorted([*self.almost, *chain.from_iterable(self.at_level)], key=lambda w: w[0])
        self.count, self.at_level, self.almost, self.n_open = [0] * len(self.count), [[] for _ in self.count], [], 0
        loose: list[tuple] = []  # pieces of the emptiest, the next one last
        low = 0

        def moved(room: int) -> list[tuple]:
            taken = []
            while room and loose:
                doc, start, ids, total = loose.pop()
                n = min(room, len(ids) // 4)
                taken.append((doc, start, ids[: 4 * n], total))
                if 4 * n < len(ids):
                    loose.append((doc, start + n, ids[4 * n :], total))
                room -= n
                self.placed -= n
                self.cut += n
            return taken

        while low < len(windows):
            held, pieces = windows.pop()
            while held < self.window and (loose or low < len(windows)):
                if not loose:
                    loose = windows[low][1][::-1]
                    low += 1
                more = moved(self.window - held)
                pieces += more
                held += sum(len(ids) for _, _, ids, _ in more) // 4
            if held < self.window:
                loose = pieces[::-1]
                break
            self.close(pieces)
        while loose:
            left = sum(len(ids) for _, _, ids, _ in loose) // 4
            self.close(moved(1 << (left.bit_length() - 1)))

    def packed(self) -> list[tuple]:
        rows, self.rows = self.rows, []
        return rows


def pack(docs: DataFrame, tokenizer_path: str, window: int = WINDOW, end_id: int = END_ID, id_col: str = "doc_id", text_col: str = "text", levels: int = LEVELS, open_windows: int = OPEN_WINDOWS) -> DataFrame:
    """One row for each piece: id, start (ids of its document before it), length, ids_crc32, doc_tokens, sequence_id, offset.

    A null or empty text has the end id alone. Repeated rows are packed each for itself, null ids
    are kept, further columns are ignored, an empty table gives no rows. There is no shuffle: a task
    packs the rows of its partition, whose number heads the sequence ids.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        speller, end = Speller.of(tokenizer_path), np.array([end_id], "<u4").tobytes()
        packer = SumOfSquares(window, levels, open_windows, TaskContext.get().partitionId() << 32)
        kind = None

        def out(rows: list[tuple]) -> pa.RecordBatch:
            columns = list(zip(*rows))
            return pa.RecordBatch.from_arrays([pa.array(columns[0], kind), *(pa.array(c, pa.int64()) for c in columns[1:])], ["id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"])

        for batch in batches:
            kind = batch.schema.field(0).type
            for doc, (_, ids, _) in zip(batch.column(0), batches_of(batch.column(1), speller)):
                packer.add(doc.as_py(), ids + end)
            if rows := packer.packed():
                yield out(rows)
        packer.flush()
        if rows := packer.packed():
            yield out(rows)

    kind = dict(docs.dtypes)[id_col]
    return in_small_batches(docs.select(id_col, text_col)).mapInArrow(tidy(run), f"id {kind}, {FIELDS}").withColumnRenamed("id", id_col)
