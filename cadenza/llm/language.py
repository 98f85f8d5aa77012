"""Language of texts, and of spans in texts of several languages.

The script of a word's first letter narrows the languages to those whose training texts use
it. Each word has a score for each of these from its letter n-grams; a Viterbi pass with a
penalty for each change of language labels the words, so a lone odd word doesn't make a span.
The language that covers most letters is the text's.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cadenza.llm.common import in_small_batches, tidy
from cadenza.llm.words import mix

#: Hashed n-grams, the most languages that are learned, and words a worker remembers.
BUCKETS = 1 << 15
MOST_LANGUAGES = 2000
REMEMBERED = 150_000
SWITCH_PENALTY = 12.0
#: A language uses a script if so large a part of its words does.
SCRIPT_SHARE = 0.005
#: Numbers that a step over many words or texts holds at once.
ROOM = 4_000_000

#: First code points of Unicode ranges of scripts, each up to the next.
SCRIPTS = [(0x0, "latin"), (0x370, "greek"), (0x400, "cyrillic"), (0x530, "armenian"), (0x590, "hebrew"), (0x600, "arabic"), (0x700, "other"), (0x900, "devanagari"), (0x980, "bengali"), (0xA00, "gurmukhi"), (0xA80, "gujarati"), (0xB00, "oriya"), (0xB80, "tamil"), (0xC00, "telugu"), (0xC80, "kannada"), (0xD00, "malayalam"), (0xD80, "sinhala"), (0xE00, "thai"), (0xE80, "lao"), (0xF00, "tibetan"), (0x1000, "myanmar"), (0x10A0, "georgian"), (0x1100, "hangul"), (0x1200, "ethiopic"), (0x1400, "other"), (0x1780, "khmer"), (0x1800, "other"), (0x1E00, "latin"), (0x1F00, "greek"), (0x2000, "other"), (0x3040, "kana"), (0x3100, "other"), (0x3400, "han"), (0xA000, "other"), (0xAC00, "hangul"), (0xD7B0, "other"), (0xF900, "han"), (0xFB00, "other"), (0xFF21, "latin"), (0xFF66, "kana"), (0xFFA0, "hangul"), (0xFFE0, "other"), (0x20000, "han"), (0x32000, "other")]
NAMES = sorted({n for _, n in SCRIPTS})
_STARTS = np.array([s for s, _ in SCRIPTS])
_NUMBER = np.array([NAMES.index(n) for _, n in SCRIPTS])

_U = np.uint64
_PLACES = mix(np.arange(1, 9, dtype=np.uint64) * _U(0x9E3779B97F4A7C15)) | _U(1)
_WORD = re.compile(r"[^\W\d_]+")


def scripts_of(letters: list[str]) -> np.ndarray:
    return _NUMBER[np.searchsorted(_STARTS, np.fromiter(map(ord, letters), np.int64, len(letters)), "right") - 1]


def grams(words: list[str], buckets: int) -> tuple[np.ndarray, np.ndarray]:
    """For each byte of the words' UTF-8, ends marked, the buckets of three n-grams (columns): the 3 and the 4 bytes from there on, and at a word's start the whole word; `buckets` where there is none. And where words start."""
    data = [b"^%b$" % w.encode("utf-8", "replace") for w in words]
    sizes = np.fromiter(map(len, data), np.int64, len(data))
    flat = np.frombuffer(b"".join(data), np.uint8).astype(np.uint64)
    n = len(flat)
    starts = np.cumsum(sizes) - sizes
    left = np.repeat(starts + sizes, sizes) - np.arange(n)  # bytes from here to the word's end
    out = np.full((n, 3), buckets, np.int64)
    h = np.zeros(n, np.uint64)
    for k in range(4):
        h[: n - k] += (flat[k:] + _U(1)) * _PLACES[k]
        if k >= 2:
            whole = left > k
            out[whole, k - 2] = (mix(h[whole]) % _U(buckets)).astype(np.int64)
    if n:
        # longer words than one 4-gram have themselves too: a sum over their bytes, each by its place
        place = mix((np.arange(n) - np.repeat(starts, sizes)).astype(np.uint64) + _U(17)) | _U(1)
        total = np.add.reduceat((flat + _U(1)) * place, starts)
        long = sizes > 4
        out[starts[long], 2] = (mix(total[long]) % _U(buckets)).astype(np.int64)
    return out, starts


def first_letter(word: str) -> str:
    """The first letter; empty if the word has none (some numerals count as word characters)."""
    return word[0] if word[0].isalpha() else next((c for c in word if c.isalpha()), "")


@dataclass
class Model:
    languages: list[str]
    weights: np.ndarray  # log share of each n-gram, by language
    scripts: np.ndarray  # by language and script, whether it is used
    buckets: int = BUCKETS
    known: dict[str, int] = field(default_factory=dict, repr=False)
    scores: np.ndarray | None = field(default=None, repr=False)

    def __getstate__(self):
        return {**self.__dict__, "known": {}, "scores": None}

    def score(self, words: list[str]) -> np.ndarray:
        """A row of scores by language for each word; n-grams overlap, so their sum says less than as many independent ones and is halved."""
        weights = np.concatenate([self.weights, np.zeros((len(self.languages), 1))], axis=1)
        found = np.zeros((len(words), len(self.languages)))
        at = 0
        while at < len(words):
            end, held = at, 0
            while end < len(words) and (end == at or held < ROOM // (3 * len(self.languages))):
                held += len(words[end]) + 2
                end += 1
            places, starts = grams(words[at:end], self.buckets)
            for j, w in enumerate(weights):
                found[at:end, j] = np.add.reduceat(w[places].sum(axis=1), starts) / 2.0
            at = end
        if words:
            used = self.scripts[:, scripts_of([first_letter(w) for w in words])].T
            found = np.where(used | ~used.any(axis=1, keepdims=True), found, -1e4)
        return found

    def numbers(self, words: list[list[str]]) -> list[np.ndarray]:
        """For each list of words the rows of self.scores; row 0 is for words without letters."""
        every = set().union(*words)
        new = every.difference(self.known)
        if self.scores is None or len(self.known) + len(new) > REMEMBERED:
            self.known, self.scores = {}, np.zeros((1, len(self.languages)))
            new = every
        lettered = [w for w in new if first_letter(w)]
        if len(lettered) < len(new):
            self.known.update((w, 0) for w in new if not first_letter(w))
        if lettered:
            self.known.update(zip(lettered, range(len(self.scores), len(self.scores) + len(lettered))))
            self.scores = np.concatenate([self.scores, self.score(lettered)])
        known = self.known.__getitem__
        return [np.fromiter(map(known, ws), np.int32, len(ws)) for ws in words]


def _step(value: np.ndarray, gained: np.ndarray, penalty: float, own: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Values after one more word, by sequence and label, and the labels they come from."""
    best = value.argmax(axis=1)[:, None]
    changed = value.max(axis=1, keepdims=True) - penalty
    stays = value >= changed
    return np.where(stays, value, changed) + gained, np.where(stays, own, best)


def _constant(scores: np.ndarray, penalty: float) -> int | None:
    """The label that all words of a sequence surely have, or None if that can't be told at once.

    If no stretch of words gains as much as one change costs by any other label, each path that leaves the best label loses.
    """
    best = int(scores.sum(axis=0).argmax())
    gained = np.cumsum(scores - scores[:, best : best + 1], axis=0)
    lowest = np.minimum(np.minimum.accumulate(gained, axis=0), 0.0)
    most = max(gained[0].max(), (gained[1:] - lowest[:-1]).max(initial=0.0))
    return best if most < penalty - 1e-6 else None


def viterbi_rows(numbers: list[np.ndarray], table: np.ndarray, penalty: float, room: int = ROOM) -> list[np.ndarray]:
    """The best labels of each sequence of rows of a table of scores, many sequences at a time.

    What is held is bounded by room: a sequence too long for it is passed over twice, first for the
    values at some of its places, then backwards from place to place.
    """
    n_labels = table.shape[1]
    out: list[np.ndarray] = [np.empty(0, np.int64)] * len(numbers)
    open_ones = []
    for i, n in enumerate(numbers):
        label = _constant(table[n], penalty) if 0 < len(n) * n_labels <= room else None
        if label is not None:
            out[i] = np.full(len(n), label, np.int64)
        elif len(n):
            open_ones.append(i)
    order = sorted(open_ones, key=lambda i: -len(numbers[i]))
    own = np.arange(n_labels, dtype=np.int16)
    at = 0
    while at < len(order):
        longest = len(numbers[order[at]])
        group = order[at : at + max(1, min(512, room // (longest * n_labels)))]
        at += len(group)
        # past its end a sequence has row 0, whose scores are 0, and so stays in its best label
        rows = np.zeros((longest, len(group)), np.int32)
        for j, i in enumerate(group):
            rows[: len(numbers[i]), j] = numbers[i]
        span = max(1, min(longest, room // (len(group) * n_labels)))
        value, kept = table[rows[0]].copy(), []
        for t in range(1, longest):
            if (t - 1) % span == 0:
                kept.append(value)
                if longest - t <= span:
                    break  # the last stretch is passed over below
            value, _ = _step(value, table[rows[t]], penalty, own)
        labels = np.empty((longest, len(group)), np.int64)
        label, each = value.argmax(axis=1) if longest == 1 else None, np.arange(len(group))
        for k in range(len(kept) - 1, -1, -1):
            first, value = 1 + k * span, kept[k]
            source = []
            for t in range(first, min(first + span, longest)):
                value, came = _step(value, table[rows[t]], penalty, own)
                source.append(came)
            label = value.argmax(axis=1) if label is None else label
            for t in range(first + len(source) - 1, first - 1, -1):
                labels[t] = label
                label = source[t - first][each, label].astype(np.int64)
        labels[0] = label
        for j, i in enumerate(group):
            out[i] = labels[: len(numbers[i]), j]
    return out


def viterbi(scores: list[np.ndarray], penalty: float, room: int = ROOM) -> list[np.ndarray]:
    """The same for sequences of score rows."""
    ends = np.cumsum([1, *map(len, scores)])
    return viterbi_rows([np.arange(a, b) for a, b in zip(ends, ends[1:])], np.concatenate([np.zeros((1, scores[0].shape[1])), *scores]) if scores else np.zeros((1, 1)), penalty, room)


def train(docs: DataFrame, text_col: str = "text", lang_col: str = "lang", buckets: int = BUCKETS, most_languages: int = MOST_LANGUAGES) -> Model:
    """From all rows of docs that have a text and a language. Counts are made where the rows lie; buckets + scripts numbers for each language come to the driver.

    Of more languages than most_languages those with the most texts are learned, ties by name.
    """
    docs = docs.where(F.col(text_col).isNotNull() & F.col(lang_col).isNotNull()).select(F.col(lang_col).cast("string").alias("lang"), F.col(text_col).alias("text"))
    languages = sorted(r.lang for r in docs.groupBy("lang").count().orderBy(F.desc("count"), "lang").limit(most_languages).collect())
    number = {lang: i for i, lang in enumerate(languages)}
    width = buckets + len(NAMES)

    def counted(counter: Counter) -> np.ndarray:
        words = [w for w in counter if first_letter(w)]
        times = np.fromiter((counter[w] for w in words), np.float64, len(words))
        row = np.zeros(width + 1)
        for i in range(0, len(words), 100_000):
            some = words[i : i + 100_000]
            places, starts = grams(some, buckets)
            each = np.repeat(times[i : i + 100_000], np.diff(np.append(starts, len(places))))
            row += np.bincount(np.where(places == buckets, width, places).ravel(), np.repeat(each, 3), width + 1)
            row += np.bincount(buckets + scripts_of([first_letter(w) for w in some]), times[i : i + 100_000], width + 1)
        return row[:width]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, Counter] = {}

        def out() -> Iterator[pa.RecordBatch]:
            for lang, counter in held.items():
                row = counted(counter)
                bucket = row.nonzero()[0]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(bucket), lang, np.int32)), pa.array(bucket.astype(np.int32)), pa.array(row[bucket])], ["lang", "bucket", "n"])
            held.clear()

        for batch in batches:
            for lang, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                if lang in number:
                    held.setdefault(number[lang], Counter()).update(_WORD.findall(text.as_py().lower()))
            if sum(map(len, held.values())) > 4 * REMEMBERED:
                yield from out()
        yield from out()

    counts = np.zeros((len(languages), width))
    for r in in_small_batches(docs).mapInArrow(tidy(run), "lang int, bucket int, n double").groupBy("lang", "bucket").agg(F.sum("n").alias("n")).toLocalIterator():
        counts[r.lang, r.bucket] = r.n
    shares = counts[:, :buckets] + 0.5
    scripts = counts[:, buckets:]
    return Model(languages, np.log(shares / shares.sum(axis=1, keepdims=True)), scripts >= SCRIPT_SHARE * np.maximum(scripts.sum(axis=1, keepdims=True), 1), buckets)


def identify(docs: DataFrame, model: Model, penalty: float = SWITCH_PENALTY, with_spans: bool = True, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row for each row of docs: id, lang_pred, score (part of the letters that are in it), spans array<struct<start, end, lang>> (code points; null if not asked for).

    A null text, or one without letters, is `und` with score 0 and no spans, as is every text if the
    model knows no language. Ties go to the language first in order. Repeated rows and null ids are
    kept; further columns are ignored; an empty table gives no rows. There is no shuffle.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)
    span_type = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64()), ("lang", pa.string())]))

    def judge(texts: list[str]) -> list[tuple[str, float, list | None]]:
        m = shared.value
        if not m.languages:
            return [("und", 0.0, [] if with_spans else None)] * len(texts)
        places = [[(x.start(), x.end()) for x in _WORD.finditer(t)] for t in texts] if with_spans else []
        words = [[t[a:b].lower() for a, b in p] for t, p in zip(texts, places)] if with_spans else [_WORD.findall(t.lower()) for t in texts]
        numbers = m.numbers(words)
        labels = viterbi_rows(numbers, m.scores, penalty)
        out = []
        for i, (ws, n, label) in enumerate(zip(words, numbers, labels)):
            sizes = np.fromiter(map(len, ws), np.int64, len(ws)) * (n > 0)
            if not sizes.any():
                out.append(("und", 0.0, [] if with_spans else None))
                continue
            letters = np.bincount(label, sizes, len(m.languages))
            best = int(letters.argmax())
            spans = None
            if with_spans:
                cuts = np.flatnonzero(np.diff(label)) + 1
                starts, ends = [0, *cuts.tolist()], [*cuts.tolist(), len(ws)]
                spans = [{"start": places[i][a][0], "end": places[i][b - 1][1], "lang": m.languages[label[a]]} for a, b in zip(starts, ends)]
            out.append((m.languages[best], float(letters[best] / letters.sum()), spans))
        return out

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found, some, held = [], [], 0
            for value in batch.column(1):
                some.append(value.as_py() or "")
                held += len(some[-1])
                if held > ROOM:
                    found += judge(some)
                    some, held = [], 0
            found += judge(some)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([x for x, _, _ in found], pa.string()), pa.array([x for _, x, _ in found], pa.float64()), pa.array([x for _, _, x in found], span_type)], ["id", "lang_pred", "score", "spans"])

    kind = dict(docs.dtypes)[id_col]
    return in_small_batches(docs.select(id_col, text_col)).mapInArrow(tidy(run), f"id {kind}, lang_pred string, score double, spans array<struct<start:bigint,end:bigint,lang:string>>").withColumnRenamed("id", id_col)
