"""Token counts and ids of whole texts, exactly as the tokenizer library gives them.

A huge text is encoded by the library in overlapping chunks, with offsets. In the overlap the words
(pre-tokens) of both chunks are aligned: where several successive words have the same offsets and the
same ids in both, the first one's start is a common boundary and the chunks are spliced there. If no run
of words agrees, the overlap is widened; if it already reaches back to the last splice, the chunk itself
is made longer, at worst to the whole text.

Such a boundary is proven stable for tokenizers whose normaliser and pre-tokenizer scan from left to
right and look no further than one character ahead, with merges inside a word only: the left chunk has all
that stands before the boundary and words enough behind it, and from the boundary on the right chunk's
scan is that of the whole text. scans_forward() reads that from the tokenizer's own file; a text of any
other tokenizer is encoded as a whole.

Texts that aren't huge are one chunk. For lower-casing word tokenizers with word ends their pieces between
blanks are encoded once and remembered, up to a fixed number for a worker.
"""

from __future__ import annotations

import json
import re
from collections.abc import Iterable, Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from cadenza.llm.common import in_small_batches, tidy

#: Characters of a chunk, of the overlap at first, words that must agree, and pieces remembered by a worker (two generations of them).
CHUNK_CHARS = 65_536
OVERLAP_CHARS = 256
RUN_WORDS = 3
REMEMBERED = 200_000
#: Texts are encoded together up to so many characters.
TOGETHER_CHARS = 1 << 20

#: Marks of ASCII that form one word when they stand together; no apostrophe and no angle bracket, as contractions and special strings begin with these.
MARKS = "!#$%&*+,./:;=?@^_`|~-()[]{}\""
#: Lower-case letters of Latin-1, which no step of normalisation changes.
_LATIN = re.compile(r"[a-z\xdf-\xf6\xf8-\xff]+")

#: Kinds of normalisers and pre-tokenizers that scan forward.
FORWARD_NORMALISERS = {"NFC", "NFD", "NFKC", "NFKD", "Lowercase", "StripAccents"}
FORWARD_SPLITTERS = {"Whitespace", "WhitespaceSplit", "BertPreTokenizer", "Punctuation"}


def _parts(node: dict | None, inner: str) -> list[dict]:
    if node is None:
        return []
    return [x for part in node[inner] for x in _parts(part, inner)] if node["type"] == "Sequence" else [node]


def _looks_one_ahead(pattern: dict) -> bool:
    """Whether a pattern has no look-around but that for one character of white space, and no anchors."""
    if "String" in pattern:
        return True
    rest = re.sub(r"\(\?!\\S\)|\(\?i:|\(\?:", "", pattern["Regex"])
    return not re.search(r"\(\?|\\[AbBGzZ]|(?<!\\)\$|(?<![\\\[])\^", rest)


def scans_forward(spec: dict) -> bool:
    """Whether boundaries between words are stable, by the tokenizer's own description."""
    model = spec["model"]
    if model["type"] not in ("BPE", "WordPiece", "WordLevel") or model.get("dropout"):
        return False
    for x in _parts(spec.get("normalizer"), "normalizers"):
        if x["type"] not in FORWARD_NORMALISERS and not (x["type"] == "Replace" and x["pattern"] in ({"Regex": r"\s+"}, {"String": " "})):
            return False
    splits = False
    for x in _parts(spec.get("pre_tokenizer"), "pretokenizers"):
        if x["type"] == "Split":
            if x["behavior"] not in ("Removed", "Isolated") or not _looks_one_ahead(x["pattern"]):
                return False
            splits = True
        elif x["type"] == "ByteLevel":
            if x["add_prefix_space"]:
                return False
            splits = splits or x["use_regex"]
        elif x["type"] in FORWARD_SPLITTERS:
            splits = True
        else:
            return False
    return splits


def splits_at_blanks(spec: dict) -> bool:
    """Whether pieces between blanks can be encoded each for itself, and runs of letters and of marks in them too: lower case, white space dropped, word ends in the vocabulary."""
    kinds = [x["type"] for x in _parts(spec.get("normalizer"), "normalizers")]
    before = _parts(spec.get("pre_tokenizer"), "pretokenizers")
    if not scans_forward(spec) or kinds != ["NFC", "Replace", "Lowercase"] or [x["type"] for x in before] != ["Split", "ByteLevel"]:
        return False
    split = before[0]
    words = split["pattern"].get("Regex") == r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+" and split["behavior"] == "Removed" and split["invert"]
    plain = all(not x["lstrip"] and not x["rstrip"] and not re.search(r"\s", x["content"]) and x["content"].startswith("<|") for x in spec["added_tokens"])
    return bool(words and plain and not before[1]["use_regex"] and spec["model"].get("end_of_word_suffix"))


class Speller:
    """Ids as little-endian unsigned 32-bit bytes."""

    _shared: dict[str, "Speller"] = {}

    def __init__(self, path: str, remembered: int = REMEMBERED):
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.library.no_truncation()
        self.library.no_padding()
        spec = json.loads(self.library.to_str())
        self.forward, self.by_blanks = scans_forward(spec), splits_at_blanks(spec)
        self.remembered = remembered
        self.new: dict[str, bytes] = {"": b""}
        self.old: dict[str, bytes] = {}
        if self.by_blanks:
            from tokenizers import pre_tokenizers

            self.model = self.library.model
            self.packed = [i.to_bytes(4, "little") for i in range(self.library.get_vocab_size(with_added_tokens=True))]
            level = pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)
            # the library's own byte alphabet; plain letters stand for themselves
            self.alphabet = {ord(c): level.pre_tokenize_str(c)[0][0] for c in map(chr, range(0xDF, 0x100))}

    @classmethod
    def of(cls, path: str) -> Speller:
        """One for each worker process and path."""
        if path not in cls._shared:
            cls._shared[path] = cls(path)
        return cls._shared[path]

    def encode_whole(self, texts: list[str]) -> list[bytes]:
        """By the library, text by text."""
        return [np.array(e.ids, "<u4").tobytes() for e in self.library.encode_batch(texts, add_special_tokens=False)]

    # texts that aren't huge, by pieces between blanks

    def _learn(self, pieces: Iterable[str]) -> dict[str, bytes]:
        """A mapping that has all these pieces."""
        wanted = set(pieces)
        missing = wanted.difference(self.new)
        if not missing:
            return self.new
        if len(self.new) + len(missing) > self.remembered:
            self.old, self.new = self.new, {"": b""}
            missing = wanted
            missing.discard("")
        new, old, tokenize, packed, alphabet = self.new, self.old, self.model.tokenize, self.packed, self.alphabet
        odd, marked = [], []
        for p in missing:
            if (known := old.get(p)) is not None:
                new[p] = known
                continue
            word = p.strip(MARKS)
            if word.isascii():
                plain = word.isalpha() and word.islower()
                spelt = word
            else:
                plain = _LATIN.fullmatch(word)
                spelt = word.translate(alphabet) if plain else word
            if not plain:
                odd.append(p)
                continue
            if word not in new:
                known = old.get(word)
                new[word] = known if known is not None else b"".join([packed[t.id] for t in tokenize(spelt)])
            if len(word) < len(p):
                marked.append((p, word))
        runs = {r for p, word in marked for r in p.split(word, 1)}
        odd += runs.difference(new)
        for i in range(0, len(odd), 5000):
            new.update(zip(odd[i : i + 5000], self.encode_whole(odd[i : i + 5000])))
        for p, word in marked:
            before, _, after = p.partition(word)
            new[p] = new[before] + new[word] + new[after]
        return new

    # huge texts

    def words(self, text: str, low: int, high: int) -> list[tuple[int, int, bytes]]:
        """(start, end, ids) of each word of a chunk, placed in the text."""
        e = self.library.encode(text[low:high], add_special_tokens=False)
        ids = np.array(e.ids, "<u4")
        which = e.word_ids
        cuts = [0, *(i for i in range(1, len(which)) if which[i] is None or which[i] != which[i - 1]), len(which)]
        at = e.offsets
        return [(at[i][0] + low, at[j - 1][1] + low, ids[i:j].tobytes()) for i, j in zip(cuts, cuts[1:]) if j > i]

    def spliced(self, text: str, chunk: int = CHUNK_CHARS, overlap: int = OVERLAP_CHARS, run: int = RUN_WORDS) -> tuple[list[bytes], int]:
        """Ids of the words of a whole text, and the number of chunks they are from."""
        if not self.forward:
            return self.encode_whole([text]), 1
        out: list[bytes] = []
        start, end = 0, min(chunk, len(text))
        left, taken, chunks = self.words(text, start, end), 0, 1
        while end < len(text):
            wide, beyond = overlap, min(end + chunk, len(text))
            cut = None
            while cut is None and end - wide > start:
                right = self.words(text, end - wide, beyond)
                cut = common_boundary(left, taken, right, end - wide, end, run)
                wide = wide if cut else 2 * wide
            if cut:
                out += [ids for _, _, ids in left[taken : cut[0]]]
                left, taken, start, end = right, cut[1], end - wide, beyond
                chunks += 1
            else:  # as far back as it goes: the chunk becomes longer
                end = min(end + (end - start), len(text))
                left = self.words(text, start, end)
        out += [ids for _, _, ids in left[taken:]]
        return out, chunks


def common_boundary(left: list[tuple], taken: int, right: list[tuple], low: int, end: int, run: int) -> tuple[int, int] | None:
    """Indices, in the words of two chunks, of a word from which on `run` words agree in offsets and ids; they touch neither the right chunk's start (low) nor the left one's end. Words of the left one before `taken` are spliced already."""
    place = {w[0]: j for j, w in enumerate(right) if low < w[0] < end}
    for i in range(len(left) - run, taken - 1, -1):
        if left[i][0] <= low:
            return None
        j = place.get(left[i][0])
        if j is not None and left[i + run - 1][1] < end and left[i : i + run] == right[j : j + run]:
            return i, j
    return None


def _pieces(text: str) -> list[str]:
    """Pieces between blanks; lower-cased where that surely agrees with the library's own way."""
    try:
        text.encode("latin-1")
        text = text if "<|" in text else text.lower()
    except UnicodeEncodeError:
        pass
    return text.replace("\n", " ").replace("\t", " ").split(" ")


def encode(text: str | None, speller: Speller) -> bytes:
    """Ids of the whole text as little-endian unsigned 32-bit bytes; null has none."""
    return encode_all([text], speller)[0][0]


def encode_all(texts: list[str | None], speller: Speller, chunk: int = CHUNK_CHARS, overlap: int = OVERLAP_CHARS) -> list[tuple[bytes, int]]:
    """For each text its ids and the number of chunks they are from."""
    out: list[tuple[bytes, int] | None] = [None] * len(texts)
    held: list[tuple[int, str]] = []
    size = 0

    def spell() -> None:
        if speller.by_blanks:
            pieces = [_pieces(text) for _, text in held]
            known = speller._learn(chain.from_iterable(pieces)).__getitem__
            found = [b"".join(map(known, p)) for p in pieces]
        else:
            found = speller.encode_whole([text for _, text in held])
        for (i, _), ids in zip(held, found):
            out[i] = (ids, 1)
        held.clear()

    for i, text in enumerate(texts):
        if len(text := text or "") > chunk:
            words, chunks = speller.spliced(text, chunk, overlap)
            out[i] = (b"".join(words), chunks)
            continue
        held.append((i, text))
        if (size := size + len(text)) > TOGETHER_CHARS:
            spell()
            size = 0
    spell()
    return out


def batches_of(column: pa.Array, speller: Speller, chunk: int = CHUNK_CHARS, overlap: int = OVERLAP_CHARS) -> Iterator[tuple[str, bytes, int]]:
    """Each text of a column (null: empty) with its ids and number of chunks; some texts at a time."""
    some: list[str] = []
    held = 0
    for value in column:
        some.append(value.as_py() or "")
        held += len(some[-1])
        if held > TOGETHER_CHARS:
            yield from ((t, *x) for t, x in zip(some, encode_all(some, speller, chunk, overlap)))
            some, held = [], 0
    yield from ((t, *x) for t, x in zip(some, encode_all(some, speller, chunk, overlap)))


def count_tokens(docs: DataFrame, tokenizer_path: str, limit: int = 2048, id_col: str = "doc_id", text_col: str = "text", chunk: int = CHUNK_CHARS, overlap: int = OVERLAP_CHARS) -> DataFrame:
    """One row for each row of docs: id, n_bytes of UTF-8, n_tokens, over_limit, n_chunks that were spliced.

    Null counts as empty (0 tokens, one chunk). Repeated rows and null ids are kept as they are;
    further columns are ignored; an empty table gives an empty result. There is no shuffle.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        speller = Speller.of(tokenizer_path)
        for batch in batches:
            found = [(len(text.encode("utf-8")), len(ids) // 4, n) for text, ids, n in batches_of(batch.column(1), speller, chunk, overlap)]
            n_bytes, n_tokens, n_chunks = ([r[j] for r in found] for j in range(3))
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(n_bytes, pa.int64()), pa.array(n_tokens, pa.int64()), pa.array([n > limit for n in n_tokens], pa.bool_()), pa.array(n_chunks, pa.int64())],
                ["id", "n_bytes", "n_tokens", "over_limit", "n_chunks"],
            )

    kind = dict(docs.dtypes)[id_col]
    counted = in_small_batches(docs.select(id_col, text_col)).mapInArrow(tidy(run), f"id {kind}, n_bytes bigint, n_tokens bigint, over_limit boolean, n_chunks bigint")
    return counted.withColumnRenamed("id", id_col)
