"""Token counts of whole texts, equal to the library's own, by overlap resynchronisation.

A text is worked through in chunks of ``CHUNK`` characters that overlap by ``OVERLAP``. A chunk's encoding is the
sequence of its words with their places, each word standing for its tokens; neighbouring chunks are spliced at a
*proven* border, a place where the tokenizer cuts whatever stands on either side:

* a word (a run between blanks, tabs or line feeds) that both chunks hold at the same place, whole in both;
* without one, a change between letters, digits and other characters at which the library's encoding of the overlap
  splits in two as well (texts without blanks, such as base64 or some scripts).

If neither is found, the overlap is doubled, up to all that isn't counted yet. Token counts of words are remembered,
so a frequent word is encoded once a worker.

What is proven rests on the tokenizer's file, so :class:`Rules` checks its normaliser, pattern and added tokens when it
is loaded. Texts for any other file are encoded whole by the library, which is right for every file.

Defined cases: a null or blank text has 0 tokens; repeated rows get equal counts; extra columns are ignored.
"""

from __future__ import annotations

import json
import os
import re
import sys
import unicodedata
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

CHUNK, OVERLAP = 4096, 256
LIMIT = 2048
REMEMBERED, ROWS, CHARACTERS = 1_000_000, 2000, 4_000_000


def load(path: str):
    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer

    tokenizer = Tokenizer.from_file(path)
    tokenizer.no_truncation()
    tokenizer.no_padding()
    return tokenizer


class Rules:
    """What the file of a tokenizer proves about its borders."""

    #: The normaliser and the pattern under which white space and changes of character class are borders.
    NORMALIZERS = [("NFC", None, None), ("Replace", r"\s+", " "), ("Lowercase", None, None)]
    PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as file:
            spec = json.load(file)
        steps = (spec.get("normalizer") or {}).get("normalizers", [])
        found = [(s["type"], (s.get("pattern") or {}).get("Regex"), s.get("content")) for s in steps]
        cuts = (spec.get("pre_tokenizer") or {}).get("pretokenizers", [])
        split = len(cuts) == 2 and cuts[0].get("type") == "Split" and cuts[0].get("behavior") == "Removed" and cuts[0].get("invert") is True and cuts[0]["pattern"].get("Regex") == self.PATTERN
        bytes_after = split and cuts[1].get("type") == "ByteLevel" and not cuts[1].get("add_prefix_space") and not cuts[1].get("use_regex")
        added = spec.get("added_tokens", [])
        plain = not any(t.get("normalized") or t.get("lstrip") or t.get("rstrip") or t.get("single_word") for t in added)
        model = spec.get("model", {})
        self.known = found == self.NORMALIZERS and bool(bytes_after) and plain and model.get("type") == "BPE" and not model.get("dropout") and not any(re.search(r"[ \n\t]", t["content"]) for t in added)
        self.added = [t["content"] for t in added]

    def border(self, text: str, at: int) -> bool:
        """Whether every text is cut between ``text[at - 1]`` and ``text[at]``."""
        a, b = text[at - 1], text[at]
        kinds = [unicodedata.category(c)[0] for c in (a, b)]
        if "M" in kinds or "C" in kinds or (kinds[0] == kinds[1] or set(kinds) <= {"P", "S"}) and "N" not in kinds:
            return False
        if a == "'" or any(not c.isascii() and c.lower() != c for c in (a, b)) or unicodedata.normalize("NFC", a + b) != a + b:
            return False
        after = text[at + 1 : at + 2]
        if after and unicodedata.category(after) == "M" or any(unicodedata.combining(c) for c in (b, after or " ")):
            return False
        return not any(t in text[max(0, at - len(t) + 1) : at + len(t) - 1] for t in self.added)


def words(text: str) -> list[str]:
    """Runs between blanks; single blanks separate, so places follow from lengths."""
    return text.replace("\n", " ").replace("\t", " ").split(" ")


def common_word(left: list[str], right: list[str], start: int, end: int) -> tuple[int, int] | None:
    """Indices of a word that the end of ``left`` (a chunk up to ``end``) and ``right`` (from ``start``) hold at the same
    place, cut in neither."""
    places, at = {}, end
    for i in range(len(left) - 1, 0, -1):
        at -= len(left[i])
        if at < start:
            break
        if i < len(left) - 1 and left[i]:
            places[at] = i
        at -= 1
    at = start
    for j, word in enumerate(right[:-1]):
        if at + len(word) >= end:
            return None
        if j and word and (i := places.get(at)) is not None and left[i] == word:
            return i, j
        at += len(word) + 1
    return None


class Counter:
    """Counts with a memory of words and of the pieces that the pre-tokenizer cuts them into.

    Words of printable ASCII and Latin-1 letters are cut and mapped to byte symbols here, by the pattern that
    :class:`Rules` found in the file, and only their pieces go to the tokenizer's model; any other word, and any that
    holds the start of an added token, goes through the whole library.
    """

    #: What the pattern takes as one piece, for the characters that SIMPLE admits.
    PIECES = re.compile("'s|'t|'re|'ve|'m|'ll|'d|[a-z\xdf-\xf6\xf8-\xff]+|[0-9]|[^a-z0-9\xdf-\xf6\xf8-\xff]+")
    SIMPLE = re.compile("[!-~\xc0-\xd6\xd8-\xf6\xf8-\xff]*")

    def __init__(self, path: str, chunk: int = CHUNK, overlap: int = OVERLAP):
        self.tokenizer, self.rules, self.chunk, self.overlap = load(path), Rules(path), chunk, overlap
        self.known: dict[str, int] = {}
        self.pieces: dict[str, int] = {}
        if self.rules.known:
            symbol = lambda c: self.tokenizer.pre_tokenizer.pre_tokenize_str(c)[0][0]
            self.table = str.maketrans({c: symbol(c) for c in map(chr, [*range(33, 127), *range(0xDF, 0x100)]) if c != "\xf7"})
            self.special = [t[:2] for t in self.rules.added]

    def encoded(self, text: str) -> int:
        return len(self.tokenizer.encode(text, add_special_tokens=False))

    def word(self, word: str) -> int | None:
        if not self.SIMPLE.fullmatch(word) or any(s in word for s in self.special):
            return None
        total = 0
        for piece in self.PIECES.findall(word.lower()):
            count = self.pieces.get(piece)
            if count is None:
                count = self.pieces[piece] = len(self.tokenizer.model.tokenize(piece.translate(self.table)))
            total += count
        return total

    def class_border(self, text: str, start: int, end: int) -> int | None:
        """The last change of character class in [start + 1, end) that is a border and that the library confirms."""
        for at in range(end - 1, start, -1):
            if self.rules.border(text, at):
                lo, hi = max(start, at - 64), min(end, at + 64)
                if self.encoded(text[lo:hi]) == self.encoded(text[lo:at]) + self.encoded(text[at:hi]):
                    return at
        return None

    def spliced(self, text: str) -> list[list[str]]:
        """The words of the text, as lists of one chunk each, every word once."""
        out, begin, end = [], 0, min(len(text), self.chunk)
        left = words(text[:end])
        while end < len(text):
            width = self.overlap
            while True:
                start = max(begin, end - width)
                stop = min(len(text), start + max(self.chunk, 2 * width))
                right = words(text[start:stop])
                if (both := common_word(left, right, start, end)) is not None:
                    i, j = both
                    out.append(left[:i])
                    begin = start + sum(map(len, right[:j])) + j
                    left = right[j:]
                    break
                if width >= 4 * self.overlap and (at := self.class_border(text, start, end)) is not None:
                    out.append(words(text[begin:at]))
                    begin, left = at, words(text[at:stop])
                    break
                if start == begin:  # nothing left to widen by: go on from there in one longer piece
                    stop = min(len(text), max(stop, 2 * end - begin))
                    left = words(text[begin:stop])
                    break
                width *= 2
            end = stop
        return [*out, left]

    def batch(self, texts: list[str]) -> list[int]:
        if not self.rules.known:
            return [len(x) for x in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]
        split = [self.spliced(t) for t in texts]
        if len(self.known) > REMEMBERED:
            self.known.clear()
        if len(self.pieces) > REMEMBERED:
            self.pieces.clear()
        hard = []
        for w in {w for parts in split for part in parts for w in part}.difference(self.known):
            count = self.word(w)
            if count is None:
                hard.append(w)
            else:
                self.known[w] = count
        for at in range(0, len(hard), 4096):
            part = hard[at : at + 4096]
            self.known.update(zip(part, map(len, self.tokenizer.encode_batch_fast(part, add_special_tokens=False)), strict=True))
        get = self.known.__getitem__
        return [sum(sum(map(get, part)) for part in parts) for parts in split]


def _portions(texts: list[str]) -> Iterator[list[str]]:
    """Rows of a batch, so many at a time that words in memory stay bounded by ``CHARACTERS`` or one text."""
    held, size = [], 0
    for t in texts:
        if held and (len(held) >= ROWS or size + len(t) > CHARACTERS):
            yield held
            held, size = [], 0
        held.append(t)
        size += len(t)
    if held:
        yield held


def _counts(path: str, chunk: int, overlap: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = sys.__dict__.setdefault("_hopline_counters", {})  # one a worker process, for all its tasks
        counter = held.get((path, chunk, overlap)) or held.setdefault((path, chunk, overlap), Counter(path, chunk, overlap))
        for batch in batches:
            texts = [x or "" for x in batch.column("text").to_pylist()]
            counts = [n for part in _portions(texts) for n in counter.batch(part)]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("n_bytes"), pa.array(counts, pa.int64())], names=["doc_id", "n_bytes", "n_tokens"])

    return run


def token_counts(docs: DataFrame, path: str, limit: int = LIMIT, chunk: int = CHUNK, overlap: int = OVERLAP) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit; ``path`` names the tokenizer's file on every executor."""
    row = docs.select("doc_id", "text", F.octet_length(F.coalesce("text", F.lit(""))).cast("long").alias("n_bytes"))
    return row.mapInArrow(_counts(path, chunk, overlap), "doc_id long, n_bytes long, n_tokens long").withColumn("over_limit", F.col("n_tokens") > limit)
