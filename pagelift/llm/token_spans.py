"""Token counts by section: whole documents are encoded once, and token spans are joined to section spans.

A document's sections are given as character spans (here: its lines, each with the line feed that ends it, or named
fields that are laid end to end).  Tokens come with their character offsets; token spans and section spans are both
sorted and so are joined as intervals by binary search.  A token over a boundary belongs to the section that holds most
of its characters, the earlier one on a tie; `n_crossing` says how many of a section's tokens reach outside it.

Encoding works on runs that the byte-level rules never look across: a worker remembers how many bytes each token of a run
has.  A text's tokens cover its bytes without gaps, so running sums of these are the tokens' offsets, and the bytes'
characters turn them into character spans.  Where all white space is single spaces and line feeds, runs are words with the
space before them, and line feeds; in other texts they are what lies between single spaces; texts with white space next to
a space are encoded whole.  Spans and sections of all documents of a slice are laid end to end and joined at once.

Defined results: a null text is one empty section without tokens; every section gives a row, empty ones too; rows that
share an id give their sections each; an empty table gives an empty result.
"""

from __future__ import annotations

import re
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pagelift.llm.common import documents, names_of, thrifty
from pagelift.llm.packing import byte_letters, declared

MAX_CACHED = 150_000  # runs of a generation that a worker remembers; it keeps two
#: What a vocabulary file declares whose rules cut a run of letters and signs between the two only, and
#: turn each byte into a letter of the alphabet.
FRONT_END = {"normalizer": None, "pre_tokenizer": {"type": "ByteLevel", "add_prefix_space": False, "trim_offsets": True, "use_regex": True}, "end_of_word_suffix": None}
#: A space at most, letters, signs: the byte-level rules cut such a run between letters and signs only.
LETTERS_SIGNS = re.compile("( ?)([A-Za-z\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u00ff]+)([.,!?;:#$%&*|]*)")
UNSAFE = re.compile(r" \s|\s ")
SECTIONS = "doc_id long, section int, start long, end long, n_tokens long, n_crossing long"


class RunLengths(dict):
    """Run (with the space before it, if any) -> bytes of its tokens, one unsigned number each."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        super().__init__()
        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = True
        self.tokenize, self.to_alphabet, self.old = self.tokenizer.model.tokenize, byte_letters(), {}
        self.code = "B" if max(map(len, self.tokenizer.get_vocab())) < 256 else "H"
        self.short = declared(path) == FRONT_END

    def _long(self, text: str) -> bytes:
        """By the tokenizer; tokens are written in a letter a byte."""
        return array(self.code, map(len, self.tokenizer.encode(text, add_special_tokens=False).tokens)).tobytes()

    def _short(self, run: str) -> bytes | None:
        """By the model alone, without the tokenizer's front end; a run's tokens are those of its letters and its signs."""
        found = LETTERS_SIGNS.fullmatch(run)
        if found is None:
            return None
        letters = found[1] + found[2]
        letters = letters.replace(" ", "\u0120") if letters.isascii() else letters.encode().decode("latin-1").translate(self.to_alphabet)
        out = [len(t.value) for t in self.tokenize(letters)]
        if found[3]:
            out += [len(t.value) for t in self.tokenize(found[3])]
        return array(self.code, out).tobytes()

    def __missing__(self, run: str) -> bytes:
        out = self.old.get(run)
        if out is None and self.short and len(run) < 64:
            out = self._short(run)
        if out is None:
            out = self._long(run) if run else b""
        if len(self) >= MAX_CACHED:
            self.old = dict(self)
            self.clear()
        if len(run) < 64:
            self[run] = out
        return out

    def runs(self, text: str) -> list[str] | None:
        """The text cut into runs that are encoded by themselves; None if it has to be encoded whole."""
        if plain(text):
            return text.replace(" ", "\0 ").replace("\n", "\0\n\0").split("\0")
        if UNSAFE.search(text):
            return None
        first, *rest = text.split(" ")
        return [first, *(" " + r for r in rest)]

    def spans(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Start and end characters of the tokens of whole texts that are laid end to end, and where each text begins."""
        parts: list[bytes] = []
        for text in texts:
            runs = self.runs(text) if text else []
            if runs is None:
                parts.append(self._long(text))
            else:
                parts += map(self.__getitem__, runs)
        sizes = np.frombuffer(b"".join(parts), np.uint8 if self.code == "B" else np.uint16)
        ends = np.cumsum(sizes, dtype=np.int64)
        spans = np.column_stack([ends - sizes, ends])
        if not all(map(str.isascii, texts)):  # bytes to the characters they lie in
            data = np.frombuffer("".join(texts).encode(), np.uint8)
            char = np.cumsum((data & 0xC0) != 0x80)
            spans = np.column_stack([char[spans[:, 0]] - 1, char[spans[:, 1] - 1]])
        return spans, np.cumsum([0, *map(len, texts)])


#: White space but a space or a line feed; the ASCII ones also one by one, as that is faster to look for.
OTHER_SPACE = re.compile(r"[^\S \n]")
ASCII_SPACES = "\t\r\x0b\x0c\x1c\x1d\x1e\x1f"
JOINED = ("  ", " \n", "\n ", "\n\n")


def plain(text: str) -> bool:
    """Are all runs of white space single spaces or single line feeds?  Then a line feed is a token of its own, and each
    word is encoded by itself, with the space before it."""
    if "\0" in text or any(x in text for x in JOINED):
        return False
    return not any(x in text for x in ASCII_SPACES) if text.isascii() else OTHER_SPACE.search(text) is None


_RUNS: dict[str, RunLengths] = {}


def run_lengths(path: str) -> RunLengths:
    if path not in _RUNS:
        _RUNS[path] = RunLengths(path)
    return _RUNS[path]


def owners(spans: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Section of each token, and whether it reaches outside; sections begin at starts and end where the next begins."""
    first = np.searchsorted(starts, spans[:, 0], side="right") - 1
    last = np.searchsorted(starts, np.maximum(spans[:, 1] - 1, spans[:, 0]), side="right") - 1
    own, crosses = first.copy(), first != last
    ends = np.append(starts[1:], np.iinfo(np.int64).max)
    for i in np.flatnonzero(crosses):
        a, b = spans[i]
        within = range(first[i], last[i] + 1)
        own[i] = max(within, key=lambda s: (min(b, ends[s]) - max(a, starts[s]), -s))
    return own, crosses


def line_starts(text: str) -> np.ndarray:
    cuts = [m.end() for m in re.finditer("\n", text)]
    return np.array([0, *cuts], np.int64)


def counted(runs: RunLengths, texts: list[str], starts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Tokens and crossing tokens of all sections of some texts; starts: where each text's sections begin in it."""
    spans, at = runs.spans(texts)
    own, crosses = owners(spans, np.concatenate([s + a for s, a in zip(starts, at)]) if texts else np.zeros(0, np.int64))
    n = sum(map(len, starts))
    return np.bincount(own, minlength=n), np.bincount(own[crosses], minlength=n)


def by_section(docs: DataFrame, vocabulary: str, starts_of=line_starts) -> DataFrame:
    """One row a section of every document."""

    def stream(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        runs = run_lengths(vocabulary)
        for batch in thrifty(batches):
            texts = [t or "" for t in batch.column("text").to_pylist()]
            starts = [starts_of(t) for t in texts]
            tokens, crossing = counted(runs, texts, starts)
            each = np.array([len(x) for x in starts], np.int64)
            flat = np.concatenate(starts) if starts else np.zeros(0, np.int64)
            ends = np.append(flat[1:], 0)
            ends[np.cumsum(each) - 1] = [len(t) for t in texts]
            section = np.arange(len(flat)) - np.repeat(np.cumsum(each) - each, each)
            ids = batch.column("doc_id").take(pa.array(np.repeat(np.arange(len(texts)), each)))
            columns = [ids, *(pa.array(c, t) for c, t in zip((section, flat, ends, tokens, crossing), (pa.int32(), *[pa.int64()] * 4)))]
            yield pa.RecordBatch.from_arrays(columns, names=names_of(SECTIONS))

    return documents(docs).mapInArrow(stream, SECTIONS)


def by_field(docs: DataFrame, fields: list[str], vocabulary: str, joint: str = "\n") -> DataFrame:
    """Tokens of each named field: the fields are laid end to end with `joint` between them and encoded as one text; a
    joint belongs to the field before it.  Null fields are empty."""
    parts = [F.coalesce(F.col(f"`{f}`").cast("string"), F.lit("")) for f in fields]
    text = F.concat(*[x for part in parts for x in (part, F.lit(joint))][:-1])
    sizes = [F.char_length(part) + (len(joint) if f != fields[-1] else 0) for f, part in zip(fields, parts)]
    base = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text.alias("text"), F.array(*[s.cast("long") for s in sizes]).alias("sizes"))

    def stream(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        runs = run_lengths(vocabulary)
        for batch in thrifty(batches):
            starts = [np.cumsum([0, *size[:-1]]).astype(np.int64) for size in batch.column("sizes").to_pylist()]
            tokens, crossing = counted(runs, batch.column("text").to_pylist(), starts)
            ids = batch.column("doc_id").take(pa.array(np.repeat(np.arange(batch.num_rows), len(fields))))
            yield pa.RecordBatch.from_arrays([ids, pa.array(fields * batch.num_rows, pa.string()), pa.array(tokens, pa.int64()), pa.array(crossing, pa.int64())], names=["doc_id", "field", "n_tokens", "n_crossing"])

    return base.mapInArrow(stream, "doc_id long, field string, n_tokens long, n_crossing long")
