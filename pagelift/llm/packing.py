"""Best-fit packing of tokenised documents into sequences, planned on the histogram of lengths.

1. One pass encodes whole texts and emits one row a piece: length and digest, no ids.
2. The histogram of lengths (at most `capacity` rows) is planned on the driver: best fit, longest first, over counts.
   Sequences that are filled alike are one group, so the plan's size depends on the capacity and not on the corpus.
3. Documents take their slots by joining on (length, rank).  Ranks are counted within (length, bucket) and shifted by
   the buckets' totals.  A length has as many buckets as its count asks for, so one that a third of all pieces have is
   ranked by many tasks of RANKED rows each.

Defined results: a null text is empty and packs as the closing token alone; rows that share an id are separate
documents; an empty table packs into nothing.
"""

from __future__ import annotations

import json
import re
import sys
import zlib
from array import array
from collections import defaultdict
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pagelift.llm.common import cut, documents, names_of, raw, thrifty

RANKED = 10_000  # pieces of a length that one task ranks
MOST_SLOTS = 1_000_000  # slots that are broadcast
MAX_CACHED = 200_000  # runs of a generation that a worker remembers; it keeps two
#: Runs of unaccented or Latin-1 letters and of plain signs: the vocabulary's rules cut a run between the two only.
SIGNS = b".,!?;:#$%&*|"
LETTERS_SIGNS = re.compile("([A-Za-z\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u00ff]*)([.,!?;:#$%&*|]*)")


#: What a vocabulary file declares that composes and lower-cases, and cuts runs of letters from runs of signs.
FRONT_END = {
    "normalizer": {"type": "Sequence", "normalizers": [{"type": "NFC"}, {"type": "Replace", "pattern": {"Regex": "\\s+"}, "content": " "}, {"type": "Lowercase"}]},
    "pre_tokenizer": {"type": "Sequence", "pretokenizers": [{"type": "Split", "pattern": {"Regex": "'s|'t|'re|'ve|'m|'ll|'d|[\\p{L}]+|[\\p{N}]|[^\\s\\p{L}\\p{N}]+"}, "behavior": "Removed", "invert": True}, {"type": "ByteLevel", "add_prefix_space": False, "trim_offsets": True, "use_regex": False}]},
    "end_of_word_suffix": "</w>",
}


def declared(path: str) -> dict:
    """What comes before the model in a vocabulary file."""
    with open(path, encoding="utf-8") as f:
        found = json.load(f)
    return {"normalizer": found["normalizer"], "pre_tokenizer": found["pre_tokenizer"], "end_of_word_suffix": found["model"]["end_of_word_suffix"]}


def byte_letters() -> dict[int, str]:
    """The public byte-level alphabet: a printable letter for each byte, given as Latin-1."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = [b for b in range(256) if b not in plain]
    return {b: chr(256 + i) for i, b in enumerate(rest)}


def little(ids: list[int]) -> bytes:
    """Unsigned 32-bit little-endian."""
    out = array("I", ids)
    if sys.byteorder != "little":
        out.byteswap()
    return out.tobytes()


class WordBytes(dict):
    """Run of non-space bytes -> its ids as little-endian bytes.  Encoding a run alone gives what it gives in context,
    as the vocabulary drops white space and no rule looks across it.  Runs of letters and signs skip the tokenizer's
    front end where the file declares the rules that make this the same."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        super().__init__()
        tokenizer = Tokenizer.from_file(path)
        self.encode, self.tokenize, self.old = tokenizer.encode, tokenizer.model.tokenize, {}
        self.to_alphabet = byte_letters()
        self.short = declared(path) == FRONT_END

    def _encoded(self, text: str) -> bytes:
        return little(self.encode(text, add_special_tokens=False).ids)

    def _model(self, piece: str) -> bytes:
        return little([t.id for t in self.tokenize(piece)])

    def _pieces(self, word: bytes) -> bytes | None:
        """Letters, then signs, by the model alone; both as words of their own, which are remembered."""
        if word.isalpha():  # of ASCII letters
            low = word.lower()
            return self[low] if low != word else self._model(word.decode())
        if word[:-1].isalpha() and word[-1] in SIGNS:
            return self[word[:-1]] + self[word[-1:]]
        text = word.decode()
        found = LETTERS_SIGNS.fullmatch(text)
        if found is None:
            return None
        letters, signs = found[1].lower(), found[2]
        if not letters.isascii():
            letters = letters.encode().decode("latin-1").translate(self.to_alphabet)
        return (self._model(letters) if letters else b"") + (self._model(signs) if signs else b"")

    def __missing__(self, word: bytes) -> bytes:
        out = self.old.get(word)
        if out is None and self.short and len(word) <= 64:
            out = self._pieces(word)
        if out is None:
            out = self._encoded(word.decode()) if word else b""
        if len(self) >= MAX_CACHED:
            self.old = dict(self)
            self.clear()
        if len(word) <= 64:
            self[word] = out
        return out


_WORDS: dict[str, WordBytes] = {}  # of this worker process, over its tasks


def word_bytes(path: str) -> WordBytes:
    if path not in _WORDS:
        _WORDS[path] = WordBytes(path)
    return _WORDS[path]


SPACES = bytes.maketrans(b"\t\n\r", b"   ")
PIECES = "doc_id long, row long, piece int, start long, length long, ids_crc32 long"


def encode_pieces(path: str, capacity: int, end_id: int):
    end = little([end_id])

    def stream(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = word_bytes(path)
        for batch in thrifty(batches):
            rows = []
            for i, r, text in zip(batch.column("doc_id").to_pylist(), batch.column("row").to_pylist(), raw(batch.column("text"))):
                ids = b"".join(map(words.__getitem__, (text or b"").translate(SPACES).split(b" "))) + end
                for piece, at in enumerate(range(0, len(ids), 4 * capacity)):
                    part = ids[at : at + 4 * capacity]
                    rows.append((i, r, piece, at // 4, len(part) // 4, zlib.crc32(part)))
            kinds = (pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(list(zip(*rows)) or [[]] * 6, kinds)], names=names_of(PIECES))

    return stream


def plan(histogram: dict[int, int], capacity: int) -> list[tuple[int, int, int, int, int]]:
    """Slots (length, first rank, last rank + 1, sequence of the first, offset) for all pieces: best fit, longest first.

    A group is sequences that hold the same lengths.  Putting n pieces into the groups whose room fits most tightly fills
    each sequence with as many as fit before the next, as the sequence just used has the tightest room left.
    """
    room: dict[int, list[tuple[int, int]]] = defaultdict(list)  # room -> runs of sequences (first, end), all with that room
    slots, made = [], 0
    for length in sorted(histogram, reverse=True):
        rank, left = 0, histogram[length]

        def fill(first: int, end: int, space: int) -> None:
            nonlocal rank, left
            each = space // length
            full, rest = divmod(left, each)
            take = min(end - first, full)
            for k in range(each if take else 0):
                slots.append((length, rank, rank + take, first, capacity - space + k * length))
                rank += take
            if take:
                room[space - each * length].append((first, first + take))
                left -= take * each
            first += take
            if first < end and 0 < left < each:
                for k in range(left):
                    slots.append((length, rank, rank + 1, first, capacity - space + k * length))
                    rank += 1
                room[space - left * length].append((first, first + 1))
                left, first = 0, first + 1
            if first < end:
                room[space].append((first, end))

        for space in sorted(s for s in room if s >= length):
            runs = room.pop(space)
            for i, (first, end) in enumerate(runs):
                if not left:
                    room[space] += runs[i:]
                    break
                fill(first, end, space)
            if not left:
                break
        if left:
            new = -(-left // (capacity // length))
            first, made = made, made + new
            fill(first, made, capacity)
    return slots


def pack(spark: SparkSession, docs: DataFrame, vocabulary: str, capacity: int = 2048, end_id: int = 0) -> DataFrame:
    """One row a piece: doc_id, piece, start, length, ids_crc32, sequence_id, offset."""
    docs = documents(docs).withColumn("row", F.xxhash64("doc_id", "text"))
    pieces = cut(spark, docs.mapInArrow(encode_pieces(vocabulary, capacity, end_id), PIECES), "pieces")
    counts = {r[0]: r[1] for r in pieces.groupBy("length").count().collect()}  # at most capacity rows
    planned = plan(counts, capacity) or [(0, 0, 0, 0, 0)]
    slots = spark.createDataFrame(planned, "length long, first long, last long, base long, offset long")
    buckets = spark.createDataFrame([(k, -(-n // RANKED)) for k, n in counts.items()] or [(0, 1)], "length long, buckets long")
    keyed = pieces.join(F.broadcast(buckets), "length").withColumn("bucket", F.pmod(F.xxhash64("row", "piece"), F.col("buckets"))).drop("buckets")
    sizes = keyed.groupBy("length", "bucket").count()
    shifts = sizes.withColumn("shift", F.sum("count").over(Window.partitionBy("length").orderBy("bucket")) - F.col("count")).drop("count")
    local = F.row_number().over(Window.partitionBy("length", "bucket").orderBy("doc_id", "row", "piece")) - 1
    ranked = keyed.withColumn("local", local).join(shifts, ["length", "bucket"]).withColumn("rank", F.col("local") + F.col("shift"))
    cond = (ranked["length"] == slots["length"]) & (F.col("rank") >= F.col("first")) & (F.col("rank") < F.col("last"))
    # the slots are at most a few for each pair of lengths; beyond the bound the join shuffles by length
    side = F.broadcast(slots) if len(planned) <= MOST_SLOTS else slots
    placed = ranked.join(side, cond).drop(slots["length"])
    return placed.select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("base") + F.col("rank") - F.col("first")).alias("sequence_id"), "offset")


def pack_documents(spark: SparkSession, docs: DataFrame, vocabulary: str | None = None, capacity: int = 2048) -> DataFrame:
    if vocabulary is None:
        import public_tokenizers

        vocabulary = public_tokenizers.path("word_bpe_49k.json")
    return pack(spark, docs, vocabulary, capacity)
