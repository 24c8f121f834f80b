"""Substring deduplication: remove every word that lies in a window of words which already started earlier.

Two forms:

* `remove_repeats` (the query): repeats within the whole corpus.  The reference is then the corpus itself, which has no
  size bound, so it can't be broadcast; streaming all documents through the automata of all its shards would cost the
  square of the corpus.  Windows are compared through the batch-to-shard exchange instead: batches are runs of doc_id,
  each sends the sorted set of its window hashes, and a shard answers one bit a window, "an earlier batch has it".
  Within a batch the first place is known by position.
* `remove_reference` (matching against a given reference, such as a collection of known texts): executors build suffix
  automata of its shards, which are broadcast in waves of bounded size; documents are streamed through them for matching
  statistics, and the maximal spans of at least `window` words go.

Order is (doc_id, then a hash of the text among rows that share an id, then place); null ids come first.  Defined
results: null text has no words; a text shorter than the window keeps all; the last words of an empty result give the empty text.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pagelift.llm import exchange as ex
from pagelift.llm.common import WordIds, cut, documents, mix, names_of, pair_hash, raw, thrifty

KEPT = "doc_id long, n_words long, n_removed long, kept_text string"


def window_hashes(tokens: np.ndarray, width: int) -> np.ndarray:
    """Hash of each run of width tokens, by doubling; entry i is the run that starts at i (runs off the end are cut)."""
    out, have, power, size, at = None, 0, tokens, 1, 0
    n = len(tokens) - width + 1
    if n <= 0:
        return np.array([], np.uint64)
    while True:
        if width & size:
            piece = power[at : at + n]
            out = piece if out is None else pair_hash(out, piece)
            at, have = at + size, have + size
        if have == width:
            return out if width > 1 else mix(out)
        power = pair_hash(power[: len(power) - size], power[size:])
        size *= 2


def batch_windows(table: pa.Table, width: int):
    """The batch's documents in order, their words, and hash and word position of every window."""
    table = table.sort_by([("doc_id", "ascending"), ("spot", "ascending"), ("text", "ascending")], null_placement="at_start") if table.num_rows else table
    ids, texts, parts = WordIds(), [], []
    for text in raw(table.column("text")):
        words = text.split() if text else []
        texts.append(words)
        parts.append(ids.code(words))
    bounds = np.concatenate([[0], np.cumsum([len(p) for p in parts])]).astype(np.int64)
    codes = np.concatenate(parts) if parts else np.array([], np.int64)
    tokens = ids.table()[codes] if len(codes) else np.array([], np.uint64)
    del parts
    h = window_hashes(tokens, width)
    ends = np.repeat(bounds[1:], np.diff(bounds))[: len(h)]
    starts = np.flatnonzero(np.arange(len(h)) + width <= ends)
    return table, texts, bounds, h[starts], starts


def ask(width: int, bits: int):
    def make(key, table):
        *_, h, _ = batch_windows(table, width)
        uniq = np.unique(h)
        at, b = ex.slices(uniq, bits), key[0].as_py()
        rows = [(b, s, ex.pack_sorted(uniq[at[s] : at[s + 1]])) for s in range(len(at) - 1) if at[s] < at[s + 1]]
        return pa.table([pa.array(c, t) for c, t in zip(list(zip(*rows)) or [[]] * 3, (pa.int32(), pa.int32(), pa.binary()))], names=["batch", "shard", "keys"])

    return make


def earlier(table: pa.Table) -> pa.Table:
    """For each batch's windows in a shard: has a smaller batch the same?"""
    shard, owner = table.column("shard")[0].as_py(), np.asarray(table.column("batch"))
    vectors = [ex.unpack_sorted(x) for x in table.column("keys").to_pylist()]
    at = np.concatenate([[0], np.cumsum([len(v) for v in vectors])]).astype(np.int64)
    by = np.argsort(owner, kind="stable")
    flat = np.concatenate([vectors[i] for i in by])
    _, first = np.unique(flat, return_index=True)
    seen = np.ones(len(flat), bool)
    seen[first] = False
    sizes = np.diff(at)[by]
    split = np.split(seen, np.cumsum(sizes)[:-1])
    rows = [(int(owner[i]), shard, np.packbits(bit).tobytes(), len(bit)) for i, bit in zip(by, split)]
    return pa.table([pa.array(c, t) for c, t in zip(zip(*rows), (pa.int32(), pa.int32(), pa.binary(), pa.int64()))], names=["batch", "shard", "seen", "n"])


def strip(width: int, finish):
    def make(key, docs, replies):
        docs, texts, bounds, h, starts = batch_windows(docs, width)
        drop = np.zeros(bounds[-1] + 1, np.int64)
        if len(h):
            uniq, first, inv = np.unique(h, return_index=True, return_inverse=True)
            replies = replies.sort_by("shard")
            bits = [np.unpackbits(np.frombuffer(x, np.uint8), count=n) for x, n in zip(replies.column("seen").to_pylist(), replies.column("n").to_pylist())]
            gone = (first[inv] != np.arange(len(h))) | (np.concatenate(bits)[inv] > 0)
            np.add.at(drop, starts[gone], 1)
            np.add.at(drop, starts[gone] + width, -1)
        keep = np.cumsum(drop)[:-1] == 0
        return finish(docs, texts, bounds, keep)

    return make


def kept_texts(docs: pa.Table, texts: list, bounds: np.ndarray, keep: np.ndarray) -> pa.Table:
    out = []
    for words, a, b in zip(texts, bounds, bounds[1:]):
        k = keep[a:b]
        out.append(b" ".join(words if k.all() else [w for w, on in zip(words, k.tolist()) if on]).decode())
    n = np.diff(bounds)
    left = np.add.reduceat(np.append(keep, 0).astype(np.int64), bounds[:-1]) * (n > 0) if len(n) else n
    return pa.table({"doc_id": docs.column("doc_id"), "n_words": pa.array(n), "n_removed": pa.array(n - left), "kept_text": pa.array(out, pa.string())})


def kept_digests(docs: pa.Table, texts: list, bounds: np.ndarray, keep: np.ndarray) -> pa.Table:
    full = kept_texts(docs, texts, bounds, keep)
    sha = [hashlib.sha256(x).hexdigest() for x in raw(full.column("kept_text"))]
    return full.drop_columns(["kept_text"]).append_column("kept_sha256", pa.array(sha, pa.string()))


def remove_repeats(docs: DataFrame, window: int = 20, digest: bool = False) -> DataFrame:
    """One row a document: its words, how many went, and what is left (its text, or with digest its SHA-256)."""
    docs = documents(docs)
    docs, batches = ex.ordered_batches(docs.sparkSession, docs, ex.batch_count(docs))
    bits = ex.shard_bits(batches)
    asked = docs.groupBy("batch").applyInArrow(ask(window, bits), "batch int, shard int, keys binary")
    told = asked.groupBy("shard").applyInArrow(earlier, "batch int, shard int, seen binary, n long")
    schema = KEPT.replace("kept_text", "kept_sha256") if digest else KEPT
    return docs.groupBy("batch").cogroup(told.groupBy("batch")).applyInArrow(strip(window, kept_digests if digest else kept_texts), schema)


class SuffixAutomaton:
    """Of a sequence of word hashes; a separator (None) ends a reference text."""

    def __init__(self, words):
        self.next, self.link, self.size = [{}], [-1], [0]
        last = 0
        for w in words:
            if w is None:  # nothing continues over a separator
                last = 0
                continue
            last = self._extend(last, w)

    def _extend(self, last: int, w) -> int:
        nxt, link, size = self.next, self.link, self.size
        if w in nxt[last]:  # after a separator the state may exist already
            q = nxt[last][w]
            if size[q] == size[last] + 1:
                return q
            return self._clone(last, w, q)
        cur = len(nxt)
        nxt.append({})
        link.append(0)
        size.append(size[last] + 1)
        p = last
        while p >= 0 and w not in nxt[p]:
            nxt[p][w] = cur
            p = link[p]
        if p >= 0:
            q = nxt[p][w]
            link[cur] = q if size[q] == size[p] + 1 else self._clone(p, w, q)
        return cur

    def _clone(self, p: int, w, q: int) -> int:
        nxt, link, size = self.next, self.link, self.size
        new = len(nxt)
        nxt.append(dict(nxt[q]))
        link.append(link[q])
        size.append(size[p] + 1)
        link[q] = new
        while p >= 0 and nxt[p].get(w) == q:
            nxt[p][w] = new
            p = link[p]
        return new

    def packed(self) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """As sorted vectors, at most some 60 bytes a word: word hashes, transitions (state and word number in one, and
        target), suffix links and lengths."""
        words = np.unique(np.array([w for t in self.next for w in t], np.uint64))
        count = np.array([len(t) for t in self.next], np.int64)
        flat = np.array([w for t in self.next for w in t], np.uint64)
        keys = np.repeat(np.arange(len(count)), count).astype(np.uint64) << np.uint64(32) | np.searchsorted(words, flat).astype(np.uint64)
        to = np.array([q for t in self.next for q in t.values()], np.int32)
        by = np.argsort(keys)
        return words, keys[by], to[by], np.array(self.link, np.int32), np.array(self.size, np.int32)


class PackedAutomaton:
    """Matching statistics of many texts at once: all texts take a step together."""

    def __init__(self, words: np.ndarray, keys: np.ndarray, to: np.ndarray, link: np.ndarray, size: np.ndarray):
        self.words, self.keys, self.to, self.link, self.size = words, keys, to, link, size

    def _target(self, state: np.ndarray, word: np.ndarray) -> np.ndarray:
        """Where a word leads from a state, or -1."""
        wanted = state.astype(np.uint64) << np.uint64(32) | word.astype(np.uint64)
        at = np.minimum(np.searchsorted(self.keys, wanted), len(self.keys) - 1)
        return np.where(self.keys[at] == wanted, self.to[at], -1)

    def matching(self, tokens: np.ndarray, bounds: np.ndarray) -> np.ndarray:
        """For each place of texts that are laid end to end, the length of the longest run ending there that the reference
        contains."""
        out = np.zeros(len(tokens), np.int64)
        if not len(self.keys):
            return out
        number = np.minimum(np.searchsorted(self.words, tokens), len(self.words) - 1)
        known = self.words[number] == tokens
        length = np.diff(bounds)
        order = np.argsort(-length, kind="stable")  # texts that end drop off the end
        first, length = bounds[:-1][order], length[order]
        state, have = np.zeros(len(order), np.int64), np.zeros(len(order), np.int64)
        for step in range(int(length[0]) if len(length) else 0):
            live = int(np.searchsorted(-length, -step, "left"))
            at = first[:live] + step
            state, have = state[:live], have[:live]
            state[~known[at]] = have[~known[at]] = 0
            open_ = np.flatnonzero(known[at])
            while len(open_):
                target = self._target(state[open_], number[at[open_]])
                on = target >= 0
                moved = open_[on]
                have[moved] += 1
                state[moved] = target[on]
                open_ = open_[~on]
                have[open_[state[open_] == 0]] = 0
                open_ = open_[state[open_] > 0]
                state[open_] = self.link[state[open_]]
                have[open_] = self.size[state[open_]]
            out[at] = have
        return out


def covered(lengths: np.ndarray, bounds: np.ndarray, window: int) -> np.ndarray:
    """Places inside a match of at least window words."""
    drop = np.zeros(len(lengths) + 1, np.int64)
    ends = np.flatnonzero(lengths >= window)
    np.add.at(drop, ends - lengths[ends] + 1, 1)
    np.add.at(drop, ends + 1, -1)
    return np.cumsum(drop)[:-1] > 0


SHARD_WORDS = 250_000  # words of a reference shard: its automaton is built by one task, in some 100 MB
WAVE_BYTES = 64 << 20  # of automata that are broadcast at once
SHARDS = "shard long, words binary, keys binary, to binary, link binary, size binary"


def _automaton(table: pa.Table) -> pa.Table:
    """The automaton of a shard's texts."""
    words: list = []
    for text in raw(table.column("text")):
        words += [*hashed(text)[1].tolist(), None]
    columns = [pa.array([x.tobytes()], pa.binary()) for x in SuffixAutomaton(words).packed()]
    return pa.table([table.column("shard")[:1].combine_chunks(), *columns], names=names_of(SHARDS))


def hashed(text: bytes | None) -> tuple[list[bytes], np.ndarray]:
    """Words of a text and their hashes."""
    ids, words = WordIds(), text.split() if text else []
    codes = ids.code(words)
    return words, ids.table()[codes] if len(codes) else np.array([], np.uint64)


def _restored(row) -> PackedAutomaton:
    return PackedAutomaton(*(np.frombuffer(row[k], t) for k, t in zip(("words", "keys", "to", "link", "size"), ("<u8", "<u8", "<i4", "<i4", "<i4"))))


def _spans(sent, window: int):
    """row and spans (first word, end) of the words that some automaton of the wave covers."""

    def stream(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        automata = [PackedAutomaton(*x) for x in sent.value]
        for batch in thrifty(batches):
            tokens = [hashed(t)[1] for t in raw(batch.column("text"))]
            bounds = np.concatenate([[0], np.cumsum([len(t) for t in tokens])]).astype(np.int64)
            flat = np.concatenate(tokens) if tokens else np.array([], np.uint64)
            gone = np.zeros(len(flat), bool)
            for a in automata:
                gone |= covered(a.matching(flat, bounds), bounds, window)
            found = [np.flatnonzero(np.diff(gone[a:b].astype(np.int8), prepend=0, append=0)).reshape(-1, 2).tolist() for a, b in zip(bounds, bounds[1:])]
            some = [i for i, x in enumerate(found) if x]
            yield pa.RecordBatch.from_arrays([batch.column("row").take(pa.array(some, pa.int64())), pa.array([found[i] for i in some], pa.list_(pa.list_(pa.int64())))], names=["row", "spans"])

    return stream


def _cut_out(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in thrifty(batches):
        rows = []
        for i, text, waves in zip(*(batch.column(c).to_pylist() if c != "text" else raw(batch.column(c)) for c in ("doc_id", "text", "spans"))):
            words = text.split() if text else []
            keep = np.ones(len(words), bool)
            for first, end in (s for wave in waves or () for s in wave):
                keep[first:end] = False
            rows.append((i, len(words), int((~keep).sum()), b" ".join(w for w, k in zip(words, keep.tolist()) if k).decode()))
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(list(zip(*rows)) or [[]] * 4, (pa.int64(), pa.int64(), pa.int64(), pa.string()))], names=names_of(KEPT))


def remove_reference(spark: SparkSession, docs: DataFrame, reference: DataFrame, window: int = 20) -> DataFrame:
    """Remove the maximal spans of at least window words that a text of the reference has.

    Executors build an automaton for each shard of reference texts (a text stays whole).  As many as fit into WAVE_BYTES are
    broadcast at once and all documents are streamed through them; a larger reference takes more waves, a pass over the
    documents each.  What the waves cover is put together by document.
    """
    docs = documents(docs).withColumn("row", F.xxhash64("doc_id", "text"))
    texts = reference.select(F.col("text").cast("string").alias("text")).where("text IS NOT NULL").withColumn("n", F.size(F.split("text", r"\s+")))
    total = texts.agg(F.sum("n")).first()[0] or 0
    shards = max(1, -(-total // SHARD_WORDS))
    built = texts.select("text", F.pmod(F.xxhash64("text"), F.lit(shards)).alias("shard")).groupBy("shard").applyInArrow(_automaton, SHARDS)
    built = cut(spark, built, "automata")
    sizes = built.select("shard", sum((F.length(c) for c in ("words", "keys", "to", "link", "size")), F.lit(0)).alias("bytes")).orderBy("shard").collect()  # a row a shard
    found, wave, held = None, [], 0
    for k, (shard, size) in enumerate(sizes):
        wave.append(shard)
        held += size
        if k + 1 == len(sizes) or held + sizes[k + 1][1] > WAVE_BYTES:
            rows = built.where(F.col("shard").isin(wave)).collect()
            sent = spark.sparkContext.broadcast([(a.words, a.keys, a.to, a.link, a.size) for a in map(_restored, rows)])
            part = cut(spark, docs.select("row", "text").mapInArrow(_spans(sent, window), "row long, spans array<array<long>>"), "spans")
            found, wave, held = part if found is None else found.unionByName(part), [], 0
    if found is None:
        found = spark.createDataFrame([], "row long, spans array<array<long>>")
    gathered = found.distinct().groupBy("row").agg(F.collect_list("spans").alias("spans"))
    return docs.join(gathered, "row", "left").select("doc_id", "text", "spans").mapInArrow(_cut_out, KEPT)
