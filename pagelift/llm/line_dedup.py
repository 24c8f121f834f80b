"""Reversible line deduplication: exact reference counts of line keys, with sharded cuckoo filters in front.

A state holds two tables that are kept up together:

* (hi, lo, refs): how many documents hold the line key with that 128-bit hash;
* one cuckoo filter a shard of the hash space, of the keys with at least `least` references.

Inserting documents adds their distinct keys to the counts and puts keys that reach the threshold into their shard's
filter; deleting documents takes references off again and takes keys that fall below it out of the filter.  So dropping
lines never depends on history.  Filters are built anew only when the number of their keys has doubled.

A filter answers "surely not" for nearly all lines, and the exact table decides the rest: while its frequent keys are at
most EXACT_KEYS they are broadcast and texts are rewritten where they are read; beyond, what the filters let through is
joined with the table.  As many filters as fit into FILTER_BYTES are broadcast; keys of the other shards go to that join.

A key's count is summed within each Arrow batch first, so a line of a third of all documents reaches the shuffle once a
batch.  Defined results: a null text is one empty line; lines whose key is shorter than `min_chars` stay; repeated rows
are separate documents; an empty table gives an empty result; further columns may have any names.
"""

from __future__ import annotations

import hashlib
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pagelift.llm.common import cut, documents, raw, thrifty

SHARD_KEYS = 1 << 16  # keys of a filter when it is built
FILTER_BYTES = 64 << 20  # most filters that are broadcast
EXACT_KEYS = 1 << 21  # most frequent keys that are broadcast, of 16 bytes each


def line_key(line: bytes, min_chars: int) -> bytes | None:
    """Stripped, A-Z lower-cased; None when shorter than min_chars code points."""
    key = line.strip().lower()
    return key if len(key) >= min_chars and (min_chars <= 1 or len(key.decode()) >= min_chars) else None


def halves(key: bytes) -> tuple[int, int]:
    d = xxhash.xxh3_128_digest(key)
    return int.from_bytes(d[:8], "big", signed=True), int.from_bytes(d[8:], "big", signed=True)


class CuckooFilter:
    """Buckets of four 16-bit fingerprints; a key is in one of two buckets.  Keys are (hi, lo) hash halves."""

    SLOTS = 4

    def __init__(self, capacity: int):
        need = max(1, int(capacity / (0.9 * self.SLOTS)) + 1)
        self.mask = (1 << (need - 1).bit_length()) - 1
        self.cells = np.zeros((self.mask + 1, self.SLOTS), np.uint16)
        self.rest: set[tuple[int, int]] = set()  # exact home of what no bucket could take

    @staticmethod
    def _print(hi: np.ndarray, lo: np.ndarray):
        f = ((lo.view(np.uint64) >> np.uint64(40)) & np.uint64(0xFFFF)).astype(np.int64)
        return np.where(f == 0, 1, f)

    def _places(self, hi: np.ndarray, lo: np.ndarray):
        f = self._print(hi, lo)
        a = (lo.view(np.uint64) & np.uint64(self.mask)).astype(np.int64)
        return f, a, self._other(a, f)

    def _other(self, at, f):
        return (at ^ (f * 0x5BD1E995)) & self.mask

    def insert(self, hi: np.ndarray, lo: np.ndarray) -> None:
        f, a, b = (x.tolist() for x in self._places(hi, lo))
        cells, turn = self.cells, 0
        for i, (print_, one, two) in enumerate(zip(f, a, b)):
            at, now = one, print_
            for place in (one, two):
                free = np.flatnonzero(cells[place] == 0)
                if len(free):
                    cells[place, free[0]] = now
                    now = 0
                    break
            moves = []
            for _ in range(200):
                if not now:
                    break
                turn = (turn + 1) % self.SLOTS
                moves.append((at, turn, int(cells[at, turn])))
                cells[at, turn], now = now, int(cells[at, turn])
                at = self._other(at, now)
                free = np.flatnonzero(cells[at] == 0)
                if len(free):
                    cells[at, free[0]] = now
                    now = 0
            if now:  # undo, and keep the key itself
                for at, slot, was in reversed(moves):
                    cells[at, slot] = was
                self.rest.add((int(hi[i]), int(lo[i])))

    def delete(self, hi: np.ndarray, lo: np.ndarray) -> None:
        """Of keys that were inserted."""
        f, a, b = (x.tolist() for x in self._places(hi, lo))
        for i, (print_, one, two) in enumerate(zip(f, a, b)):
            key = (int(hi[i]), int(lo[i]))
            if key in self.rest:
                self.rest.remove(key)
                continue
            for place in (one, two):
                held = np.flatnonzero(self.cells[place] == print_)
                if len(held):
                    self.cells[place, held[0]] = 0
                    break

    def may_hold(self, hi: np.ndarray, lo: np.ndarray) -> np.ndarray:
        f, a, b = self._places(hi, lo)
        found = (self.cells[a] == f[:, None]).any(axis=1) | (self.cells[b] == f[:, None]).any(axis=1)
        if self.rest:
            found |= np.fromiter(((x, y) in self.rest for x, y in zip(hi.tolist(), lo.tolist())), bool, len(hi))
        return found


def shard_of(hi: np.ndarray, shards: int) -> np.ndarray:
    return np.mod(hi, shards)


def _counts(min_chars: int, sign: int):
    def stream(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n: Counter = Counter()
            for text in raw(batch.column("text")):
                n.update({k for line in (text or b"").split(b"\n") if (k := line_key(line, min_chars)) is not None})
            keys = [halves(k) for k in n]
            yield pa.RecordBatch.from_arrays([pa.array([k[0] for k in keys], pa.int64()), pa.array([k[1] for k in keys], pa.int64()), pa.array([sign * x for x in n.values()], pa.int64())], names=["hi", "lo", "refs"])

    return stream


def key_counts(docs: DataFrame, min_chars: int = 1, sign: int = 1) -> DataFrame:
    """(hi, lo, refs): in how many documents each key occurs."""
    return documents(docs).select("text").mapInArrow(_counts(min_chars, sign), "hi long, lo long, refs long").groupBy("hi", "lo").agg(F.sum("refs").alias("refs"))


FILTERS = "shard long, mask long, cells binary, rest array<struct<hi:long,lo:long>>"


def _stored(shard: int, f: CuckooFilter) -> pa.Table:
    kinds = (pa.int64(), pa.int64(), pa.binary(), pa.list_(pa.struct([("hi", pa.int64()), ("lo", pa.int64())])))
    row = (shard, f.mask, f.cells.tobytes(), [{"hi": a, "lo": b} for a, b in sorted(f.rest)])
    return pa.table([pa.array([x], t) for x, t in zip(row, kinds)], names=["shard", "mask", "cells", "rest"])


def _restore(mask: int, cells: bytes, rest) -> CuckooFilter:
    f = CuckooFilter(1)
    f.mask, f.cells, f.rest = mask, np.frombuffer(cells, np.uint16).reshape(-1, CuckooFilter.SLOTS).copy(), set(rest)
    return f


def _build(table: pa.Table) -> pa.Table:
    """A shard's filter, with room for as many keys again."""
    f = CuckooFilter(2 * table.num_rows)
    f.insert(*(np.asarray(table.column(c)).astype(np.int64) for c in ("hi", "lo")))
    return _stored(table.column("shard")[0].as_py(), f)


def _update(capacity: int):
    """A shard's filter after keys have come (up) and gone."""

    def make(key, held, changes):
        if held.num_rows:
            row = held.to_pylist()[0]
            f = _restore(row["mask"], row["cells"], [(x["hi"], x["lo"]) for x in row["rest"]])
        else:
            f = CuckooFilter(capacity)
        if changes.num_rows:
            hi, lo = (np.asarray(changes.column(c)).astype(np.int64) for c in ("hi", "lo"))
            up = changes.column("up").to_numpy(zero_copy_only=False).astype(bool)
            f.delete(hi[~up], lo[~up])
            f.insert(hi[up], lo[up])
        return _stored(key[0].as_py(), f)

    return make


class LineState:
    """Reference counts of all inserted documents' lines, and the filters of those with at least `least` references."""

    def __init__(self, spark: SparkSession, min_chars: int = 1, least: int = 10, counts: DataFrame | None = None, filters: DataFrame | None = None, shards: int = 0, frequent: int = 0, built_for: int = 0):
        self.spark, self.min_chars, self.least, self.counts = spark, min_chars, least, counts
        self.filters, self.shards, self.frequent, self.built_for = filters, shards, frequent, built_for

    def insert(self, docs: DataFrame) -> LineState:
        return self._with(key_counts(docs, self.min_chars))

    def delete(self, docs: DataFrame) -> LineState:
        """Take documents off that were inserted before; lines they made frequent become ordinary again."""
        return self._with(key_counts(docs, self.min_chars, -1))

    def _with(self, change: DataFrame) -> LineState:
        if self.counts is None:
            return self._built(cut(self.spark, change, "lines"))
        change = cut(self.spark, change.withColumnRenamed("refs", "step"), "change")
        both = change.join(self.counts, ["hi", "lo"], "left").withColumn("was", F.coalesce("refs", F.lit(0)) >= self.least).withColumn("up", F.coalesce("refs", F.lit(0)) + F.col("step") >= self.least)
        crossing = cut(self.spark, both.where("was <> up").select("hi", "lo", "up"), "crossing")
        new = self.counts.unionByName(change.withColumnRenamed("step", "refs")).groupBy("hi", "lo").agg(F.sum("refs").alias("refs")).where("refs > 0")
        new = cut(self.spark, new, "lines")
        frequent = self.frequent + crossing.agg(F.coalesce(F.sum(F.when(F.col("up"), 1).otherwise(-1)), F.lit(0))).first()[0]
        if frequent > 2 * self.built_for:
            return self._built(new, frequent)
        sharded = crossing.withColumn("shard", F.pmod("hi", F.lit(self.shards)))
        filters = self.filters.groupBy("shard").cogroup(sharded.groupBy("shard")).applyInArrow(_update(2 * max(1, self.built_for // self.shards)), FILTERS)
        return LineState(self.spark, self.min_chars, self.least, new, cut(self.spark, filters, "filters"), self.shards, frequent, self.built_for)

    def _built(self, counts: DataFrame, frequent: int | None = None) -> LineState:
        hot = counts.where(F.col("refs") >= self.least)
        frequent = hot.count() if frequent is None else frequent
        shards = max(1, -(-frequent // SHARD_KEYS))
        keyed = hot.select(F.pmod("hi", F.lit(shards)).alias("shard"), "hi", "lo")
        filters = cut(self.spark, keyed.groupBy("shard").applyInArrow(_build, FILTERS), "filters")
        return LineState(self.spark, self.min_chars, self.least, counts, filters, shards, frequent, frequent)

    def sent_filters(self) -> dict:
        """Shard -> filter, of as many shards as may be broadcast."""
        largest = self.filters.agg(F.max(F.length("cells"))).first()[0] or 1
        held = self.filters.where(F.col("shard") < max(1, FILTER_BYTES // largest))
        return {r[0]: (r[1], bytes(r[2]), [tuple(x) for x in r[3]]) for r in held.collect()}


class Frequent:
    """What executors know of the frequent keys: filters by shard, and the keys themselves where they are few."""

    def __init__(self, shards: int, filters: dict, every: bool, exact: tuple[np.ndarray, np.ndarray] | None):
        self.shards, self.every, self.exact = shards, every, exact
        self.filters = {s: _restore(*f) for s, f in filters.items()}

    def may_hold(self, hi: np.ndarray, lo: np.ndarray) -> np.ndarray:
        may, part = np.zeros(len(hi), bool), shard_of(hi, self.shards)
        if not self.every:
            may = ~np.isin(part, list(self.filters))  # no word on shards whose filter isn't here
        for s in np.intersect1d(part, list(self.filters)).tolist():
            at = np.flatnonzero(part == s)
            may[at] = self.filters[s].may_hold(hi[at], lo[at])
        return may

    def holds(self, hi: np.ndarray, lo: np.ndarray) -> np.ndarray:
        """By the exact keys, sorted by hi and lo."""
        out = self.may_hold(hi, lo)
        keys, rest = self.exact
        for i in np.flatnonzero(out).tolist():
            a, b = np.searchsorted(keys, hi[i], "left"), np.searchsorted(keys, hi[i], "right")
            out[i] = bool((rest[a:b] == lo[i]).any())
        return out


def _keys(texts: list[bytes | None], min_chars: int) -> dict[bytes, tuple[int, int]]:
    found = {k for text in texts for line in (text or b"").split(b"\n") if (k := line_key(line, min_chars)) is not None}
    return {k: halves(k) for k in found}


def _vectors(keys) -> tuple[np.ndarray, np.ndarray]:
    pairs = list(keys)
    return np.array([k[0] for k in pairs], np.int64), np.array([k[1] for k in pairs], np.int64)


def _without(text: bytes | None, min_chars: int, gone) -> tuple[int, int, bytes]:
    """Lines, lines dropped, and the text without the lines whose key is in gone."""
    lines = (text or b"").split(b"\n")
    left = [x for x in lines if line_key(x, min_chars) not in gone] if gone else lines
    return len(lines), len(lines) - len(left), b"\n".join(left)


def _probe(min_chars: int, sent):
    """Distinct keys of each document that may be frequent."""

    def stream(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in thrifty(batches):
            rows, keys = [], []
            for row, text in zip(batch.column("row").to_pylist(), raw(batch.column("text"))):
                mine = _keys([text], min_chars).values()
                keys += mine
                rows += [row] * len(mine)
            hi, lo = _vectors(keys)
            may = sent.value.may_hold(hi, lo)
            yield pa.RecordBatch.from_arrays([pa.array(np.array(rows, np.int64)[may]), pa.array(hi[may]), pa.array(lo[may])], names=["row", "hi", "lo"])

    return stream


def _fields(batch: pa.RecordBatch) -> list[pa.Array]:
    return batch.column("doc").flatten()


def _rewrite(state_min: int, text_at: int, finish, sent=None):
    """finish(fields of a batch's documents, results of _without) of documents, by the broadcast keys, or by a column drop."""

    def stream(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in thrifty(batches):
            fields = _fields(batch)
            texts = raw(fields[text_at])
            if sent is not None:
                keys = _keys(texts, state_min)
                gone = {k for k, on in zip(keys, sent.value.holds(*_vectors(keys.values()))) if on}
                done = [_without(t, state_min, gone) for t in texts]
            else:
                done = []
                for text, drop in zip(texts, batch.column("drop").to_pylist()):
                    drop = {(d["hi"], d["lo"]) for d in drop or ()}
                    done.append(_without(text, state_min, {k for k, h in _keys([text], state_min).items() if h in drop} if drop else ()))
            yield finish(fields, done)

    return stream


def _applied(state: LineState, docs: DataFrame, finish, schema) -> DataFrame:
    """Documents without the lines of frequent keys; columns travel inside one struct, so their names don't matter."""
    spark, at = state.spark, docs.columns.index("text")
    packed = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("doc"))
    few = state.frequent <= EXACT_KEYS
    hot, exact = state.counts.where(F.col("refs") >= state.least).select("hi", "lo"), None
    if few:
        keys = hot.orderBy("hi", "lo").toArrow()
        exact = tuple(keys.column(c).to_numpy() for c in ("hi", "lo"))
    filters = state.sent_filters()
    sent = spark.sparkContext.broadcast(Frequent(state.shards, filters, few or len(filters) == state.shards, exact))
    if few:
        return packed.mapInArrow(_rewrite(state.min_chars, at, finish, sent), schema)
    keyed = packed.withColumn("row", F.xxhash64(*(F.col("doc").getField(c) for c in ("doc_id", "text"))))
    maybe = keyed.select("row", F.col("doc").getField("text").alias("text")).mapInArrow(_probe(state.min_chars, sent), "row long, hi long, lo long")
    drops = maybe.join(hot, ["hi", "lo"]).groupBy("row").agg(F.collect_set(F.struct("hi", "lo")).alias("drop"))
    return keyed.join(drops, "row", "left").select("doc", "drop").mapInArrow(_rewrite(state.min_chars, at, finish), schema)


def drop_lines(state: LineState, docs: DataFrame, digest: bool = False) -> DataFrame:
    """doc_id, n_lines, n_dropped and kept_text (with digest its SHA-256), without lines whose key is frequent in the state."""
    last = "kept_sha256" if digest else "kept_text"

    def finish(fields, done):
        kept = [hashlib.sha256(t).hexdigest() if digest else t.decode() for _, _, t in done]
        counts = [pa.array([x[k] for x in done], pa.int64()) for k in (0, 1)]
        return pa.RecordBatch.from_arrays([fields[0], *counts, pa.array(kept, pa.string())], names=["doc_id", "n_lines", "n_dropped", last])

    return _applied(state, documents(docs), finish, f"doc_id long, n_lines long, n_dropped long, {last} string")


def dedup(spark: SparkSession, docs: DataFrame, least: int = 10, min_chars: int = 1, digest: bool = False) -> DataFrame:
    return drop_lines(LineState(spark, min_chars, least).insert(docs), docs, digest)


def rewrite(spark: SparkSession, docs: DataFrame, least: int = 10, min_chars: int = 1) -> DataFrame:
    """docs, all columns, with texts that lack the frequent lines."""
    at, names = docs.columns.index("text"), docs.columns

    def finish(fields, done):
        fields[at] = pa.array([t.decode() for _, _, t in done], pa.string())
        return pa.RecordBatch.from_arrays(fields, names=names)

    return _applied(LineState(spark, min_chars, least).insert(docs), docs, finish, docs.schema)
