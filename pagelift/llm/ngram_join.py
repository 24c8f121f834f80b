"""Near-duplicate join on word n-grams: Jaccard similarity at or above a threshold, exactly.

N-grams have one global order: rare ones first (by document frequency), then by hash.

1. Every text becomes its set of n-gram hashes; document frequencies come back through the batch-to-shard exchange.
   Equal sets form a class; only its smallest document goes on.  The global order of all shared n-grams is cut into
   fragments of about equal weight, at pivots (frequency, hash); each set is cut at the pivots.  They follow from the
   frequencies in shard 0, which are those of an even part of all hashes, and go to every batch with the answers, so
   texts are shuffled once; where the pivots lie changes the sizes of fragments and no result.
2. Two sets of the wanted similarity share an n-gram among the first few of both in the global order (its prefix, as long
   as the number of n-grams that may differ, and one).  N-grams of one document only can't be shared, so a text whose
   prefix is all its own has no partner, however many others hold the same passages.
3. Pairs of a key of at most HOT documents are listed, each once.  Those that the sets' parity bitmaps don't prove too
   different are counted: every fragment counts the pair's overlap in it by itself, and the counts are added up per pair.
4. Documents of more frequent keys form groups, which are compared in blocks, block by block as separate tasks: bitmaps
   first, then overlaps, as a matrix product where many pairs are left.  A task returns each document's number of links
   and the links that connect its documents, so a dense group makes no row a pair.  Groups that are only loosely held
   together are compared key by key.  A pair belongs to step 3 if it shares a key of that step, and to its first common
   key otherwise, so each is counted once.

So all similar pairs of different sets are counted, and n_links is the true number.

Defined results: texts with fewer words than n are one n-gram, their whole sequence; texts without words have no n-grams
and link with nothing, each its own component; rows that share an id are one document for links; an empty table gives an
empty result.
"""

from __future__ import annotations

import json
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pagelift.llm import exchange as ex
from pagelift.llm import idfilter
from pagelift.llm.common import WordIds, cut, documents, drop, mix, names_of, pair_hash, raw, release, thrifty
from pagelift.llm.components import components

PARTS = 4  # fragments of the global order
HOT = 32  # documents of a key whose pairs are listed
BLOCK = 512  # documents that are compared with as many others at once
FEW = 20_000  # pairs of two blocks that are counted one by one
WIDE = 4096  # n-grams of a matrix product


class Rule:
    """Similarity at or above percent/100 on n-grams of n words."""

    def __init__(self, n: int = 3, percent: int = 90):
        self.n, self.percent = n, percent

    def linked(self, both: int, one: int, two: int) -> bool:
        return 100 * both >= self.percent * (one + two - both)

    def most_apart(self, one, two):
        """The largest symmetric difference that two similar sets of these sizes can have."""
        return np.floor((100 - self.percent) * (one + two) / (100 + self.percent) + 1e-9)

    def prefix(self, size):
        """How many n-grams of a set, in the global order, are enough to meet every similar set's."""
        return size - (self.percent * size + 99) // 100 + 1


def hash_sets(texts: list[bytes | None], n: int) -> list[np.ndarray]:
    """Sorted distinct n-gram hashes of each text."""
    ids, parts = WordIds(), []
    for text in texts:
        parts.append(ids.code(text.lower().split()) if text else np.array([], np.int64))
    table, out = mix(ids.table()) if len(ids) else np.array([], np.uint64), []
    for codes in parts:
        h = table[codes]
        if 0 < len(h) < n:
            whole = h[:1]
            for k in range(1, len(h)):
                whole = pair_hash(whole, h[k : k + 1])
            out.append(mix(whole + np.uint64(len(h))))
            continue
        g = h[: max(0, len(h) - n + 1)]
        for k in range(1, n):
            g = pair_hash(g, h[k : len(g) + k])
        out.append(np.unique(g))
    return out


def parity(s: np.ndarray) -> bytes:
    """Bit i tells whether an odd number of members falls on i; two bitmaps differ in no more bits than the sets in members."""
    bits = 1 << max(9, (3 * len(s)).bit_length())
    return np.packbits((np.bincount((s & np.uint64(bits - 1)).astype(np.int64), minlength=bits) & 1).astype(np.uint8)).tobytes()


def folded(bitmap: np.ndarray, size: int) -> np.ndarray:
    """A shorter parity bitmap: positions are taken modulo its bits."""
    return np.bitwise_xor.reduce(bitmap.reshape(-1, size), axis=0)


def batch_sets(table: pa.Table, rule: Rule):
    """Set sizes of a batch's texts, their n-gram hashes laid end to end, and the document each belongs to."""
    sets = hash_sets(raw(table.column("text")), rule.n)
    sizes = np.array([len(s) for s in sets], np.int64)
    flat = np.concatenate(sets) if sets else np.array([], np.uint64)
    return sets, sizes, flat, np.repeat(np.arange(len(sets)), sizes)


def _ask(rule: Rule, bits: int):
    names = ["batch", "shard", "keys", "counts"]

    def make(key, table):
        _, _, flat, _ = batch_sets(table, rule)
        uniq, n = np.unique(flat, return_counts=True)
        at, b = ex.slices(uniq, bits), key[0].as_py()
        rows = [(b, s, ex.pack_sorted(uniq[at[s] : at[s + 1]]), ex.pack_counts(n[at[s] : at[s + 1]])) for s in range(len(at) - 1) if at[s] < at[s + 1]]
        return pa.table([pa.array(c, t) for c, t in zip(list(zip(*rows)) or [[]] * 4, (pa.int32(), pa.int32(), pa.binary(), pa.binary()))], names=names)

    return make


def cell_of(df: np.ndarray) -> np.ndarray:
    """Cells of a histogram of frequencies: one a frequency up to 256, then sixteen for each doubling."""
    return np.where(df <= 256, df, 128 + np.floor(16 * np.log2(np.maximum(df, 1)))).astype(np.int64)


def _frequencies(batches: int):
    def make(table: pa.Table) -> pa.Table:
        """Document frequencies of each batch's n-grams in a shard, in the batch's order; shard 0 also tells every batch the
        pivots, as shard -1."""
        shard, owner = table.column("shard")[0].as_py(), table.column("batch").to_pylist()
        vectors = [ex.unpack_sorted(x) for x in table.column("keys").to_pylist()]
        at = np.concatenate([[0], np.cumsum([len(v) for v in vectors])]).astype(np.int64)
        _, inv = np.unique(np.concatenate(vectors), return_inverse=True)
        df = np.bincount(inv, weights=np.concatenate([ex.unpack_counts(x) for x in table.column("counts").to_pylist()])).astype(np.int64)
        counts, shards = [ex.pack_counts(df[inv[a:b]]) for a, b in zip(at, at[1:])], [shard] * len(owner)
        if shard == 0:
            shared = df[df > 1]
            cells, which = np.unique(cell_of(shared), return_inverse=True)
            weight = np.bincount(which, weights=shared, minlength=len(cells)).astype(np.int64)
            told = json.dumps(pivots(list(zip(cells.tolist(), weight.tolist())), PARTS)).encode()
            owner, counts, shards = owner + list(range(batches)), counts + [told] * batches, shards + [-1] * batches
        return pa.table([pa.array(c, t) for c, t in zip((owner, shards, counts), (pa.int32(), pa.int32(), pa.binary()))], names=["batch", "shard", "counts"])

    return make


def pivots(histogram: list[tuple[int, int]], parts: int) -> list[tuple[int, int]]:
    """Places (frequency, hash) that cut the global order into parts of about equal weight.  Within a frequency the order
    is by hash, and hashes are even, so a share of a cell is a share of the hash space."""
    total, before, out = sum(n for _, n in histogram), 0, []
    for cell, n in sorted(histogram):
        while len(out) < parts - 1 and before + n > total * (len(out) + 1) / parts:
            share = (total * (len(out) + 1) / parts - before) / n
            out.append((cell, int(share * 2.0**64)) if cell <= 256 else (int(np.ceil(2 ** ((cell - 128) / 16))), 0))
        before += n
    return out


def fragments(keys: np.ndarray, df: np.ndarray, cuts: list[tuple[int, int]]) -> list[bytes]:
    """A set's shared n-grams, cut at the pivots; within a fragment by hash."""
    part = np.zeros(len(keys), np.int64)
    for f, h in cuts:
        part += (df > f) | ((df == f) & (keys >= np.uint64(min(h, (1 << 64) - 1))))
    shared = df > 1
    return [keys[shared & (part == k)].tobytes() for k in range(len(cuts) + 1)]


SETS = "doc_id long, n_shingles long, hi long, lo long, prefix array<long>, own long, parts array<binary>"


def _prefixes(rule: Rule):
    """Of every text: size and digest of its set; of texts that may have a partner also the prefix, the number of n-grams
    that no other document has, and the fragments of the others."""

    def make(key, docs, replies):
        sets, sizes, flat, owner = batch_sets(docs, rule)
        _, inv = np.unique(flat, return_inverse=True)
        replies = replies.sort_by("shard")
        told = [(s, x) for s, x in zip(replies.column("shard").to_pylist(), replies.column("counts").to_pylist())]
        cuts = next((json.loads(x) for s, x in told if s < 0), [])
        found = [ex.unpack_counts(x) for s, x in told if s >= 0]
        df = np.concatenate(found)[inv] if found else np.array([], np.int64)
        need, own = rule.prefix(sizes), np.bincount(owner, df == 1, len(sets)).astype(np.int64)
        ends = np.cumsum(sizes)
        prefix: list = [[]] * len(sets)
        parts: list = [[]] * len(sets)
        for i in np.flatnonzero((own < need) & (sizes > 0)):  # the others' prefixes are all their own
            s, f = sets[i], df[ends[i] - sizes[i] : ends[i]]
            first = np.lexsort((s, f))[: need[i]]
            prefix[i] = s[first[f[first] > 1]].view(np.int64).tolist()
            parts[i] = fragments(s, f, cuts)
        d = [xxhash.xxh3_128_digest(s.tobytes()) for s in sets]
        half = lambda a, b: [int.from_bytes(x[a:b], "big", signed=True) for x in d]
        columns = (docs.column("doc_id"), pa.array(sizes), pa.array(half(0, 8), pa.int64()), pa.array(half(8, 16), pa.int64()), pa.array(prefix, pa.list_(pa.int64())), pa.array(own), pa.array(parts, pa.list_(pa.binary())))
        return pa.table(list(columns), names=["doc_id", "n_shingles", "hi", "lo", "prefix", "own", "parts"])

    return make


def _picked(batch: pa.RecordBatch, sent) -> pa.RecordBatch:
    """The rows whose doc_id the broadcast IdFilter, if there is one, may hold."""
    batch = batch.filter(batch.column("doc_id").is_valid())
    return batch if sent is None else batch.filter(pa.array(sent.value.may_hold(np.asarray(batch.column("doc_id")))))


MEMBERS = "doc_id long, part int, size long, own long, data binary"


def _members(active):
    """Fragments of the sets of documents that may be active; fragment -1 holds the bitmap."""

    def stream(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in thrifty(batches):
            batch, rows = _picked(batch, active), []
            for i, size, own, parts in zip(*(batch.column(c).to_pylist() for c in ("doc_id", "n_shingles", "own", "parts"))):
                rows.append((i, -1, size, own, parity(np.frombuffer(b"".join(parts), np.uint64))))
                rows += [(i, k, size, own, data) for k, data in enumerate(parts) if data]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(list(zip(*rows)) or [[]] * 5, (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.binary()))], names=names_of(MEMBERS))

    return stream


def _overlap(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        both = [len(np.intersect1d(np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64), assume_unique=True)) for x, y in zip(batch.column("x").to_pylist(), batch.column("y").to_pylist())]
        yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in ("a", "b", "one", "two")), pa.array(both, pa.int64())], names=["a", "b", "one", "two", "both"])


def _apart(rule: Rule):
    """Pairs that the bitmaps leave possible; n-grams of one document only differ in any case."""

    def stream(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            on = np.zeros(batch.num_rows, bool)
            one, two, own = (np.asarray(batch.column(c)) for c in ("one", "two", "own"))
            most = rule.most_apart(one, two) - own
            for i, (x, y) in enumerate(zip(batch.column("x").to_pylist(), batch.column("y").to_pylist())):
                x, y = np.frombuffer(x, np.uint8), np.frombuffer(y, np.uint8)
                short = min(len(x), len(y))
                on[i] = abs(int(one[i]) - int(two[i])) <= most[i] + own[i] and np.bitwise_count(folded(x, short) ^ folded(y, short)).sum() <= most[i]
            yield pa.RecordBatch.from_arrays([batch.column("a"), batch.column("b")], names=["a", "b"]).filter(pa.array(on))

    return stream


def verified(spark: SparkSession, pairs: DataFrame, members: DataFrame, rule: Rule) -> DataFrame:
    """The pairs (a, b) that are similar: bitmaps first, then overlaps by fragment, added up."""
    side = lambda parts, doc, size, own, data: members.where(parts).selectExpr(f"doc_id AS {doc}", "part", f"size AS {size}", f"own AS {own}", f"data AS {data}")
    maps = pairs.join(side("part = -1", "a", "one", "p", "x").drop("part"), "a").join(side("part = -1", "b", "two", "q", "y").drop("part"), "b")
    near = cut(spark, maps.select("a", "b", "one", "two", (F.col("p") + F.col("q")).alias("own"), "x", "y").mapInArrow(_apart(rule), "a long, b long").distinct(), "near")
    left, right = side("part >= 0", "a", "one", "p", "x").drop("p"), side("part >= 0", "b", "two", "q", "y").drop("q")
    rows = near.join(left, "a").join(right, ["b", "part"]).select("a", "b", "one", "two", "x", "y")
    counted = rows.mapInArrow(_overlap, "a long, b long, one long, two long, both long").groupBy("a", "b", "one", "two").agg(F.sum("both").alias("both"))
    return counted.where(100 * F.col("both") >= rule.percent * (F.col("one") + F.col("two") - F.col("both"))).select("a", "b").distinct()


def _whole(active):
    """Shared n-grams of the documents that may be active."""

    def stream(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in thrifty(batches):
            batch = _picked(batch, active)
            data = [np.sort(np.frombuffer(b"".join(p), np.uint64)).tobytes() for p in batch.column("parts").to_pylist()]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in ("doc_id", "n_shingles", "own")), pa.array(data, pa.binary())], names=["doc_id", "size", "own", "data"])

    return stream


def similar(left: list[np.ndarray], right: list[np.ndarray], open_: np.ndarray, rule: Rule, own: tuple | None = None) -> np.ndarray:
    """Which of the open pairs of two lists of sets are similar.  own: how many members more each set has, of its own."""
    own_left, own_right = own or (np.zeros(len(left), np.int64), np.zeros(len(right), np.int64))
    one, two = (np.array([len(s) for s in x], np.int64) + n for x, n in ((left, own_left), (right, own_right)))
    open_ = open_ & (one[:, None] > 0) & (two[None, :] > 0)
    maps = [np.frombuffer(parity(s), np.uint8) for s in (*left, *right)]
    bits = np.vstack([folded(m, min(map(len, maps))) for m in maps])
    for i in range(len(left)):
        open_[i] &= np.bitwise_count(bits[len(left) :] ^ bits[i]).sum(axis=1) <= rule.most_apart(one[i], two) - own_left[i] - own_right
    both = np.zeros(open_.shape, np.int64)
    if open_.sum() <= FEW:
        for i, j in zip(*np.nonzero(open_)):
            both[i, j] = len(np.intersect1d(left[i], right[j], assume_unique=True))
    else:
        common = np.intersect1d(np.concatenate(left), np.concatenate(right))

        def places(sets):
            at = [np.searchsorted(common, s) for s in sets]
            return [x[common[np.minimum(x, len(common) - 1)] == s] for x, s in zip(at, sets)] if len(common) else []

        x, y = places(left), places(right)
        for low in range(0, len(common), WIDE):
            u, v = (np.zeros((len(rows), WIDE), np.float32) for rows in (x, y))
            for m, rows in ((u, x), (v, y)):
                for i, at in enumerate(rows):
                    m[i, at[np.searchsorted(at, low) : np.searchsorted(at, low + WIDE)] - low] = 1
            both += np.rint(u @ v.T).astype(np.int64)
    return open_ & (100 * both >= rule.percent * (one[:, None] + two[None, :] - both))


def _blocks(rule: Rule):
    """Links of two blocks: (a, null, n) for a document's number, (a, b, 0) for those that connect the blocks' documents."""

    def make(table: pa.Table) -> pa.Table:
        table = table.sort_by("doc_id")
        ids, block, own = (np.asarray(table.column(c)) for c in ("doc_id", "block", "own"))
        low, high, key = (table.column(c)[0].as_py() for c in ("low", "high", "key"))
        sets = [np.frombuffer(x, np.uint64) for x in table.column("data").to_pylist()]
        cold, hot = ([frozenset(x or ()) for x in table.column(c).to_pylist()] for c in ("cold", "hot"))
        left = np.flatnonzero(block == low)
        right = left if low == high else np.flatnonzero(block == high)
        if not len(left) or not len(right):
            return pa.table({"a": pa.array([], pa.int64()), "b": pa.array([], pa.int64()), "n": pa.array([], pa.int64())})
        open_ = ids[left][:, None] != ids[right][None, :]
        by_cold: dict[int, list[int]] = {}
        for j, k in enumerate(right):
            for c in cold[k]:
                by_cold.setdefault(c, []).append(j)
        for i, k in enumerate(left):
            for c in cold[k]:
                open_[i, by_cold.get(c, [])] = False
        if key is not None:
            for i, j in zip(*np.nonzero(open_)):
                open_[i, j] = min(hot[left[i]] & hot[right[j]], default=None) == key
        found = similar([sets[k] for k in left], [sets[k] for k in right], open_, rule, (own[left], own[right]))
        # several texts of an id are one document
        names, at = np.unique(ids, return_inverse=True)
        linked = np.zeros((len(names), len(names)), bool)
        i, j = np.nonzero(found)
        linked[at[left[i]], at[right[j]]] = linked[at[right[j]], at[left[i]]] = True
        degree, group, links = linked.sum(axis=1), np.arange(len(names)), []
        for i in range(len(names)):
            near = np.flatnonzero(linked[i])
            other, first = np.unique(group[near], return_index=True)
            for g, j in zip(other, near[first]):
                if g != group[i]:
                    links.append((int(names[i]), int(names[j])))
            group[np.isin(group, other)] = group[i]
        some = np.flatnonzero(degree)
        a = [*names[some].tolist(), *(x[0] for x in links)]
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array([None] * len(some) + [x[1] for x in links], pa.int64()), "n": pa.array([*degree[some].tolist(), *[0] * len(links)], pa.int64())})

    return make


def hot_links(spark: SparkSession, sets: DataFrame, keyed: DataFrame, rule: Rule) -> DataFrame:
    """a, b, n as of _blocks, over the pairs of frequent keys; keyed has doc_id, key, b (the key's smallest id) and docs."""
    frequent = keyed.where(F.col("docs") > HOT)
    parts = components(spark, frequent.selectExpr("doc_id AS a", "b").where("a <> b"), "groups").withColumnRenamed("id", "doc_id").withColumnRenamed("component", "unit")
    blocks = lambda n: F.ceil(F.col(n) / BLOCK)
    # a group's documents travel once for each block of the group, or once for each key and block of the key
    members = parts.groupBy("unit").agg(F.count(F.lit(1)).alias("size"))
    by_key = frequent.join(parts, "doc_id").groupBy("unit").agg(F.sum(blocks("docs")).alias("cost"))
    groups = cut(spark, members.join(by_key, "unit").select("unit", "size", (F.col("size") * blocks("size") <= F.col("cost")).alias("together")), "groups")
    owned = parts.join(groups, "unit")
    rows = owned.where("together").selectExpr("doc_id", "unit", "CAST(NULL AS long) AS key", "size AS docs")
    loose = owned.where("NOT together").select("doc_id", "unit")
    rows = rows.unionByName(frequent.join(loose, "doc_id").select("doc_id", "unit", "key", "docs"))
    n = blocks("docs").cast("int")
    rows = rows.withColumn("block", F.pmod(F.xxhash64("doc_id"), n).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), n - 1)))
    rows = rows.withColumn("low", F.least("block", "other")).withColumn("high", F.greatest("block", "other"))
    some = cut(spark, keyed.join(parts.select("doc_id"), "doc_id", "left_semi").groupBy("doc_id").agg(F.collect_set(F.when(F.col("docs") <= HOT, F.col("key"))).alias("cold"), F.collect_set(F.when(F.col("docs") > HOT, F.col("key"))).alias("hot")), "frequent")
    sets, active = idfilter.narrowed(spark, sets, some.select("doc_id"), "doc_id")
    whole = sets.mapInArrow(_whole(active), "doc_id long, size long, own long, data binary")
    packed = rows.join(whole.join(some, "doc_id"), "doc_id")
    return cut(spark, packed.groupBy("unit", "key", "low", "high").applyInArrow(_blocks(rule), "a long, b long, n long"), "hot")


def near_duplicates(spark: SparkSession, docs: DataFrame, n: int = 3, percent: int = 90) -> DataFrame:
    """One row a document: doc_id, n_shingles, class_id (equal sets), n_links, component_id; n_links counts the classes that
    the document's class is similar to."""
    rule = Rule(n, percent)
    docs = documents(docs)
    batches = ex.batch_count(docs)
    dealt = ex.hashed_batches(docs, batches)
    asked = dealt.groupBy("batch").applyInArrow(_ask(rule, ex.shard_bits(batches)), "batch int, shard int, keys binary, counts binary")
    told = asked.groupBy("shard").applyInArrow(_frequencies(batches), "batch int, shard int, counts binary")
    sets = cut(spark, dealt.groupBy("batch").cogroup(told.groupBy("batch")).applyInArrow(_prefixes(rule), SETS), "sets")
    filled = sets.where("n_shingles > 0")
    classes = cut(spark, filled.groupBy("hi", "lo").agg(F.min("doc_id").alias("class_id")), "classes")
    heads = filled.where(F.size("prefix") > 0).join(classes, ["hi", "lo"]).where("doc_id = class_id").select("doc_id", F.explode("prefix").alias("key")).distinct()
    heads = cut(spark, heads, "prefixes")
    first = heads.groupBy("key").agg(F.min("doc_id").alias("b"), F.count(F.lit(1)).alias("docs")).where("docs > 1")
    near = cut(spark, heads.join(first, "key"), "keys")  # the keys of several documents
    listed = near.where(F.col("docs") <= HOT).select("key", "doc_id")
    pairs = listed.selectExpr("key", "doc_id AS a").join(listed.selectExpr("key", "doc_id AS b"), "key").where("a > b").select("a", "b").distinct()
    pairs = cut(spark, pairs, "pairs")
    partnered = sets.where(F.size("prefix") > 0).select("doc_id", "n_shingles", "own", "parts")
    paired, active = idfilter.narrowed(spark, partnered, listed.select("doc_id").distinct(), "doc_id")
    members = cut(spark, paired.mapInArrow(_members(active), MEMBERS), "members")
    links = cut(spark, verified(spark, pairs, members, rule), "links")
    drop(spark, members)
    drop(spark, pairs)
    release(spark)
    hot = hot_links(spark, partnered, near, rule)
    final = components(spark, links.unionByName(hot.where("b IS NOT NULL").select("a", "b")))
    release(spark)
    ends = links.selectExpr("a AS class_id", "1L AS n").unionByName(links.selectExpr("b AS class_id", "1L AS n")).unionByName(hot.where("b IS NULL").selectExpr("a AS class_id", "n"))
    degree = ends.groupBy("class_id").agg(F.sum("n").alias("n_links"))
    out = sets.select("doc_id", "n_shingles", "hi", "lo").join(classes, ["hi", "lo"], "left")
    out = out.withColumn("class_id", F.when(F.col("n_shingles") > 0, F.col("class_id")).otherwise(F.col("doc_id")))
    out = out.join(degree, "class_id", "left").join(final.withColumnRenamed("id", "class_id").withColumnRenamed("component", "component_id"), "class_id", "left")
    return out.select("doc_id", "n_shingles", "class_id", F.coalesce("n_links", F.lit(0)).alias("n_links"), F.coalesce("component_id", "class_id").alias("component_id"))
