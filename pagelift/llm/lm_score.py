"""Deleted-interpolation language model: scores of whole texts under a corpus-wide n-gram model.

The model mixes maximum-likelihood estimates of the orders 1..order with an additively smoothed unigram model.
The mixture weights depend on the frequency bucket of the longest context (powers of two) and come from
expectation-maximisation on held-out counts: a tenth of the batches is deleted from the counts, and its n-grams are
the events.  The final model uses the counts of all training documents.

Plan: one exchange carries the counts (see exchange.py), one pass over the deleted tenth makes the events, one pass
scores.  Events reach the driver as cells of a fixed grid (bucket x quantised log-probabilities), so their number has
a bound that does not depend on the corpus.

Defined results: a null or empty text is the end token alone; repeated rows are scored each; an empty table gives an
empty result; further columns of the input are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pagelift.llm import exchange as ex
from pagelift.llm.common import WordIds, crc_mod, cut, documents, mix, names_of, pair_hash, raw

BUCKETS = 24  # contexts seen 0, 1, 2-3, 4-7, ... times
GRID = 4  # cells a unit of log2
FLOOR = 64 * GRID  # cell of probabilities of 2^-64 and less; also of zero
FOLDS = 10  # every FOLDS-th batch is the deleted part
END, START = np.uint64(0x5E6D0F0A11C3B7D1), np.uint64(0x1F83D9ABFB41BD6B)  # hashes of the end token and of a text's start
SALT = np.uint64(0xA0761D6478BD642F)


def coded(table: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    """Word hashes of all texts of a batch, each text closed by the end token, and the texts' bounds."""
    ids, parts, sizes = WordIds(), [], []
    for text in raw(table.column("text")):
        words = text.lower().split() if text else []
        parts.append(ids.code(words))
        sizes.append(len(words) + 1)
    bounds = np.concatenate([[0], np.cumsum(np.array(sizes, dtype=np.int64))]).astype(np.int64)
    out = np.full(bounds[-1], END, dtype=np.uint64)
    hashes = mix(ids.table() ^ SALT) if len(ids) else np.array([], np.uint64)
    for part, at in zip(parts, bounds):
        out[at : at + len(part)] = hashes[part]
    return out, bounds


def grams(table: pa.Table, order: int) -> tuple[list[np.ndarray], np.ndarray]:
    """For each order 1..order the hash of the n-gram that ends at each token."""
    tokens, bounds = coded(table)
    out, before = [tokens], tokens
    for k in range(1, order):
        earlier = np.roll(tokens, k)
        for j in range(k):  # the tokens whose k-th predecessor lies before the text
            at = bounds[:-1] + j
            at = at[at < bounds[1:]]
            earlier[at] = mix(np.array([START + np.uint64(k - j)], np.uint64))[0]
        before = pair_hash(before, earlier)
        out.append(before)
    return out, bounds


def contexts(keys: list[np.ndarray], bounds: np.ndarray) -> np.ndarray:
    """Position of the n-gram that ends before each token, or -1 at a text's start."""
    at = np.arange(len(keys[0])) - 1
    at[bounds[:-1]] = -1
    return at


def request_rows(order: int, bits: int):
    def make(key, table):
        batch = key[0].as_py()
        keys, bounds = grams(table, order)
        train = np.repeat(np.asarray(table.column("train")), np.diff(bounds))
        rows = []
        for k, h in enumerate(keys):
            uniq, inv = np.unique(h, return_inverse=True)
            n = np.bincount(inv, weights=train, minlength=len(uniq)).astype(np.int64)
            at = ex.slices(uniq, bits)
            for s in range(len(at) - 1):
                u, c = uniq[at[s] : at[s + 1]], n[at[s] : at[s + 1]]
                if len(u):
                    rows.append((batch, s, k, len(u), ex.pack_sorted(u), ex.pack_counts(c)))
        return pa.table([pa.array(c, t) for c, t in zip(list(zip(*rows)) or [[]] * 6, (pa.int32(), pa.int32(), pa.int32(), pa.int64(), pa.binary(), pa.binary()))], names=names_of(REQUEST))

    return make


def shard_sums(folds: int):
    def add(table: pa.Table) -> pa.Table:
        rows, shard = [], table.column("shard")[0].as_py()
        orders, batches = np.asarray(table.column("ord")), np.asarray(table.column("batch"))
        for k in np.unique(orders):
            part = table.filter(pa.array(orders == k))
            owner = batches[orders == k]
            vectors = [ex.unpack_sorted(x) for x in part.column("keys").to_pylist()]
            counts = [ex.unpack_counts(x) for x in part.column("counts").to_pylist()]
            at = np.concatenate([[0], np.cumsum([len(v) for v in vectors])]).astype(np.int64)
            uniq, inv = np.unique(np.concatenate(vectors), return_inverse=True)
            flat = np.concatenate(counts)
            total = np.bincount(inv, weights=flat, minlength=len(uniq)).astype(np.int64)
            left = np.repeat(owner % folds != 0, np.diff(at))
            keep = np.bincount(inv, weights=flat * left, minlength=len(uniq)).astype(np.int64)
            for i, b in enumerate(owner):
                mine = inv[at[i] : at[i + 1]]
                rows.append((int(b), shard, int(k), ex.pack_counts(total[mine]), ex.pack_counts(keep[mine]) if b % folds == 0 else None, 0, 0, 0, 0))
            if k == 0:
                rows.append((-1, shard, 0, None, None, int(total.sum()), int((total > 0).sum()), int(keep.sum()), int((keep > 0).sum())))
        kinds = (pa.int32(), pa.int32(), pa.int32(), pa.binary(), pa.binary(), *[pa.int64()] * 4)
        return pa.table([pa.array(c, t) for c, t in zip(zip(*rows), kinds)], names=names_of(REPLY))

    return add


REQUEST = "batch int, shard int, ord int, n long, keys binary, counts binary"
REPLY = "batch int, shard int, ord int, total binary, keep binary, tokens long, words long, keep_tokens long, keep_words long"


def answers(replies: pa.Table, column: str, k: int) -> np.ndarray:
    part = replies.filter(pa.array(np.asarray(replies.column("ord")) == k)).sort_by("shard")
    found = [ex.unpack_counts(x) for x in part.column(column).to_pylist()]
    return np.concatenate(found) if found else np.array([], np.int64)


def estimates(table: pa.Table, replies: pa.Table, column: str, order: int, size: tuple[int, int]):
    """Per token: count of the word, bucket of the longest context, and the probabilities of the orders 0..order."""
    keys, bounds = grams(table, order)
    n, v = size
    counts = [answers(replies, column, k)[np.unique(h, return_inverse=True)[1]] for k, h in enumerate(keys)]
    before = contexts(keys, bounds)
    texts = _start_count(replies, column)
    ml = [(counts[0] + 0.5) / (n + 0.5 * (v + 1)), counts[0] / max(1, n)]
    bucket = np.zeros(len(before), np.int64)
    for k in range(1, order):
        seen = np.where(before >= 0, counts[k - 1][before], texts)
        ml.append(np.divide(counts[k], seen, out=np.zeros(len(seen)), where=seen > 0))
        bucket = np.minimum(BUCKETS - 1, np.ceil(np.log2(seen + 1)).astype(np.int64))
    return counts[0], bucket, np.vstack(ml), bounds


def _start_count(replies: pa.Table, column: str) -> int:
    return int(replies.schema.metadata[b"texts" if column == "total" else b"keep_texts"])


def event_cells(order: int, size: tuple[int, int], texts: tuple[int, int]):
    def make(key, docs, replies):
        replies = replies.replace_schema_metadata({"texts": str(texts[0]), "keep_texts": str(texts[1])})
        _, bucket, ml, bounds = estimates(docs, replies, "keep", order, size)
        with np.errstate(divide="ignore"):
            q = np.minimum(FLOOR, np.round(-GRID * np.log2(ml)))
        train = np.repeat(np.asarray(docs.column("train")), np.diff(bounds))  # the answers cover all texts of the batch
        grid, n = np.unique(np.column_stack([bucket, q.T.astype(np.int64)])[train], axis=0, return_counts=True)
        return pa.table([pa.array(grid.astype(np.int32).tolist(), pa.list_(pa.int32())), pa.array(n.astype(np.int64))], names=["cell", "events"])

    return make


def learn(cells: list, order: int, rounds: int = 40) -> np.ndarray:
    """Mixture weights [bucket, order 0..order] by expectation-maximisation over the cells; a unit of prior each."""
    weights = np.full((BUCKETS, order + 1), 1.0 / (order + 1))
    if not cells:
        return weights
    grid = np.array([c for c, _ in cells], dtype=np.int64)
    n = np.array([x for _, x in cells], dtype=float)
    p = np.where(grid[:, 1:] >= FLOOR, 0.0, 2.0 ** (-grid[:, 1:] / GRID))
    for _ in range(rounds):
        share = weights[grid[:, 0]] * p
        share /= np.maximum(share.sum(axis=1, keepdims=True), 1e-300)
        new = np.full_like(weights, 0.01)
        np.add.at(new, grid[:, 0], share * n[:, None])
        weights = new / new.sum(axis=1, keepdims=True)
    return weights


def text_scores(order: int, size: tuple[int, int], texts: tuple[int, int], weights: np.ndarray):
    def make(key, docs, replies):
        replies = replies.replace_schema_metadata({"texts": str(texts[0]), "keep_texts": str(texts[1])})
        known, bucket, ml, bounds = estimates(docs, replies, "total", order, size)
        total = lambda x: np.add.reduceat(x, bounds[:-1])
        score = np.log10((weights[bucket] * ml.T).sum(axis=1))
        return pa.table(
            {
                "doc_id": docs.column("doc_id"),
                "held_out": docs.column("held_out"),
                "n_tokens": pa.array(np.diff(bounds).astype(np.int64)),
                "n_known": pa.array(total((known > 0).astype(np.int64))),
                "train_tokens": pa.array(np.full(docs.num_rows, size[0], np.int64)),
                "base_score": pa.array(total(np.log10(ml[0]))),
                "score": pa.array(total(score)),
            }
        )

    return make


SCORES = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"


def score(spark: SparkSession, docs: DataFrame, held_out, order: int = 2) -> DataFrame:
    """Score every text; rows where the Column held_out is true are not learned from."""
    docs = documents(docs).withColumn("held_out", F.coalesce(held_out, F.lit(False))).withColumn("train", ~F.col("held_out"))
    batches = ex.batch_count(docs, multiple=FOLDS)
    bits = ex.shard_bits(batches)
    dealt = ex.hashed_batches(docs, batches)
    asked = dealt.groupBy("batch").applyInArrow(request_rows(order, bits), REQUEST)
    replies = cut(spark, asked.groupBy("shard").applyInArrow(shard_sums(FOLDS), REPLY), "lm")
    n, v, kept_n, kept_v = (int(x or 0) for x in replies.where("batch = -1").agg(*(F.sum(c) for c in ("tokens", "words", "keep_tokens", "keep_words"))).first())
    texts, kept_texts = (int(x or 0) for x in dealt.where("train").agg(F.count(F.lit(1)), F.sum((F.col("batch") % FOLDS != 0).cast("int"))).first())
    deleted = F.col("batch") % FOLDS == 0
    answered = replies.where("batch >= 0")
    events = _cogroup(dealt.where(deleted), answered.where(deleted), event_cells(order, (kept_n, kept_v), (texts, kept_texts)), "cell array<int>, events long")
    cells = [(r[0], r[1]) for r in events.groupBy("cell").agg(F.sum("events")).collect()]
    weights = learn(cells, order)
    return _cogroup(dealt, answered, text_scores(order, (n, v), (texts, kept_texts), weights), SCORES)


def _cogroup(docs: DataFrame, replies: DataFrame, f, schema: str) -> DataFrame:
    return docs.groupBy("batch").cogroup(replies.groupBy("batch")).applyInArrow(f, schema)


def held_out_column():
    return crc_mod("doc_id", 5) == 1
