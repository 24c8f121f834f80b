"""Exact top-k by integer inner product over an impact-ordered index, score at a time.

Vectors are quantised to integers.  Each dimension gives two posting lists whose impacts are not negative: the distance
from the shard's lowest value (for positive query weights) and from its highest (for negative ones).  A list is cut into
segments by quantised impact.  For a block of queries the segments are processed from the highest impact down, all lists
of a band at once as one matrix product; what is left unseen in a list can add at most the band's edge less one.  As
soon as the bounds prove that few vectors can still be members, those are rescored exactly; nothing stops on less.

Nothing is shuffled but results.  Queries are broadcast in waves of WAVE_BYTES; a task cuts the vectors that it reads
into shards of SHARD_ROWS, indexes each once a wave, and searches it with the bars, the k-th best scores so far, that the
task's earlier shards have left.  It returns k rows a query at most, and a window over those picks the best.

Defined results: vectors that are null or hold null or non-finite components take no part; missing trailing components
count as zero; ties go to the smaller id; rows that share an id are queries each, and none of them is a candidate of the
others; an empty table, or one without queries, gives an empty result; further columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from pagelift.llm.common import cut

SHARD_ROWS, TILE = 8192, 256
WAVE_BYTES = 32 << 20  # of queries that are broadcast at once
#: Share of the postings that lie below each band's edge; the last band has none below it.
BANDS = (0.4, 0.04, 0.004, 0.0)
FEW = 0.05  # rescore when at most this share of the shard can be a member


def quantised(ids: pa.Array, vectors: pa.Array, scale: float) -> tuple[np.ndarray, np.ndarray]:
    """Ids and whole-number vectors (rows of one width) of the rows that take part."""
    on = np.asarray(ids.is_valid()) & np.asarray(vectors.is_valid())
    ids, vectors = ids.filter(pa.array(on)), vectors.filter(pa.array(on))
    size = np.asarray(pc.list_value_length(vectors)).astype(np.int64)
    out = np.zeros((len(size), int(size.max(initial=0))))
    out[np.arange(out.shape[1]) < size[:, None]] = np.floor(scale * vectors.flatten().to_numpy(zero_copy_only=False).astype(np.float64))
    fine = np.isfinite(out).all(axis=1)  # nulls are not
    return np.asarray(ids).astype(np.int64)[fine], out[fine].astype(np.int64)


def widened(x: np.ndarray, wide: int) -> np.ndarray:
    return x if x.shape[1] == wide else np.pad(x, ((0, 0), (0, wide - x.shape[1])))


class ImpactIndex:
    """Of one shard."""

    def __init__(self, ids: np.ndarray, x: np.ndarray):
        by = np.argsort(ids, kind="stable")
        self.ids, self.x = ids[by], x[by]
        self.low, self.high = self.x.min(axis=0), self.x.max(axis=0)
        lists = np.hstack([self.x - self.low, self.high - self.x])
        self.top = int(lists.max(initial=0))
        self.kind = None
        edges = [0 if share == 0 else int(np.quantile(lists, share)) for share in BANDS]
        self.bands, above = [], self.top + 1
        for edge in edges:
            if edge < above:
                inside = (lists >= edge) & (lists < above)
                self.bands.append((edge, np.where(inside, lists, 0), lists < edge))
                above = edge

    def search(self, ids: np.ndarray, q: np.ndarray, k: int, bars: np.ndarray | None = None):
        """(query position, vector position, score) of each query's best k, of those that reach the query's bar."""
        # impacts are counted from the shard's lowest and highest values, and so are bars here
        shift = np.maximum(q, 0) @ self.low - np.maximum(-q, 0) @ self.high
        bars = np.full(len(q), -np.inf) if bars is None else bars - shift
        weight = np.hstack([np.maximum(q, 0), np.maximum(-q, 0)])
        most = int(weight.max(initial=0)) * max(self.top, 1) * max(1, weight.shape[1])
        if most >= 1 << 53:  # beyond exact floats: every vector is scored
            score = q @ self.x.T
            near = self.ids[None, :] != ids[:, None]
            return self._best(*np.nonzero(near), score[near], k)
        kind = np.float32 if most < 1 << 24 else np.float64
        if self.kind is not kind:
            self.kind, self.bands = kind, [(e, p.astype(kind), u.astype(kind)) for e, p, u in self.bands]
        weight = weight.astype(kind)
        own = self.ids[None, :] == ids[:, None]
        n = len(self.ids)
        parts = []
        got = np.zeros((len(q), n), kind)
        live = np.arange(len(q))
        for edge, postings, unseen in self.bands:
            got[live] += weight[live] @ postings.T
            upper = got[live] + weight[live] @ unseen.T * max(edge - 1, 0) if edge else got[live]
            lower = np.where(own[live], -np.inf, got[live])
            bar = np.maximum(bars[live], np.partition(lower, n - k, axis=1)[:, n - k] if n > k else -np.inf)
            possible = (upper >= bar[:, None]) & ~own[live]
            ready = (possible.sum(axis=1) <= max(4 * k, FEW * n)) if edge else np.ones(len(live), bool)
            at, v = np.nonzero(possible[ready])
            parts.append((live[ready][at], v))
            live = live[~ready]
            if not len(live):
                break
        who, v = (np.concatenate(p) for p in zip(*parts))
        score = np.empty(len(who), np.int64)
        for a in range(0, len(who), 1 << 16):
            b = slice(a, a + (1 << 16))
            score[b] = (q[who[b]] * self.x[v[b]]).sum(axis=1)
        return self._best(who, v, score, k)

    def _best(self, who, v, score, k):
        by = np.lexsort((self.ids[v], -score, who))
        who, v, score = who[by], v[by], score[by]
        first = np.searchsorted(who, who)
        keep = np.arange(len(who)) - first < k
        return who[keep], v[keep], score[keep]


class Best:
    """The best k so far of each query."""

    def __init__(self, n: int, k: int):
        self.k, self.who, self.vec, self.score = k, *(np.zeros(0, np.int64) for _ in range(3))
        self.bars = np.full(n, -np.inf)

    def add(self, who: np.ndarray, vec: np.ndarray, score: np.ndarray) -> None:
        who, vec, score = (np.concatenate(x) for x in ((self.who, who), (self.vec, vec), (self.score, score)))
        by = np.lexsort((vec, -score, who))
        who, vec, score = who[by], vec[by], score[by]
        place = np.arange(len(who)) - np.searchsorted(who, who)
        self.who, self.vec, self.score = (x[place < self.k] for x in (who, vec, score))
        last = place == self.k - 1
        self.bars[who[last]] = score[last]


def searching(k: int, scale: float, sent, shard_rows: int):
    names = ["query", "query_id", "vec_id", "score"]

    def stream(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        qids, q = sent.value
        best, held, rows = Best(len(qids), k), [], 0

        def search(held):
            found = []
            wide = max([q.shape[1], *(x.shape[1] for _, x in held)])
            shard, queries = ImpactIndex(np.concatenate([i for i, _ in held]), np.vstack([widened(x, wide) for _, x in held])), widened(q, wide)
            for a in range(0, len(q), TILE):
                who, v, s = shard.search(qids[a : a + TILE], queries[a : a + TILE], k, best.bars[a : a + TILE])
                found.append((who + a, shard.ids[v], s))
            best.add(*(np.concatenate(x) for x in zip(*found)))

        for batch in batches if len(qids) else ():
            for at in range(0, batch.num_rows, shard_rows):
                part = batch.slice(at, shard_rows)
                ids, x = quantised(part.column("vec_id"), part.column("v"), scale)
                if len(ids):
                    held.append((ids, x))
                    rows += len(ids)
                if rows >= shard_rows:
                    search(held)
                    held, rows = [], 0
        if held:
            search(held)
        for a in range(0, len(best.who), 1 << 16):
            who, vec, score = (x[a : a + (1 << 16)] for x in (best.who, best.vec, best.score))
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in (who, qids[who], vec, score)], names=names)

    return stream


def top_k(vectors: DataFrame, is_query, k: int = 20, scale: float = 64.0, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """query_id, rank, vec_id, score: the best k of all other rows for each row where the Column is_query holds."""
    spark = vectors.sparkSession
    source = vectors.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vector_col).cast("array<double>").alias("v"), F.coalesce(is_query, F.lit(False)).alias("asks"))
    asked, wide = (int(x or 0) for x in source.where("asks").agg(F.count(F.lit(1)), F.max(F.size("v"))).first())
    waves = max(1, -(-asked * 8 * max(1, wide) // WAVE_BYTES))
    found = None
    for wave in range(waves):
        mine = source.where("asks").where(F.pmod(F.xxhash64("vec_id", "v"), F.lit(waves)) == wave).orderBy("vec_id", "v").toArrow()
        sent = spark.sparkContext.broadcast(quantised(*(mine.column(c).combine_chunks() for c in ("vec_id", "v")), scale))
        part = source.select("vec_id", "v").mapInArrow(searching(k, scale, sent, SHARD_ROWS), "query long, query_id long, vec_id long, score long").withColumn("wave", F.lit(wave))
        part = part if waves == 1 else cut(spark, part, "wave")
        found = part if found is None else found.unionByName(part)
    best = Window.partitionBy("wave", "query").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(best).cast("int")).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
