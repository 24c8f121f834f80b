"""Benchmark decontamination by spaced seeds, in DataFrame operations only.

Words are lower-cased runs of letters and digits.  A mask keeps some of the places of a span of words and ignores the
others; the kept words' hash is a seed.  Seeds of all places of all documents meet the seeds of the benchmark in a join.
Hits of one document and item on one diagonal have all words of that diagonal compared, one by one.  A region runs from
one agreeing word to another; it counts when at least `share` of its words agree and it is SPAN words long, or when it is
a whole item.  Of a diagonal's regions that count, the one with most agreeing words is returned, so what was changed
between two copied pieces costs neither of them.

The masks hit every region that counts at a share of 0.8 or more: a longer region has a part of SPAN to 2 * SPAN - 1 words
with that share, and they fit into every such part, wherever its differing words are (a test tries all).

Items shorter than the span have masks of their own, of all their words, or of all but one where the share leaves one
free: as long as the item, so they fit wherever the share does.

The benchmark's seeds are broadcast while their measured number is below a bound; beyond it the join shuffles by seed, and
the session's adaptive execution splits the seeds that many documents hold.  Equal items are one item (the smallest id).

Defined results: null texts have no words; items without words match nothing; rows that share an id count as one
document; a table without benchmark rows gives an empty result; further columns of either table are ignored.
"""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from pagelift.llm.common import cut, documents

SPAN = 10
#: Fixed masks of six places in at most ten words, found by a greedy search over all places of differing words.
MASKS = ((0, 1, 2, 3, 5, 6), (0, 1, 4, 6, 7, 8), (0, 1, 2, 4, 8, 9), (0, 2, 3, 4, 5, 6), (0, 1, 2, 4, 5, 6), (0, 1, 2, 3, 6, 8))
MAX_BROADCAST_SEEDS = 1_000_000


def word_hashes(text: Column) -> Column:
    words = F.array_remove(F.split(F.lower(F.coalesce(text, F.lit(""))), r"[^\p{L}\p{N}]+"), "")
    return F.transform(words, lambda w: F.xxhash64(w))


def short_masks(width: int, share: float) -> list[tuple[int, ...]]:
    """Masks of an item of so few words: without each number of words that may differ."""
    free = int((1000 - round(1000 * share)) * width // 1000)
    return list(combinations(range(width), width - free))


def short_seeds(width: int, share: float, word) -> list[Column]:
    return [F.xxhash64(F.lit(100 + width), F.lit(m), *(word(k) for k in mask)) for m, mask in enumerate(short_masks(width, share))]


def places(rows: DataFrame, keys: list[str], short: list[int], share: float, words: str = "h") -> DataFrame:
    """keys, pos, seed: the seeds of every place; also of every run of a length in short."""
    n = F.size(words)
    run = lambda width: F.arrays_zip(*[F.slice(words, k + 1, F.greatest(n - (width - 1), F.lit(0))).alias(f"w{k}") for k in range(width)])
    word = lambda k: F.col("w").getField(f"w{k}")
    # masks shorter than the span also start at the last words; w0 to w9 are null beyond the end
    tail = F.arrays_zip(*[F.slice(words, k + 1, n).alias(f"w{k}") for k in range(SPAN)])
    spans = rows.where(n >= SPAN).select(*keys, F.posexplode(tail).alias("pos", "w"))
    masks = [F.when(word(mask[-1]).isNotNull(), F.xxhash64(F.lit(m), *(word(k) for k in mask))).alias(f"s{m}") for m, mask in enumerate(MASKS)]
    stacked = f"stack({len(MASKS)}, {', '.join(f's{m}' for m in range(len(MASKS)))}) AS seed"
    out = spans.select(*keys, "pos", *masks).selectExpr(*keys, "pos", stacked).where("seed IS NOT NULL")
    for width in short:
        part = rows.select(*keys, F.posexplode(run(width)).alias("pos", "w"))
        out = out.unionByName(part.select(*keys, "pos", F.explode(F.array(*short_seeds(width, share, word))).alias("seed")))
    return out


def best_region(at: Column, words: Column, share: float) -> Column:
    """Of the regions that count, by the sorted places of a diagonal's agreeing words, the one with most of them: a struct
    of matched, first (negative) and length; null without one."""
    n = F.size(at)
    every = F.when(n > 0, F.sequence(F.lit(0), n - 1)).otherwise(F.array().cast("array<int>"))
    place = lambda k: F.get(at, k)
    # a best region can't be extended by an agreeing word
    starts = F.filter(every, lambda k: (k == 0) | (place(k - 1) != place(k) - 1))
    ends = F.filter(every, lambda k: (k == n - 1) | (place(k + 1) != place(k) + 1))
    permille = round(1000 * share)
    fits = lambda i, j: (1000 * (j - i + 1) >= permille * (place(j) - place(i) + 1)) & ((place(j) - place(i) + 1 >= SPAN) | ((place(i) == 0) & (place(j) == words - 1)))
    region = lambda i, j: F.struct((j - i + 1).alias("matched"), (-place(i)).alias("first"), (place(j) - place(i) + 1).alias("length"))
    return F.array_max(F.flatten(F.transform(starts, lambda i: F.transform(F.filter(ends, lambda j: (j >= i) & fits(i, j)), lambda j: region(i, j)))))


def overlaps(spark: SparkSession, docs: DataFrame, benchmark: DataFrame, share: float = 0.8) -> DataFrame:
    """doc_id, item_id, start, length, matched, item_words: the best region of every document and item that overlap."""
    docs = documents(docs)
    items = benchmark.select(F.col("item_id").cast("long").alias("item_id"), word_hashes(F.col("text").cast("string")).alias("h")).where(F.size("h") > 0)
    items = items.groupBy("h").agg(F.min("item_id").alias("item_id"))
    short = sorted(r[0] for r in items.select(F.size("h").alias("n")).where(F.col("n") < SPAN).distinct().collect())  # at most SPAN - 1 lengths
    whole = items.withColumn("n", F.size("h"))
    seeds = places(whole.where(F.col("n") >= SPAN), ["item_id"], [], share)
    for width in short:  # a short item is one run
        seeds = seeds.unionByName(whole.where(F.col("n") == width).select("item_id", F.lit(0).alias("pos"), F.explode(F.array(*short_seeds(width, share, lambda k: F.get("h", F.lit(k))))).alias("seed")))
    seeds = cut(spark, seeds.select("item_id", F.col("pos").alias("at"), "seed").distinct(), "seeds")
    held = F.broadcast(seeds) if seeds.count() <= MAX_BROADCAST_SEEDS else seeds
    tokens = docs.select("doc_id", word_hashes(F.col("text")).alias("h"))
    hits = places(tokens, ["doc_id"], short, share).join(held, "seed")
    regions = cut(spark, hits.select("doc_id", "item_id", (F.col("pos") - F.col("at")).alias("shift")).distinct(), "regions")
    held_docs = docs.join(regions.select("doc_id").distinct(), "doc_id", "left_semi").select("doc_id", word_hashes(F.col("text")).alias("h"))
    both = regions.join(held_docs, "doc_id").join(items.withColumnRenamed("h", "b"), "item_id")
    # places of the item where it agrees with a document's text; with several texts of an id, a region lies in one of them
    same = F.filter(F.sequence(F.lit(0), F.size("b") - 1), lambda i: F.get("h", i + F.col("shift")) == F.get("b", i))
    found = both.select("doc_id", "item_id", "shift", F.size("h").alias("doc_words"), F.size("b").alias("item_words"), same.alias("same"))
    whole = (F.col("shift") >= 0) & (F.col("shift") + F.col("item_words") <= F.col("doc_words")) & (1000 * F.size("same") >= F.lit(round(1000 * share)) * F.col("item_words"))
    region = F.when(whole, F.struct(F.size("same").alias("matched"), F.lit(0).alias("first"), F.col("item_words").alias("length"))).otherwise(best_region(F.col("same"), F.col("item_words"), share))
    fits = found.select("doc_id", "item_id", "shift", "item_words", region.alias("r")).where("r IS NOT NULL")
    good = fits.select("doc_id", "item_id", (F.col("shift") - F.col("r.first")).alias("start"), "r.length", "r.matched", "item_words")
    best = good.groupBy("doc_id", "item_id").agg(F.max(F.struct("matched", (-F.col("start")).alias("s"), "length", "item_words")).alias("m"))
    return best.select("doc_id", "item_id", *(x.cast("long") for x in ((-F.col("m.s")).alias("start"), F.col("m.length").alias("length"), F.col("m.matched").alias("matched"), F.col("m.item_words").alias("item_words"))))
