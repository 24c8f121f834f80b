"""Corpus operators against brute force on small tables, with nulls, empty and repeated rows, ties and clashing columns."""

import hashlib
import math
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from pagelift.llm import decontaminate, exchange, licenses, line_dedup, lm_score, ngram_join, packing, quality, substring, token_spans, topk
from pagelift.llm.components import components

WORDS = re.compile(rb"[^\x20\x09-\x0D]+")
SCHEMA = "doc_id long, text string, batch string, row int, score string, lang string"


def words(text, lower=True):
    data = (text or "").encode()
    return WORDS.findall(data.lower() if lower else data)


@pytest.fixture(scope="module")
def rows():
    rng = np.random.default_rng(5)
    vocab = [f"w{i}" for i in range(40)] + ["Été", "ÅB", "x\x1cy", "a b"]
    passage = " ".join(f"p{i}" for i in range(30))
    out = [(0, None), (1, ""), (2, " \n\t "), (3, "one"), (4, "One TWO"), (5, passage), (6, "intro " + passage.upper() + " outro"), (7, "pre " + passage + " post " + passage)]
    for i in range(8, 60):
        t = " ".join(rng.choice(vocab, rng.integers(1, 120)))
        if i % 3 == 0:
            t += "\n  Common Line \n" + t[:30]
        if i % 7 == 0:
            t = out[-1][1] or t
        if i % 11 == 0:
            t = passage + "\n" + t
        out.append((i, t))
    base = " ".join(rng.choice(vocab, 300)).split()
    for k in range(6):
        near = list(base)
        near[k * 40] = "changed"
        out.append((60 + k, " ".join(near)))
    out.append((66, " ".join(base * 40)))  # long
    out.append((3, "one"))  # a repeated row
    return out


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame([(i, t, "b", 1, "s", "en") for i, t in rows], SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


def test_packed_vectors_come_back():
    rng = np.random.default_rng(1)
    for n in (0, 1, 2, 1000):
        v = np.unique(rng.integers(0, 1 << 63, n).astype(np.uint64) * np.uint64(2))
        assert np.array_equal(exchange.unpack_sorted(exchange.pack_sorted(v)), v)
        for top in (2, 300, 1 << 40):
            c = rng.integers(0, top, n)
            assert np.array_equal(exchange.unpack_counts(exchange.pack_counts(c)), c)
    v = np.sort(rng.integers(0, 1 << 63, 500).astype(np.uint64))
    at = exchange.slices(v, 3)
    assert at[0] == 0 and at[-1] == len(v) and all((v[a:b] >> np.uint64(61) == k).all() for k, (a, b) in enumerate(zip(at, at[1:])))


@pytest.mark.parametrize("order", [2, 3])
def test_language_model(spark, docs, rows, order):
    held = {i for i, _ in rows if zlib.crc32(str(i).encode()) % 5 == 1}
    got = lm_score.score(spark, docs, lm_score.held_out_column(), order).collect()
    assert len(got) == len(rows) and all(r.held_out == (r.doc_id in held) for r in got)
    train = Counter()
    for i, t in rows:
        if i not in held:
            train.update([*words(t), None])
    n, v = sum(train.values()), len(train)
    want = {i: [*words(t), None] for i, t in rows}
    for r in got:
        tokens = want[r.doc_id]
        assert r.n_tokens == len(tokens) and r.train_tokens == n and r.n_known == sum(train[x] > 0 for x in tokens)
        assert r.base_score == pytest.approx(sum(math.log10((train[x] + 0.5) / (n + 0.5 * (v + 1))) for x in tokens))
        assert r.score < 0
    assert sum(r.score for r in got) > sum(r.base_score for r in got)


def test_language_model_is_a_mixture_of_counts(spark, docs, rows):
    """Bigram counts by brute force, with the model's weights taken from one text that all weights are solved from."""
    held = {i for i, _ in rows if zlib.crc32(str(i).encode()) % 5 == 1}
    uni, bi, starts = Counter(), Counter(), 0
    for i, t in rows:
        if i not in held:
            tokens = [*words(t), None]
            starts += 1
            uni.update(tokens)
            bi.update(zip(["<s>", *tokens], tokens))
    n, v = sum(uni.values()), len(uni)
    got = {r.doc_id: r.score for r in lm_score.score(spark, docs, lm_score.held_out_column(), 2).collect()}
    # empty texts have one event: the end after the start
    p = [(uni[None] + 0.5) / (n + 0.5 * (v + 1)), uni[None] / n, bi[("<s>", None)] / starts]
    assert got[0] == got[1] == got[2]
    assert math.log10(min(p)) - 1e-9 <= got[0] <= math.log10(max(p)) + 1e-9


@pytest.mark.parametrize("order", [1, 2, 3])
def test_language_model_scores_by_brute_force(spark, docs, rows, order, monkeypatch):
    """Every text's score under given mixture weights."""
    rng = np.random.default_rng(order)
    weights = rng.random((lm_score.BUCKETS, order + 1))
    weights /= weights.sum(axis=1, keepdims=True)
    monkeypatch.setattr(lm_score, "learn", lambda cells, order: weights)
    held = {i for i, _ in rows if zlib.crc32(str(i).encode()) % 5 == 1}
    counts, texts = Counter(), 0

    def grams(t):
        """For each token, the n-grams of all orders that end there; marks stand before the text."""
        tokens = [*(("<", k) for k in range(order, 0, -1)), *words(t), None]
        return [[tuple(tokens[at - k : at + 1]) for k in range(order)] for at in range(order, len(tokens))]

    for i, t in rows:
        if i not in held:
            texts += 1
            counts.update(g for place in grams(t) for g in place)
    n = sum(c for g, c in counts.items() if len(g) == 1)
    v = sum(len(g) == 1 for g in counts)
    for r in lm_score.score(spark, docs, lm_score.held_out_column(), order).collect():
        want = []
        for t in {t for i, t in rows if i == r.doc_id}:
            total = 0.0
            for place in grams(t):
                p, bucket = [(counts[place[0]] + 0.5) / (n + 0.5 * (v + 1)), counts[place[0]] / n], 0
                for k in range(1, order):
                    context = place[k][:-1]
                    seen = texts if all(isinstance(x, tuple) for x in context) else counts[context]
                    p.append(counts[place[k]] / seen if seen else 0.0)
                    bucket = min(lm_score.BUCKETS - 1, math.ceil(math.log2(seen + 1)))
                total += math.log10(float(weights[bucket] @ p))
            want.append(total)
        assert any(r.score == pytest.approx(x, rel=1e-9) for x in want)


def test_weights_follow_the_events():
    cells = [([3, 4, 400, 0], 90), ([3, 4, 0, 400], 10)]
    w = lm_score.learn(cells, 2)
    assert w.shape == (lm_score.BUCKETS, 3) and np.allclose(w.sum(axis=1), 1) and w[3, 2] > w[3, 1]
    assert np.allclose(lm_score.learn([], 2), 1 / 3)


def test_empty_tables(spark, none):
    labels = spark.createDataFrame([], "doc_id long, quality int, text string")
    assert lm_score.score(spark, none, lm_score.held_out_column()).count() == 0
    assert quality.score(spark, none, labels).count() == 0
    assert ngram_join.near_duplicates(spark, none).count() == 0
    assert line_dedup.dedup(spark, none).count() == 0
    assert packing.pack_documents(spark, none).count() == 0
    assert substring.remove_repeats(none).count() == 0
    assert decontaminate.overlaps(spark, none, spark.createDataFrame([], "item_id long, text string")).count() == 0
    assert topk.top_k(spark.createDataFrame([], "vec_id long, embedding array<float>"), F.lit(True)).count() == 0
    assert licenses.scan(spark, none.withColumn("path", F.lit("a/b"))).count() == 0
    import public_tokenizers

    assert token_spans.by_section(none, public_tokenizers.path("byte_bpe_50k.json")).count() == 0


def test_null_ids(spark):
    """Rows without id are kept, and come first in order."""
    text = " ".join(f"w{i}" for i in range(30))
    frame = spark.createDataFrame([(None, text), (5, text), (2, None), (None, None)], "doc_id long, text string")
    labels = spark.createDataFrame([(None, 1), (5, 0), (2, 1)], "doc_id long, quality int")
    assert lm_score.score(spark, frame, lm_score.held_out_column()).count() == 4
    assert quality.score(spark, frame, labels).count() == 4
    assert ngram_join.near_duplicates(spark, frame).count() == 4
    assert line_dedup.dedup(spark, frame).count() == 4
    assert packing.pack_documents(spark, frame).count() == 4
    assert {(r.doc_id, r.n_removed) for r in substring.remove_repeats(frame).collect()} == {(None, 0), (5, 30), (2, 0)}
    assert decontaminate.overlaps(spark, frame, spark.createDataFrame([(None, text), (1, text)], "item_id long, text string")).count() >= 1
    assert topk.top_k(spark.createDataFrame([(None, [1.0]), (20, [1.0]), (3, [2.0])], "vec_id long, embedding array<float>"), F.col("vec_id") % 20 == 0).count() == 1
    assert licenses.scan(spark, frame.withColumn("path", F.lit(None).cast("string"))).count() == 4
    import public_tokenizers

    sections = token_spans.by_section(frame, public_tokenizers.path("byte_bpe_50k.json")).collect()
    assert Counter((r.doc_id, r.n_tokens) for r in sections) == Counter([(None, next(r.n_tokens for r in sections if r.doc_id == 5)), (5, next(r.n_tokens for r in sections if r.doc_id == 5)), (2, 0), (None, 0)])


def test_quality(spark, rows, docs):
    rng = np.random.default_rng(2)
    many = [(i, " ".join(rng.choice(["alpha", "beta", "gamma"], 20)) + ("!! ### $$$" * 8 if i % 3 == 0 else ".")) for i in range(300)]
    frame = spark.createDataFrame([*many, (1000, None), (1001, "")], "doc_id long, text string")
    labels = spark.createDataFrame([(i, int(i % 3 != 0), "x") for i, _ in many] + [(5, None, "x"), (7777, 1, "x")], "doc_id long, quality int, text string")
    got = {r.doc_id: r for r in quality.score(spark, frame, labels).collect()}
    assert len(got) == 302 and all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.3) for r in got.values())
    held = [r for i, r in got.items() if i < 1000 and r.held_out]
    assert held and all(r.predicted == int(r.doc_id % 3 != 0) for r in held)
    no_labels = quality.score(spark, docs, labels.where("false")).collect()
    assert len(no_labels) == len(rows) and {r.score for r in no_labels} == {0.5}
    kept = quality.keep_good(spark, frame.withColumn("score", F.lit("keep")), labels)
    assert kept.columns == ["doc_id", "text", "score"] and {r.doc_id for r in kept.collect()} == {i for i, r in got.items() if r.predicted}


def test_pair_tables_learn_what_single_tables_cannot():
    rng = np.random.default_rng(3)
    x = rng.random((3000, len(quality.FEATURES)))
    y = ((x[:, 0] > 0.5) ^ (x[:, 1] > 0.5)).astype(float)
    plain = quality.fit(x, y, n_pairs=0)
    pairs = quality.fit(x, y)
    hit = lambda m: ((m.score(x) > 0.5) == y).mean()
    assert hit(plain) < 0.8 < 0.9 < hit(pairs)


def jaccard_components(rows, n, percent):
    sets = defaultdict(list)
    for i, t in rows:
        w = words(t)
        sets[i].append(frozenset(tuple(w[k : k + n]) for k in range(len(w) - n + 1)) if len(w) >= n else frozenset([tuple(w)] if w else []))
    ids = sorted(sets)
    root = {i: i for i in ids}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for a in ids:
        for b in ids:
            if a < b and any(x and y and 100 * len(x & y) >= percent * len(x | y) for x in sets[a] for y in sets[b]):
                p, q = find(a), find(b)
                root[max(p, q)] = min(p, q)
    return {i: find(i) for i in ids}, {i: len(s[0]) for i, s in sets.items()}


@pytest.mark.parametrize("n, percent", [(3, 90), (5, 80), (2, 60)])
def test_ngram_join(spark, docs, rows, n, percent):
    want, size = jaccard_components(rows, n, percent)
    got = ngram_join.near_duplicates(spark, docs, n, percent).collect()
    assert len(got) == len(rows)
    assert {r.doc_id: r.component_id for r in got} == want and all(r.n_shingles == size[r.doc_id] for r in got)


def test_ngram_join_chains(spark):
    """A ladder of texts of which only neighbours are similar; the ends meet through all of them."""
    base = [f"t{i}" for i in range(200)]
    rows = []
    for k in range(30):
        rows.append((100 - k, " ".join([*base[: 200 - 3 * k], *(f"new{i}" for i in range(3 * k))])))
    want, _ = jaccard_components(rows, 3, 90)
    frame = spark.createDataFrame(rows, "doc_id long, text string")
    assert {r.doc_id: r.component_id for r in ngram_join.near_duplicates(spark, frame, 3, 90).collect()} == want
    assert set(want.values()) == {71}


def test_many_near_copies_below_the_threshold_are_told_apart(spark):
    rng = np.random.default_rng(9)
    base = [f"t{i}" for i in range(150)]
    rows = []
    for k in range(80):
        t = list(base)
        for j in rng.choice(150, 6, replace=False):
            t[j] = f"u{k}_{j}"
        rows.append((k, " ".join(t)))
    want, _ = jaccard_components(rows, 3, 80)
    frame = spark.createDataFrame(rows, "doc_id long, text string")
    assert {r.doc_id: r.component_id for r in ngram_join.near_duplicates(spark, frame, 3, 80).collect()} == want


@pytest.mark.parametrize("bounds", [{}, {"HOT": 3, "BLOCK": 7}])
def test_every_link_counts(spark, monkeypatch, bounds):
    for name, value in bounds.items():
        monkeypatch.setattr(ngram_join, name, value)
    rows = []
    for k in range(50):  # all similar to each other and all different, and a loose group of five
        t = [f"t{i}" for i in range(200)]
        t[4 * k % 200] = f"u{k}"
        rows.append((k, " ".join(t)))
    rows += [(100 + k, " ".join([*(f"s{i}" for i in range(6 * k, 150 + 6 * k))])) for k in range(5)]
    rows += [(200, rows[0][1])]  # an exact copy
    sets = {i: {tuple(t.split()[k : k + 3]) for k in range(len(t.split()) - 2)} for i, t in rows[:-1]}
    want = {i: sum(i != j and 100 * len(x & y) >= 90 * len(x | y) for j, y in sets.items()) for i, x in sets.items()}
    want[200] = want[0]
    frame = spark.createDataFrame(rows, "doc_id long, text string")
    got = ngram_join.near_duplicates(spark, frame, 3, 90).collect()
    assert {r.doc_id: r.n_links for r in got} == want and want[0] == 49 and want[101] == 2


def test_ngram_join_beyond_the_filter(spark, docs, rows, monkeypatch):
    """Where the ids are too many for a filter, a join does its work."""
    from pagelift.llm import idfilter

    monkeypatch.setattr(idfilter, "MOST_BITS", 0)
    monkeypatch.setattr(ngram_join, "HOT", 3)
    want, _ = jaccard_components(rows, 3, 90)
    assert {r.doc_id: r.component_id for r in ngram_join.near_duplicates(spark, docs, 3, 90).collect()} == want


def test_pivots_cut_the_global_order():
    """Fragments hold every shared n-gram once, in order, and about as many places each."""
    rng = np.random.default_rng(12)
    keys = np.unique(rng.integers(0, 1 << 63, 20_000).astype(np.uint64) * np.uint64(2))
    df = np.where(rng.random(len(keys)) < 0.7, rng.integers(1, 4, len(keys)), rng.integers(2, 3000, len(keys)))
    shared = df > 1
    cells, which = np.unique(ngram_join.cell_of(df[shared]), return_inverse=True)
    cuts = ngram_join.pivots(list(zip(cells.tolist(), np.bincount(which, df[shared]).astype(int).tolist())), 4)
    parts = [np.frombuffer(x, np.uint64) for x in ngram_join.fragments(keys, df, cuts)]
    assert len(parts) == 4 and sorted(np.concatenate(parts).tolist()) == keys[shared].tolist()
    place = dict(zip(keys.tolist(), df.tolist()))
    ends = [(min((place[k], k) for k in p.tolist()), max((place[k], k) for k in p.tolist())) for p in parts]
    assert all(a[1] < b[0] for a, b in zip(ends, ends[1:]))
    weight = [sum(place[k] for k in p.tolist()) for p in parts]
    assert max(weight) < 1.3 * min(weight)
    assert ngram_join.pivots([], 4) == [] and ngram_join.fragments(keys[:0], df[:0], cuts) == [b""] * 4


def test_matrix_counts_what_sets_count(monkeypatch):
    rng = np.random.default_rng(10)
    sets = [np.unique(rng.choice(100, 95)).astype(np.uint64) for _ in range(20)]
    rule, open_ = ngram_join.Rule(3, 60), np.ones((20, 20), bool)
    one = ngram_join.similar(sets, sets, open_, rule)
    monkeypatch.setattr(ngram_join, "FEW", 0)
    monkeypatch.setattr(ngram_join, "WIDE", 16)
    assert (one == ngram_join.similar(sets, sets, open_, rule)).all() and one.any() and not one.all()


def test_components(spark):
    links = [(i, i + 1) for i in range(40, 60)] + [(1, 2), (2, 1), (5, 5), (9, 7), (9, 8)]
    got = {r.id: r.component for r in components(spark, spark.createDataFrame(links, "a long, b long")).collect()}
    assert got == {**{i: 40 for i in range(40, 61)}, 1: 1, 2: 1, 7: 7, 8: 7, 9: 7}


def test_lines(spark, docs, rows):
    def key(x):
        return re.sub(rb"^[\x20\x09-\x0D]+|[\x20\x09-\x0D]+$", b"", x).lower()

    seen = Counter()
    for _, t in rows:
        seen.update({key(x) for x in (t or "").encode().split(b"\n")})
    want = Counter()
    for i, t in rows:
        lines = (t or "").encode().split(b"\n")
        left = [x for x in lines if not key(x) or seen[key(x)] < 10]
        want[(i, len(lines), len(lines) - len(left), hashlib.sha256(b"\n".join(left)).hexdigest())] += 1
    got = line_dedup.dedup(spark, docs, least=10, digest=True).collect()
    assert Counter((r.doc_id, r.n_lines, r.n_dropped, r.kept_sha256) for r in got) == want
    assert any(r.n_dropped for r in got)


def test_line_deletions_are_reversible(spark, docs):
    before = line_dedup.LineState(spark, least=4).insert(docs)
    more = docs.where("doc_id > 40").withColumn("doc_id", F.col("doc_id") + 1000)
    between = before.insert(more)
    after = between.delete(more)
    as_set = lambda s: {tuple(r) for r in s.counts.collect()}
    assert as_set(before) == as_set(after) != as_set(between)

    def held(state):
        """Frequent keys by the exact counts; they must be in the filters, and hardly others."""
        hot = np.array(sorted((h, lo) for h, lo, n in as_set(state) if n >= state.least), np.int64).reshape(-1, 2)
        cold = np.array(sorted((h, lo) for h, lo, n in as_set(state) if n < state.least), np.int64).reshape(-1, 2)
        known = line_dedup.Frequent(state.shards, state.sent_filters(), True, None)
        assert known.may_hold(hot[:, 0], hot[:, 1]).all() and known.may_hold(cold[:, 0], cold[:, 1]).sum() <= 0.05 * len(cold)
        assert state.frequent == len(hot)
        return {tuple(x) for x in hot.tolist()}

    assert held(before) == held(after) and held(before) < held(between)
    gone = after.delete(docs)
    assert as_set(gone) == set() and held(gone) == set()


def test_filters_are_updated_in_place(spark):
    """While the number of frequent keys has not doubled, filters take insertions and deletions."""
    text = lambda a, b: "\n".join(f"line {i}" for i in range(a, b))
    frame = lambda a, b, n=2: spark.createDataFrame([(i, text(a, b)) for i in range(n)], "doc_id long, text string")
    state = line_dedup.LineState(spark, least=2).insert(frame(0, 100))
    more = state.insert(frame(100, 150)).delete(frame(0, 60, 1))
    assert (more.built_for, more.frequent) == (100, 90)
    known = line_dedup.Frequent(more.shards, more.sent_filters(), True, None)
    keys = [line_dedup.halves(f"line {i}".encode()) for i in range(150)]
    may = known.may_hold(*(np.array(x, np.int64) for x in zip(*keys)))
    assert may[60:].all() and may[:60].mean() < 0.05
    left = line_dedup.drop_lines(more, frame(0, 150, 1)).collect()[0]
    assert left.n_dropped == 90 and left.kept_text == text(0, 60)


@pytest.mark.parametrize("bounds", [{"EXACT_KEYS": 0}, {"EXACT_KEYS": 0, "FILTER_BYTES": 0, "SHARD_KEYS": 1}])
def test_lines_beyond_the_broadcast_bounds(spark, docs, monkeypatch, bounds):
    want = Counter(map(tuple, line_dedup.dedup(spark, docs, least=4).collect()))
    for name, value in bounds.items():
        monkeypatch.setattr(line_dedup, name, value)
    assert Counter(map(tuple, line_dedup.dedup(spark, docs, least=4).collect())) == want


@pytest.mark.parametrize("few", [True, False])
def test_line_stage_keeps_columns_of_any_name(spark, monkeypatch, few):
    if not few:
        monkeypatch.setattr(line_dedup, "EXACT_KEYS", 0)
    names = ["doc", "row", "drop", "n_lines", "hi", "refs", "kept_text", "a.b"]
    frame = spark.createDataFrame([(i, "same line\nown %d" % i, *(f"{n}{i}" for n in names)) for i in range(12)] + [(99, None, *names), (None, "", *names)], ["doc_id", "text", *names])
    got = line_dedup.rewrite(spark, frame)
    assert got.columns == frame.columns
    assert Counter(tuple(r) for r in got.collect()) == Counter((r[0], f"own {r[0]}" if r[0] is not None and r[0] < 99 else "", *r[2:]) for r in frame.collect())


def test_cuckoo_filter():
    rng = np.random.default_rng(4)
    hi, lo = (rng.integers(-(1 << 62), 1 << 62, 20_000) for _ in range(2))
    f = line_dedup.CuckooFilter(10_000)
    f.insert(hi[:10_000], lo[:10_000])
    assert f.may_hold(hi[:10_000], lo[:10_000]).all()
    assert f.may_hold(hi[10_000:], lo[10_000:]).mean() < 0.002
    f.delete(hi[:5000], lo[:5000])
    assert f.may_hold(hi[5000:10_000], lo[5000:10_000]).all() and f.may_hold(hi[:5000], lo[:5000]).mean() < 0.01
    tiny = line_dedup.CuckooFilter(1)
    tiny.insert(hi[:100], lo[:100])  # far over its capacity: what finds no place is kept exactly
    assert tiny.may_hold(hi[:100], lo[:100]).all()


def test_packing(spark, docs, rows):
    import public_tokenizers
    from tokenizers import Tokenizer

    encode = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json")).encode
    odd = [(900, "Hello  world <|endoftext|> x<|startoftext|>y <|STARTOFTEXT|>"), (901, "İstanbul ΣΑΣ ß ﬀ é é l'été don't I'll 12ab 3,4"), (902, "🤗🤗 a.b.c! ???"), (903, "w " * 5000)]
    frame = docs.select("doc_id", "text").union(spark.createDataFrame(odd, "doc_id long, text string"))
    got = packing.pack_documents(spark, frame, capacity=256).collect()
    want = Counter()
    for i, t in [*rows, *odd]:
        ids = [*encode(t or "", add_special_tokens=False).ids, 0]
        for k, at in enumerate(range(0, len(ids), 256)):
            part = np.array(ids[at : at + 256], "<u4")
            want[(i, k, at, len(part), zlib.crc32(part.tobytes()))] += 1
    assert Counter((r.doc_id, r.piece, r.start, r.length, r.ids_crc32) for r in got) == want
    held = defaultdict(list)
    for r in got:
        held[r.sequence_id].append((r.offset, r.length))
    for parts in held.values():
        end = 0
        for at, size in sorted(parts):
            assert at == end
            end += size
        assert end <= 256
    assert len(held) <= math.ceil(sum(r.length for r in got) / 256) + 2


def test_plan_is_small_and_best_fit():
    rng = np.random.default_rng(6)
    counts = {n: int(rng.integers(1, 100_000)) for n in range(1, 513)}
    slots = packing.plan(counts, 512)
    assert len(slots) < 20_000 and sum(s[2] - s[1] for s in slots) == sum(counts.values())
    made = max(s[3] + s[2] - s[1] for s in slots)
    assert made <= math.ceil(sum(n * c for n, c in counts.items()) / 512) * 1.01


@pytest.mark.parametrize("width", [1, 5, 20])
def test_substrings(docs, rows, width):
    seen, want = set(), Counter()
    for i, t in sorted(rows, key=lambda r: (r[0], r[1] or "")):
        w = words(t, lower=False)
        gone = [False] * len(w)
        for k in range(len(w) - width + 1):
            key = tuple(w[k : k + width])
            if key in seen:
                gone[k : k + width] = [True] * width
            seen.add(key)
        want[(i, len(w), sum(gone), hashlib.sha256(b" ".join(x for x, g in zip(w, gone) if not g)).hexdigest())] += 1
    got = substring.remove_repeats(docs, width, digest=True).collect()
    assert Counter((r.doc_id, r.n_words, r.n_removed, r.kept_sha256) for r in got) == want


def test_suffix_automaton():
    rng = np.random.default_rng(7)
    for _ in range(30):
        ref = [[int(x) for x in rng.integers(0, 3, rng.integers(1, 40))] for _ in range(3)]
        flat = [x for r in ref for x in [*r, None]]
        auto = substring.SuffixAutomaton(flat)
        text = [int(x) for x in rng.integers(0, 3, 50)]
        have = {tuple(r[a:b]) for r in ref for a in range(len(r)) for b in range(a + 1, len(r) + 1)}
        want = [max((n for n in range(e + 2) if n == 0 or tuple(text[e + 1 - n : e + 1]) in have), default=0) for e in range(len(text))]
        packed = substring.PackedAutomaton(*auto.packed())
        more = [int(x) for x in rng.integers(0, 4, 7)]
        tokens, bounds = np.array([*more, *text, *text[:20]], np.uint64), np.array([0, 7, 57, 57, 77], np.int64)
        got = packed.matching(tokens, bounds)
        assert got[7:57].tolist() == want and got[57:].tolist() == want[:20]
        for window in (2, 5):
            cover = [any(want[e] >= window and e - want[e] < i <= e for e in range(len(text))) for i in range(len(text))]
            assert substring.covered(got, bounds, window)[7:57].tolist() == cover


@pytest.mark.parametrize("bounds", [{}, {"SHARD_WORDS": 40, "WAVE_BYTES": 1}])
def test_reference_removal(spark, docs, rows, monkeypatch, bounds):
    """One wave of one automaton, or a wave for each of several; against all windows."""
    for name, value in bounds.items():
        monkeypatch.setattr(substring, name, value)
    texts = [" ".join(f"p{i}" for i in range(30)), rows[61][1], rows[62][1], rows[20][1], None, ""]
    reference = spark.createDataFrame([(t, 1) for t in texts], "text string, doc_id int")
    have = {tuple(w[k : k + 20]) for w in (words(t, False) for t in texts) for k in range(len(w) - 19)}
    want = Counter()
    for i, t in rows:
        w = words(t, False)
        gone = {j for k in range(len(w) - 19) if tuple(w[k : k + 20]) in have for j in range(k, k + 20)}
        want[(i, len(w), len(gone), b" ".join(x for j, x in enumerate(w) if j not in gone).decode())] += 1
    got = substring.remove_reference(spark, docs, reference, 20).collect()
    assert Counter(map(tuple, got)) == want
    assert {r.doc_id: r for r in got}[7].kept_text == "pre post"
    none = reference.where("false")
    assert all(r.n_removed == 0 for r in substring.remove_reference(spark, docs, none).collect())


@pytest.mark.parametrize("bounds", [{}, {"SHARD_ROWS": 40, "WAVE_BYTES": 700}])
def test_top_k(spark, monkeypatch, bounds):
    for name, value in bounds.items():
        monkeypatch.setattr(topk, name, value)
    rng = np.random.default_rng(8)
    v = [(i, [float(x) for x in rng.normal(0, 0.2, 16)]) for i in range(300)]
    v += [(300 + i, v[0][1]) for i in range(30)] + [(400, None), (401, [1.0, None]), (402, [float("nan")] * 16), (403, [float("inf")] * 16), (420, [1e6] * 16), (421, [-3e7, 2.0])]
    frame = spark.createDataFrame([(i, x, "c") for i, x in v], "vec_id long, embedding array<double>, score string")
    got = topk.top_k(frame, F.col("vec_id") % 20 == 0, 7).collect()
    q = {i: np.pad(np.floor(64 * np.array(x)), (0, 16 - len(x))) for i, x in v if x and None not in x and np.isfinite(x).all()}
    want = {}
    for i in q:
        if i % 20 == 0:
            best = sorted((-int(q[i] @ q[j]), j) for j in q if j != i)[:7]
            want |= {(i, k + 1): (j, -s) for k, (s, j) in enumerate(best)}
    assert {(r.query_id, r["rank"]): (r.vec_id, r.score) for r in got} == want


def test_top_k_of_repeated_ids(spark):
    """Rows that share an id are queries each; none of them is the others' candidate, and each can be a candidate twice."""
    frame = spark.createDataFrame([(20, [1.0, 0.0]), (20, [0.0, 1.0]), (3, [1.0, 0.5]), (3, [1.0, 0.5]), (4, [0.0, 2.0])], "vec_id long, embedding array<double>")
    got = Counter(tuple(r) for r in topk.top_k(frame, F.col("vec_id") % 20 == 0, 2).collect())
    assert got == Counter([(20, 1, 3, 4096), (20, 2, 3, 4096), (20, 1, 4, 8192), (20, 2, 3, 2048)])


def test_token_sections(spark, docs, rows):
    import public_tokenizers
    from tokenizers import Tokenizer

    path = public_tokenizers.path("byte_bpe_50k.json")
    tok = Tokenizer.from_file(path)
    tok.encode_special_tokens = True
    odd = [(900, "a\n\n\n\n"), (901, "x   y\n z <|endoftext|> \n"), (902, "🤗é́ ÉTÉ, don't"), (903, "a" * 40000)]
    frame = docs.select("doc_id", "text", "score").union(spark.createDataFrame([(i, t, "s") for i, t in odd], "doc_id long, text string, score string"))
    want = Counter()
    for i, t in [*rows, *odd]:
        t = t or ""
        starts = [0, *(m.end() for m in re.finditer("\n", t))]
        ends = [*starts[1:], len(t)]
        n, cross = Counter(), Counter()
        for a, b in tok.encode(t, add_special_tokens=False).offsets:
            share = [(min(b, e) - max(a, s), -k) for k, (s, e) in enumerate(zip(starts, ends))]
            own = -max(share)[1]
            n[own] += 1
            cross[own] += sum(x[0] > 0 for x in share) > 1
        want.update((i, k, s, e, n[k], cross[k]) for k, (s, e) in enumerate(zip(starts, ends)))
    assert Counter(tuple(r) for r in token_spans.by_section(frame, path).collect()) == want
    fields = token_spans.by_field(frame, ["text", "score"], path).groupBy("doc_id").agg(F.sum("n_tokens").alias("n")).collect()
    for r in fields:
        if r.doc_id >= 900:
            assert r.n == len(tok.encode(dict(odd)[r.doc_id] + "\ns", add_special_tokens=False).ids)


def test_words_repeat_across_rows_without_id(spark, monkeypatch):
    """Rows that share an id, or have none, lie in several batches: each window stays once."""
    monkeypatch.setattr(exchange, "BATCH_BYTES", 400)
    monkeypatch.setattr(exchange, "MOST_BYTES", 400)
    texts = [" ".join(f"w{(k * 13 + j) % 60}" for j in range(30 + k % 9)) for k in range(90)]
    frame = spark.createDataFrame([(None if k % 3 == 0 else 5 if k % 3 == 1 else k, t) for k, t in enumerate(texts)], "doc_id long, text string").repartition(3)
    got = substring.remove_repeats(frame, 5).collect()
    # what is kept starts each window of the corpus once: all texts are cyclic, 60 windows in all
    seen = {tuple((t.split() * 2)[k : k + 5]) for t in texts for k in range(len(t.split()) - 4)}
    assert sum(r.n_words for r in got) == sum(len(t.split()) for t in texts)
    kept = [r.kept_text.split() for r in got if r.n_removed < r.n_words]
    left = Counter(tuple(w[k : k + 5]) for w in kept for k in range(len(w) - 4))
    assert len(got) == 90 and len(kept) < 10 and set(left) <= seen and max(left.values()) == 1


def test_batches_are_runs_of_ids_with_equal_bytes(spark):
    """Ids near 2^62 that differ by one, very unequal texts, null ids."""
    base = 1 << 62
    rows = [(base + i, "x" * (20_000 if i % 97 == 0 else 100)) for i in range(2000)] + [(None, "y"), (-base, None)]
    frame = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    dealt, n = exchange.ordered_batches(spark, frame, 20)
    got = dealt.selectExpr("doc_id", "batch", "coalesce(length(text), 0) AS size").collect()
    by = sorted((r.doc_id, r.batch) for r in got if r.doc_id is not None)
    assert [b for _, b in by] == sorted(b for _, b in by) and {r.batch for r in got} == set(range(n)) and n >= 18
    assert {r.batch for r in got if r.doc_id is None} == {0}
    hot = spark.createDataFrame([(None if i % 3 else 7, f"{i} " * 300) for i in range(900)] + [(k, "a " * 300) for k in range(300)], "doc_id long, text string")
    dealt, n = exchange.ordered_batches(spark, hot, 12)
    rows = dealt.selectExpr("coalesce(doc_id, -1) AS i", "spot", "batch").collect()
    assert [r.batch for r in sorted(rows, key=lambda r: (r.i, r.spot))] == sorted(r.batch for r in rows)
    assert max(Counter(r.batch for r in rows).values()) < 2 * 1200 / 12 and n >= 11
    size = Counter()
    for r in got:
        size[r.batch] += r.size
    assert max(size.values()) < sum(size.values()) / 20 + 20_101


def test_decontamination(spark, docs):
    item = " ".join(f"q{i}" for i in range(25))
    changed = item.replace("q5", "zz").replace("q15", "zz")
    texts = [(100, "Start. " + item.upper() + "!"), (101, "a b c " + changed), (102, " ".join(item.split()[:8])), (103, "short item here ok"), (104, "nothing of that kind")]
    bench = spark.createDataFrame([(1, item, "x"), (2, item, "x"), (3, "Short item, here", "x"), (4, None, "x"), (5, "", "x")], "item_id long, text string, doc_id string")
    frame = docs.select("doc_id", "text").union(spark.createDataFrame(texts, "doc_id long, text string"))
    got = {(r.doc_id, r.item_id): (r.start, r.length, r.matched) for r in decontaminate.overlaps(spark, frame, bench).collect()}
    assert got[(100, 1)] == (1, 25, 25) and got[(101, 1)][0] == 3 and got[(101, 1)][2] >= 20 and got[(103, 3)] == (0, 3, 3)
    assert set(got) == {(100, 1), (101, 1), (103, 3)}


def test_masks_fit_every_region_that_counts():
    from itertools import combinations

    sets = [sum(1 << k for k in mask) for mask in decontaminate.MASKS]
    for n in range(decontaminate.SPAN, 2 * decontaminate.SPAN):
        for gone in combinations(range(n), n // 5):
            left = sum(1 << i for i in range(n) if i not in gone)
            assert any((left >> at) & s == s and at + s.bit_length() <= n for s in sets for at in range(n))


def test_decontamination_finds_pieces_and_scattered_changes(spark):
    item = [f"q{i}" for i in range(59)]
    other = lambda t, gone: " ".join(f"z{i}" if i in gone else w for i, w in enumerate(t))
    small = [f"s{i}" for i in range(15)]
    texts = [(1, "a b " + other(item, range(25, 45))), (2, other(item, range(4, 59, 5))), (3, "a " + other(small, (5, 7, 9)) + " b"), (4, other(item, range(0, 59, 3))), (5, "a " + other([f"t{i}" for i in range(10)], (0, 9)) + " b")]
    frame = spark.createDataFrame(texts, "doc_id long, text string")
    bench = spark.createDataFrame([(1, " ".join(item)), (2, " ".join(small)), (3, " ".join(f"t{i}" for i in range(10)))], "item_id long, text string")
    got = {(r.doc_id, r.item_id): (r.start, r.length, r.matched) for r in decontaminate.overlaps(spark, frame, bench).collect()}
    assert got == {(1, 1): (2, 25, 25), (2, 1): (0, 59, 48), (3, 2): (1, 15, 12), (5, 3): (1, 10, 8)}


def brute_overlaps(texts, items, share=0.8):
    """All diagonals, all regions, without seeds."""
    cut = lambda t: [w for w in re.split(r"[\W_]+", (t or "").lower()) if w]
    first = {}
    for i, t in sorted((i, t) for i, t in items if i is not None):
        if cut(t):
            first.setdefault(tuple(cut(t)), i)
    out = {}
    for d, t in texts:
        w = cut(t)
        for item, i in first.items():
            best = None
            for shift in range(-len(item) + 1, len(w)):
                at = [p for p in range(len(item)) if 0 <= p + shift < len(w) and w[p + shift] == item[p]]
                if not at:
                    continue
                if shift >= 0 and shift + len(item) <= len(w) and 1000 * len(at) >= 1000 * share * len(item):
                    found = [(len(at), 0, len(item))]
                else:
                    found = [(y - x + 1, -at[x], at[y] - at[x] + 1) for x in range(len(at)) for y in range(x, len(at)) if 1000 * (y - x + 1) >= 1000 * share * (at[y] - at[x] + 1) and (at[y] - at[x] + 1 >= decontaminate.SPAN or (at[x] == 0 and at[y] == len(item) - 1))]
                if found:
                    m, f, n = max(found)
                    best = max(best or (0, 0, 0), (m, -(shift - f), n))
            if best:
                out[(d, i)] = (-best[1], best[2], best[0])
    return out


def test_decontamination_by_brute_force(spark):
    """Random pieces of items with random substitutions, short items and tiny vocabularies, against all diagonals."""
    rng = np.random.default_rng(21)
    items = [(k, " ".join(rng.choice([f"b{i}" for i in range(200)], n))) for k, n in enumerate((1, 2, 4, 5, 6, 9, 10, 12, 15, 30, 60))]
    items += [(50, "x y x y x y x y x y x y"), (51, None), (52, " ... "), (53, items[8][1])]
    texts = []
    for d in range(120):
        _, item = items[rng.integers(0, 11)]
        t = item.split()
        a = int(rng.integers(0, max(1, len(t) // 2)))
        t = t[a : a + int(rng.integers(1, len(t) + 1))]
        for j in rng.choice(len(t), int(rng.integers(0, len(t) // 3 + 1)), replace=False):
            t[j] = f"z{j}"
        texts.append((d, " ".join([*(f"l{i}" for i in range(rng.integers(0, 5))), *t, *(f"r{i}" for i in range(rng.integers(0, 5)))])))
    texts += [(200, "x y x y x y x y x y x y x y y x y x y"), (201, None), (202, "")]
    want = brute_overlaps(texts, items)
    frame, bench = spark.createDataFrame(texts, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")
    got = {(r.doc_id, r.item_id): (r.start, r.length, r.matched) for r in decontaminate.overlaps(spark, frame, bench).collect()}
    assert got == want and len(want) > 40


def test_decontamination_runs_no_python(spark, docs):
    bench = spark.createDataFrame([(1, "a b c d e f g h i j k l")], "item_id long, text string")
    plan = decontaminate.overlaps(spark, docs, bench)._jdf.queryExecution().toString()
    assert not re.search("Python|Pandas|Arrow|CartesianProduct|NestedLoop", plan)


def test_licenses(spark):
    mit, gpl = "Released under the MIT License.", "This work is licensed under the GNU General Public License, version 3."
    files = [(1, "a/LICENSE", mit), (2, "a/b/x.txt", "plain words"), (3, "a/b/c/LICENSE.txt", "intro\n" + gpl), (4, "a/b/c/d/y.py", "code"), (5, "z/w.txt", None), (6, "top.txt", ""), (7, None, "x"), (8, "z/v.txt", "word " * 50 + "\n" + mit)]
    got = {r.doc_id: r for r in licenses.scan(spark, spark.createDataFrame([(*f, "n") for f in files], "doc_id long, path string, text string, name string")).collect()}
    assert [(got[i].license, got[i].origin) for i in range(1, 9)] == [("MIT", "own"), ("MIT", "inherited"), ("GPL-3.0", "own"), ("GPL-3.0", "inherited"), (None, "none"), (None, "none"), (None, "none"), ("MIT", "own")]
    assert got[4].license_dir == "a/b/c" and got[2].license_dir == "a"


def test_license_lines_hold_other_words_in_corpora_of_any_size(spark, monkeypatch):
    lines = ["This file is licensed under the Apache License, Version 2.0", "Copyright 2020 Jane Doe. Released under the MIT License.", " ".join(f"r{i}" for i in range(45)) + " released under the MIT License by " + " ".join(f"v{i}" for i in range(45)), "Released by Qfoo under the MIT License"]
    want = ["Apache-2.0", "MIT", "MIT", "MIT", "MIT", None]
    wrapped = "Permission is hereby granted, free of charge, to any\nperson obtaining a copy\nof this software"
    for fill in (60, 6000):
        rows = [(i, f"a{i}/x.txt", t) for i, t in enumerate(lines)] + [(4, "b/LICENSE", wrapped), (5, "c/x.txt", "the license of the version is under a tree of words")]
        rows += [(100 + i, f"d/{i}.txt", f"the word of n{i} and n{i + 1} is by and under a tree") for i in range(fill)]
        frame = spark.createDataFrame(rows, "doc_id long, path string, text string")
        got = []
        for common in (1, licenses.COMMON):  # nearly all frequencies by the join, or few
            monkeypatch.setattr(licenses, "COMMON", common)
            got.append({r.doc_id: (r.own, r.score) for r in licenses.detect(spark, frame).collect()})
        assert [got[0][i][0] for i in range(6)] == want and all(x[0] is None for i, x in got[0].items() if i > 4)
        assert {i: x[0] for i, x in got[0].items()} == {i: x[0] for i, x in got[1].items()}
        assert all(got[0][i][1] == pytest.approx(got[1][i][1]) for i in range(5))


def test_licenses_by_brute_force(spark):
    """Scores of random lines of licence words, by all windows the scan speaks of."""
    rng = np.random.default_rng(31)
    known = licenses.VOCABULARY
    lines = []
    for _ in range(150):
        _, texts = list(licenses.TEMPLATES.items())[rng.integers(0, len(licenses.TEMPLATES))]
        t = licenses.TERM.findall(texts[rng.integers(0, len(texts))].lower())
        for _ in range(rng.integers(0, 4)):
            t.insert(int(rng.integers(0, len(t) + 1)), str(rng.choice([*known, "foo", "bar", "baz"])))
        lines.append(" ".join([*(f"p{i}" for i in range(rng.integers(0, 40))), *t, *(f"q{i}" for i in range(rng.integers(0, 3)))]))
    rows = [(i, f"d/{i}.txt", t) for i, t in enumerate(lines)]
    n, total = Counter(), 0
    for _, _, t in rows:
        for terms in licenses.passages(t):
            total += 1
            n.update(set(terms))

    def cosine(a, b):
        weigh = lambda terms: {t: (1 + math.log(c)) * licenses.weight(total, n[t]) for t, c in Counter(terms).items()}
        x, y = weigh(a), weigh(b)
        return sum(w * y.get(t, 0) for t, w in x.items()) / math.sqrt(sum(w * w for w in x.values()) * sum(w * w for w in y.values()))

    got = {r.doc_id: (r.own, r.score) for r in licenses.detect(spark, spark.createDataFrame(rows, "doc_id long, path string, text string")).collect()}
    for i, _, t in rows:
        terms, best = t.split(), (0.0, "")
        for name, texts in sorted(licenses.TEMPLATES.items()):
            for text in texts:
                template = licenses.TERM.findall(text.lower())
                size = len(template)
                windows = [terms] + [terms[a : a + licenses.WINDOW] for a in range(0, len(terms) - licenses.WINDOW + licenses.STEP, licenses.STEP) if len(terms) > licenses.WINDOW]
                at = [k for k, x in enumerate(terms) if x in known]
                windows += [terms[max(0, min(k, len(terms) - size)) :][:size] for k in at]
                windows += [terms[a : b + 1] for a in at for b in at if size < b + 1 - a <= math.ceil(licenses.REACH * size)]
                for w in windows:
                    c = cosine(w, template)
                    if c > best[0] + 1e-9:
                        best = (c, name)
        if abs(best[0] - licenses.THRESHOLD) < 1e-9:
            continue
        if best[0] < licenses.THRESHOLD:
            assert got[i] == (None, None) or got[i][0] is None
        else:
            assert got[i][0] == best[1] and got[i][1] == pytest.approx(best[0])


@pytest.mark.parametrize("turned", [False, True])
def test_license_ties_do_not_depend_on_row_order(spark, turned):
    """Two licence files of a directory with equal scores: the smaller name, also where the first letters are the same."""
    found = [(1, "a/LICENSE", "MPL-2.0", 1.0), (2, "a/COPYING", "MIT", 1.0), (3, "a/x.txt", None, None)]
    frame = spark.createDataFrame(found[::-1] if turned else found, "doc_id long, path string, own string, score double")
    assert {r.doc_id: r.license for r in licenses.inherit(frame).collect()}[3] == "MIT"


EXTRA = ("row", "drop", "n_lines", "batch", "score", "x", "seed", "key", "hi", "part")


@pytest.fixture(scope="module")
def small_corpus(spark, rows, tmp_path_factory):
    """Nulls, empty and repeated texts, near copies, benchmark passages, and columns with the names of inner ones."""
    at = str(tmp_path_factory.mktemp("corpus"))
    item = " ".join(f"q{i}" for i in range(30))
    more = [(70, "before " + item + " after"), (71, item.replace("q7", "zz")), (None, "no id at all"), (80, "b1 b2\nsame\nend"), (81, "b1 b2\nsame\nend")]
    junk = [(200 + i, "!! ### $$$ " * (5 + i % 3) + f"j{i}") for i in range(30)]
    good = [(300 + i, " ".join(f"g{(i * 7 + k) % 50}" for k in range(40)) + ".") for i in range(60)]
    good += [(400 + k, good[k][1] + " " + item + " " + good[k + 3][1]) for k in range(2)]
    data = [(i, t, "en", "s", len(t or ""), *([str(i)] * len(EXTRA))) for i, t in [*rows, *more, *junk, *good]]
    spark.createDataFrame(data, "doc_id long, text string, lang string, source string, n_chars long, " + ", ".join(f"`{c}` string" for c in EXTRA)).write.parquet(f"{at}/documents.parquet")
    spark.createDataFrame([(i, 0, 0) for i, _ in junk] + [(i, 1, 0) for i, _ in good], "doc_id long, quality int, toxic int").write.parquet(f"{at}/labels.parquet")
    spark.createDataFrame([(1, item), (2, None)], "item_id long, text string").write.parquet(f"{at}/benchmark.parquet")
    return at


def test_pipeline_by_brute_force(spark, small_corpus):
    import corpus_pipeline
    import public_tokenizers
    from tokenizers import Tokenizer

    from pagelift.llm.common import cut, table

    docs = table(spark, small_corpus, "documents")
    columns, before = docs.columns, [(r.doc_id, r.text) for r in docs.collect()]
    after = {}
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = cut(spark, stage(spark, docs, small_corpus), "test")
        assert docs.columns == columns
        held = docs.collect()
        assert all(r[c] == str(r.doc_id) or r.doc_id is None for r in held for c in EXTRA) and all(r.n_chars == len(r.text or "") for r in held)
        after[name] = [(r.doc_id, r.text) for r in held]
    # quality: the model by the same labels, scored here
    model = quality.learn(spark, table(spark, small_corpus, "documents"), table(spark, small_corpus, "labels"), quality.trained_on())
    x = np.array([quality.features((t or "").encode()) for _, t in before])
    want = Counter(d for d, s in zip(before, model.score(x)) if s >= quality.THRESHOLD)
    assert Counter(after["quality classifier"]) == want and not any(200 <= (i or 0) < 300 for i, _ in want)
    # lines
    key = lambda line: re.sub(rb"^[\x20\x09-\x0D]+|[\x20\x09-\x0D]+$", b"", line).lower()
    seen = Counter(k for _, t in after["quality classifier"] for k in {key(line) for line in (t or "").encode().split(b"\n")})
    want = Counter((i, b"\n".join(line for line in (t or "").encode().split(b"\n") if not key(line) or seen[key(line)] < 10).decode()) for i, t in after["quality classifier"])
    assert Counter(after["line dedup"]) == want
    # near copies
    some = [(i, t) for i, t in after["line dedup"] if i is not None]
    component, _ = jaccard_components(some, 5, 80)
    assert Counter(after["n-gram Jaccard join"]) == Counter(d for d in after["line dedup"] if d[0] is None or component[d[0]] == d[0])
    assert len(after["n-gram Jaccard join"]) < len(after["line dedup"])
    # benchmark
    items = [(r.item_id, r.text) for r in table(spark, small_corpus, "benchmark").collect()]
    gone = {d for d, _ in brute_overlaps([d for d in after["n-gram Jaccard join"] if d[0] is not None], items)}
    assert Counter(after["benchmark decontamination"]) == Counter(d for d in after["n-gram Jaccard join"] if d[0] not in gone) and gone
    # packing, of the whole run
    tok = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    sizes = Counter()
    for i, t in after["benchmark decontamination"]:
        sizes[i] += len(tok.encode(t or "", add_special_tokens=False).ids) + 1
    packed = Counter()
    for r in corpus_pipeline.run(spark, small_corpus).collect():
        packed[r.doc_id] += r.length
    assert packed == sizes


def test_stages_take_empty_tables(spark, small_corpus):
    import corpus_pipeline

    from pagelift.llm.common import table

    none = table(spark, small_corpus, "documents").where("false")
    for _, stage in corpus_pipeline.STAGES[:-1]:
        got = stage(spark, none, small_corpus)
        assert got.columns == none.columns and got.count() == 0
    assert corpus_pipeline.STAGES[-1][1](spark, none, small_corpus).count() == 0


def test_pipeline(spark, sf_dir):
    import corpus_pipeline

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    frame = docs
    for _, stage in corpus_pipeline.STAGES[:-1]:
        frame = stage(spark, frame, sf_dir)
        assert frame.columns == docs.columns
    kept = {r.doc_id for r in frame.collect()}
    packed = corpus_pipeline.run(spark, sf_dir)
    assert kept and {r.doc_id for r in packed.collect()} == kept
    bad = {r.doc_id for r in spark.read.parquet(f"{sf_dir}/labels.parquet").where("quality = 0").collect()}
    assert len(bad & kept) <= 0.2 * len(bad) and len(kept) > 0.6 * docs.count()
