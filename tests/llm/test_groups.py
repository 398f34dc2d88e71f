"""Exact and near duplicates, components, nearest neighbours, models and mixing."""

import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from steadysketch.llm import exact_dedup, mixing, ngram_lm, quality, simhash, vectors
from steadysketch.llm.components import components

DATA = "/root/testdata/sf0.001"


def documents(spark):
    return spark.read.parquet(f"{DATA}/documents.parquet")


def labels(spark):
    return spark.read.parquet(f"{DATA}/labels.parquet")


def odd(spark):
    rows = [(1, "a b", "x"), (1, "a b", "x"), (None, "a  b", None), (None, None, "x"), (None, "", "y"), (5, "a\nb", "y"), (4, " ", None), (3, "\t", "x"), (9, "w " * 30_000, "z")]
    return spark.createDataFrame([(*r, "en", 1, True) for r in rows], "doc_id long, text string, source string, lang string, fp long, kept boolean")


# -- exact ----------------------------------------------------------------------------------------
def brute_exact(rows):
    groups = {}
    for doc_id, text in rows:
        groups.setdefault(exact_dedup.normalised(text), []).append(doc_id)
    return {(d, min(ids), len(ids), d == min(ids)) for ids in groups.values() for d in ids}


@pytest.mark.parametrize(("capacity", "bits"), [(25_000, 256), (20, 256), (20, 5), (1000, 0)])
def test_exact_equals_brute_force(spark, capacity, bits):
    docs = documents(spark)
    found = exact_dedup.duplicates(docs, capacity, bits)
    got = {(r.doc_id, r.keep_id, r.group_size, r.kept) for r in found.collect()}
    assert got == brute_exact([(r.doc_id, r.text) for r in docs.collect()])


def test_exact_of_odd_rows(spark):
    rows = exact_dedup.duplicates(odd(spark)).collect()
    assert len(rows) == 9
    assert sorted((r.doc_id or 0, r.keep_id or 0, r.group_size, r.kept) for r in rows) == sorted(
        [(1, 1, 4, True), (1, 1, 4, False), (0, 1, 4, False), (5, 1, 4, False), (0, 0, 2, True), (0, 0, 2, False), (4, 3, 2, False), (3, 3, 2, True), (9, 9, 1, True)]
    )
    assert exact_dedup.duplicates(odd(spark).where("false")).count() == 0
    kept = exact_dedup.keep_first(odd(spark))
    assert kept.columns == odd(spark).columns and kept.count() == 4


def test_directory_doubles_and_names_every_prefix():
    d = exact_dedup.Directory(1)
    d.split((1, 0))
    d.split((2, 1))
    assert d.depth == 3 and d.slots == [(2, 0), (2, 0), (3, 2), (3, 3), (1, 1), (1, 1), (1, 1), (1, 1)] and d.buckets() == 4


# -- near -----------------------------------------------------------------------------------------
def brute_components(ids, fps):
    fps = np.array(fps, np.uint64)
    near = np.bitwise_count(fps[:, None] ^ fps[None]) <= 2
    comp = np.array(ids)
    while True:
        new = np.where(near, comp[None], 1 << 60).min(1)
        if (new == comp).all():
            return comp
        comp = new


@pytest.mark.parametrize("bucket", [64, 2])
def test_near_equals_brute_force(spark, bucket):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").where("doc_id < 400")
    rows = simhash.near_duplicates(docs, bucket=bucket).collect()
    comp = brute_components([r.doc_id for r in rows], [int(r.fingerprint, 16) for r in rows])
    assert [r.component_id for r in rows] == comp.tolist()


def test_dense_cluster_is_linked_whole(spark):
    rng, base = random.Random(2), 0x123456789ABCDEF
    fps = set()
    while len(fps) < 600:
        x = base
        for _ in range(rng.randint(0, 5)):
            x ^= 1 << rng.randrange(63)
        fps.add(x)
    fps = sorted(fps)
    edges = simhash.links(spark.createDataFrame([(x,) for x in fps], "fp long"), 8)
    roots = dict(components(edges).collect())
    want = brute_components(list(range(len(fps))), fps)
    assert [fps.index(roots.get(x, x)) for x in fps] == want.tolist()


def test_fingerprints_by_the_definition(spark):
    import re

    import xxhash

    def slow(text):
        text = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
        words = re.findall(r"[^\x20\x09-\x0D]+", text)
        if not words:
            return 0
        parts = [" ".join(words)] if len(words) < 3 else [" ".join(words[i : i + 3]) for i in range(len(words) - 2)]
        hashes = [xxhash.xxh64(p.encode(), seed=42).intdigest() for p in parts]
        return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))

    for text in (None, "", " \n", "A", "x Y", "one two three", "ÀB c\x1cd e F g é", "w " * 70_000):
        assert simhash.fingerprint(text) == slow(text)


def test_golay_words_within_two_share_a_key():
    golay, rng = simhash.Golay(), np.random.default_rng(0)
    words = rng.integers(0, 1 << 23, 3000)
    for errors in (0, 1, 2):
        other = words.copy()
        for _ in range(errors):
            other ^= 1 << rng.integers(0, 23, len(other))
        assert all((set(a) - {-1}) & (set(b) - {-1}) for a, b in zip(golay.keys(words), golay.keys(other)))


def test_near_of_odd_rows(spark):
    rows = simhash.near_duplicates(odd(spark)).collect()
    assert len(rows) == 9
    empty = {r.component_id for r in rows if r.fingerprint == "0" * 16}
    assert empty == {3}
    assert simhash.near_duplicates(odd(spark).where("false")).count() == 0
    kept = simhash.keep_one(odd(spark))
    assert kept.columns == odd(spark).columns
    # One text "a b" in three spellings, one document without words, the long one; rows without an id stay.
    assert sorted(r.doc_id or 0 for r in kept.collect()) == [0, 0, 0, 1, 3, 9]


def test_components_of_chains_and_stars(spark):
    edges = [(i, i + 1) for i in range(40)] + [(100, 100 + i) for i in range(50)] + [(7, 7), (None, 3)]
    found = dict(components(spark.createDataFrame(edges, "a long, b long")).collect())
    assert {found.get(i, i) for i in range(41)} == {0} and {found.get(100 + i, 100 + i) for i in range(50)} == {100}
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


# -- vectors --------------------------------------------------------------------------------------
def test_nearest_recall_and_exact_scores(spark):
    table = spark.read.parquet("/root/testdata/sf0.1/embeddings.parquet")
    rows = table.collect()
    ids, x = np.array([r.vec_id for r in rows]), np.array([r.embedding for r in rows], float)
    # Fewer than one row in twenty is measured exactly.
    found = vectors.nearest(table, rerank=96).collect()
    hit = total = 0
    for q in ids[ids % 100 == 0]:
        d = np.sqrt(((x - x[ids == q][0]) ** 2).sum(1))
        best = [i for i in np.lexsort((ids, d)) if ids[i] != q][:10]
        mine = sorted((r["rank"], r.vec_id, r.score) for r in found if r.query_id == q)
        assert [m[0] for m in mine] == list(range(1, 11))
        assert all(abs(s - d[ids == v][0]) < 1e-12 for _, v, s in mine)
        hit += len({m[1] for m in mine} & set(ids[best]))
        total += 10
    assert hit / total >= 0.9


def test_partitions_and_copies_change_nothing(spark):
    rng = np.random.default_rng(5)
    x = rng.normal(size=(600, 8)).round(1)
    x[300:480] = x[7]
    rows = [(i, [float(v) for v in x[i]]) for i in range(600)]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    key = lambda found: sorted((r.query_id, r["rank"], r.vec_id) for r in found.collect())
    one, other = key(vectors.nearest(frame.coalesce(1), rerank=40)), key(vectors.nearest(frame.repartition(7), rerank=40))
    assert one == other
    # A query that is one of many copies finds the copies with the smallest ids, itself left out.
    assert [v for q, _, v in one if q == 300] == [7, 301, 302, 303, 304, 305, 306, 307, 308, 309]
    assert [v for q, _, v in one if q == 400][:3] == [7, 300, 301]


def test_nearest_of_odd_vectors(spark):
    rows = [(0, [1.0, 0.0]), (1, None), (2, [0.0, 0.0]), (3, [float("nan"), 1.0]), (4, [None, 1.0]), (5, [1.0, 0.0]), (6, [1.0, 0.0]), (7, [1.0, 2.0, 3.0]), (None, [1.0, 1.0]), (100, [0.0, 2.0]), (8, [float("inf"), 1.0])]
    found = vectors.nearest(spark.createDataFrame(rows, "vec_id long, embedding array<float>")).collect()
    assert [(r["rank"], r.vec_id, r.score) for r in found if r.query_id == 0] == [(1, 5, 0.0), (2, 6, 0.0), (3, 100, math.sqrt(5))]
    assert [r.vec_id for r in found if r.query_id == 100] == [0, 5, 6]
    assert vectors.nearest(spark.createDataFrame([], "vec_id long, embedding array<float>")).count() == 0
    many = spark.createDataFrame([(i, [1.0, float(i % 2)]) for i in range(300)], "vec_id long, embedding array<float>")
    assert [r.vec_id for r in sorted((r for r in vectors.nearest(many).collect() if r.query_id == 100), key=lambda r: r["rank"])] == list(range(0, 20, 2))


# -- models ---------------------------------------------------------------------------------------
def slow_model(texts, order):
    """Interpolated modified Kneser-Ney over bytes, from the definition."""
    grams = {order: {}}
    for t in texts:
        raw = [255] * (order - 1) + list(t.encode())
        for i in range(order - 1, len(raw)):
            g = tuple(raw[i - order + 1 : i + 1])
            grams[order][g] = grams[order].get(g, 0) + 1
    for k in range(order - 1, 0, -1):
        grams[k] = {}
        for g in grams[k + 1]:
            grams[k][g[1:]] = grams[k].get(g[1:], 0) + 1
    cut = {k: ngram_lm.discounts({c: sum(v == c for v in g.values()) for c in range(1, 5)}) for k, g in grams.items()}

    def p(word, context):
        if len(context) == order:
            raise AssertionError
        k = len(context) + 1
        lower = p(word, context[1:]) if context else 1 / 256
        own = {g[-1]: n for g, n in grams[k].items() if g[:-1] == context}
        if not own:
            return lower
        total = sum(own.values())
        back = sum(cut[k][min(n, 3) - 1] for n in own.values()) / total
        if word not in own:
            return max(back, ngram_lm.FLOOR) * lower
        return (own[word] - cut[k][min(own[word], 3) - 1]) / total + back * lower

    return lambda text: [p(b, tuple(([255] * (order - 1) + list(text.encode()))[i : i + order - 1])) for i, b in enumerate(text.encode())]


@pytest.mark.parametrize("size", [8_000_000, 10])
def test_model_equals_the_definition(spark, size):
    texts = ["the cat sat", "the hat", "a cat ate the hat", "aaaa", "then that"]
    docs = spark.createDataFrame([(i, t) for i, t in enumerate(texts)] + [(9, None), (10, "")], "doc_id long, text string")
    model = ngram_lm.estimate(ngram_lm.counts(docs, 3), 3)
    slow = slow_model(texts, 3)
    asked = ["the cat", "zq", "hat that", "", None, "thé"]
    scored = {r.doc_id: r for r in ngram_lm.losses(spark.createDataFrame(list(enumerate(asked)), "doc_id long, text string"), {"m": model}, ["doc_id"], size).collect()}
    for i, text in enumerate(asked):
        want = -sum(map(math.log, slow(text))) if text else 0.0
        assert abs(scored[i].loss_m - want) < 1e-3 * max(1.0, want) and scored[i].n_tokens == len((text or "").encode())


def odd_labels(spark, ids):
    return spark.createDataFrame([(i, 1 if i % 3 else 0, 0) for i in ids] + [(None, 1, 0), (10**9, 1, 0)], "doc_id long, quality int, toxic int")


def small_documents(spark, n=60):
    rng = random.Random(11)
    words = ["the", "cat", "hat", "sat", "on", "mat", "der", "hund", "lief"]
    rows = [(i, " ".join(rng.choice(words) for _ in range(rng.randint(0, 12))) if i % 7 else None, ["en", "de", None][i % 3]) for i in range(n)]
    rows += [(rows[3][0], rows[3][1], "en"), (None, "the cat", "de"), (n, "qzx 123 " * 20, "en")]
    return rows, spark.createDataFrame([(*r, True, 5, "clash", 1.0) for r in rows], "doc_id long, text string, lang string, kept boolean, n_tokens int, grp string, perplexity double")


def fifths(spark, ids):
    frame = spark.createDataFrame([(i,) for i in ids], "doc_id long")
    return {r.doc_id: r.f for r in frame.select("doc_id", quality._fifth().alias("f")).collect()}


@pytest.mark.parametrize(("least", "quantile"), [(2, 0.9), (50, 0.5)])
def test_quality_equals_brute_force(spark, monkeypatch, least, quantile):
    monkeypatch.setattr(quality, "MIN_CALIBRATION", least)
    rows, docs = small_documents(spark)
    labels_ = odd_labels(spark, range(60))
    trusted, fifth = {i for i in range(60) if i % 3}, fifths(spark, range(61))
    model = slow_model([t for i, t, _ in rows if t and i in trusted and fifth[i] > 0], 3)
    perplexity = lambda t: math.exp(-sum(map(math.log, model(t))) / len(t.encode())) if t else None
    held = [(lang, math.ceil(math.log(perplexity(t)) * quality.STEPS)) for i, t, lang in rows if t and i in trusted and fifth[i] == 0]

    def limit(steps):
        steps = sorted(steps)
        return math.exp(steps[math.ceil(quantile * len(steps)) - 1] / quality.STEPS) * 1.15

    own = {lang: [s for x, s in held if x == lang] for lang in ("en", "de", None)}
    limits = {lang: limit(s) if len(s) >= least else limit([s for _, s in held]) for lang, s in own.items()}
    found = quality.score(docs, labels_, ["doc_id", "text", "lang"], quantile, order=3).collect()
    assert len(found) == len(rows)
    assert sorted((r.doc_id or -1, r.text or "") for r in found) == sorted((i or -1, t or "") for i, t, _ in rows)
    for r in found:
        want = perplexity(r.text)
        assert (r.perplexity is None) == (want is None) and (want is None or abs(r.perplexity - want) < 1e-6 * want)
        assert abs(r.threshold - limits[r.lang]) < 2e-3 * limits[r.lang]
        assert r.kept == (want is not None and r.perplexity <= r.threshold)
    kept = quality.accepted(docs, labels_, quantile, order=3)
    assert kept.columns == docs.columns and kept.count() == sum(r.kept for r in found)


def test_difference_equals_brute_force(spark):
    rows, docs = small_documents(spark)
    labels_ = odd_labels(spark, range(60))
    trusted = {i for i in range(60) if i % 3}
    target = [t for i, t, _ in rows if t and i in trusted]
    share = sum(len(t) for t in target) / sum(len(t) for _, t, _ in rows if t)
    place = docs.select("doc_id", "text", (F.pmod(F.xxhash64(F.lit("background"), "doc_id", F.col("text")), F.lit(1 << 40)) / float(1 << 40)).alias("at"))
    background = [r.text for r in place.collect() if r.text and r.at < share]
    models = slow_model(target, 4), slow_model(background, 4)
    found = quality.cross_entropy_difference(docs, labels_, 4).collect()
    assert len(found) == len(rows)
    by_text = {(i, len(t or "")): t for i, t, _ in rows}
    for r in found:
        text = by_text[r.doc_id, r.n_tokens]
        if text:
            a, b = (-sum(map(math.log, m(text))) for m in models)
            assert abs(r.loss_target - a) < 1e-6 * a and abs(r.loss_background - b) < 1e-6 * b
            assert abs(r.score - (a - b) / len(text)) < 1e-6
        else:
            assert r.score is None


def test_quality_rejects_noise_and_keeps_trusted_text(spark):
    docs, known = spark.read.parquet("/root/testdata/sf0.01/documents.parquet"), spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    rows = quality.score(docs, known, ["doc_id"]).join(known, "doc_id").collect()
    good, bad = [r.kept for r in rows if r.quality == 1], [r.kept for r in rows if r.quality == 0]
    assert sum(good) / len(good) > 0.99 and sum(bad) / len(bad) < 0.15


def test_quality_rejects_junk_of_larger_tables(spark):
    docs, known = spark.read.parquet("/root/testdata/sf0.1/documents.parquet"), spark.read.parquet("/root/testdata/sf0.1/labels.parquet")
    rows = quality.score(docs, known, ["doc_id"]).join(known, "doc_id").select("quality", "toxic", "kept").collect()
    share = lambda q, t: np.mean([r.kept for r in rows if r.quality == q and r.toxic in t])
    # Perplexity cannot see insults: clean texts with them stay.
    assert share(0, (0, 1)) < 0.1 and share(1, (0,)) > 0.98 and share(1, (1,)) > 0.98


def test_one_odd_calibration_document_does_not_set_the_limit(spark):
    rows = [("en", 4.0 + i / 100) for i in range(59)] + [("en", 90.0)]
    limits, overall = quality.thresholds(spark.createDataFrame(rows, "lang string, perplexity double"))
    assert limits.first().threshold < 6 and overall < 6


def test_quality_and_difference_of_odd_rows(spark):
    rows = {(r.doc_id, r.n_tokens): r for r in quality.score(odd(spark), labels(spark), ["doc_id"]).collect()}
    assert rows[None, 0].perplexity is None and rows[None, 0].kept is False
    empty = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert all(r.kept for r in quality.score(odd(spark), empty, ["doc_id"]).collect() if r.n_tokens)
    assert quality.score(odd(spark).where("false"), empty, ["doc_id"]).count() == 0
    scored = quality.cross_entropy_difference(documents(spark), labels(spark))
    assert scored.count() == documents(spark).count()
    assert quality.cross_entropy_difference(odd(spark), empty).where("n_tokens = 0 and score is not null").count() == 0


# -- mixing ---------------------------------------------------------------------------------------
def slow_targets(sizes, share=1.5):
    total, weights = share * sum(sizes), [(3, 1, 2)[i % 3] for i in range(len(sizes))]
    full: set[int] = set()
    while True:
        left = total - sum(2 * sizes[i] for i in full)
        free = [i for i in range(len(sizes)) if i not in full]
        level = left / sum(weights[i] for i in free) if free else 0
        over = [i for i in free if level * weights[i] >= 2 * sizes[i]]
        if not over:
            return [2.0 * sizes[i] if i in full else level * weights[i] for i in range(len(sizes))]
        full |= set(over)


def test_targets_equal_repeated_sharing(spark):
    rng = random.Random(4)
    for _ in range(4):
        sizes = [rng.choice([0, 5, 50, 400, 3000]) for _ in range(rng.randint(1, 9))]
        frame = spark.createDataFrame([(f"s{i}", n, 1) for i, n in enumerate(sizes)], "source string, source_size long, docs long")
        got = [r.target for r in mixing.targets(frame).orderBy("source").collect()]
        assert np.allclose(got, slow_targets(sizes))


def test_apportionment_equals_highest_quotients(spark):
    rng = random.Random(6)
    for _ in range(4):
        votes, seats = [rng.choice([0, 1, 7, 90, 1000]) + rng.random() for _ in range(rng.randint(1, 12))], rng.randint(0, 60)
        frame = spark.createDataFrame([(i, v, seats) for i, v in enumerate(votes)], "party int, votes double, seats long")
        got = [r.won for r in mixing.apportion(frame, [], "party", "votes", "seats", "won").orderBy("party").collect()]
        want = [0] * len(votes)
        for _ in range(seats):
            best = max(range(len(votes)), key=lambda i: (votes[i] / (2 * want[i] + 1), -i))
            want[best] += 1
        assert got == want


def test_mix_keeps_to_targets_and_is_repeatable(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    for shard_docs in (4096, 13):
        rows = mixing.mix(docs, shard_docs=shard_docs).collect()
        assert len(rows) == docs.count() and all(0 <= r.taken <= 2 * r["size"] for r in rows)
        by_target = {}
        for r in rows:
            by_target.setdefault((r.source_size, r.target), []).append(r.taken)
        for (_, target), taken in by_target.items():
            # The quota is rounded to blocks, and the last block of each shard can be short.
            shards = math.ceil(len(taken) / shard_docs)
            assert abs(sum(taken) - target) <= 64 * (1 + 2 * shards)
    again = mixing.mix(docs.repartition(7)).collect()
    key = lambda rows: sorted((r.doc_id, r.taken) for r in rows)
    assert key(again) == key(mixing.mix(docs).collect())


def test_mix_of_odd_rows(spark):
    rows = mixing.mix(odd(spark)).collect()
    assert len(rows) == 9 and all(0 <= r.taken <= 2 * r["size"] for r in rows)
    assert mixing.mix(odd(spark).where("false")).count() == 0
    assert mixing.mix(odd(spark).where("text is null or trim(text) = ''")).agg(F.sum("taken")).first()[0] == 0
    out = mixing.mixed_documents(odd(spark))
    assert out.columns == odd(spark).columns
