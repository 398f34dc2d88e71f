"""Language identification, token counts, byte-level BPE and licence scans."""

import hashlib
import random
import re
import zlib

import numpy as np
import pytest

from steadysketch.llm import bpe, langid, licences, token_counts

tokens = pytest.importorskip("public_tokenizers")
DATA = "/root/testdata/sf0.001"
ODD = [None, "", " ", "\n\t ", "a", "a b c", "é漢字🙂", "x" * 30_000, "ab " * 20_000, "<s> </s> <|endoftext|>", "\x1c\x85\xa0　", "▁a  b", "١٢ ½ Ⅷ"]


def frame(spark, texts):
    return spark.createDataFrame([(i, t, "en", "s", 7, "clash") for i, t in enumerate(texts)], "doc_id long, text string, lang string, source string, n_tokens long, score string")


def documents(spark):
    return spark.read.parquet(f"{DATA}/documents.parquet")


def random_texts(n, seed):
    rng = random.Random(seed)
    alphabets = [" \t\n\x0babcdeXYZ'sé漢字🙂1٣.,!?-_$%", "ab ", "aaa ", "   a\n", "thering "]
    return ["".join(rng.choice(rng.choice(alphabets)) for _ in range(rng.randint(0, 80))) for _ in range(n)]


# -- byte-level BPE -------------------------------------------------------------------------------
@pytest.fixture(scope="module")
def reference():
    import tiktoken

    ranks = bpe.read_ranks(tokens.path("byte_bpe_50k.tiktoken"))
    return tiktoken.Encoding("own", pat_str=tokens.PATTERN, mergeable_ranks=ranks, special_tokens={}), bpe.Encoder(ranks, tokens.PATTERN)


def test_bpe_equals_the_library(spark, reference):
    texts = ODD + random_texts(300, 1)
    rows = bpe.encode_documents(frame(spark, texts), tokens.path("byte_bpe_50k.tiktoken"), tokens.PATTERN, with_ids=True).collect()
    assert sorted(r.doc_id for r in rows) == list(range(len(texts)))
    for r in rows:
        text = texts[r.doc_id] or ""
        ids = reference[0].encode_ordinary(text)
        assert r.ids == ids and r.n_tokens == len(ids)
        assert r.ids_sha256 == hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest()
        assert r.decoded_sha256 == hashlib.sha256(text.encode()).hexdigest()


def test_bpe_round_trip_and_empty_table(spark):
    path = tokens.path("byte_bpe_50k.tiktoken")
    docs = documents(spark)
    encoded = bpe.encode_documents(docs, path, tokens.PATTERN, with_ids=True)
    back = {r.doc_id: r.text for r in bpe.decode_documents(encoded, path).collect()}
    assert back == {r.doc_id: r.text or "" for r in docs.collect()}
    assert bpe.encode_documents(docs.where("false"), path, tokens.PATTERN).count() == 0


def test_trees_of_both_kinds_agree(reference):
    coder = reference[1]
    rng = random.Random(5)
    pieces = ["".join(rng.choice("theringéx") for _ in range(rng.randint(1, 40))) for _ in range(500)]
    together = dict(coder.encode_pieces(sorted(set(pieces))))
    assert all(together[p] == coder.piece(p.encode()) for p in together)


def test_forgetting_changes_nothing(reference, monkeypatch):
    monkeypatch.setattr(bpe, "REMEMBER", 3)
    coder = bpe.Encoder(reference[1].ranks, tokens.PATTERN)
    texts = random_texts(60, 9)
    assert [coder.encode(t) for t in texts] == [reference[0].encode_ordinary(t) for t in texts]


# -- token counts ---------------------------------------------------------------------------------
def test_counts_equal_the_library(spark):
    import sentencepiece

    path = tokens.path("piece_bpe_32k.model")
    library = sentencepiece.SentencePieceProcessor(model_file=path)
    texts = ODD + random_texts(300, 2)
    rows = token_counts.count_tokens(frame(spark, texts), path, limit=50).collect()
    assert sorted(r.doc_id for r in rows) == list(range(len(texts)))
    for r in rows:
        text = texts[r.doc_id] or ""
        n = len(library.encode(text))
        assert (r.n_tokens, r.n_bytes, r.over_limit) == (n, len(text.encode()), n > 50)
    assert token_counts.count_tokens(documents(spark).where("false"), path).count() == 0


def test_long_unbroken_runs_equal_the_library():
    import sentencepiece

    path = tokens.path("piece_bpe_32k.model")
    library, machine = sentencepiece.SentencePieceProcessor(model_file=path), token_counts.Transducer(token_counts.read_model(path))
    rng = random.Random(12)
    for text in ("".join(rng.choice("abcdefghij") for _ in range(20_000)), "therein" * 3_000, "a" * 20_001, " " * 9_000, "ab\n" * 5_000):
        assert len(text) > 2 * token_counts.CHUNK and machine.count(text) == len(library.encode(text))


def test_a_restart_between_chunks_changes_nothing(monkeypatch):
    machine = token_counts.Transducer(token_counts.read_model(tokens.path("piece_bpe_32k.model")))
    texts = random_texts(10, 5) + ["thereinafter" * 60]
    want = [machine.counts_by_chunk(t, 16) if t else [] for t in texts]
    monkeypatch.setattr(token_counts, "COMPILED", 5)
    assert [machine.counts_by_chunk(t, 16) if t else [] for t in texts] == want


def test_chunk_maps_compose_to_whole_counts():
    machine = token_counts.Transducer(token_counts.read_model(tokens.path("piece_bpe_32k.model")))
    for text in random_texts(60, 3) + ["a" * 500, "ab cd\n" * 100]:
        whole = machine.count(text)
        for size in (1, 3, 7, 64):
            if text:
                assert machine.counts_by_chunk(text, size)[-1] == whole
    maps = [machine.chunk_map(c) for c in ("▁he", "llo▁wo", "rld", "▁x\n", "yz")]
    left = machine.compose(machine.compose(maps[0], maps[1]), maps[2])
    right = machine.compose(maps[0], machine.compose(maps[1], maps[2]))
    assert machine.apply(left) == machine.apply(right) == machine.run(token_counts.START, "▁hello▁world")[1]


# -- language -------------------------------------------------------------------------------------
def test_language_on_held_out_documents(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    found = {r.doc_id: r for r in langid.identify(docs, langid.learn_profiles(docs)).collect()}
    right = total = 0
    for r in docs.collect():
        assert found[r.doc_id].held_out == (zlib.crc32(str(r.doc_id).encode()) % 3 == 1)
        if found[r.doc_id].held_out:
            total += 1
            right += found[r.doc_id].lang_pred == r.lang
    assert right / total > 0.97


def slow_list(text, places):
    """A text's most frequent n-grams as tuples of code points, blanks as 0: most frequent first, then shorter, then by code."""
    codes = [0]
    for c in text.lower():
        codes.append(ord(c) if c.isalpha() else 0)
    codes = [c for c, before in zip([*codes, 0], [None, *codes]) if c or before != 0]
    counts = {}
    for i, c in enumerate(codes):
        found = [(c,)] * (c > 0) + [tuple(codes[i : i + 2])] * (i + 1 < len(codes))
        found += [tuple(codes[i : i + 3])] * (i + 2 < len(codes) and codes[i + 1] > 0)
        for gram in found:
            counts[gram] = counts.get(gram, 0) + 1
    return sorted(counts, key=lambda g: (-counts[g], len(g), g))[:places] if len(codes) > 2 else []


def test_language_distance_equals_brute_force():
    rng = random.Random(8)
    text = lambda letters: "".join(rng.choice(letters) for _ in range(400))
    learned = {"a": text("abc ,."), "b": text("bcd  é"), "c": text("xyz1 ")}
    matcher = langid.Matcher([(name, langid.ranked(t, 40)) for name, t in learned.items()], 40)
    profiles = {name: {g: i for i, g in enumerate(slow_list(t, 40))} for name, t in learned.items()}
    for asked in [text("abcd é") for _ in range(20)] + [text("xyzab ,") for _ in range(20)] + ["a", "Éa b", " x "]:
        own = slow_list(asked, 40)
        apart = {name: sum(abs(places[g] - i) if g in places else 40 for i, g in enumerate(own)) for name, places in profiles.items()}
        best = min(apart, key=lambda name: (apart[name], name))
        assert matcher.match(asked) == (best, max(0.0, 1 - apart[best] / (40 * len(own))))


def test_too_many_languages_are_refused(spark, monkeypatch):
    monkeypatch.setattr(langid, "MAX_LANGUAGES", 1)
    with pytest.raises(ValueError):
        langid.learn_profiles(documents(spark))


def test_language_of_odd_texts(spark):
    docs = frame(spark, ODD)
    profiles = langid.learn_profiles(documents(spark))
    found = {r.doc_id: r for r in langid.identify(docs, profiles).collect()}
    assert all(found[i].lang_pred == "und" and found[i].score == 0 for i in (0, 1, 2, 3, 10))
    assert all(0 <= r.score <= 1 for r in found.values())
    nothing = langid.learn_profiles(docs.where("false"))
    assert {r.lang_pred for r in langid.identify(docs, nothing).collect()} == {"und"}
    nulls = spark.createDataFrame([(None, "abc", None)], "doc_id long, text string, lang string")
    assert langid.learn_profiles(nulls) == [] and langid.identify(nulls, profiles).first().held_out is False


# -- licences -------------------------------------------------------------------------------------
def brute_licences(docs):
    words = lambda t: re.sub(r"[\W_]+", " ", t.lower()).split()
    cut = lambda w: {tuple(w[i : i + 5]) for i in range(len(w) - 4)}
    wanted = {k: cut(licences.template_words(v)) for k, v in licences.TEMPLATES.items()}
    return {(i, k) for i, t in docs if t for k, v in wanted.items() if len(cut(words(t)) & v) >= 0.8 * len(v)}


def test_licences_equal_brute_force(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    found = {(r.doc_id, r.template_id) for r in licences.scan(docs).collect()}
    assert found == brute_licences([(r.doc_id, r.text) for r in docs.collect()]) and found


def test_licences_whole_edited_and_odd(spark):
    grant = licences.TEMPLATES["mit-grant"].split()
    edited = list(grant)
    edited[20] = "changed"
    texts = ODD + ["word " * 5000 + " ".join(grant) + " tail" * 300, " ".join(edited), " ".join(grant[:25]), "license " * 50]
    found = {(r.doc_id, r.template_id): r.containment for r in licences.scan(frame(spark, texts)).collect()}
    n = len(ODD)
    assert found[n, "mit-grant"] == 1.0 and 0.8 <= found[n + 1, "mit-grant"] < 1
    assert not [k for k in found if k[0] not in (n, n + 1)]
    assert licences.scan(documents(spark).where("false")).count() == 0
    repeated = spark.createDataFrame([(None, licences.TEMPLATES["mit-line"]), (None, licences.TEMPLATES["mit-line"])], "doc_id long, text string")
    assert [(r.doc_id, r.template_id) for r in licences.scan(repeated).collect()] == [(None, "mit-line")]


def test_a_task_begins_by_handing_back_memory(spark, monkeypatch):
    """The pipeline's near-duplicate stage ran beside what the quality stage's workers still held."""
    from steadysketch.llm import common

    seen = []

    class Frame:
        sparkSession = spark

        def mapInArrow(self, run, schema):
            return run

    def batches():
        seen.append("read")
        yield 1

    monkeypatch.setattr(common, "give_back", lambda: seen.append("back"))
    assert list(common.map_batches(Frame(), iter, "x int")(batches())) == [1]
    assert seen == ["back", "read", "back"]


class Tasks:
    """Stands for a frame: mapInArrow gives the task's function itself."""

    def __init__(self, spark):
        self.sparkSession = spark

    def mapInArrow(self, run, schema):
        return run


def test_tasks_on_groups_hold_no_documents(spark):
    """Executors of the pipeline's quality stage came to more than 3000 MB; each worker held a group's rows, texts and copies."""
    import weakref

    import pyarrow as pa

    from steadysketch.llm import ngram_lm

    alive, most, rows = [], [], 20

    def batches():
        for at in range(40):
            batch = pa.RecordBatch.from_arrays([pa.array(range(rows)), pa.array([f"text {at} {i} " * 50 for i in range(rows)])], ["doc_id", "text"])
            alive.append(weakref.ref(batch))
            yield batch
            del batch
            most.append(sum(ref() is not None for ref in alive))

    grams = list(ngram_lm.asked(Tasks(spark), 3)(batches()))
    assert max(most) <= 2
    alive.clear(), most.clear()
    bundles = list(ngram_lm.bundled(Tasks(spark), ["doc_id"])(batches()))
    assert max(most) <= 2
    assert {b.column("grp")[0].as_py() for b in bundles} == {g.column("grp")[0].as_py() for g in grams} and len(bundles) == 40
    back = [pa.ipc.open_stream(b.column("rows")[0].as_buffer()).read_all() for b in bundles]
    assert pa.concat_tables(back).equals(pa.Table.from_batches(list(batches())))


def test_groups_do_not_depend_on_batches():
    import pyarrow as pa

    from steadysketch.llm import ngram_lm

    values = ["abc", None, "", "é" * 7, "x" * 30, "abc", "yz", None]

    def found(step):
        cut = [pa.RecordBatch.from_arrays([pa.array(values[a : a + step], pa.string())], ["text"]) for a in range(0, len(values), step)]
        out, rows = [], []
        for part, raws, name in ngram_lm.groups(iter(cut), 12):
            assert [(t or "").encode() for t in part.column("text").to_pylist()] == raws
            rows += part.column("text").to_pylist()
            if name is not None:
                out.append((name, rows))
                rows = []
        assert not rows
        return out

    assert [texts for _, texts in found(1)] == [["abc", None, "", "é" * 7], ["x" * 30], ["abc", "yz", None]]
    assert found(1) == found(3) == found(8)
    assert list(ngram_lm.groups(iter([]), 12)) == []


def test_tasks_drop_what_other_operators_kept(spark):
    from steadysketch.llm import common

    seen = []

    def read():
        seen.append(sorted(common.KEPT))
        yield 1

    common.KEPT["bpe"] = "an encoder"
    list(common.map_batches(Tasks(spark), iter, "x int", keeps="bpe")(read()))
    list(common.map_batches(Tasks(spark), iter, "x int")(read()))
    assert seen == [["bpe"], []]
