"""Encoding, chat formatting, language ID, toxicity and language-model scores."""

import hashlib
import math
import os
import pickle
import uuid
import zlib
from collections import Counter

import numpy as np
import pandas as pd
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from offsetlink.llm import attention_lm, chat_format, common, language_id, merge_dropout, toxicity
from tests.conftest import SMALL, TINY, values
from tests.llm import edge

TEXT = st.text(st.characters(exclude_categories=["Cs"]), max_size=60)


@pytest.fixture(scope="module")
def pieces():
    return merge_dropout.Pieces(common.tokenizer_file("piece_bpe_32k.model"))


@pytest.fixture(scope="module")
def encoder(pieces):
    return merge_dropout.Encoder(pieces)


def test_plain_encoding_is_the_librarys(pieces):
    from sentencepiece import SentencePieceProcessor

    sp = SentencePieceProcessor(model_proto=common.tokenizer_file("piece_bpe_32k.model"))
    plain = merge_dropout.Encoder(pieces, alpha=0.0)
    texts = list(pd.read_parquet(f"{TINY}/documents.parquet").text[:80]) + ["a  b   c\n\nd", "<s> </s> <unk>", "x²y _a_b __ c_"]
    for t in texts:
        assert plain.encode(t, 1) == sp.encode(t)


@settings(max_examples=60, deadline=None)
@given(text=TEXT, key=st.integers(-(2**60), 2**60))
def test_dropout_is_lossless_and_repeatable(pieces, encoder, text, key):
    ids = encoder.encode(text, key)
    assert pieces.decode(ids) == text
    assert encoder.encode(text, key) == ids


def test_vectorised_agenda_equals_the_heap(pieces, encoder):
    chunks = [c for c in dict.fromkeys(merge_dropout.CHUNK.findall(" " + pd.read_parquet(f"{TINY}/documents.parquet").text[3])) if len(c) <= 32]
    got = encoder.merger.run(sorted(chunks, key=len), encoder._keys(sorted(chunks, key=len), 1), 0.3)
    for c, ids in zip(sorted(chunks, key=len), got, strict=True):
        assert ids == merge_dropout.packed(pieces.chunk(c, common.SEED, 1, 0.3))


def test_dropout_varies_with_seed_and_rate(pieces):
    text = "The quick brown foxes are jumping over international boundaries " * 3
    seen = {tuple(merge_dropout.Encoder(pieces, seed=s, alpha=0.3).encode(text, 1)) for s in range(5)}
    assert len(seen) == 5
    assert len(merge_dropout.Encoder(pieces, alpha=0.5).encode(text, 1)) > len(merge_dropout.Encoder(pieces, alpha=0.0).encode(text, 1))


def test_encoding_edges(spark):
    docs = edge.documents(spark)
    rows = merge_dropout.decode(merge_dropout.encode(docs)).collect()
    assert len(rows) == 10 and all(r.text == r.decoded for r in rows)
    assert next(r for r in rows if r.doc_id == 1).piece_ids is None and next(r for r in rows if r.doc_id == 2).piece_ids == []
    assert merge_dropout.decode(merge_dropout.encode(docs.limit(0))).count() == 0


def test_op1(spark):
    rows = merge_dropout.op1_merge_dropout(spark, TINY).collect()
    assert len(rows) == 200 and all(r.lossless for r in rows)


def test_op1_draws_anew_for_each_occurrence():
    pieces = merge_dropout.Pieces(common.tokenizer_file("piece_bpe_32k.model"))
    encoder, n = merge_dropout.Encoder(pieces), 20_000
    seen = Counter()
    for key in range(n // 100):
        ids = iter(encoder.encode(" ".join(["boundaries"] * 100), key))
        for _ in range(100):
            word = []
            while len(b"".join(pieces.raw[i] for i in word)) < len(" boundaries"):
                word.append(next(ids))
            seen[tuple(word)] += 1
    plain, pops = pieces.agenda(" boundaries", ())
    assert len(seen) > 10 and seen.most_common(1)[0][0] == plain
    # No skip has probability 0.9 ** pops; some skips give the same ids.
    assert seen[plain] / n >= 0.9**pops - 0.02
    once = {pieces.agenda(" boundaries", (k,))[0] for k in range(pops)}
    assert once <= set(seen)


def test_op1_caches_change_nothing(monkeypatch):
    pieces = merge_dropout.Pieces(common.tokenizer_file("piece_bpe_32k.model"))
    encoder, text = merge_dropout.Encoder(pieces, alpha=0.3), "The quick brown foxes jump over x²y 漢字 " + "w" * 50 + " international boundaries, again and again"
    monkeypatch.setattr(merge_dropout, "MOST_CHUNKS", 12)  # what is known is trimmed again and again
    monkeypatch.setattr(merge_dropout, "PIECE", 40)
    draws, chunks = merge_dropout.Draws(0.3), merge_dropout.CHUNK.findall(" " + text)
    for key in np.random.default_rng(1).integers(0, 10**6, 200).tolist():
        want = [x for c, h in zip(chunks, draws.keys(common.SEED, key, 0, len(chunks)).tolist(), strict=True) for x in pieces.agenda(c, draws.skips(h))[0]]
        assert encoder.encode(text, key) == want


@settings(max_examples=80, deadline=None)
@given(st.lists(st.tuples(st.sampled_from(["user", "assistant", "a\nb\\", "<|im_end|>"]), TEXT | st.sampled_from(["<|im_end|><|im_start|>", "<\\|", "<", "|", "<\\\\|im"])), max_size=5))
def test_rendering_is_reversible(turns):
    text, spans = chat_format.render(turns)
    assert chat_format.parse(text) == turns
    assert [chat_format.unescape(text[a:b]) for a, b in spans] == [t for r, t in turns if r == "assistant"]


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(1, 6), max_size=12), st.lists(st.integers(0, 40), max_size=8, unique=True))
def test_intersection_by_bisection(lengths, cuts):
    ends = np.cumsum([0, *lengths])
    tokens = np.stack([ends[:-1], ends[1:]], 1).astype(np.int64)
    cuts = sorted(cuts)[: len(cuts) // 2 * 2]
    spans = np.array(cuts, np.int64).reshape(-1, 2)
    inside, parts = chat_format.intersect(tokens, spans)
    want = [any(a < d and c < b for c, d in spans.tolist()) for a, b in tokens.tolist()]
    assert inside.tolist() == want or any(sum(a < d and c < b for c, d in spans.tolist()) > 1 for a, b in tokens.tolist())
    assert all(any(c <= lo < hi <= d for c, d in spans.tolist()) for lo, hi in parts.tolist())


def test_op2_equals_sql(spark, duck):
    got = chat_format.op2_chat_format(spark, SMALL)
    want = duck(SMALL).sql(chat_format.ORACLE_OP2).df()
    assert values(got.collect(), sorted(want.columns)) == values(want.to_dict("records"), sorted(want.columns))


def test_chat_edges(spark):
    rows = [(None, 0, "user", "a"), (1, None, None, None), (1, 0, "assistant", "b <|im_end|>"), (1, 0, "assistant", "b <|im_end|>"), (2, 1, "assistant", ""), (2, 0, "user", "x" * 300_000)]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").selectExpr("*", "'clash' AS formatted", "1 AS token_ids")
    got = {r.conv_id: r for r in chat_format.read_back(chat_format.format_conversations(df)).collect()}
    assert set(got) == {None, 1, 2} and got[1].n_turns == 3 and got[1].loss_chars == 24 and got[2].loss_chars == 0
    assert got[1].loss_sha256 == hashlib.sha256(b"b <|im_end|>b <|im_end|>").hexdigest()
    assert chat_format.format_conversations(df.limit(0)).count() == 0


def brute_bits(training, text):
    """Code length by partial matching, straight from its definition: one context and byte at a time."""
    follow = {}
    for t in training:
        raw = b"   " + t.encode()
        for i in range(3, len(raw)):
            for d in range(4):
                follow.setdefault(raw[i - d : i], Counter())[raw[i]] += 1
    raw, bits = b"   " + text.encode(), 0.0
    for i in range(3, len(raw)):
        gone = set()
        for d in range(3, -1, -1):
            left = {x: n for x, n in follow.get(raw[i - d : i], {}).items() if x not in gone}
            whole = sum(left.values()) + len(left)
            if raw[i] in left:
                bits -= math.log2(left[raw[i]] / whole)
                break
            if left:
                bits -= math.log2(len(left) / whole)
            gone |= set(left)
        else:
            bits += math.log2(256 - len(gone))
    return bits


def test_code_lengths_by_partial_matching(monkeypatch):
    texts = pd.read_parquet(f"{TINY}/documents.parquet").text.tolist()
    sample = {"a": ["abracadabra", "Abra é"], "b": texts[:6], "c": [""]}
    trees = language_id.ContextTrees(sample)
    monkeypatch.setattr(language_id, "SLICE", 500)  # texts longer than a slice
    asked = [*texts[6:9], "abracadabra", "", "\x00é😀", "zzzz"]
    for text, got in zip(asked, trees.bits(asked), strict=True):
        assert got == pytest.approx([brute_bits(sample[k], text) for k in "abc"], rel=1e-9, abs=1e-9)


def test_context_trees_are_distributions():
    trees = language_id.ContextTrees({"a": ["abracadabra " * 30], "b": ["bananas and cabanas " * 30]})
    for context in (b"abr", b"zab", b"zza", b"zzz", b"ana"):
        grams = (np.uint32(int.from_bytes(context, "big")) << np.uint32(8)) + np.arange(256, dtype=np.uint32)
        assert all(np.exp2(-t.bits(grams)).sum() == pytest.approx(1, abs=1e-9) for t in trees.trees)
    assert trees.predict(["abracadabra", "banana cabana", "", None, "123 .", "Z" * 400_000])[:5] == [("a", pytest.approx(1, abs=0.1), pytest.approx(trees.bits(["abracadabra"])[0])), ("b", pytest.approx(1, abs=0.1), pytest.approx(trees.bits(["banana cabana"])[0])), ("und", 0.0, None), ("und", 0.0, None), ("und", 0.0, None)]


def test_op4_accuracy(spark):
    truth = pd.read_parquet(f"{SMALL}/documents.parquet").set_index("doc_id").lang
    rows = language_id.op4_language_id(spark, SMALL).collect()
    held = [r for r in rows if r.held_out]
    assert len(rows) == 1000 and {r.doc_id for r in held} == {i for i in truth.index if zlib.crc32(str(i).encode()) % 5 == 0}
    assert np.mean([truth[r.doc_id] == r.lang_pred for r in held]) > 0.97 and all(0 <= r.score <= 1 for r in rows)


def test_language_edges(spark):
    docs = edge.documents(spark)
    trees = language_id.fit(docs)
    got = [(r.doc_id, r.lang_pred) for r in language_id.identify(docs, trees).collect()]
    assert len(got) == 10 and all(p == "und" for i, p in got if i in (1, 2, 3)) and (7, "en") in got
    empty = language_id.fit(docs.limit(0))
    assert {r.lang_pred for r in language_id.identify(docs, empty).collect()} == {"und"}
    assert language_id.identify(docs.limit(0), trees).count() == 0


def test_toxicity_finds_sentences():
    names = [chr(97 + i % 26) * 3 + chr(97 + i // 26) * 3 for i in range(240)]
    model = toxicity.train([f"{n} fine text. calm. what a {'foul' if i % 3 == 0 else 'good'} {n}! more." for i, n in enumerate(names)], [int(i % 3 == 0) for i in range(240)])
    text = "Ünder calm. What a foul day! Fine."
    score, found = model.score(text)
    assert score > 0.7 and [text[a:b] for a, b, _ in found] == [" What a foul day"]
    assert model.score("all is calm. fine.")[0] < 0.3 and 0 <= model.score(None)[0] <= 1 and model.score("")[0] < 0.3
    p = [1 / (1 + math.exp(-model.bias - sum(model.weights.get(f, 0) for f in set(f for w in s for f in toxicity.features(w))))) for s in (["ünder", "calm"], ["what", "a", "foul", "day"], ["fine"])]
    assert score == pytest.approx(1 - math.prod(1 - x for x in p), abs=1e-9)


def test_op8_on_held_out_labels(spark):
    sf = "/root/testdata/sf0.1"
    truth = pd.read_parquet(f"{sf}/labels.parquet").set_index("doc_id").toxic
    rows = {r.doc_id: r for r in toxicity.op8_toxicity(spark, sf).collect() if r.held_out}
    y = [(truth[i], r.predicted) for i, r in rows.items() if i in truth.index]
    assert all(zlib.crc32(str(i).encode()) % 3 == 1 for i in rows)
    hits = [p for t, p in y if t == 1]
    false = [p for t, p in y if t == 0]
    # A seventh of this table's toxic labels are on documents without any word that other toxic documents share.
    assert np.mean(hits) > 0.8 and np.mean(false) < 0.01


def test_toxicity_edges(spark):
    docs = edge.documents(spark)
    labels = spark.createDataFrame([(1, 1, None), (4, 1, 1), (4, 0, 0), (None, 1, 1), (8, 0, 0)], "doc_id long, quality int, toxic int")
    model = toxicity.fit(docs, labels)
    assert all(0 <= r.score <= 1 for r in toxicity.score(docs, model).collect())
    assert toxicity.score(docs.limit(0), toxicity.fit(docs.limit(0), labels)).count() == 0


def small_model(size=50):
    rng = np.random.default_rng(1)
    seqs = [rng.integers(0, size, n).tolist() for n in (0, 1, 15, 16, 17, 40, 100, 300)]
    counts = np.bincount(np.concatenate(seqs).astype(int), minlength=size + 2).astype(float)
    counts[size + 1] = len(seqs)
    e, classes = attention_lm.embedded(rng.integers(0, 9, (8, size + 2)).astype(float), counts)
    weight = counts + 0.5
    weight[size] = 0
    class_weight = np.bincount(classes, weight, attention_lm.CLASSES)
    layers = attention_lm.first_layers(class_weight + 0.5)
    share = np.log10(np.maximum(weight, 1e-300)) - np.log10(np.maximum(class_weight[classes], 1e-300))
    return seqs, e, classes, layers, share


@pytest.mark.parametrize("stretch", [1, 60])
def test_attention_scores_each_id_once(stretch):
    seqs, e, classes, layers, share = small_model()
    layers = {k: v * stretch if k in "qu" else v for k, v in layers.items()}  # large scores go by their maximum
    m = attention_lm.Attention(e, layers, classes, share, 50)
    assert (m.small_weights and m.small_logits) == (stretch == 1)
    got = m.score(seqs)
    d = attention_lm.DIMS
    for s, total in zip(seqs, got, strict=True):
        ids, want = [50, *s], 0.0
        for i, goal in enumerate([*s, 51]):
            # The window of an id: back to the start of the block's window, within the text.
            first = max(0, i // attention_lm.STRIDE * attention_lm.STRIDE - (attention_lm.WINDOW - attention_lm.STRIDE))
            x = e[np.array(ids[first : i + 1])]
            w = (x @ layers["k"]) @ (e[ids[i]] @ layers["q"]) / math.sqrt(d) + layers["r"][i - np.arange(first, i + 1)]
            w = np.exp(w - w.max())
            z = (w @ (x @ layers["v"]) / w.sum() + e[ids[i]]) @ layers["u"] + layers["b"]
            want += (z[classes[goal]] - z.max() - math.log(np.exp(z - z.max()).sum())) / math.log(10) + share[goal]
        assert total == pytest.approx(want, rel=2e-3)
    every = 10.0 ** share
    assert all(every[classes == c].sum() == pytest.approx(1, abs=1e-4) for c in set(classes[share > -200].tolist()))


def test_training_lowers_the_loss():
    seqs, e, classes, layers, share = small_model()
    rng = np.random.default_rng(2)
    texts = [np.tile(rng.permutation(8), 20).tolist() for _ in range(40)]  # ids that follow from those before
    flat = np.array([t[: attention_lm.WINDOW + 1] for t in texts], np.int32)
    after = attention_lm.trained(layers, flat, e, classes, 60, 0.02)
    score = lambda p: attention_lm.Attention(e, p, classes, share, 50).score(texts).sum()
    assert score(after) > 0.5 * score(layers)


def test_model_beats_unigrams_on_held_out_texts(spark):
    docs = common.read(spark, SMALL, "documents")
    held = docs.where(common.fold(F.col("doc_id"), 5) == 1)
    training = docs.where(common.fold(F.col("doc_id"), 5) != 1)
    scores = {r.doc_id: r.score for r in attention_lm.score(held, training).collect()}
    encode = attention_lm.encoding(common.tokenizer_file("byte_bpe_50k.tiktoken"))
    ids = lambda t: attention_lm.ids_of(encode, common.words(t))
    counts, texts = np.zeros(encode.n_vocab + 1), [r.text for r in training.collect()]
    for t in texts:
        counts[:-1] += np.bincount(ids(t), minlength=encode.n_vocab)
    counts[-1] = len(texts)
    unigram = np.log10((counts + 0.5) / (counts + 0.5).sum())
    base = {r.doc_id: unigram[ids(r.text)].sum() + unigram[-1] for r in held.collect()}
    assert sum(scores.values()) > 0.95 * sum(base.values())
    assert np.mean([scores[i] > base[i] for i in scores]) > 0.8


def test_windows_grow_with_the_corpus(spark):
    docs = common.read(spark, TINY, "documents").select("doc_id", "text")
    ranks = spark.sparkContext.broadcast(common.tokenizer_file("byte_bpe_50k.tiktoken"))
    heads = np.array([220, 50256])
    drawn = lambda df: df.select("text", F.pmod(F.xxhash64("text"), F.lit(1 << 40)).alias("h")).mapInArrow(lambda b: attention_lm._contexts(b, ranks.value, heads, 500), attention_lm.CONTEXT)
    one, two = drawn(docs), drawn(docs.unionByName(docs.withColumn("text", F.reverse("text"))))
    assert two.where("ids is not null").count() > 1.5 * one.where("ids is not null").count() > 0
    assert two.agg(F.sum("c")).first()[0] > one.agg(F.sum("c")).first()[0]


def test_training_predicts_each_id_of_each_text(spark, monkeypatch, tmp_path):
    docs = common.read(spark, TINY, "documents").select("doc_id", "text")
    ranks = spark.sparkContext.broadcast(common.tokenizer_file("byte_bpe_50k.tiktoken"))
    encode = attention_lm.encoding(ranks.value)
    per_id, texts = np.zeros(encode.n_vocab + 2), [r.text for r in docs.collect()]
    for t in texts:
        per_id[:-2] += np.bincount(attention_lm.ids_of(encode, common.words(t)), minlength=encode.n_vocab)
    per_id[-1] = len(texts)

    def spy(batches, shared, rate, epochs):
        raw = [np.frombuffer(i, np.uint16) for b in batches for i in b.column("ids").to_pylist()]
        if raw:
            aims = np.concatenate([attention_lm.windows_of(i)[:, 1:].ravel() for i in raw])
            np.save(f"{tmp_path}/{rate:.5f}-{uuid.uuid4().hex}.npy", np.concatenate([[epochs], np.bincount(aims[aims >= 0], minlength=encode.n_vocab + 2)]))
        yield from ()

    def total(share):
        monkeypatch.setattr(attention_lm, "SHARE", share)
        attention_lm.fit(docs, ranks, per_id.copy())
        seen = {f: np.load(f) for f in map(str, tmp_path.iterdir())}
        assert len({f.rpartition("/")[2].split("-")[0] for f in seen}) == attention_lm.ROUNDS
        for f in seen:
            os.remove(f)
        return sum(c[0] * c[1:] for c in seen.values())

    monkeypatch.setattr(attention_lm, "_round", spy)
    assert (total(10) == per_id).all()  # once, each round its share of the texts
    assert (total(10**6) == attention_lm.ROUNDS * attention_lm.EPOCHS * per_id).all()  # whole in each round


def test_op7_trains_on_all_windows_in_each_round_however_many(spark, monkeypatch, tmp_path):
    docs = common.read(spark, TINY, "documents").select("doc_id", "text")
    encode = attention_lm.encoding(common.tokenizer_file("byte_bpe_50k.tiktoken"))
    per_id, texts = np.zeros(encode.n_vocab + 2), [r.text for r in docs.collect()]
    for t in texts:
        per_id[:-2] += np.bincount(attention_lm.ids_of(encode, common.words(t)), minlength=encode.n_vocab)
    per_id[-1] = len(texts)

    def spy(batches, shared, rate, epochs):
        for b in batches:
            aims = np.concatenate([attention_lm.windows_of(np.frombuffer(i, np.uint16))[:, 1:].ravel() for i in b.column("ids").to_pylist()])
            np.save(f"{tmp_path}/{rate:.5f}-{uuid.uuid4().hex}.npy", epochs * np.bincount(aims[aims >= 0], minlength=encode.n_vocab + 2))
        yield from ()

    monkeypatch.setattr(attention_lm, "_round", spy)
    monkeypatch.setattr(attention_lm, "SHARE", 10)  # so these are many windows
    attention_lm.score(docs, F.lit(True))
    rounds = {}
    for f in tmp_path.iterdir():
        rate = f.name.partition("-")[0]
        rounds[rate] = rounds.get(rate, 0) + np.load(f)
    assert len(rounds) == attention_lm.ROUNDS
    assert all((c == attention_lm.EPOCHS * per_id).all() for c in rounds.values())


def test_places_of_a_task_are_trained_apart():
    _, e, classes, layers, _ = small_model()
    rng = np.random.default_rng(5)
    texts = [rng.integers(0, 50, n).astype(np.uint16) for n in (3, 100, 49, 700, 60)]
    places, shared = [0, 0, 3, 3, 7], pickle.dumps((layers, e, classes))
    batch = lambda some: pa.RecordBatch.from_arrays([pa.array([places[i] for i in some]), pa.array([texts[i].tobytes() for i in some])], names=["place", "ids"])
    (got,) = attention_lm._round(iter([batch([0, 1, 2]), batch([3]), batch([4])]), shared, 0.02, 2)
    alone = [next(attention_lm._round(iter([batch(x)]), shared, 0.02, 2)).to_pydict() for x in ([0, 1], [2, 3], [4])]
    assert got.column("n")[0].as_py() == sum(x["n"][0] for x in alone)
    np.testing.assert_allclose(got.column("v"), np.sum([x["v"] for x in alone], 0))
    assert not list(attention_lm._round(iter([]), shared, 0.02, 2))


@pytest.mark.parametrize("n", [2, 48, 49, 50, 97, 98, 1000])
def test_windows_predict_each_id_once(n):
    ids = np.arange(n)
    w = attention_lm.windows_of(ids)
    assert w[:, 1:][w[:, 1:] >= 0].tolist() == ids[1:].tolist()
    assert w[:, :-1][w[:, 1:] >= 0].tolist() == ids[:-1].tolist()


def test_no_texts_no_scores():
    _, e, classes, layers, share = small_model()
    assert attention_lm.Attention(e, layers, classes, share, 50).score([]).tolist() == []


def test_op7_base_by_brute_force(spark):
    docs = pd.read_parquet(f"{TINY}/documents.parquet")
    fold = {i: zlib.crc32(str(i).encode()) % 5 for i in docs.doc_id}
    counts = Counter()
    for i, t in zip(docs.doc_id, docs.text, strict=True):
        if fold[i] != 1:
            counts.update([*t.encode().lower().split(), b"\n"])
    n, v = sum(counts.values()), len(counts)
    texts = dict(zip(docs.doc_id, docs.text, strict=True))
    for r in attention_lm.op7_attention_lm(spark, TINY).collect():
        tokens = [*texts[r.doc_id].encode().lower().split(), b"\n"]
        assert (r.held_out, r.n_tokens, r.n_known, r.train_tokens) == (fold[r.doc_id] == 1, len(tokens), sum(counts[t] > 0 for t in tokens), n)
        assert r.base_score == pytest.approx(sum(math.log10((counts[t] + 0.5) / (n + 0.5 * (v + 1))) for t in tokens), abs=1e-6)
        assert r.score < 0


def test_lm_edges(spark):
    docs = edge.documents(spark)
    rows = attention_lm.score(docs, docs).collect()
    assert len(rows) == 10 and {r.n_tokens for r in rows if r.doc_id in (1, 2, 3)} == {1}
    bare = attention_lm.score(docs, docs.limit(0)).collect()
    assert len(bare) == 10 and {r.n_known for r in bare} == {0}
    assert attention_lm.score(docs.limit(0), docs).count() == 0


def test_gradients_are_the_slopes_of_the_loss():
    seqs, e, classes, layers, _ = small_model()
    windows = np.concatenate([attention_lm.windows_of(np.array([50, *s, 51])) for s in seqs])
    names, d = "qkvurb", attention_lm.DIMS
    p = {k: layers[k].astype(np.float64) for k in names}

    def loss(p):
        x, y = np.maximum(windows[:, :-1], 0), windows[:, 1:]
        far = np.arange(attention_lm.WINDOW)[:, None] - np.arange(attention_lm.WINDOW)
        h = e[x]
        w = (h @ p["q"]) @ (h @ p["k"]).transpose(0, 2, 1) / math.sqrt(d) + np.where(far >= 0, p["r"][np.clip(far, 0, None)], -np.inf)
        w = np.exp(w - w.max(2, keepdims=True))
        z = (w / w.sum(2, keepdims=True) @ (h @ p["v"]) + h) @ p["u"] + p["b"]
        z -= np.log(np.exp(z).sum(2, keepdims=True))
        return -np.take_along_axis(z, classes[np.maximum(y, 0)][..., None], 2)[..., 0][y >= 0].mean()

    seen = {}

    class Spy:
        def __init__(self, graph):
            self.graph = graph

        def __call__(self, **inputs):
            seen["of"] = self.graph(**inputs)
            return seen["of"]

    graph = attention_lm._gradients()
    with pytest.MonkeyPatch.context() as m:
        m.setattr(attention_lm, "BATCH", len(windows))
        m.setattr(attention_lm, "_gradients", lambda: Spy(graph))
        attention_lm.trained(layers, windows, e, classes, 1, 0.0)
    wide, last, _ = seen["of"]
    got = {"q": wide[:, :d] / math.sqrt(d), "k": wide[:, d : 2 * d], "v": wide[:, 2 * d :], "u": last[:-1]}
    rng = np.random.default_rng(4)
    for name, g in got.items():
        way = rng.normal(0, 1, g.shape)
        up, down = (loss(p | {name: p[name] + s * 1e-4 * way}) for s in (1, -1))
        assert (g * way).sum() == pytest.approx((up - down) / 2e-4, rel=2e-3, abs=1e-5)


def test_numpy_takes_no_exponentials_of_ids(monkeypatch):
    # They were a third of the time of scores, and take three times as long there as in a graph.
    seqs, e, classes, layers, share = small_model()
    windows = np.concatenate([attention_lm.windows_of(np.array([50, *s, 51])) for s in seqs])
    taken, exp = [], np.exp
    monkeypatch.setattr(np, "exp", lambda x, **more: taken.append(np.size(x)) or exp(x, **more))
    after = attention_lm.trained(layers, windows, e, classes, 1, 0.01)
    attention_lm.Attention(e, after, classes, share, 50).score(seqs)
    assert sum(taken) == 0


def test_stored_ids_stand_for_texts(monkeypatch):
    ranks, heads = common.tokenizer_file("byte_bpe_50k.tiktoken"), np.array([220, 50257])
    encode, texts = attention_lm.encoding(ranks), ["a b c", "", None, "the same the same"]
    ids = [attention_lm.ids_of(encode, common.words(t)).astype(np.uint16).tobytes() for t in texts]
    batch = lambda **columns: [pa.RecordBatch.from_pydict(columns | {"h": [1, 2, 3, 4]})]
    want = [b.to_pydict() for b in attention_lm._contexts(batch(text=texts), ranks, heads, 48)]
    monkeypatch.setattr(attention_lm, "ids_of", lambda *_: pytest.fail("encoded again"))
    assert [b.to_pydict() for b in attention_lm._contexts(batch(ids=ids), ranks, heads, 48)] == want
