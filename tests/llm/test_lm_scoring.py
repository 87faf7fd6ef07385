import math

import numpy as np
import pyarrow as pa
import pytest

from provspark.llm import lm_scoring as lm
from provspark.llm.subwords import default_path, encoder

from . import cases as make


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(make.documents(), make.SCHEMA).repartition(3)


def tokens_and_layer(texts, experts=3, states=5):
    tokens = lm.Tokens(pa.array(texts), default_path())
    layer = lm.Attention(tokens.vocabulary, experts, states)
    layer.p["place"] = np.random.default_rng(1).normal(size=lm.WINDOW).astype(np.float32)
    return tokens, layer


def softmax(z):
    e = np.exp(np.asarray(z, float) - np.max(z))
    return e / e.sum()


def plain_logits(layer, ids):
    """Of the last of ``ids``, which begin with the begin mark, by the definition."""
    p = layer.p
    near = ids[-lm.WINDOW :]
    x = p["embed"][near].astype(float)
    z = x @ p["key"] @ (x[-1] @ p["query"]) / np.sqrt(lm.WIDTH) + p["place"][np.arange(len(near) - 1, -1, -1)]
    return softmax(z) @ (x @ p["value"]) + p["bias"]


TEXTS = ["", "one two three four five six seven eight nine ten " * 12, "a", "the end"]


def test_every_place_reads_the_ids_before_it_and_no_other():
    tokens, layer = tokens_and_layer(TEXTS)
    got = np.concatenate([out for _, out in layer.logits(tokens)])
    for at, first in enumerate(tokens.text_at):
        assert got[at] == pytest.approx(plain_logits(layer, tokens.seq[first : at + 1]), abs=1e-4)


def test_tokens_and_their_ids():
    library = encoder(default_path()).library
    tokens = lm.Tokens(pa.array(TEXTS), default_path())
    t = 0
    for text in TEXTS:
        for word in [*text.split(), None]:
            ids = [tokens.vocabulary] if word is None else library.encode(word, add_special_tokens=False).ids
            assert tokens.after[tokens.owner[t] : tokens.owner[t] + tokens.size[t]].tolist() == ids
            t += 1
    assert t == len(tokens.codes)


@pytest.mark.parametrize("blocks", [False, True])
def test_gradient_of_the_layer(blocks):
    texts = ["some words stand here " * 30, "", "and a few more there"]
    tokens, layer = tokens_and_layer(texts)
    if blocks:
        tokens = lm.Tokens(lm.Blocks(pa.array(texts), 2, 4), default_path())
    layer.p = {k: v.astype(np.float64) for k, v in layer.p.items()}
    rng = np.random.default_rng(2)
    mine, some = np.arange(len(tokens.codes)), np.arange(-(-len(tokens.seq) // lm.STEP))
    words, emit = rng.uniform(0.1, 1, (len(mine), 2)), rng.dirichlet(np.ones(tokens.vocabulary + 1) / 9, 5).T + 1e-6
    nothing, none = np.zeros(0, int), np.zeros((0, 2))
    grads, used, _, (ids, shares) = layer.gradient(tokens, some, emit, nothing, none)
    assert len(ids) == tokens.known.sum() and shares.sum(1) == pytest.approx(np.ones(len(ids)))

    def slope(value, at, loss):
        kept, found = value[at], []
        for step in (1e-4, -1e-4):
            value[at] = kept + step
            found.append(loss())
        value[at] = kept
        return (found[0] - found[1]) / 2e-4

    for name, value in layer.p.items():  # the prediction of the next ids
        for _ in range(4):
            row = int(rng.integers(len(used) if name == "embed" else len(value)))
            at = (used[row] if name == "embed" else row, *(() if value.ndim == 1 else (int(rng.integers(value.shape[1])),)))
            assert grads[name][(row, *at[1:])] == pytest.approx(slope(value, at, lambda: layer.gradient(tokens, some, emit, nothing, none)[2]), abs=2e-5)
    both = layer.gradient(tokens, some, emit, mine, words)[0]
    for k in range(layer.experts):  # the mixture, in which the layer's own prediction is taken as given
        assert both["bias"][k] == pytest.approx(slope(layer.p["bias"], (k,), lambda: mixture_loss(layer, tokens, some, emit, words)), abs=2e-5)


def mixture_loss(layer, tokens, some, emit, words):
    """The part of the loss that the experts' weights move."""
    logits = np.concatenate([out for _, out in layer.logits(tokens)])
    gates = lm._softmax(logits[:, : layer.experts])
    state = lm._softmax(logits[:, layer.experts :])
    likely = np.maximum((state * emit[tokens.after]).sum(1), 1e-30)
    sums = np.concatenate([[0.0], np.cumsum(np.log(likely))])
    whole = (tokens.size > 0) & (tokens.owner % lm.STEP + tokens.size <= lm.STEP)
    own = np.exp(sums[tokens.owner + tokens.size] - sums[tokens.owner])[whole]
    mixed = (np.concatenate([words[whole], own[:, None]], 1) * gates[tokens.owner[whole]]).sum(1)
    return -np.log(mixed).sum() / whole.sum()


def test_learning_lowers_the_loss():
    tokens, layer = tokens_and_layer(["red green blue red green blue " * 40, "one two one two " * 50])
    emit = np.full((tokens.vocabulary + 1, 5), 1e-6)
    for k, i in enumerate(np.unique(tokens.after)):
        emit[i, k % 5] = 0.2
    some, words = np.arange(-(-len(tokens.seq) // lm.STEP)), np.full((len(tokens.codes), 2), 1e-4)
    loss = lambda: layer.gradient(tokens, some, emit, np.arange(len(words)), words)[2]
    before = loss()
    for seed in range(30):
        layer.learn(tokens, emit, lambda mine: words[mine], seed=seed)
    assert loss() < before - 1


def test_score_by_the_definition(docs, monkeypatch):
    """One text after another: the mixture of the experts and of the product over the subword ids, in plain Python."""
    held = []
    own = lm.learn_pass
    monkeypatch.setattr(lm, "learn_pass", lambda training, model: held.append(model) or own(training, model))
    got = {r["doc_id"]: r for r in lm.scores(docs, default_path()).collect()}
    model = held[-1]
    at = {w: i for i, w in enumerate(model.words.to_pylist())}
    library = encoder(default_path()).library
    unseen = 0.5 / model.denominator
    for doc_id in (1, 3, 10, 20, 25, 31):
        text = next(t for d, t, *_ in make.documents() if d == doc_id) or ""
        text = "".join(c.lower() if "A" <= c <= "Z" else c for c in text)
        ids, score = [model.attention.p["embed"].shape[0] - 1], 0.0
        for word in [*text.split(), ""]:
            pieces = library.encode(word, add_special_tokens=False).ids if word else [len(model.emit) - 1]
            gates = softmax(plain_logits(model.attention, ids)[: model.attention.experts])
            spelled = 1.0 if pieces else 0.0
            for piece in pieces:
                states = softmax(plain_logits(model.attention, ids)[model.attention.experts :])
                spelled *= float(states @ model.emit[piece])
                ids.append(piece)
            counted = model.experts[at[word]] if word in at else np.append(model.lent * unseen, unseen)
            score += math.log10(float(counted @ gates[:-1]) + spelled * float(gates[-1]))
        assert got[doc_id]["score"] == pytest.approx(score, rel=1e-3)


def test_tail_words_have_the_probabilities_of_their_experts(docs, monkeypatch):
    monkeypatch.setattr(lm, "EPOCHS", 0)
    monkeypatch.setattr(lm, "PASSES", 0)
    whole = {r["doc_id"]: r["score"] for r in lm.scores(docs, default_path()).collect()}
    monkeypatch.setattr(lm, "HEAD", 20)
    split = {r["doc_id"]: r["score"] for r in lm.scores(docs, default_path()).collect()}
    assert split == pytest.approx(whole, rel=1e-4)


def test_all_training_documents_teach(docs, monkeypatch):
    learnt, refits = [], []
    own, refit = lm.learn_pass, lm.Clusters.refit
    monkeypatch.setattr(lm, "learn_pass", lambda *given: learnt.append(own(*given)))
    monkeypatch.setattr(lm.Clusters, "refit", lambda self, table, ends: (refits.append(ends.sum()), refit(self, table, ends)))
    monkeypatch.setattr(lm, "TRAIN_DOCS", 20)
    monkeypatch.setattr(lm, "LEARN_EVERY", 1)
    got = lm.scores(docs, default_path()).collect()
    assert learnt == [got[0]["train_tokens"]] * lm.PASSES and refits == [sum(not r["held_out"] for r in got)] * lm.REFITS


def test_blocks_are_drawn_from_all_parts_of_texts():
    texts = pa.array([" ".join(f"w{i}" for i in range(1000)), "", "x y"])
    every = lm.Blocks(texts, 1, 0)
    assert every.counts.sum() == 1002 and every.begin.sum() == 3 and every.end.sum() == 3
    drawn = [lm.Blocks(texts, 4, seed) for seed in range(60)]
    assert 0.15 < np.mean([b.counts.sum() for b in drawn]) / 1002 < 0.35
    assert {w for b in drawn for w in b.values.to_pylist()} >= {f"w{i}" for i in range(1000)}


def test_repeated_rows_null_ids_and_other_columns(spark):
    rows = [(7, "a b c d", "x", 1.0), (7, "a b c d", "x", 1.0), (None, "a b", "y", 2.0), (8, None, "z", 3.0)]
    got = lm.scores(spark.createDataFrame(rows, "doc_id long, text string, word string, score double"), default_path()).collect()
    assert len(got) == 4 and len({r["score"] for r in got if r["doc_id"] == 7}) == 1
    assert sorted(r["n_tokens"] for r in got) == [1, 3, 5, 5]


def test_words_of_the_head_are_encoded_once(monkeypatch):
    """What a word of the head costs a slice is one look-up; ids and places are those of the encoder."""
    texts = pa.array(["Red tail red, zz42", "", "blue tail2"])
    head = lm.Head(pa.array(["", "blue", "red", "zz42"]), default_path())
    plain, library, encoded = lm.Tokens(texts, default_path()), encoder(default_path()), []
    own = type(library)._encode
    monkeypatch.setattr(library, "words", {})
    monkeypatch.setattr(type(library), "_encode", lambda self, word: encoded.append(word) or own(self, word))
    got = lm.Tokens(texts, default_path(), head)
    assert sorted(encoded) == ["red,", "tail", "tail2"]
    for name in ("seq", "after", "text_at", "codes", "owner", "size", "kind"):
        assert np.array_equal(getattr(got, name), getattr(plain, name))
    assert got.place[got.codes].tolist() == [2, 4, 4, 3, 0, 0, 1, 4, 0]


def test_parts_of_coded_texts_are_those_texts(monkeypatch):
    """Distinct words of a run of texts are looked up and encoded once; its parts have the tokens of their own texts."""
    texts = pa.array(["Red tail red, zz42", "", "blue tail2 zz42 tail", "red", "tail2 end"])
    head, library = lm.Head(pa.array(["blue", "red", "zz42"]), default_path()), encoder(default_path())
    monkeypatch.setattr(library, "words", {})
    encoded, own = [], type(library)._encode
    monkeypatch.setattr(type(library), "_encode", lambda self, word: encoded.append(word) or own(self, word))
    parts = list(lm.Coded(texts, head).parts(np.array([18, 0, 20, 3, 9]), 20))
    got = [(rows, lm.Tokens(part, default_path(), head)) for rows, part in parts]
    assert sorted(encoded) == ["end", "red,", "tail", "tail2"]
    assert [(rows.start, rows.stop) for rows, _ in got] == [(0, 2), (2, 3), (3, 5)]
    for rows, tokens in got:
        plain = lm.Tokens(texts[rows.start : rows.stop], default_path())
        for name in ("seq", "after", "text_at", "owner", "size", "kind", "whole", "counts"):
            assert np.array_equal(getattr(tokens, name), getattr(plain, name))
        words, same = [*tokens.words.values.to_pylist(), ""], [*plain.words.values.to_pylist(), ""]
        assert [words[c] for c in tokens.codes] == [same[c] for c in plain.codes]
        assert [tokens.place[c] for c in tokens.codes] == [{"blue": 0, "red": 1, "zz42": 2}.get(same[c], 3) for c in plain.codes]


def test_workers_keep_few_words_and_get_small_batches(docs, monkeypatch):
    """An executor's memory: words kept by the encoder and the text handed over at once are bounded; the session's own bound comes back."""
    name, seen, own = "spark.sql.execution.arrow.maxBytesPerBatch", [], lm.stored
    before = docs.sparkSession.conf.get(name)
    monkeypatch.setattr(lm, "stored", lambda df, at: seen.append(df.sparkSession.conf.get(name)) or own(df, at))
    lm.scores(docs, default_path()).collect()
    assert set(seen) == {str(lm.BATCH_BYTES)} and docs.sparkSession.conf.get(name) == before
    library, head = encoder(default_path()), lm.Head(pa.array(["a"]), default_path())
    monkeypatch.setattr(lm, "KEPT_WORDS", 50)
    for i in range(8):
        lm.Coded(pa.array([" ".join(f"w{i}x{k}" for k in range(40))]), head)
        assert len(library.words) <= 3 * 50
