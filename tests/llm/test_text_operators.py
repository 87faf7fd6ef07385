"""The operators on small tables with nulls, empty and long texts, ties, repeated rows and extra columns."""

import hashlib
import re
import zlib
from collections import Counter

import numpy as np
import pytest

from . import cases as make

WORD = re.compile(r"[^\x20\x09-\x0D]+")
DOCS = make.documents()


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(DOCS, make.SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def nothing(spark):
    return spark.createDataFrame([], make.SCHEMA)


def lowered(text):
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")


def test_quality_measures(docs, nothing):
    from provspark.llm import quality

    got = {r["doc_id"]: r for r in quality.judged(docs.select("doc_id", "text")).collect()}
    for doc_id, text, *_ in DOCS:
        words = WORD.findall(text or "")
        assert got[doc_id]["n_words"] == len(words) and got[doc_id]["word_chars"] == sum(map(len, words))
        lines = [x for x in (text or "").split("\n") if WORD.search(x)]
        assert got[doc_id]["n_dup_lines"] == len(lines) - len(set(lines))
        windows = Counter(tuple(words[i : i + 8]) for i in range(len(words) - 7))
        covered = {j for i in range(len(words) - 7) if windows[tuple(words[i : i + 8])] > 1 for j in range(i, i + 8)}
        assert got[doc_id]["n_repeat_words"] == len(covered)
    assert quality.judged(nothing).count() == 0
    assert quality.kept(docs.withColumnRenamed("source", "n_words")).columns == ["doc_id", "text", "lang", "n_words"]


def test_jaccard_components(docs, nothing):
    from provspark.llm import jaccard_join

    def grams(text):
        words = WORD.findall(lowered(text))
        return {tuple(words)} - {()} if len(words) < 5 else set(zip(*(words[k:] for k in range(5)), strict=False))

    sets = {d: grams(t) for d, t, *_ in DOCS}
    label = {d: d for d in sets}
    moved = True
    while moved:
        moved = False
        for a in sets:
            for b in sets:
                both = len(sets[a] & sets[b])
                if both and 100 * both >= 80 * len(sets[a] | sets[b]) and label[a] != label[b]:
                    label[a] = label[b] = min(label[a], label[b])
                    moved = True
    got = {r["doc_id"]: r for r in jaccard_join.joined(docs).collect()}
    assert {d: r["component_id"] for d, r in got.items()} == label
    assert {d: r["n_shingles"] for d, r in got.items()} == {d: len(s) for d, s in sets.items()}
    assert jaccard_join.joined(nothing).count() == 0


@pytest.mark.parametrize("size", [1, 2, 5, 9, 40, 130, 700])
def test_pigeonhole_signatures_meet(size):
    """Sets that link share a signature, whatever their sizes."""
    import pyarrow as pa

    from provspark.llm import jaccard_join as j

    rng = np.random.default_rng(size)
    for _ in range(12):
        a = [f"w{x}" for x in rng.integers(0, 10**6, size + 4)]
        b = list(a)
        for at in rng.integers(0, len(b), max(1, size // 60)):
            b[at] = "changed"
        sets = j.Sets(pa.array([" ".join(a), " ".join(b)]))
        x, y = (sets.items[sets.starts[i] : sets.starts[i + 1]] for i in (0, 1))
        who, sig = j.signatures(sets, np.array([0, 1]))
        if j.links(x, y):
            assert set(sig[who == 0].tolist()) & set(sig[who == 1].tolist())


def test_token_files_round_trip(docs, nothing):
    from tokenizers import Tokenizer

    from provspark.llm import token_files
    from provspark.llm.subwords import default_path

    library, start = Tokenizer.from_file(default_path()), 0
    got = {r["doc_id"]: r for r in token_files.token_files(docs, default_path()).collect()}
    for doc_id, text, *_ in sorted(DOCS):
        ids = [*library.encode(text or "", add_special_tokens=False).ids, 2]
        assert (got[doc_id]["start"], got[doc_id]["n_tokens"]) == (start, len(ids))
        assert got[doc_id]["ids_crc32"] == zlib.crc32(np.array(ids, "<u4").tobytes())
        start += len(ids)
    assert token_files.token_files(nothing, default_path()).count() == 0


def test_rank_code():
    from provspark.llm.token_files import decode_ranks, encode_ranks

    for ranks in ([], [0], [255, 256, 65_535, 65_536, 2**24, 2**32 - 1, 7]):
        control, data = encode_ranks(np.array(ranks, np.uint32))
        assert decode_ranks(control, data, len(ranks)).tolist() == ranks


def test_packing_covers_every_token_once(docs, nothing):
    from provspark.llm import packing
    from provspark.llm.subwords import default_path

    rows = packing.pack(docs, default_path(), 64).collect()
    by = {}
    for r in rows:
        by.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
        assert r["length"] <= 64 and r["start"] == 64 * r["piece"]
    for places in by.values():
        at = 0
        for offset, length in sorted(places):
            assert offset == at
            at += length
        assert at <= 64
    assert len({(r["doc_id"], r["piece"]) for r in rows}) == len(rows)
    assert packing.pack(nothing, default_path()).count() == 0


def test_packing_is_near_the_bound():
    from provspark.llm.packing import plan

    rng = np.random.default_rng(1)
    need = np.bincount(rng.integers(1, 900, 3000), minlength=1025)[:1025]
    found = plan(need, 1024)
    used = np.zeros(1025, int)
    for config, times in found.chosen:
        assert sum(config) <= 1024
        np.add.at(used, config, times)
    assert (used == need).all()
    assert found.placed >= 0.9 * need.sum()  # by the program, the rest by best fit
    assert sum(t for _, t in found.chosen) <= 1.005 * -(-(need * np.arange(1025)).sum() // 1024) + 1


def test_knapsack_against_all_multisets():
    import itertools

    from provspark.llm.packing import knapsack

    rng = np.random.default_rng(2)
    for _ in range(30):
        value, most = np.zeros(13), np.zeros(13, int)
        kinds = rng.choice(np.arange(1, 13), 4, replace=False)
        value[kinds], most[kinds] = rng.random(4), rng.integers(1, 5, 4)
        best = max(sum(n * value[k] for n, k in zip(ns, kinds, strict=True)) for ns in itertools.product(*(range(most[k] + 1) for k in kinds)) if sum(n * k for n, k in zip(ns, kinds, strict=True)) <= 12)
        got = knapsack(value, most, 12)
        assert sum(k * n for k, n in got.items()) <= 12 and all(n <= most[k] for k, n in got.items())
        assert sum(n * value[k] for k, n in got.items()) == pytest.approx(best)


def test_fractional_solution_covers_every_length():
    from provspark.llm.packing import fractional

    need = np.bincount([7, 7, 7, 5, 5, 3, 2, 2, 2, 2], minlength=13)
    covered = np.zeros(13)
    for config, times in fractional(need, 12, np.random.default_rng(0)):
        assert sum(k * n for k, n in config.items()) <= 12
        for k, n in config.items():
            covered[k] += n * times
    assert (covered >= need - 1e-9).all()


def test_packed_ids_are_those_of_the_library(docs):
    from tokenizers import Tokenizer

    from provspark.llm import packing
    from provspark.llm.subwords import default_path

    library = Tokenizer.from_file(default_path())
    texts = {d: t or "" for d, t, *_ in DOCS}
    for r in packing.pack(docs, default_path(), 64).collect():
        ids = [*library.encode(texts[r["doc_id"]], add_special_tokens=False).ids, 1][r["start"] : r["start"] + 64]
        assert len(ids) == r["length"] and zlib.crc32(np.array(ids, "<u4").tobytes()) == r["ids_crc32"]


def test_mixing_meets_targets(docs, nothing):
    from provspark.llm import mixing

    rows = mixing.copies(docs).collect()
    assert len(rows) == len(DOCS) and all(0 <= r["copies"] <= 3 for r in rows)
    total = sum(r["size"] for r in rows)
    targets = {r["key"]: r["target"] for r in rows}
    assert sum(targets.values()) <= total + 1e-6
    for key, target in targets.items():
        own = [r for r in rows if r["key"] == key]
        assert abs(sum(r["copies"] * r["size"] for r in own) - target) <= max(r["size"] for r in own)
    assert sorted(map(tuple, mixing.copies(docs).collect())) == sorted(map(tuple, rows))
    assert mixing.copies(nothing).count() == 0


def test_personal_data_base_spans_stay(docs, nothing):
    from provspark.llm import pii

    got = {r["doc_id"]: r for r in pii.report(docs).collect()}
    for doc_id, text, *_ in DOCS:
        base = pii.digest(pii.base_spans(text or ""))
        assert got[doc_id]["base_sha256"] == hashlib.sha256(base.encode()).hexdigest()
        assert set(filter(None, base.split(","))) <= set(got[doc_id]["spans"].split(","))
    assert pii.report(nothing).count() == 0
    clean = {r["doc_id"]: r["text"] for r in pii.redacted(docs).collect()}
    assert "<EMAIL>" in clean[3] and "@" not in clean[3] and clean[1] is None


def test_fingerprints_of_edits_and_neighbours(docs, nothing):
    from provspark.llm import fingerprints

    got = {r["doc_id"]: r for r in fingerprints.with_neighbours(docs).collect()}
    order = sorted(DOCS, key=lambda r: -r[0])
    for (doc_id, text, *_), after in zip(order, order[1:] + order[:1], strict=True):
        text, follow = text or "", after[1] or ""
        new = text[: len(text) - len(text) // 3] + follow[: len(text) // 3]
        r = got[doc_id]
        assert r["n_chars"] == len(text) and r["edited_sha256"] == hashlib.sha256(new.encode()).hexdigest()
        assert 0 <= r["near_next"] <= 1
        assert doc_id <= 30 or r["near_edited"] > 0.4 > r["near_next"]  # the others are small, equal or near each other
    prints = {}
    for doc_id, text, *_ in DOCS:
        prints.setdefault(text or "", set()).add(got[doc_id]["fingerprint"])
    assert all(len(x) == 1 for x in prints.values())
    assert fingerprints.with_neighbours(nothing).count() == 0


def test_language_model_scores(docs, nothing):
    from provspark.llm import lm_scoring
    from provspark.llm.subwords import default_path

    tokens = {d: [*WORD.findall(lowered(t)), None] for d, t, *_ in DOCS}
    held = {d: zlib.crc32(str(d).encode()) % 5 == 1 for d in tokens}
    counts = Counter(x for d, ts in tokens.items() if not held[d] for x in ts)
    n, v = sum(counts.values()), len(counts)
    got = {r["doc_id"]: r for r in lm_scoring.scores(docs, default_path()).collect()}
    for d, ts in tokens.items():
        base = sum(np.log10((counts[x] + 0.5) / (n + 0.5 * (v + 1))) for x in ts)
        r = got[d]
        assert (r["held_out"], r["n_tokens"], r["n_known"], r["train_tokens"]) == (held[d], len(ts), sum(counts[x] > 0 for x in ts), n)
        assert r["base_score"] == pytest.approx(base) and np.isfinite(r["score"]) and r["score"] < 0
    assert lm_scoring.scores(nothing, default_path()).count() == 0


def test_language_identification(docs, nothing):
    from provspark.llm import langid

    got = {r["doc_id"]: r for r in langid.identify(docs).collect()}
    assert got[1]["lang_pred"] == got[2]["lang_pred"] == got[5]["lang_pred"] == "und"
    right = [got[d]["lang_pred"] == lang for d, text, lang, _ in DOCS if lang and text and len(text) > 60]
    assert np.mean(right) > 0.9
    assert langid.identify(nothing).count() == 0


def test_toxicity(spark, docs, nothing):
    from provspark.llm import toxicity

    labels = spark.createDataFrame([(d, 1 if "vorgle" in (t or "") else 0) for d, t, *_ in DOCS], "doc_id long, toxic int")
    got = {r["doc_id"]: r for r in toxicity.scored(docs, labels).collect()}
    assert len(got) == len(DOCS) and all(0 <= r["score"] <= 1 for r in got.values())
    toxic = [got[d]["score"] for d, t, *_ in DOCS if "vorgle" in (t or "")]
    clean = [got[d]["score"] for d, t, *_ in DOCS if "vorgle" not in (t or "")]
    assert min(toxic) > max(clean)
    assert toxicity.scored(nothing, labels).count() == 0


def test_levenshtein_automaton():
    import pyarrow as pa

    from provspark.llm.toxicity import Automaton

    a = Automaton(["stupid", "scum"], ["lowe"])
    words = ["stupid", "stupd", "stuppid", "stupit", "stipit", "scum", "scam", "lowehr", "low", ""]
    assert a.match(pa.array(words)).tolist() == [0, 1, 1, 1, -1, 2, -1, 4, -1, -1]


def test_viterbi_against_all_paths():
    import itertools

    from provspark.llm import pii

    field = pii.Field()
    rng = np.random.default_rng(0)
    field.index = {f"f{i}": i for i in range(4)}
    field.weights, field.moves = rng.normal(size=(4, len(pii.LABELS))), rng.normal(size=(len(pii.LABELS),) * 2)
    sequence = [["f0", "f1"], ["f2"], ["f3", "f0"]]
    best = None
    for path in itertools.product(range(len(pii.LABELS)), repeat=3):
        if not field.start[path[0]] or not all(field.allowed[a, b] for a, b in itertools.pairwise(path)):
            continue
        z = sum(field.weights[[field.index[f] for f in fs], p].sum() for fs, p in zip(sequence, path, strict=True)) + sum(field.moves[a, b] for a, b in itertools.pairwise(path))
        if best is None or z > best[0]:
            best = z, list(path)
    assert field.decode([sequence, sequence[:1]])[0] == best[1]
