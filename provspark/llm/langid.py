"""Language identification with interpolated Kneser-Ney character models, one per language.

A word is modelled from its boundary on, up to ``ORDER`` characters back but never over the boundary before it, so a
text's cross-entropy is the sum over its words.  All languages share one sorted array of n-gram hashes per order, beside
a row of discounted masses and one of back-off masses per language; a batch is scored with one binary search per order.
The language of lowest length-normalised cross-entropy wins; its score is calibrated on the training texts, and
``rejected`` marks texts that fit no learned language (cross-entropy above the language's accepted range).

Null texts and texts without a letter are ``und`` with score 0.  Ties go to the language first in order.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Words, crc_mod, slices

ORDER, DISCOUNT = 5, 0.75
#: Bound of the training sample: whole documents per language, taken by hash.
TRAIN_DOCS = 400
#: Words a worker keeps the cross-entropies of.
CACHE_WORDS = 600_000
_MIX = np.uint64(0x9E3779B97F4A7C15)


def letters_of(values: pa.Array) -> pa.Array:
    """Words in lower case with nothing but their letters."""
    return pc.replace_substring_regex(pc.utf8_lower(values), r"[^\p{L}]+", "")


def ngrams(words: list[str], order: int = ORDER) -> tuple[list[np.ndarray], np.ndarray, np.ndarray]:
    """Hashes per order at each predicted character (0 where the word is too short), its word, and its place in it."""
    codes = np.frombuffer((" " + " ".join(words) + " ").encode("utf-32-le"), np.uint32).astype(np.uint64)
    lengths = np.fromiter(map(len, words), np.int64, len(words)) + 1
    word = np.repeat(np.arange(len(words)), lengths)
    place = np.arange(len(word)) - np.repeat(np.cumsum(lengths) - lengths, lengths) + 1  # characters before it in its word
    at = np.arange(1, len(codes))
    hashes, grown = [], np.zeros(len(at), np.uint64)
    for k in range(1, order + 1):
        back = np.maximum(at - k + 1, 0)
        grown = (grown + codes[back] + np.uint64(k)) * _MIX
        grown ^= grown >> np.uint64(29)
        hashes.append(np.where(place >= k - 1, grown | np.uint64(1), np.uint64(0)))
    return hashes, word, place


class Model:
    """langs; per order: sorted hashes, discounted masses and back-off masses [n-grams, languages]; floor: uniform mass."""

    def __init__(self, counts: dict[str, Counter], order: int = ORDER, discount: float = DISCOUNT):
        self.langs = sorted(counts)
        self.order = order
        self.accept = np.full(len(self.langs), np.inf)
        self.sharpness = 20.0
        parts = [self._language(counts[x], order, discount) for x in self.langs]
        self.floor = 1.0 / (1 + max((p[1] for p in parts), default=1))
        self.rest = np.array([p[2] for p in parts], np.float32)
        self.keys, self.mass, self.back = [], [], []
        for k in range(order):
            keys = np.unique(np.concatenate([p[0][k][0] for p in parts] or [np.zeros(0, np.uint64)]))
            mass, back = np.zeros((len(keys), len(self.langs)), np.float32), np.ones((len(keys), len(self.langs)), np.float32)
            for j, (tables, _, _) in enumerate(parts):
                at = np.searchsorted(keys, tables[k][0])
                mass[at, j], back[at, j] = tables[k][1], tables[k][2]
            self.keys.append(keys)
            self.mass.append(mass)
            self.back.append(back)

    @staticmethod
    def _language(counts: Counter, order: int, discount: float):
        """Per order: hashes, discounted mass of each n-gram in its context, back-off mass of it as a context."""
        words = [w for w in counts if w]
        if not words:
            empty = np.zeros(0, np.uint64)
            return [(empty, np.zeros(0), np.zeros(0))] * order, 1, 1.0
        weights = np.array([counts[w] for w in words], float)
        hashes, word, place = ngrams(words, order)
        weight = weights[word]
        found = []
        for k in range(order):
            valid = hashes[k] != 0
            keys, inverse = np.unique(hashes[k][valid], return_inverse=True)
            raw = np.bincount(inverse, weight[valid])
            if k + 1 < order:  # lower orders count the distinct characters before, but for n-grams that begin a word
                longer = hashes[k + 1] != 0
                pairs = np.unique(np.stack([hashes[k][longer], hashes[k + 1][longer]]), axis=1)
                continued = np.bincount(np.searchsorted(keys, pairs[0]), minlength=len(keys)).astype(float)
                first = np.zeros(len(keys), bool)
                first[np.searchsorted(keys, hashes[k][valid & (place == k)])] = True
                raw = np.where(first & (k > 0), raw, np.maximum(continued, 1))
            found.append((keys, raw))
        tables, n_unigrams = [], len(found[0][0])
        context_total = found[0][1].sum()
        back = [np.zeros(len(keys)) + 1.0 for keys, _ in found]
        unigram_mass = np.maximum(found[0][1] - discount, 0) / context_total
        masses = [unigram_mass]
        for k in range(1, order):
            keys, raw = found[k]
            at = np.flatnonzero(hashes[k] != 0)
            one, where = np.unique(hashes[k][at], return_index=True)
            # the context of an n-gram is the (k)-gram one character earlier
            context = np.where(at[where] > 0, hashes[k - 1][at[where] - 1], 0)
            space = place[at[where]] == k
            known, inverse = np.unique(np.where(space & (k == 1), np.uint64(0), context), return_inverse=True)
            total = np.bincount(inverse, raw)
            types = np.bincount(inverse)
            masses.append(np.maximum(raw - discount, 0) / total[inverse])
            lower = found[k - 1][0]
            spots = np.searchsorted(lower, known)
            real = (spots < len(lower)) & (known != 0)
            real[real] = lower[spots[real]] == known[real]
            back[k - 1][spots[real]] = np.minimum(1.0, discount * types[real] / total[real])
        for k in range(order):
            tables.append((found[k][0], masses[k], back[k]))
        return tables, n_unigrams, min(1.0, discount * n_unigrams / context_total)

    def cross_entropies(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Summed negative log2 probability per word and language; characters predicted per word."""
        hashes, word, place = ngrams(words, self.order)
        p = np.full((len(word), len(self.langs)), self.floor, np.float32)
        before = np.ones_like(p)
        for k in range(self.order):
            keys = self.keys[k]
            if not len(keys):
                continue
            at = np.minimum(np.searchsorted(keys, hashes[k]), len(keys) - 1)
            hit = keys[at] == hashes[k]
            mass = np.where(hit[:, None], self.mass[k][at], np.float32(0))
            if k == 0:
                p = mass + self.rest * p
            else:
                usable = (place >= k)[:, None]
                p = np.where(usable & (before < 1), mass + before * p, p)
            # the n-gram at a character is the context of the next one in its word
            back = np.where(hit[:, None], self.back[k][at], np.float32(1))
            before = np.ones_like(p)
            before[1:] = np.where((place[1:] > 1)[:, None], back[:-1], np.float32(1))
        bits = -np.log2(np.maximum(p, 1e-12))
        edges = np.flatnonzero(place == 1)
        return np.add.reduceat(bits, edges, axis=0) if len(edges) else np.zeros((0, len(self.langs))), np.bincount(word, minlength=len(words))

    def texts(self, texts: pa.Array, cache: dict[str, int], store: list) -> tuple[np.ndarray, np.ndarray]:
        """Cross-entropy per character and language, and characters, of each text."""
        words = Words(texts, lower=False)
        plain = letters_of(words.values)
        coded = plain.dictionary_encode()
        distinct = coded.dictionary.to_pylist()
        new = [w for w in distinct if w and w not in cache]
        if new:
            bits, length = self.cross_entropies(new)
            rows = np.concatenate([bits, length[:, None]], 1).astype(np.float32)
            base = sum(len(x) for x in store)
            store.append(rows)
            cache.update((w, base + i) for i, w in enumerate(new))
        every = np.concatenate([*store, np.zeros((1, len(self.langs) + 1), np.float32)])
        if len(store) > 1:
            store[:] = [every[:-1]]
        at = np.fromiter((cache[w] if w else -1 for w in distinct), np.int64, len(distinct))
        per_word = every[at][coded.indices.to_numpy(zero_copy_only=False)] if len(distinct) else np.zeros((0, len(self.langs) + 1), np.float32)
        sums = words.sums(per_word[words.codes].astype(np.float64)) if len(words.codes) else np.zeros((len(texts), len(self.langs) + 1))
        chars = sums[:, -1]
        return sums[:, :-1] / np.maximum(chars, 1)[:, None], chars

    def calibrate(self, texts: list[str], langs: list[str]) -> None:
        """Accepted range of cross-entropy per language, and the sharpness of the score of most likelihood."""
        if not texts:
            return
        entropy, chars = self.texts(pa.array(texts), {}, [])
        gold = np.array([self.langs.index(x) for x in langs])
        use = chars > 0
        for j in range(len(self.langs)):
            own = entropy[use & (gold == j), j]
            if len(own):
                self.accept[j] = np.quantile(own, 0.995) + 0.5
        best = None
        for sharpness in (5.0, 10.0, 20.0, 40.0, 80.0):
            p = self.posterior(entropy[use], chars[use], sharpness)
            fit = np.log(np.maximum(p[np.arange(use.sum()), gold[use]], 1e-4)).sum()
            if best is None or fit > best:
                best, self.sharpness = fit, sharpness

    @staticmethod
    def posterior(entropy: np.ndarray, chars: np.ndarray, sharpness: float) -> np.ndarray:
        z = -entropy * np.minimum(chars, sharpness)[:, None] * np.log(2)
        e = np.exp(z - z.max(1, keepdims=True))
        return e / e.sum(1, keepdims=True)


def train(docs: DataFrame, per_language: int = TRAIN_DOCS) -> Model:
    """Fit on docs (text, lang) with a label: at most about ``per_language`` whole documents a language, by hash."""
    labelled = docs.where("lang is not null and text is not null").select("doc_id", F.col("lang").cast("string").alias("lang"), "text")
    share = {r["lang"]: min(1.0, per_language / r["n"]) for r in labelled.groupBy("lang").agg(F.count("*").alias("n")).collect()}
    if not share:
        return Model({})
    limit = F.create_map(*[F.lit(x) for pair in share.items() for x in pair])[F.col("lang")]
    sample = labelled.where(F.pmod(F.xxhash64("doc_id"), F.lit(1_000_000)) < limit * 1_000_000).select("doc_id", "lang", "text").collect()
    sample.sort(key=lambda r: (str(r["doc_id"]), r["lang"], r["text"]))
    counts: dict[str, Counter] = {x: Counter() for x in share}
    for r in sample:
        counts[r["lang"]].update(letters_of(pa.array(r["text"].split())).to_pylist() if r["text"].split() else [])
    for c in counts.values():
        c.pop("", None)
    model = Model(counts)
    model.calibrate([r["text"] for r in sample], [r["lang"] for r in sample])
    return model


_OUT = "doc_id long, held_out boolean, lang_pred string, score double, cross_entropy double, rejected boolean"


def _predict(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model: Model = shared.value
        names = pa.array([*model.langs, "und"])
        cache: dict[str, int] = {}
        store: list = []
        for batch in slices(batches):
            n = batch.num_rows
            if model.langs:
                if len(cache) > CACHE_WORDS:
                    cache, store = {}, []
                entropy, chars = model.texts(pc.fill_null(batch.column("text"), ""), cache, store)
                best = entropy.argmin(1)
                score = model.posterior(entropy, chars, model.sharpness)[np.arange(n), best]
                least = entropy[np.arange(n), best]
                none = chars == 0
                rejected = none | (least > model.accept[best])
            else:
                best, score, least, none, rejected = np.zeros(n, int), np.zeros(n), np.zeros(n), np.ones(n, bool), np.ones(n, bool)
            pick = np.where(none, len(model.langs), best)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("held_out"), names.take(pa.array(pick)), pa.array(np.where(none, 0.0, score)), pa.array(np.where(none, 0.0, least).astype(float)), pa.array(rejected)], _OUT.replace(" long", "").replace(" boolean", "").replace(" string", "").replace(" double", "").split(", "))

    return run


def identify(docs: DataFrame, modulus: int = 4, held: int = 2, per_language: int = TRAIN_DOCS) -> DataFrame:
    """One row per document: doc_id, held_out, lang_pred, score, cross_entropy, rejected."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", "lang", (crc_mod("doc_id", modulus) == held).alias("held_out"))
    model = docs.sparkSession.sparkContext.broadcast(train(rows.where("not held_out"), per_language))
    return rows.select("doc_id", "text", "held_out").mapInArrow(_predict(model), _OUT)
