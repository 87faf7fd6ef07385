"""Toxicity: a learned lexicon, misspellings by Levenshtein automata over its trie, and scores of the words around a hit.

The lexicon comes from labelled training documents alone: words, and stems with many endings, that occur in toxic ones
far beyond chance.  The trie of the lexicon is intersected with the Levenshtein automaton of distance one and made
deterministic once; every distinct word of a batch then runs through its transition table together, in numpy.  Terms of
fewer than ``FUZZY_LENGTH`` letters match exactly, stems match as prefixes.  What near spellings are worth is learned
too, and spellings that clean documents use stay clean.

A hit counts by its context window: less where a quotation is open around it, or near words that training found beside
hits of clean documents.  How far the hits of a term exceed what clean texts of that length have is a feature of a
logistic model.

Null and empty texts score as texts without a hit.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Words, crc_mod, slices

#: Bound of the labelled training sample, whole documents taken by hash; most terms of the lexicon.
TRAIN_DOCS, MOST_TERMS = 4000, 400
#: Letters of a stem; letters from which a term may be misspelled; words each side of a hit.
STEM_LENGTHS, FUZZY_LENGTH, REACH = range(4, 9), 5, 6
#: Precision of a term and of a stem, log odds beyond chance that they need (over all candidates), and what a quotation
#: takes away.
PRECISION, STEM_PRECISION, EVIDENCE, QUOTED = 0.9, 0.4, 3.0, -4.0
THRESHOLD = 0.7

#: Marks that open or close a quotation.
QUOTES = "\"“”„«»‹›‘’'"
_TRIM = r"^[^\p{L}\p{N}]+|[^\p{L}\p{N}]+$"


def plain(values: pa.Array) -> pa.Array:
    """Words in lower case without the signs around them."""
    return pc.replace_substring_regex(pc.utf8_lower(values), _TRIM, "")


class Automaton:
    """Deterministic union of the Levenshtein automata (distance one) of all terms and of the prefix automata of stems.

    ``final[state]``: 2 * term for an exact match, 2 * term + 1 for a near one, -1 for none; ``sticky[state]``: a stem
    matched on the way.
    """

    def __init__(self, terms: list[str], stems: list[str], fuzzy_length: int = FUZZY_LENGTH):
        self.names = [*terms, *stems]
        children: list[dict[str, int]] = [{}]
        ends: list[int] = [-1]
        for i, name in enumerate(self.names):
            node = 0
            for c in name:
                if c not in children[node]:
                    children[node][c] = len(children)
                    children.append({})
                    ends.append(-1)
                node = children[node][c]
            ends[node] = i
        # nodes on the way to a term that may be misspelled
        lenient = [False] * len(children)
        for name in terms:
            if len(name) >= fuzzy_length:
                node = 0
                lenient[0] = True
                for c in name:
                    node = children[node][c]
                    lenient[node] = True
        alphabet = sorted({c for name in self.names for c in name})
        self.codes = np.array([ord(c) for c in alphabet], np.uint32)
        self.longest = max(map(len, self.names), default=0) + 1

        def closed(states: set[tuple[int, int]]) -> frozenset[tuple[int, int]]:
            for node, edits in list(states):
                if not edits and lenient[node]:  # a letter of the term left out
                    states.update((child, 1) for child in children[node].values() if lenient[child])
            return frozenset(x for x in states if not (x[1] and (x[0], 0) in states))

        begin = closed({(0, 0)})
        number, table, todo = {begin: 1, frozenset(): 0}, [[0] * (len(alphabet) + 1)], [begin]
        while todo:
            current = todo.pop(0)
            row = []
            for c in [*alphabet, None]:
                after: set[tuple[int, int]] = set()
                for node, edits in current:
                    if c in children[node]:
                        after.add((children[node][c], edits))
                    if not edits and lenient[node]:
                        after.add((node, 1))  # a letter too many
                        after.update((child, 1) for k, child in children[node].items() if k != c and lenient[child])
                target = closed(after)
                if target not in number:
                    number[target] = len(number)
                    todo.append(target)
                row.append(target)
            table.append(row)
        rows: list = [None] * len(number)
        rows[0] = table[0]
        order = [begin, *[s for s in number if s != begin and s]]
        for state, row in zip(order, table[1:], strict=True):
            rows[number[state]] = [number[t] for t in row]
        self.moves = np.array(rows, np.int32)
        self.final = np.full(len(number), -1, np.int32)
        self.sticky = np.full(len(number), -1, np.int32)
        for state, at in number.items():
            exact = [ends[n] for n, e in state if not e and ends[n] >= 0]
            near = sorted(ends[n] for n, e in state if e and 0 <= ends[n] < len(terms) and len(self.names[ends[n]]) >= fuzzy_length)
            whole = [i for i in exact if i < len(terms)]
            self.final[at] = 2 * whole[0] if whole else 2 * near[0] + 1 if near else -1
            stem = [i for i in exact if i >= len(terms)]
            self.sticky[at] = 2 * stem[0] if stem else -1

    def match(self, words: pa.Array) -> np.ndarray:
        """2 * term, + 1 for a near spelling, of each word; -1 for none."""
        text = "\0".join(words.to_pylist()) + "\0"
        codes = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
        ends = np.flatnonzero(codes == 0)[: len(words)] if len(words) else np.zeros(0, np.int64)
        begins = np.concatenate([[0], ends[:-1] + 1]) if len(words) else ends
        at = np.minimum(np.searchsorted(self.codes, codes), max(0, len(self.codes) - 1))
        kinds = np.where(self.codes[at] == codes, at, len(self.codes)).astype(np.int32) if len(self.codes) else np.zeros(len(codes), np.int32)
        hit, state, live = np.full(len(words), -1, np.int32), np.ones(len(words), np.int32), np.arange(len(words))
        stem = hit.copy()
        for t in range(self.longest + 1):
            over = begins[live] + t >= ends[live]
            hit[live[over]] = self.final[state[live[over]]]
            live = live[~over]
            if not len(live):
                break
            state[live] = self.moves[state[live], kinds[begins[live] + t]]
            found = self.sticky[state[live]]
            stem[live] = np.where(found >= 0, found, stem[live])
            live = live[state[live] > 0]
        return np.where((hit >= 0) & (hit % 2 == 0), hit, np.where(stem >= 0, stem, hit))


@dataclass
class Model:
    automaton: Automaton
    weights: np.ndarray  # of the features of 2 * term (+ 1 for near spellings)
    usual: np.ndarray  # how often a word hits it in clean documents that have it
    clean: frozenset[str] = frozenset()
    context: dict[str, float] = field(default_factory=dict)
    rest: float = -3.0


def hits(words: Words, model: Model) -> tuple[np.ndarray, np.ndarray]:
    """Positions of the words that hit, and what they hit."""
    shapes = plain(words.values).dictionary_encode()
    found = model.automaton.match(shapes.dictionary)
    for i in np.flatnonzero(found % 2 == 1).tolist():
        if shapes.dictionary[i].as_py() in model.clean:
            found[i] = -1
    if not len(words.codes):
        return np.zeros(0, np.int64), np.zeros(0, np.int32)
    per_word = found[shapes.indices.to_numpy(zero_copy_only=False)][words.codes]
    at = np.flatnonzero(per_word >= 0)
    return at, per_word[at]


def windows(words: Words, at: np.ndarray) -> Iterator[tuple[int, list[str], int]]:
    """Text, words of the window and place of the hit in it."""
    rows = np.searchsorted(words.starts, at, "right") - 1
    for i, row in zip(at.tolist(), rows.tolist(), strict=True):
        low, high = max(int(words.starts[row]), i - REACH), min(int(words.starts[row + 1]), i + REACH + 1)
        yield row, words.values.take(pa.array(words.codes[low:high])).to_pylist(), i - low


def quoted(window: list[str], place: int) -> bool:
    """Whether a quotation is open at the hit."""
    before, own = " ".join(window[:place]), window[place]
    if own[0] in QUOTES:
        return True
    opened = sum(c in QUOTES for w in before.split() for c in (w[:1], w[-1:]) if not (len(w) == 1 and c == w[-1:]))
    return opened % 2 == 1 and any(w[-1:] in QUOTES or w.rstrip(".,;:!?")[-1:] in QUOTES for w in window[place:])


def standing(window: list[str], place: int, context: dict[str, float]) -> float:
    """What a hit counts in its context: 1, less in a quotation or near words of clean contexts."""
    near = {re.sub(r"\W+", "", w.lower()) for i, w in enumerate(window) if i != place}
    z = (QUOTED if quoted(window, place) else 0.0) + max(-2.0, min(0.0, sum(context.get(w, 0.0) for w in near)))
    return float(np.exp(z))


def text_features(texts: pa.Array, model: Model) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(text, hit, value): how far hits exceed what a clean text of that length would have."""
    words = Words(texts, lower=False)
    at, what = hits(words, model)
    found: Counter = Counter()
    for (row, window, place), hit in zip(windows(words, at), what.tolist(), strict=True):
        found[row, hit] += standing(window, place, model.context)
    keys = sorted(found)
    rows, kinds = np.array([k[0] for k in keys], int), np.array([k[1] for k in keys], int)
    value = np.log((np.array([found[k] for k in keys]) + 0.5) / (model.usual[kinds] * words.counts[rows] + 0.05)) if keys else np.zeros(0)
    return rows, kinds, np.maximum(value, 0)


def text_scores(texts: pa.Array, model: Model) -> np.ndarray:
    rows, kinds, value = text_features(texts, model)
    z = np.full(len(texts), model.rest)
    np.add.at(z, rows, model.weights[kinds] * value)
    return 1 / (1 + np.exp(-z))


def distinct_documents(texts: list[str], labels: list[int]) -> tuple[list[set[str]], list[int], list[int]]:
    """Word sets, labels and places of documents, one of each group that begins or ends alike: copies would count again."""
    seen: set[tuple[str, ...]] = set()
    sets, kept, places = [], [], []
    for i, (text, label) in enumerate(zip(texts, labels, strict=True)):
        words = text.split()
        keys = {("first", *words[:5]), ("last", *words[-5:])}
        if len(words) >= 5 and keys & seen:
            continue
        seen |= keys
        sets.append({w for w in plain(pa.array(words, pa.string())).to_pylist() if w})
        kept.append(label)
        places.append(i)
    return sets, kept, places


def lexicon(sets: list[set[str]], labels: list[int]) -> tuple[list[str], list[str]]:
    """Terms and stems: those of most evidence first; what begins like a chosen stem, or the other way round, is left out."""
    counts, forms = {0: Counter(), 1: Counter()}, {}
    for words, label in zip(sets, labels, strict=True):
        counts[label].update(words)
        counts[label].update({f"{w[:k]}*" for w in words for k in STEM_LENGTHS if len(w) > k})
    share = max(sum(labels), 1) / max(len(labels), 1)
    often = {w: n for w, n in counts[1].items() if n >= 3 and len(w) >= 3}
    for w, n in counts[1].items():
        if w[-1:] != "*":
            for k in STEM_LENGTHS:
                if f"{w[:k]}*" in often and len(w) > k:
                    forms.setdefault(f"{w[:k]}*", []).append(n)
    chance = np.log(len(often) + 1)
    evidence = {}
    for w, bad in often.items():
        good = counts[0][w]
        p = bad / (bad + good)
        if p < (PRECISION if w[-1] != "*" else STEM_PRECISION):
            continue
        if w[-1] == "*" and (len(forms.get(w, ())) < 4 or max(forms[w]) > 0.5 * bad):
            continue
        gain = bad * np.log(p / share) + (good * np.log((1 - p) / (1 - share)) if good else 0.0)
        if gain - chance > EVIDENCE:
            evidence[w] = gain
    terms, stems = [], []
    for w in sorted(evidence, key=lambda x: (-evidence[x], x))[: 4 * MOST_TERMS]:
        name = w.rstrip("*")
        if any(name.startswith(x) or x.startswith(name) and w[-1] == "*" for x in stems):
            continue
        if len(terms) + len(stems) < MOST_TERMS:
            (stems if w[-1] == "*" else terms).append(name)
    return [t for t in terms if not any(t.startswith(x) for x in stems)], stems


def logistic(x: np.ndarray, y: np.ndarray, decay: float = 0.05, rounds: int = 25) -> tuple[np.ndarray, float]:
    """Ridge-penalised logistic regression by Newton steps; features are evidence for toxicity, so no weight is negative."""
    z = np.concatenate([x, np.ones((len(x), 1))], 1)
    w = np.zeros(z.shape[1])
    penalty = np.append(np.full(x.shape[1], decay), 1e-3)
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(z @ w, -30, 30)))
        step = np.linalg.solve((z * (p * (1 - p))[:, None]).T @ z + np.diag(penalty), z.T @ (p - y) + penalty * w)
        w -= step
        w[:-1] = np.maximum(w[:-1], 0)
        if np.abs(step).max() < 1e-6:
            break
    return w[:-1], float(w[-1])


def fit(texts: list[str], labels: list[int]) -> Model:
    """From labelled texts; without toxic ones the lexicon is empty and all scores are the prior."""
    sets, kept, chosen = distinct_documents(texts, labels)
    terms, stems = lexicon(sets, kept)
    n = len(terms) + len(stems)
    model = Model(Automaton(terms, stems), np.zeros(2 * n + 1), np.zeros(2 * n + 1))
    # near spellings that clean documents use are clean
    every = sorted(set().union(*sets)) if sets else []
    found = dict(zip(every, model.automaton.match(pa.array(every, pa.string())).tolist(), strict=True)) if every else {}
    usage: dict[int, Counter] = {0: Counter(), 1: Counter()}
    for words, label in zip(sets, kept, strict=True):
        usage[label].update(w for w in words if found[w] % 2 == 1 and found[w] > 0)
    model.clean = frozenset(w for w in usage[0] if usage[0][w] >= 2 or usage[0][w] > usage[1][w])
    texts, y = [texts[i] for i in chosen], np.array(kept, float)
    total, around = np.zeros(2 * n + 1), {0: Counter(), 1: Counter()}
    spans = np.zeros(2 * n + 1)
    for a in range(0, len(texts), 200):
        words = Words(pa.array(texts[a : a + 200], pa.string()), lower=False)
        at, what = hits(words, model)
        rows = np.searchsorted(words.starts, at, "right") - 1
        good = y[a + rows] == 0
        np.add.at(total, what[good], 1)
        pairs = np.unique(np.stack([rows[good], what[good]]), axis=1)
        np.add.at(spans, pairs[1], words.counts[pairs[0]])
        for row, window, place in windows(words, at):
            around[int(y[a + row])].update({re.sub(r"\W+", "", w.lower()) for i, w in enumerate(window) if i != place})
    model.usual = np.where(spans >= 2000, total / np.maximum(spans, 1), 0.0)
    if sum(around[0].values()) >= 200:  # with fewer clean hits no context can be told from another
        totals = {k: max(1, sum(around[k].values())) for k in (0, 1)}
        for w in around[0].keys() | around[1].keys():
            if w and around[0][w] + around[1][w] >= 20:
                model.context[w] = 0.2 * float(np.clip(np.log((around[1][w] + 5) / totals[1]) - np.log((around[0][w] + 5) / totals[0]), -2, 0))
    x = np.zeros((len(texts), 2 * n + 1))
    for a in range(0, len(texts), 200):
        rows, kinds, value = text_features(pa.array(texts[a : a + 200], pa.string()), model)
        np.add.at(x, (a + rows, kinds), value)
    model.weights, model.rest = logistic(x, y) if len(y) and y.any() else (np.zeros(2 * n + 1), -3.0)
    # a near spelling that training hardly saw is worth a share of the term itself, by the length of the term
    for i, name in enumerate(terms):
        if (x[:, 2 * i + 1] > 0).sum() < 5:
            model.weights[2 * i + 1] = model.weights[2 * i] * (0.9 if len(name) >= 6 else 0.5)
    return model


def train(docs: DataFrame, labels: DataFrame, most: int = TRAIN_DOCS) -> Model:
    """Fit on at most about ``most`` labelled rows of docs; several labels of one document count as toxic if any is."""
    marks = labels.where("toxic is not null").groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max("toxic").alias("toxic"))
    marked = docs.where("text is not null").select("doc_id", "text").join(marks, "doc_id")
    n = docs.select("doc_id").join(marks, "doc_id").count()
    part = marked.where(F.pmod(F.xxhash64("doc_id", F.lit(3)), F.lit(1_000_000)) < 1_000_000 * min(1.0, most / max(1, n)))
    rows = sorted((r["doc_id"], r["text"], int(r["toxic"])) for r in part.collect())
    return fit([r[1] for r in rows], [int(r[2] > 0) for r in rows])


_OUT = "doc_id long, held_out boolean, score double, predicted int"


def _predict(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = shared.value
        for batch in slices(batches):
            score = text_scores(batch.column("text"), model)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("held_out"), pa.array(score), pa.array((score >= THRESHOLD).astype(np.int32))], ["doc_id", "held_out", "score", "predicted"])

    return run


def scored(docs: DataFrame, labels: DataFrame, modulus: int = 3, held: int = 1, most: int = TRAIN_DOCS) -> DataFrame:
    """One row per document: doc_id, held_out, score, predicted."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"), (crc_mod("doc_id", modulus) == held).alias("held_out"))
    model = docs.sparkSession.sparkContext.broadcast(train(rows.where("not held_out"), labels, most))
    return rows.mapInArrow(_predict(model), _OUT)
