"""Language-model scoring: causal self-attention over subword ids, with the corpus' counts as experts beside it.

One causal self-attention layer reads the begin mark and the ``WINDOW`` subword ids up to a place and predicts the next
subword id: the weights of ``STATES`` output states, each a distribution over all subword ids and the end.  A word's
probability under it is the product over its ids, which end words unmistakably.  The states' distributions start from the
cluster of the document and the place in the word, are fitted by expected counts along with the layer, and back off to
the ids' counts over all training documents.

The same layer gives the weights with which that prediction is mixed, word by word, with word distributions counted over
the corpus: one for each of ``EXPERTS`` clusters of documents and one for all, each backing off to the corpus' own, so
every expert is a proper distribution over the words seen, one class of unseen words, and the end.

Ids are taken in overlapping windows, one masked batch for many; every token is scored once, with its own context.  A
bounded sample gives the start of clusters and layer only: ``REFITS`` passes deal all training documents to the clusters
and count them, and ``PASSES`` passes over every token of all training documents teach the layer and count what the
output states emit: each task goes on from the shared parameters, and their moves are averaged.

Words of ``HEAD`` highest counts travel to the workers; all others meet their counts, by cluster, in a shuffle join with
the weights of their tokens, so nothing that grows with the corpus is broadcast.
"""

from __future__ import annotations

from collections.abc import Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from numpy.lib.stride_tricks import as_strided
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Words, crc_mod, ids_and_texts, slices, stored
from .subwords import encoder, spread

#: Clusters of documents; kinds of places in a word that tell output states apart; output states.
EXPERTS, KINDS = 4, 4
STATES = EXPERTS * KINDS
#: Ids that a place sees (itself included), width of queries and keys.
WINDOW, WIDTH = 16, 16
#: Places that one window scores (it reads the WINDOW ids before them too), and windows of a masked batch.
STEP, TOGETHER = 16, 96
#: Most words whose counts are broadcast.
HEAD = 1 << 18
#: Bounds of the sample that clusters and attention start from (whole documents, by hash); words that tell clusters.
TRAIN_DOCS, CLUSTER_WORDS = 300, 1 << 16
ROUNDS, EPOCHS, RATE = 20, 4, 0.05
#: Passes over all training documents that fit the clusters, and the attention; a pass learns from whole texts (1), or
#: from one block in so many of so many words.
REFITS, PASSES, LEARN_EVERY, BLOCK = 1, 1, 1, 64
#: Taken from each count of a cluster: what a count tells of a document that it doesn't hold.
DISCOUNT = 0.9
COUNT_SLICE, LEARN_SLICE, SCORE_SLICE = 8 << 20, 256 << 10, 1 << 20
#: Text whose distinct words are looked up and encoded at once; words that a worker's encoder keeps from one to the next.
CODE_SLICE, KEPT_WORDS = 4 << 20, 1 << 16
#: Bytes of texts that Spark hands a worker at once.
BATCH_BYTES = 8 << 20


class Clusters:
    """Mixture of unigrams: log probabilities [word, expert] of the words that tell clusters."""

    def __init__(self, texts: list[str], experts: int = EXPERTS, rounds: int = ROUNDS):
        words = Words(pa.array(texts, pa.string()))
        n_words = len(words.values)
        rows = words.rows()
        totals = np.bincount(words.codes, minlength=n_words)
        known = np.flatnonzero(totals >= 1)
        known = np.sort(known[np.lexsort((known, -totals[known]))][:CLUSTER_WORDS])
        place = np.full(n_words + 1, -1)
        place[known] = np.arange(len(known))
        use = place[words.codes] >= 0 if n_words else np.zeros(0, bool)
        code, row = place[words.codes[use]] if n_words else np.zeros(0, int), rows[use]
        self.words = words.values.take(pa.array(known)) if n_words else pa.array([], pa.string())
        spread = np.bincount(code, minlength=max(1, len(known))) + 0.5
        self.log = np.log(spread / spread.sum())[:, None].repeat(experts, 1)
        self.prior = np.zeros(experts)
        if not len(texts) or not len(code):
            return
        # seeds: each next one is a document that the seeds so far explain worst, by word
        n_docs = len(texts)
        size = np.maximum(np.bincount(row, minlength=n_docs), 1)
        base = np.log(spread / spread.sum())
        explained = np.full(n_docs, -np.inf)
        belongs = np.zeros(n_docs, np.int64)
        long_enough = size >= np.median(size)
        for k in range(experts):
            gap = np.bincount(row, base[code], n_docs) / size - explained if k else size.astype(float)
            seed = int(np.argmax(np.where(long_enough, gap, -np.inf)))
            own = np.bincount(code[row == seed], minlength=len(known)) + 0.2 * size[seed] * spread / spread.sum()
            fit = np.bincount(row, np.log(own / own.sum())[code], n_docs) / size
            belongs = np.where(fit > explained, k, belongs)
            explained = np.maximum(fit, explained)
        share = np.zeros((n_docs, experts))
        share[np.arange(n_docs), belongs] = 1
        for _ in range(rounds):
            counts = np.stack([np.bincount(code, share[row, k], len(known)) for k in range(experts)], 1)
            smooth = counts + 0.05 * (counts.sum(0) + 1) * (spread / spread.sum())[:, None]
            self.log = np.log(smooth / smooth.sum(0))
            self.prior = np.log((share.sum(0) + 1) / (n_docs + experts))
            scores = np.stack([np.bincount(row, self.log[code, k], n_docs) for k in range(experts)], 1) + self.prior
            share = np.exp(scores - scores.max(1, keepdims=True))
            share /= share.sum(1, keepdims=True)

    def refit(self, table: pa.Table, ends: np.ndarray) -> None:
        """Fit to the counts of a pass: ``table`` has the words that tell clusters and c0.., ``ends`` the documents dealt."""
        experts = len(self.prior)
        counts = np.stack([table.column(f"c{k}").to_numpy() for k in range(experts)], 1).astype(float)
        self.words = table.column("word").combine_chunks()
        spread = counts.sum(1) + 0.5
        smooth = counts + 0.05 * (counts.sum(0) + 1) * (spread / spread.sum())[:, None]
        self.log = np.log(smooth / smooth.sum(0))
        self.prior = np.log((ends + 1) / (ends.sum() + experts))

    def of(self, words: Words) -> np.ndarray:
        """The likeliest cluster of each text."""
        at = pc.fill_null(pc.index_in(words.values, value_set=self.words), -1).to_numpy(zero_copy_only=False)
        table = np.concatenate([self.log, np.zeros((1, self.log.shape[1]))]).astype(np.float32)
        per_word = table[at][words.codes] if len(words.codes) else np.zeros((0, self.log.shape[1]))
        return (words.sums(per_word) + self.prior).argmax(1)


def _count(shared, experts: int, telling: bool):
    """Words and c0.., and one row of the texts dealt to each cluster (word ''); ``telling``: words that tell clusters only."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        clusters = shared.value
        for batch in slices(batches, most=COUNT_SLICE):
            words = Words(batch.column("text"))
            cluster = clusters.of(words)
            n = len(words.values)
            counts = np.bincount(words.codes * np.int64(experts) + np.repeat(cluster, words.counts), minlength=n * experts).reshape(n, experts)
            ends = np.bincount(cluster, minlength=experts)[None]
            values = words.values.cast(pa.string())
            if telling:
                known = pc.is_in(values, value_set=clusters.words)
                values, counts = values.filter(known), counts[known.to_numpy(zero_copy_only=False)]
            counts = np.concatenate([counts, ends])
            names = pa.concat_arrays([values, pa.array([""])])
            yield pa.RecordBatch.from_arrays([names, *(pa.array(counts[:, k]) for k in range(experts))], ["word", *(f"c{k}" for k in range(experts))])
            pa.default_memory_pool().release_unused()

    return run


class Blocks:
    """Runs of ``BLOCK`` words of a slice of texts, one in ``every`` drawn at random; as ``Words``, a block for a text.

    ``begin`` and ``end`` tell the blocks with which a text begins and ends.
    """

    def __init__(self, texts: pa.Array, every: int, seed: int):
        words = Words(texts)
        each = np.maximum(1, -(-words.counts // BLOCK))
        text = np.repeat(np.arange(len(each)), each)
        place = np.arange(len(text)) - np.repeat(np.cumsum(each) - each, each)
        drawn = np.flatnonzero(np.random.default_rng(seed).random(len(text)) * every < 1)
        text, place = text[drawn], place[drawn]
        first = words.starts[text] + place * BLOCK
        self.counts = np.minimum(BLOCK, words.starts[text + 1] - first)
        self.begin, self.end = place == 0, place == each[text] - 1
        self.starts = np.concatenate([[0], np.cumsum(self.counts)])
        codes = words.codes[np.repeat(first - self.starts[:-1], self.counts) + np.arange(self.starts[-1])]
        used, self.codes = np.unique(codes, return_inverse=True)
        self.values = words.values.take(pa.array(used))


class Head:
    """Words that a worker knows by number, and their subword ids: one look-up of a word serves both."""

    def __init__(self, words: pa.Array, path: str):
        self.words, self.path = words, path
        self.flat, self.lengths = encoder(path).coded(words.to_pylist())
        self.begins = np.cumsum(self.lengths) - self.lengths
        self.end = pc.index(words, "").as_py() if len(words) else -1

    def coded(self, values: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Of distinct words: their ids, where those of each begin and how many, and the number of each and of the end.

        Words outside the head, which are encoded here, share the number behind its last.
        """
        place = pc.fill_null(pc.index_in(values.cast(pa.string()), value_set=self.words), len(self.words)).to_numpy(zero_copy_only=False).astype(np.int64)
        others = np.flatnonzero(place == len(self.words))
        flat, lengths = encoder(self.path).coded(values.take(pa.array(others)).to_pylist(), KEPT_WORDS)
        row = place.copy()
        row[others] += np.arange(len(others))
        begins = np.concatenate([self.begins, len(self.flat) + np.cumsum(lengths) - lengths])
        return np.concatenate([self.flat, flat]), begins[row], np.concatenate([self.lengths, lengths])[row], np.append(place, self.end if self.end >= 0 else len(self.words))


class Coded:
    """Texts whose distinct words are looked up and encoded once; ``parts`` are runs of them, as ``Words``."""

    def __init__(self, texts: pa.Array | Words | Blocks, head: Head):
        self.words = texts if isinstance(texts, (Words, Blocks)) else Words(texts)
        self.flat, self.begins, self.lengths, self.place = head.coded(self.words.values)
        self.values = self.words.values

    def ids_by_word(self, codes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        return spread(self.flat, self.begins, self.lengths, codes)

    def parts(self, sizes: np.ndarray, most: int) -> Iterator[tuple[slice, Part]]:
        """(rows, part) of texts whose bytes ``sizes`` stay near ``most`` together."""
        cuts = np.flatnonzero(np.diff(np.cumsum(sizes, dtype=np.int64) // most)) + 1
        for a, b in zip([0, *cuts], [*cuts, len(sizes)], strict=True):
            yield slice(a, b), Part(self, a, b)


class Part:
    """Texts ``a`` to ``b`` of some coded ones."""

    def __init__(self, coded: Coded, a: int, b: int):
        words = coded.words
        self.coded, self.values = coded, words.values
        self.starts, self.counts = words.starts[a : b + 1] - words.starts[a], words.counts[a:b]
        self.codes = words.codes[words.starts[a] : words.starts[b]]


class Tokens:
    """Tokens of a slice (words, then an end per text) and its subword ids, with the begin mark before each text.

    ``seq`` are the ids, ``after`` the id that follows each place (the end behind the last), ``text_at`` the place of the
    begin mark, ``kind`` what kind of place in a word the next id takes.  ``owner`` is the place before each token and
    ``size`` the number of its ids.  In blocks, ``known`` is False where what follows is not the id in ``after``, and the
    size of tokens cut off is 0.  ``whole`` tells tokens whose ids are in one window.  With a ``head``, ids of its words
    are looked up there, and ``place`` has the number of each distinct word and of the end.
    """

    def __init__(self, texts, path: str, head: Head | None = None):
        self.words = words = texts if isinstance(texts, (Blocks, Part)) else Words(texts)
        library = encoder(path)
        coded = texts.coded if isinstance(texts, Part) else Coded(words, head) if head is not None else None
        ids, each = library.ids_by_word(words) if coded is None else coded.ids_by_word(words.codes)
        self.place = None if coded is None else coded.place
        self.vocabulary = mark = library.library.get_vocab_size()
        edges = np.concatenate([[0], np.cumsum(each)])
        starts, ends = words.starts[:-1], words.starts[1:]
        n_texts = len(starts)
        self.seq = np.insert(ids.astype(np.int64), edges[starts], mark)
        lengths = edges[ends] - edges[starts] + 1
        begins = np.cumsum(lengths) - lengths
        self.text_at = np.repeat(begins, lengths)
        self.after = np.append(self.seq[1:], mark)  # the end shares the begin mark's number
        row = np.repeat(np.arange(n_texts), words.counts)
        self.end_code = len(words.values)
        self.codes = np.insert(words.codes.astype(np.int64), ends, self.end_code)
        self.counts = words.counts + 1
        self.starts = np.cumsum(self.counts) - self.counts
        self.owner = np.insert(edges[:-1] + row, ends, begins + lengths - 1)
        self.size = np.insert(each, ends, 1)
        # 0: a word's first id, 1: its second, 2: later ones, 3: a word's first id right behind the begin mark
        first = np.zeros(len(self.seq), np.int64)
        some = self.size > 0
        first[self.owner[some]] = 1
        at = np.arange(len(self.seq))
        since = at - np.maximum.accumulate(np.where(first > 0, at, 0))
        self.kind = np.where(at == self.text_at, 3, np.minimum(since, 2))
        self.known = np.ones(len(self.seq), bool)
        if isinstance(words, Blocks):
            self.known[begins[~words.begin]] = False
            self.known[(begins + lengths - 1)[~words.end]] = False
            self.size[self.starts[~words.begin]] = 0
            self.size[(self.starts + self.counts - 1)[~words.end]] = 0
        self.whole = (self.size > 0) & (self.owner % STEP + self.size <= STEP)


#: Distance of each key of a window from each of its queries; what is masked weighs nothing.
_PLACE = WINDOW + np.arange(STEP)[:, None] - np.arange(WINDOW + STEP)[None]
_OUTSIDE = (_PLACE < 0) | (_PLACE >= WINDOW)
_PLACE = np.where(_OUTSIDE, 0, _PLACE)
_INSIDE = np.flatnonzero(~_OUTSIDE)
_INSIDE_PLACE = _PLACE.ravel()[_INSIDE]


def _total(x: np.ndarray) -> np.ndarray:
    """Sums of rows: a product with ones, as sums over short rows are slow."""
    return (x.reshape(-1, x.shape[-1]) @ np.ones((x.shape[-1], 1), x.dtype)).reshape(*x.shape[:-1], 1)


def _softmax(x: np.ndarray) -> np.ndarray:
    x = np.exp(x - np.ascontiguousarray(x.T).max(0)[:, None])
    x /= _total(x)
    return x


def _short(ids: np.ndarray, most: int) -> np.ndarray:
    """Numbers below ``most``, short ones where they fit: these sort faster."""
    return ids.astype(np.uint16) if most <= 1 << 16 else ids


class Attention:
    """One causal self-attention layer from the ids up to a place to the weights of ``experts`` and of output states."""

    def __init__(self, vocabulary: int, experts: int, states: int = STATES, width: int = WIDTH, seed: int = 3):
        rng = np.random.default_rng(seed)
        normal = lambda *shape: rng.normal(0, 0.3, shape).astype(np.float32)
        self.experts = experts
        self.p = {"embed": normal(vocabulary + 1, width), "query": normal(width, width), "key": normal(width, width), "value": normal(width, experts + states), "place": np.zeros(WINDOW, np.float32), "bias": np.zeros(experts + states, np.float32)}
        self.squares = {k: np.full(v.shape, 1e-4, np.float32) for k, v in self.p.items()}

    def _attend(self, tokens: Tokens, some: np.ndarray, q: np.ndarray, k: np.ndarray) -> np.ndarray:
        """Unnormalised weights [window, query, key]."""
        scores = q @ k.transpose(0, 2, 1)
        scores += np.where(_OUTSIDE, np.float32(-1e9), self.p["place"][_PLACE])
        at = some * STEP
        last = np.minimum(at + STEP, len(tokens.seq)) - 1
        cut = np.flatnonzero(tokens.text_at[last] > at - WINDOW)  # windows that hold more than one text
        if len(cut):
            query = np.minimum(at[cut, None] + np.arange(STEP), len(tokens.seq) - 1)
            hidden = at[cut, None, None] + np.arange(-WINDOW, STEP) < tokens.text_at[query][:, :, None]
            scores[cut] += np.where(hidden, np.float32(-1e9), np.float32(0))
        np.minimum(scores, np.float32(60), out=scores)
        return np.exp(scores, out=scores)

    @staticmethod
    def _near(tokens: Tokens, some: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Places that the windows ``some`` read (those before the slice are negative), and their ids."""
        near = some[:, None] * STEP + np.arange(-WINDOW, STEP)
        return near, tokens.seq.take(near, mode="clip")

    @staticmethod
    def _overlapping(x: np.ndarray) -> np.ndarray:
        """View [window, place, figure] of what neighbouring windows read, of which each place is there once."""
        return as_strided(x, (len(x) // STEP - WINDOW // STEP, WINDOW + STEP, x.shape[1]), (STEP * x.strides[0], *x.strides), writeable=False)

    def logits(self, tokens: Tokens) -> Iterator[tuple[slice, np.ndarray]]:
        """(places, logits [place, experts + states]) window batch by window batch."""
        p, n = self.p, len(tokens.seq)
        queries, keys = p["embed"] @ (p["query"] / np.float32(np.sqrt(p["embed"].shape[1]))), p["embed"] @ p["key"]
        values = np.concatenate([p["embed"] @ p["value"], np.ones((len(p["embed"]), 1), np.float32)], 1)
        windows = -(-n // STEP)
        for a in range(0, windows, TOGETHER):
            some = np.arange(a, min(a + TOGETHER, windows))
            ids = tokens.seq.take(np.arange(a * STEP - WINDOW, (some[-1] + 1) * STEP), mode="clip")
            k, v = (self._overlapping(x.take(ids, 0)) for x in (keys, values))
            att = self._attend(tokens, some, queries.take(ids[WINDOW:], 0).reshape(len(some), STEP, -1), k)
            out = (att @ v).reshape(len(some) * STEP, -1)
            out, total = out[:, :-1], out[:, -1:]
            out = out * (1 / total)
            out += p["bias"]
            places = slice(a * STEP, min((a + TOGETHER) * STEP, n))
            yield places, out[: places.stop - places.start]

    def predict(self, tokens: Tokens, emit: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Experts' weights at each place, and log10 of the predicted probability of the id after it."""
        gates, found = np.empty((len(tokens.seq), self.experts), np.float32), np.empty(len(tokens.seq))
        apart = self._apart(np.float32)
        for places, out in self.logits(tokens):
            out = np.exp(np.clip(out, -60, 60, out=out), out=out)
            total = out @ apart
            np.multiply(out[:, : self.experts], 1 / total[:, :1], out=gates[places])
            emitted = emit.take(tokens.after[places], 0)
            emitted *= out[:, self.experts :]
            found[places] = np.maximum(_total(emitted)[:, 0] / total[:, 1], 1e-30)
        return gates, np.log10(found, out=found)

    def _apart(self, dtype: type) -> np.ndarray:
        """Columns that sum up the experts' part of a row, and the states'."""
        return np.repeat(np.eye(2, dtype=dtype), [self.experts, len(self.p["bias"]) - self.experts], 0)

    def gradient(self, tokens: Tokens, some: np.ndarray, emit: np.ndarray, mine: np.ndarray, words: np.ndarray) -> tuple[dict, np.ndarray, float, tuple[np.ndarray, np.ndarray]]:
        """Of the mean negative log likelihood of the next ids and of the tokens in the windows ``some``.

        mine: the tokens whose place before them is in the windows; words [one of mine, expert]: the experts'
        probabilities but the last one's, which is the layer's own prediction and taken as given; tokens whose ids leave
        their window don't count.  The embedding's part belongs to the ids returned beside it.  Last come the next ids,
        and the output states' shares in them.
        """
        p, width, g = self.p, self.p["embed"].shape[1], self.experts
        scale = np.float32(1 / np.sqrt(width))
        near, ids = self._near(tokens, some)
        x = p["embed"].take(ids, 0)
        flat, late = x.reshape(-1, width), x[:, WINDOW:].reshape(-1, width)
        query = p["query"] * scale
        value = np.concatenate([p["value"], np.zeros((width, 1), p["value"].dtype)], 1)
        q, k, v = (late @ query).reshape(len(some), STEP, width), (flat @ p["key"]).reshape(len(some), WINDOW + STEP, width), (flat @ value).reshape(len(some), WINDOW + STEP, -1)
        v[..., -1] = 1  # sums up the weights
        att = self._attend(tokens, some, q, k)
        out = (att @ v).reshape(-1, v.shape[2])
        over = 1 / out[:, -1:]
        out *= over
        logits = out[:, :-1] + p["bias"]
        places = near[:, WINDOW:].ravel()
        at = np.where(places < len(tokens.seq), places, 0)
        real = (places < len(tokens.seq)) & tokens.known[at]
        z = np.exp(np.clip(logits, -60, 60, out=logits), out=logits)
        total = 1 / (z @ self._apart(z.dtype))
        gate, state = z[:, :g] * total[:, :1], z[:, g:] * total[:, 1:]
        after = tokens.after[at]
        share = emit.take(after, 0) * state
        likely = np.maximum(_total(share), 1e-30)
        n = max(1, int(real.sum()))
        share /= likely
        d = np.zeros_like(out)
        state -= share
        np.multiply(state, (real / n).astype(d.dtype)[:, None], out=d[:, g:-1])
        log_likely = np.log(likely[:, 0])
        loss = -log_likely[real].sum() / n
        # tokens that begin behind a place of the windows and end in the same window
        whole = tokens.whole[mine]
        mine, words = mine[whole], words[whole]
        if len(mine):
            owner = tokens.owner[mine]
            spot = np.searchsorted(some, owner // STEP) * STEP + owner % STEP
            sums = np.zeros(len(log_likely) + 1)
            np.cumsum(log_likely, dtype=float, out=sums[1:])
            mixed, chosen = np.empty((len(mine), g), z.dtype), gate[spot]
            mixed[:, :-1], mixed[:, -1] = words, np.exp(sums[spot + tokens.size[mine]] - sums[spot])
            mixed *= chosen
            whole = np.maximum(_total(mixed), 1e-30)
            mixed /= whole
            chosen -= mixed
            chosen *= z.dtype.type(1 / len(mine))
            d[spot, :g] = chosen
            loss -= np.log(whole).sum() / len(mine)
        d_bias = (np.ones((1, len(d)), d.dtype) @ d)[0, :-1]
        # what the weights of a row have in common is the row's gradient along what it read
        np.negative(_total(out * d)[:, 0], out=d[:, -1])
        d *= over
        d = d.reshape(len(some), STEP, -1)
        d_scores = d @ v.transpose(0, 2, 1)
        d_scores *= att
        d_q = (d_scores @ k).reshape(-1, width)
        d_k, d_v = (d_scores.transpose(0, 2, 1) @ q).reshape(len(flat), -1), (att.transpose(0, 2, 1) @ d).reshape(len(flat), -1)
        d_x = d_k @ p["key"].T
        d_x += d_v @ value.T
        d_x.reshape(x.shape)[:, WINDOW:] += (d_q @ query.T).reshape(len(some), STEP, width)
        short = _short(ids.ravel(), len(p["embed"]))
        order = np.argsort(short, kind="stable")
        by = short[order]
        firsts = np.flatnonzero(np.concatenate([[True], by[1:] != by[:-1]]))
        used = by[firsts].astype(np.int64)
        embed = np.add.reduceat(d_x.take(order, 0), firsts, axis=0)
        d_place = np.ones((1, len(some)), d_scores.dtype) @ d_scores.reshape(len(some), -1)
        place = np.bincount(_INSIDE_PLACE, d_place[0, _INSIDE], WINDOW)
        grads = {"query": late.T @ d_q * scale, "key": flat.T @ d_k, "value": (flat.T @ d_v)[:, :-1], "place": place, "bias": d_bias, "embed": embed}
        return {name: x.astype(np.float32, copy=False) for name, x in grads.items()}, used, float(loss), (after[real], share[real])

    def learn(self, tokens: Tokens, emit: np.ndarray, words, rate: float = RATE, seed: int = 5, expected: np.ndarray | None = None) -> None:
        """Steps of TOGETHER windows over a slice in random order.

        ``words(tokens chosen)`` gives the experts' probabilities; ``expected`` [id, state] takes up the states' shares.
        """
        n = -(-len(tokens.seq) // STEP)
        order = np.random.default_rng(seed).permutation(n)
        edges = np.searchsorted(tokens.owner, np.arange(n + 1) * STEP)  # owners ascend
        found = []
        for a in range(0, len(order), TOGETHER):
            some = np.sort(order[a : a + TOGETHER])
            first, each = edges[some], edges[some + 1] - edges[some]
            mine = np.repeat(first - np.cumsum(each) + each, each) + np.arange(each.sum())
            grads, used, _, share = self.gradient(tokens, some, emit, mine, words(mine))
            found.append(share)
            for name, g in grads.items():
                rows = used if name == "embed" else slice(None)
                squares = g * g
                squares += self.squares[name][rows]
                self.squares[name][rows] = squares
                np.sqrt(squares, out=squares)
                np.divide(g, squares, out=squares)
                squares *= np.float32(rate)
                self.p[name][rows] -= squares
        if expected is not None and found:
            ids, shares = (np.concatenate(x) for x in zip(*found, strict=True))
            for k, share in enumerate(np.ascontiguousarray(shares.T)):
                expected[:, k] += np.bincount(ids, share, len(expected))


class Model:
    """What the workers need: the head's words and probabilities, the attention, the experts' mass outside the head."""

    def __init__(self, head: pa.Table, sums: np.ndarray, types: np.ndarray, kinds: int, path: str):
        self.path, self.words = path, head.column("word").combine_chunks()
        self.head = Head(self.words, path)
        counts = np.stack([head.column(f"c{k}").to_numpy() for k in range(len(sums))], 1).astype(float) if head.num_rows else np.zeros((0, len(sums)))
        total, tokens = counts.sum(1), sums.sum()
        self.denominator = tokens + 0.5 * (kinds + 1)
        base = (total + 0.5) / self.denominator
        # what the discount takes from a cluster's counts goes to the corpus' distribution, which is itself the last expert
        loose = np.minimum(DISCOUNT * types, sums) + 1.0
        share = (np.maximum(counts - DISCOUNT, 0) + loose * base[:, None]) / (sums + 1.0)
        share = np.concatenate([share, base[:, None]], 1)
        self.base = np.log10(base)
        #: of each expert's probability of a word: what its own count gives by occurrence, and the corpus' by probability
        self.own, self.lent = 1 / (sums + 1.0), loose / (sums + 1.0)
        rest, rest_base = np.maximum(1 - share.sum(0), 1e-12), max(1 - base.sum(), 1e-12)
        # the last row, for training: any word outside the head, against the corpus' own probability of it
        self.experts = np.concatenate([share, rest[None] / rest_base]).astype(np.float32)
        self.attention: Attention | None = None
        self.emit: np.ndarray | None = None

    def places(self, tokens: Tokens) -> np.ndarray:
        """Row of ``experts`` of each token."""
        return tokens.place[tokens.codes]

    def emissions(self, counts: np.ndarray, every: np.ndarray) -> None:
        """Output states from expected counts [id, state]; each backs off to the ids' own counts ``every``."""
        every = every + 0.5
        loose = (counts > 0.5).sum(0) + 1.0
        self.emit = ((counts + loose * (every / every.sum())[:, None]) / (counts.sum(0) + loose)).astype(np.float32)

    def start(self, texts: list[str], clusters: Clusters, epochs: int | None = None) -> None:
        """Layer and output states from the sample; ``expected`` keeps its counts."""
        vocabulary, width = encoder(self.path).library.get_vocab_size(), len(clusters.prior) * KINDS
        self.attention = Attention(vocabulary, self.experts.shape[1] + 1, width)
        parts = [Tokens(pa.array(texts[a : a + 100], pa.string()), self.path, self.head) for a in range(0, len(texts), 100)]
        self.expected = np.zeros((vocabulary + 1, width))
        for x in parts:
            lengths = np.bincount(np.searchsorted(np.unique(x.text_at), x.text_at))
            state = np.repeat(clusters.of(x.words), lengths) * KINDS + x.kind
            self.expected += np.bincount(x.after * width + state, minlength=self.expected.size).reshape(self.expected.shape)
        every = self.expected.sum(1)
        self.emissions(self.expected, every)
        for epoch in range(EPOCHS if epochs is None else epochs):
            self.expected = np.zeros_like(self.expected)
            for x in parts:
                place = self.places(x)
                self.attention.learn(x, self.emit, lambda some, place=place: self.experts.take(place[some], 0), seed=epoch, expected=self.expected)
            self.emissions(self.expected, every)


#: Figures of one row of a parameter or of the counts of an id, at most.
_WIDE = max(WIDTH, STATES + EXPERTS + 2)
_MOVES = f"name string, at int, weight double, {', '.join(f'm{i} double' for i in range(_WIDE))}"


def _rows(name: str, at: np.ndarray, weight: np.ndarray, values: np.ndarray) -> pa.RecordBatch:
    wide = np.zeros((len(at), _WIDE))
    wide[:, : values.shape[1]] = values
    return pa.RecordBatch.from_arrays([pa.array([name] * len(at), pa.string()), pa.array(at, pa.int32()), pa.array(weight), *(pa.array(np.ascontiguousarray(wide[:, i])) for i in range(_WIDE))], ["name", "at", "weight", *(f"m{i}" for i in range(_WIDE))])


def _learn(shared):
    """Moves of the parameters, by rows, over a task's documents, and the expected counts of output states.

    Moves weigh as the tokens learnt from, an id's row as its occurrences.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = shared.value
        begun = model.attention
        layer = Attention.__new__(Attention)
        layer.experts, layer.p, layer.squares = begun.experts, {k: v.copy() for k, v in begun.p.items()}, {k: v.copy() for k, v in begun.squares.items()}
        seen, total, expected = np.zeros(len(layer.p["embed"]), np.int64), 0, np.zeros(model.emit.shape)
        for batch in slices(batches, most=CODE_SLICE if LEARN_EVERY == 1 else LEARN_SLICE):
            texts = batch.column("text")
            if LEARN_EVERY == 1:
                parts = (part for _, part in Coded(texts, model.head).parts(pc.binary_length(texts).to_numpy(zero_copy_only=False), LEARN_SLICE))
            else:
                blocks = Blocks(texts, LEARN_EVERY, seed=total)
                parts = [blocks] if len(blocks.counts) else []
            for part in parts:
                tokens = Tokens(part, model.path, model.head)
                total += len(tokens.words.codes) + (int(part.end.sum()) if LEARN_EVERY > 1 else len(part.counts))
                place = model.places(tokens)
                layer.learn(tokens, model.emit, lambda some, place=place: model.experts.take(place[some], 0), seed=total, expected=expected)
                seen += np.bincount(tokens.seq, minlength=len(seen))
            del texts, parts
            pa.default_memory_pool().release_unused()
        if not total:
            return
        some = np.flatnonzero(seen)
        yield _rows("emit", some, seen[some].astype(float), expected[some])
        for name, now in layer.p.items():
            moved = now - begun.p[name]
            moved = moved.reshape(-1, 1) if moved.ndim == 1 else moved
            at = np.flatnonzero(seen) if name == "embed" else np.arange(len(moved))
            weight = seen[at].astype(float) if name == "embed" else np.full(len(at), float(total))
            yield _rows(name, at, weight, moved[at] * weight[:, None])

    return run


def learn_pass(training: DataFrame, model: Model) -> int:
    """One pass of the attention over all training documents; the number of tokens learnt from."""
    shared = training.sparkSession.sparkContext.broadcast(model)
    moves = training.select("text").mapInArrow(_learn(shared), _MOVES).groupBy("name", "at").agg(F.sum("weight").alias("weight"), *(F.sum(f"m{i}").alias(f"m{i}") for i in range(_WIDE)))
    table, learnt = moves.toArrow(), 0  # one row for each row of a parameter and each id, whatever the corpus
    names = table.column("name").to_pandas().to_numpy()
    at, weight = table.column("at").to_numpy(), table.column("weight").to_numpy()
    sums = np.stack([table.column(f"m{i}").to_numpy() for i in range(_WIDE)], 1)
    for name, value in model.attention.p.items():
        own = names == name
        step = (sums[own] / np.maximum(weight[own], 1)[:, None]).astype(np.float32)
        value[at[own]] += step[:, 0] if value.ndim == 1 else step[:, : value.shape[1]]
        learnt = int(weight[own][0]) if name == "bias" and own.any() else learnt
    own = names == "emit"
    every, expected = np.zeros(len(model.emit)), np.zeros(model.emit.shape)
    every[at[own]], expected[at[own]] = weight[own], sums[own][:, : expected.shape[1]]
    every[-1] = expected[-1].sum()  # the begin mark's number stands for the end
    # all training documents are counted: those that the layer started from not once more
    model.emissions(expected, every) if LEARN_EVERY == 1 else model.emissions(model.expected + LEARN_EVERY * expected, model.expected.sum(1) + LEARN_EVERY * every)
    return learnt


_SCORED = "row long, doc_id long, held_out boolean, n_tokens long, n_known long, base double, score double, tail array<struct<word:string,gates:array<float>,own:double>>"


def _scored(model: Model, part: Part, batch: pa.RecordBatch, row: int) -> pa.RecordBatch:
    tokens = Tokens(part, model.path, model.head)
    gates, likely = model.attention.predict(tokens, model.emit)
    sums = np.zeros(len(likely) + 1)
    np.cumsum(likely, out=sums[1:])
    own = np.where(tokens.size > 0, 10.0 ** (sums[tokens.owner + tokens.size] - sums[tokens.owner]), 0.0) * gates[tokens.owner, -1]
    place = model.places(tokens)
    outside = place == len(model.words)
    score = np.empty(len(place))
    for a in range(0, len(place), 1 << 14):
        some = slice(a, a + (1 << 14))
        mixed = model.experts.take(place[some], 0)
        mixed *= gates[:, :-1].take(tokens.owner[some], 0)
        score[some] = _total(mixed)[:, 0]
    score += own
    score[outside] = 1  # by the counts in the join
    np.log10(score, out=score)
    base = np.append(model.base, 0.0)[place]
    add = lambda x: np.add.reduceat(x, tokens.starts)  # noqa: E731  every text has its end
    tail = pa.concat_arrays([tokens.words.values.cast(pa.string()), pa.array([""])]).take(pa.array(tokens.codes[outside]))
    width = gates.shape[1] - 1
    weights = pa.ListArray.from_arrays(pa.array(np.arange(len(tail) + 1, dtype=np.int32) * width), pa.array(gates[tokens.owner[outside], :-1].ravel()))
    tail = pa.StructArray.from_arrays([tail, weights, pa.array(own[outside])], ["word", "gates", "own"])
    offsets = np.concatenate([[0], np.cumsum(add(outside.astype(np.int64)))]).astype(np.int32)
    return pa.RecordBatch.from_arrays([pa.array(row + np.arange(batch.num_rows)), batch.column("doc_id"), batch.column("held_out"), pa.array(tokens.counts), pa.array(add((~outside).astype(np.int64))), pa.array(add(base)), pa.array(add(score)), pa.ListArray.from_arrays(pa.array(offsets), tail)], ["row", "doc_id", "held_out", "n_tokens", "n_known", "base", "score", "tail"])


def _score(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model: Model = shared.value
        done, task = 0, None
        for batch in slices(batches, most=CODE_SLICE):
            if task is None:
                task = batch.column("task")[0].as_py() << 40
            texts = batch.column("text")
            for rows, part in Coded(texts, model.head).parts(pc.binary_length(texts).to_numpy(zero_copy_only=False), SCORE_SLICE):
                n = rows.stop - rows.start
                yield _scored(model, part, batch.slice(rows.start, n), task + done)
                done += n
            pa.default_memory_pool().release_unused()

    return run


@contextmanager
def _batches(spark: SparkSession, most: int) -> Iterator[None]:
    """Jobs planned inside hand workers batches of so many bytes: both sides hold a batch as a whole."""
    name = "spark.sql.execution.arrow.maxBytesPerBatch"
    before = spark.conf.get(name)
    spark.conf.set(name, str(most))
    try:
        yield
    finally:
        spark.conf.set(name, before)


def scores(docs: DataFrame, path: str, modulus: int = 5, held: int = 1, experts: int = EXPERTS) -> DataFrame:
    """One row per document: doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score (both log10).

    Null texts are an end alone.  Without training documents every word is unseen, in the model as in the base.
    """
    with _batches(docs.sparkSession, BATCH_BYTES):  # all jobs that run Python end in it
        return _scores(docs, path, modulus, held, experts)


def _scores(docs: DataFrame, path: str, modulus: int, held: int, experts: int) -> DataFrame:
    spark = docs.sparkSession
    rows = ids_and_texts(docs).withColumn("held_out", crc_mod("doc_id", modulus) == held)
    training = rows.where("not held_out")
    n = training.select("doc_id").count()
    part = training.where(F.pmod(F.xxhash64("doc_id", F.lit(9)), F.lit(1_000_000)) < 1_000_000 * min(1.0, TRAIN_DOCS / max(1, n)))
    sample = [r["text"] for r in sorted(part.select("doc_id", "text").collect())]  # about TRAIN_DOCS rows
    columns = [f"c{k}" for k in range(experts)]
    clusters = Clusters(sample, experts)
    for refit in range(REFITS + 1):
        last = refit == REFITS or not sample
        counting = training.select("text").mapInArrow(_count(spark.sparkContext.broadcast(clusters), experts, not last), "word string, " + ", ".join(f"{c} long" for c in columns))
        counts = stored(counting.groupBy("word").agg(*(F.sum(c).alias(c) for c in columns)).withColumn("c", sum(F.col(c) for c in columns)), "word-counts")
        if last:
            break
        ends = counts.where("word = ''").first()
        clusters.refit(counts.where("word <> ''").orderBy("word").toArrow(), np.array([ends[c] for c in columns], float))
    totals = counts.agg(*(F.sum(c) for c in columns), *(F.count_if(F.col(c) > 0) for c in columns), F.count("*")).first()
    sums, types, kinds = np.array([x or 0 for x in totals[:experts]], float), np.array([x or 0 for x in totals[experts:-1]], float), totals[-1]
    # the head: all words of at least so many occurrences that no more than HEAD have them
    steps = F.when(F.col("c") < 4096, F.col("c")).otherwise(F.pow(F.lit(2.0), F.floor(F.log2("c"))).cast("long"))
    least, room = 1 << 62, HEAD
    for r in sorted(counts.groupBy(steps.alias("step")).count().collect(), reverse=True):  # at most some 4,140 rows
        if r["count"] > room:
            break
        least, room = r["step"], room - r["count"]
    model = Model(counts.where(F.col("c") >= least).orderBy("word").toArrow(), sums, types, kinds, path)
    model.start(sample, clusters)
    for _ in range(PASSES if n else 0):
        learn_pass(training, model)
    shared = spark.sparkContext.broadcast(model)
    scored = stored(rows.withColumn("task", F.spark_partition_id().cast("long")).mapInArrow(_score(shared), _SCORED), "scored")
    tail = scored.select("row", F.explode("tail").alias("t")).select("row", "t.word", "t.gates", "t.own").join(counts.where(F.col("c") < least).select("word", *columns, "c"), "word", "left")
    base = (F.coalesce("c", F.lit(0)) + 0.5) / F.lit(float(model.denominator))
    each = [(F.greatest(F.coalesce(c, F.lit(0)) - F.lit(DISCOUNT), F.lit(0.0)) * float(model.own[k]) + base * float(model.lent[k])) * F.col("gates")[k] for k, c in enumerate(columns)]
    mixed = sum(each, base * F.col("gates")[experts] + F.col("own"))
    found = tail.groupBy("row").agg(F.sum(F.log10(base)).alias("tail_base"), F.sum(F.log10(mixed)).alias("tail_score"), F.count("c").alias("known"))
    out = scored.select("row", "doc_id", "held_out", "n_tokens", "n_known", "base", "score").join(found, "row", "left")
    return out.select("doc_id", "held_out", "n_tokens", (F.col("n_known") + F.coalesce("known", F.lit(0))).alias("n_known"), F.lit(int(sums.sum())).cast("long").alias("train_tokens"), (F.col("base") + F.coalesce("tail_base", F.lit(0.0))).alias("base_score"), (F.col("score") + F.coalesce("tail_score", F.lit(0.0))).alias("score"))
