"""Personal data: fixed base patterns, widened by a linear-chain conditional random field.

The base patterns decide email, ip, card and phone spans as the contract states them.  The field labels the words that
carry a digit, an ``@`` or a bracketed at sign with features of their shape and of their neighbours; besides the four
kinds it knows secrets (keys and tokens).  It is trained, by gradient steps on the exact conditional likelihood, from a
small labelled table: runs of words around base spans of a bounded sample of documents, the same spans in other common
notations, made-up card numbers and secrets, and numbers that are nobody's.  A run of the sample with a number that no
base pattern knows has no label and teaches nothing.  All other words are O by construction, so a text falls into short
runs that Viterbi decodes together in numpy batches.

What the field labels is added where it overlaps no base span and has the parts that its kind must have (``has_parts``):
a card number needs its digits but, written in error, not the right check digit.  Base spans always stay.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import ids_and_texts, slices

KINDS = ("email", "ip", "card", "phone")
#: What the field finds beyond the contract's kinds; they come after them.
MORE_KINDS = ("secret",)
ALL_KINDS = KINDS + MORE_KINDS
LABELS = ("O", *(f"{x}-{k}" for k in ALL_KINDS for x in "BI"))
#: Bound of the documents, taken by hash, whose base spans teach the field; and of the spans used.
TRAIN_DOCS, TRAIN_SPANS, EPOCHS = 2000, 400, 30
#: Most training sequences, drawn at random from those of the sample (noise among them), and their most words.
TRAIN_SEQUENCES, TRAIN_WORDS = 6000, 40
#: Made-up examples of each sort.
MADE_UP = 250
#: Words, with padding, that one batch of decoding holds.
DECODE_WORDS = 1 << 16

_WORD = re.compile(r"[^\x20\x09-\x0D]+")
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
_IP = re.compile(r"(?<![0-9])[0-9]++(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_NOT_DIGIT = re.compile(r"[^0-9]")
_SEED_WORD = re.compile(r"[0-9@]|[(\[]at[)\]]", re.I)

Span = tuple[str, int, int]


def luhn(digits: str) -> bool:
    total = 0
    for i, d in enumerate(reversed(digits)):
        x = int(d) * (1 + i % 2)
        total += x - 9 if x > 9 else x
    return total % 10 == 0


def _emails(text: str) -> Iterator[Span]:
    """Each match holds one @: the run of local characters before it, back to the last match."""
    end, at = 0, text.find("@")
    while at >= 0:
        begin = at
        while begin > end and text[begin - 1] in _LOCAL:
            begin -= 1
        found = _DOMAIN.match(text, at) if begin < at else None
        if found:
            yield "email", begin, found.end()
            end = found.end()
        at = text.find("@", max(at + 1, end))


def valid(kind: str, text: str) -> bool:
    digits = _NOT_DIGIT.sub("", text)
    if kind == "ip":
        return all(len(p.lstrip("0")) <= 3 and int(p) <= 255 for p in text.split("."))
    if kind == "card":
        return 13 <= len(digits) <= 19 and luhn(digits)
    return kind == "email" or 9 <= len(digits) <= 15


def base_spans(text: str) -> list[Span]:
    """Spans by kind as listed, then by start; code points, end exclusive."""
    found = list(_emails(text)) if "@" in text else []
    for kind, pattern in (("ip", _IP), ("card", _CARD), ("phone", _PHONE)):
        found += [(kind, m.start(), m.end()) for m in pattern.finditer(text) if valid(kind, m[0])]
    return found


# --- the field ------------------------------------------------------------------------------------------------------

#: Lengths that a feature tells apart.
_BINS = (1, 2, 3, 4, 5, 6, 8, 10, 12, 16, 20)
_CUES = {"mail": "email", "email": "email", "e-mail": "email", "ip": "ip", "address": "ip", "host": "ip", "card": "card", "visa": "card", "phone": "phone", "tel": "phone", "tel.": "phone", "call": "phone", "mobile": "phone", "fax": "phone", "token": "secret", "key": "secret", "secret": "secret", "password": "secret", "api_key": "secret", "bearer": "secret"}
#: Signs that stand around a datum without being part of it.
_AROUND = ".,;:!?\"'`#$%&*|=<>[]{}"


def shape(word: str) -> str:
    """Runs of capitals, small letters, digits as A, a, 9 with their digits counted up to five; other signs as they are."""
    out = []
    for m in re.finditer(r"[0-9]+|[^\W\d_]+|.", word):
        x = m[0]
        out.append("9" * min(len(x), 5) if x[0].isdigit() else "a" if x[0].isalpha() else x[:1])
    return "".join(out)[:24]


def _near(word: str) -> str:
    return shape(word) if _SEED_WORD.search(word) else _CUES.get(word.lower().strip(":=\"'"), "word") if word else "edge"


def features(words: list[str], i: int) -> list[str]:
    w = words[i].strip(_AROUND)
    digits, letters = sum(c.isdigit() for c in w), sum(c.isalpha() for c in w)
    bin_of = lambda n: next((b for b in _BINS if n <= b), 99)
    kind = "hex" if len(w) >= 16 and _HEX.fullmatch(w) else "code" if len(w) >= 16 and _CODE.fullmatch(w) else "other"
    out = ["bias", f"digits={bin_of(digits)}", f"letters={bin_of(letters) if letters else 0}", f"kind={kind}", f"at={'@' in w}", f"dots={w.count('.')}", f"plus={w[:1] == '+'}", f"bracket={w[:1] in '(['}"]
    if kind == "other":  # the shapes of codes are as many as codes
        out.append(f"shape={shape(w)}")
    for side, j in (("before", i - 1), ("after", i + 1)):
        out.append(f"{side}={_near(words[j] if 0 <= j < len(words) else '')}")
    if i > 1:
        out.append(f"before2={_near(words[i - 2])}")
    return out


_HEX = re.compile(r"[0-9a-f]+|[0-9A-F]+")
_CODE = re.compile(r"(?=[A-Za-z0-9_/+=-]*[0-9])(?=[A-Za-z0-9_/+=-]*[A-Za-z])[A-Za-z0-9_/+=-]+")


class Field:
    """Weights by feature and label, transitions between labels."""

    def __init__(self):
        self.index: dict[str, int] = {}
        self.weights = np.zeros((0, len(LABELS)))
        # I follows B or I of its kind only
        self.allowed = np.array([[b[0] != "I" or a[1:] == b[1:] and a != "O" for b in LABELS] for a in LABELS])
        self.start = np.array([x[0] != "I" for x in LABELS])
        self.moves = np.zeros((len(LABELS), len(LABELS)))

    def _scores(self, sequences: list[list[list[int]]]) -> tuple[np.ndarray, np.ndarray]:
        longest = max(map(len, sequences))
        scores = np.zeros((len(sequences), longest, len(LABELS)))
        for s, sequence in enumerate(sequences):
            for t, active in enumerate(sequence):
                scores[s, t] = self.weights[active].sum(0)
        return scores, np.array([len(x) for x in sequences])

    def _moves(self) -> np.ndarray:
        return np.where(self.allowed, self.moves, -1e9)

    def fit(self, sequences: list[list[list[str]]], labels: list[list[int]], epochs: int = EPOCHS, rate: float = 0.2, decay: float = 1e-4, seed: int = 7) -> None:
        for sequence in sequences:
            for active in sequence:
                for f in active:
                    self.index.setdefault(f, len(self.index))
        self.weights = np.zeros((len(self.index), len(LABELS)))
        coded = [[[self.index[f] for f in active] for active in sequence] for sequence in sequences]
        squares, move_squares = np.full_like(self.weights, 1e-2), np.full_like(self.moves, 1e-2)
        rng = np.random.default_rng(seed)
        for _ in range(epochs):
            order = rng.permutation(len(coded))
            for a in range(0, len(order), 128):
                some = order[a : a + 128]
                grad, move_grad = self._gradient([coded[i] for i in some], [labels[i] for i in some])
                grad, move_grad = grad / len(some) + decay * self.weights, move_grad / len(some) + decay * self.moves
                squares += grad**2
                move_squares += move_grad**2
                self.weights -= rate * grad / np.sqrt(squares)
                self.moves -= rate * move_grad / np.sqrt(move_squares)

    def _gradient(self, coded, labels):
        """Of the negative log likelihood, by forward and backward sums over the batch at once."""
        scores, lengths = self._scores(coded)
        n, longest, k = scores.shape
        moves = self._moves()
        forward = np.full((n, longest, k), -1e9)
        forward[:, 0] = np.where(self.start, scores[:, 0], -1e9)
        total = lambda x, axis: (m := x.max(axis, keepdims=True)).squeeze(axis) + np.log(np.exp(x - m).sum(axis))
        for t in range(1, longest):
            forward[:, t] = scores[:, t] + total(forward[:, t - 1, :, None] + moves, 1)
        backward = np.zeros((n, longest, k))
        for t in range(longest - 2, -1, -1):
            step = total(moves + (scores[:, t + 1] + backward[:, t + 1])[:, None, :], 2)
            backward[:, t] = np.where((t + 1 < lengths)[:, None], step, 0.0)
        norm = total(forward[np.arange(n), lengths - 1], 1)
        live = np.arange(longest) < lengths[:, None]
        marginal = np.where(live[:, :, None], np.exp(forward + backward - norm[:, None, None]), 0.0)
        move_grad = np.zeros_like(moves)
        for t in range(1, longest):
            pair = np.exp(forward[:, t - 1, :, None] + moves + (scores[:, t] + backward[:, t])[:, None, :] - norm[:, None, None])
            move_grad += pair[live[:, t]].sum(0)
        grad = np.zeros_like(self.weights)
        for s, sequence in enumerate(coded):
            for t, active in enumerate(sequence):
                row = marginal[s, t].copy()
                row[labels[s][t]] -= 1
                grad[active] += row
                if t:
                    move_grad[labels[s][t - 1], labels[s][t]] -= 1
        return grad, np.where(self.allowed, move_grad, 0.0)

    def decode(self, sequences: list[list[list[str]]]) -> list[list[int]]:
        """Viterbi over all sequences at once; longer ones are cut off from the batch as they end."""
        if not sequences or not len(self.weights):
            return [[0] * len(x) for x in sequences]
        coded = [[[j for f in active if (j := self.index.get(f)) is not None] for active in sequence] for sequence in sequences]
        order = sorted(range(len(coded)), key=lambda i: len(coded[i]))
        out: list[list[int]] = [[]] * len(coded)
        moves = self._moves()
        for some in _batches(order, [len(x) for x in coded]):
            scores, lengths = self._scores([coded[i] for i in some])
            n, longest, k = scores.shape
            best, back = np.where(self.start, scores[:, 0], -1e9), np.zeros((n, longest, k), np.int8)
            for t in range(1, longest):
                steps = best[:, :, None] + moves
                back[:, t] = steps.argmax(1)
                moved = steps.max(1) + scores[:, t]
                best = np.where((t < lengths)[:, None], moved, best)
            last = best.argmax(1)
            for s, i in enumerate(some):
                path = [int(last[s])]
                for t in range(lengths[s] - 1, 0, -1):
                    path.append(int(back[s, t, path[-1]]))
                out[i] = path[::-1]
        return out


def _batches(order: list[int], lengths: list[int]) -> Iterator[list[int]]:
    """Runs of ``order`` (shortest first) of at most 512 sequences and about DECODE_WORDS padded words."""
    some: list[int] = []
    for i in order:
        if some and (len(some) == 512 or (len(some) + 1) * lengths[i] > DECODE_WORDS):
            yield some
            some = []
        some.append(i)
    if some:
        yield some


def runs(text: str, most: int | None = None) -> list[tuple[list[str], list[tuple[int, int]], int, int]]:
    """Runs of words that may carry personal data: the words with their neighbours, offsets, first and last.

    ``most`` cuts longer runs (for training only: a cut may split a span).
    """
    found, words, spans = [], [], []
    for m in _WORD.finditer(text):
        words.append(m[0])
        spans.append(m.span())
    hot = [i for i, w in enumerate(words) if _SEED_WORD.search(w)]
    for a, b in _stretches(hot, most):
        low, high = max(0, a - 2), min(len(words), b + 2)
        found.append((words[low:high], spans[a : b + 1], a - low, b - low))
    return found


def _stretches(hot: list[int], most: int | None) -> Iterator[tuple[int, int]]:
    begin = None
    for i, at in enumerate(hot):
        begin = at if begin is None else begin
        if i + 1 == len(hot) or hot[i + 1] != at + 1 or most and at - begin + 1 >= most:
            yield begin, at
            begin = None


def _labels(spans: list[tuple[int, int]], gold: list[Span]) -> list[int]:
    out = []
    for a, b in spans:
        hit = next(((k, s) for k, s, e in gold if s < b and a < e), None)
        out.append(0 if hit is None else LABELS.index(f"{'B' if hit[1] >= a else 'I'}-{hit[0]}"))
    for t in range(len(out)):
        if LABELS[out[t]][0] == "I" and (t == 0 or LABELS[out[t - 1]][2:] != LABELS[out[t]][2:]):
            out[t] -= 1
    return out


def _rewritten(kind: str, text: str, k: int) -> list[str]:
    """The same datum in other notations."""
    digits = _NOT_DIGIT.sub("", text)
    if kind == "email":
        user, host = text.split("@", 1)
        return [f"{user}[at]{host}", f"{user}(at){host}"]
    if kind == "card":
        return [".".join(digits[i : i + 4] for i in range(0, len(digits), 4)), " - ".join(digits[i : i + 4] for i in range(0, len(digits), 4))]
    if kind == "phone":
        return [f"00{digits[:2]} {digits[2:5]} {digits[5:]}", f"({digits[-10:-7]}) {digits[-7:-4]}-{digits[-4:]}", f"0{digits[-10:-7]}/{digits[-7:]}"]
    return []


def _made_up(rng: np.random.Generator) -> Iterator[tuple[str, str, str]]:
    """(words before, kind or "", datum): what no pattern of the sample may hold."""
    digits = lambda n: "".join(map(str, rng.integers(0, 10, n)))
    some = lambda letters, n: "".join(letters[i] for i in rng.integers(0, len(letters), n))
    word = lambda: some("abcdefghijklmnoprstuvw", int(rng.integers(2, 9)))
    small, code = "0123456789abcdef", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789"
    for _ in range(MADE_UP):
        n = int(rng.choice([15, 16, 16, 16, 19, 13]))
        number = digits(n)
        fours = [number[i : i + 4] for i in range(0, n, 4)]
        yield word(), "card", (number, " ".join(fours), "-".join(fours), f"{number}{some('!$%*', 2)}")[int(rng.integers(0, 4))]
        secret = (some(small, 40), some(small, 32), some(small.upper(), 40), f"sk-{some(code, 32)}1a", f"{some(code, 24)}7b")[int(rng.integers(0, 5))]
        lead = ("token =", "key:", "secret =", "password:", word(), "Bearer")[int(rng.integers(0, 6))]
        yield lead, "secret", f'"{secret}"' if rng.random() < 0.5 else secret
    for _ in range(MADE_UP):  # numbers that are nobody's
        year, day, big = int(rng.integers(1900, 2100)), int(rng.integers(1, 29)), int(rng.integers(10**3, 10**8))
        for datum in (f"{year}-0{day % 9 + 1}-{day:02d}", f"{day}.{day % 12 + 1}.{year}", f"{big}", f"{big:,}", f"{day}.{day}.", f"{day % 9}.{day % 7}.{day}", f"${big / 100:.2f}", f"{day}%", f"v{day}.{day % 5}", f"{year}", f"{day}:{day + 20}", f"{day}th", f"{day % 9}.0", f"978-{day % 9}-{digits(6)}-{digits(2)}-{day % 7}", f"{word()}{day}", f"#{some(small, 6)}", f"{word()}-{day}"):
            if rng.random() < 0.25:
                yield word(), "", datum


def training_table(texts: Iterator[str], most: int = TRAIN_SPANS, seed: int = 11) -> tuple[list, list]:
    """Sequences of feature lists and their labels: at most TRAIN_SEQUENCES, all runs of the texts with equal chance."""
    rng = np.random.default_rng(seed)
    sequences, labels, spans_used, seen = [], [], 0, 0

    def learn(text: str, gold: list[Span], always: bool = False) -> None:
        nonlocal seen
        for words, spans, a, b in runs(text, TRAIN_WORDS):
            own = _labels(spans, gold)
            if not always and 0 in own:
                continue  # a number that no base pattern knows has no label
            seen += 1
            at = len(sequences) if len(sequences) < TRAIN_SEQUENCES else int(rng.integers(0, seen))
            if at < TRAIN_SEQUENCES:
                sequences[at:at + 1] = [[features(words, i) for i in range(a, b + 1)]]
                labels[at:at + 1] = [own]

    examples = []
    for text in texts:
        gold = base_spans(text)
        learn(text, gold)
        for k, s, e in gold if spans_used < most else []:
            spans_used += 1
            before, after = " ".join(text[max(0, s - 60) : s].split()[-2:]), " ".join(text[e : e + 60].split()[:1])
            examples += [(before, k, other, after) for other in _rewritten(k, text[s:e], spans_used)]
    examples += [(before, k, datum, "and") for before, k, datum in _made_up(rng)]
    for before, k, datum, after in examples:
        start = len(before) + 1
        learn(f"{before} {datum} {after}", [(k, start, start + len(datum))] if k else [], True)
    return sequences, labels


def train(docs: DataFrame, most: int = TRAIN_DOCS) -> Field:
    """From at most about ``most`` documents, taken by hash among those with a digit or @."""
    rows = ids_and_texts(docs).where(F.col("text").rlike("[0-9@]"))
    n = rows.count()
    picked = rows.where(F.pmod(F.xxhash64("doc_id", F.lit(5)), F.lit(1_000_000)) < 1_000_000 * min(1.0, most / max(n, 1))).orderBy("doc_id").select("text")
    field = Field()
    field.fit(*training_table(r["text"] for r in picked.toLocalIterator()))
    return field


def added_spans(texts: list[str], base: list[list[Span]], field: Field) -> list[list[Span]]:
    """What the field finds beyond the base spans."""
    owners, offsets, sequences, out = [], [], [], [[] for _ in texts]
    taken: dict[int, bytearray] = {}
    for i, text in enumerate(texts):
        if not _SEED_WORD.search(text):
            continue
        taken[i] = bytearray(len(text))
        for _, s, e in base[i]:
            taken[i][s:e] = b"\1" * (e - s)
        for words, spans, a, b in runs(text):
            if all(1 in taken[i][x:y] for x, y in spans):
                continue
            owners.append(i)
            offsets.append(spans)
            sequences.append([features(words, j) for j in range(a, b + 1)])
    for i, spans, path in zip(owners, offsets, field.decode(sequences), strict=True):
        t = 0
        while t < len(path):
            if not path[t]:
                t += 1
                continue
            kind, first = LABELS[path[t]][2:], t
            t += 1
            while t < len(path) and LABELS[path[t]] == f"I-{kind}":
                t += 1
            begin, end = spans[first][0], spans[t - 1][1]
            begin, end = _trimmed(texts[i], begin, end)
            if begin < end and has_parts(kind, texts[i][begin:end]) and 1 not in taken[i][begin:end]:
                out[i].append((kind, begin, end))
                taken[i][begin:end] = b"\1" * (end - begin)
    return out


def _trimmed(text: str, begin: int, end: int) -> tuple[int, int]:
    while begin < end and text[begin] in _AROUND:
        begin += 1
    while begin < end and text[end - 1] in _AROUND:
        end -= 1
    return begin, end


_AT = re.compile(r"[^@]+(?:@|[\[(]at[\])])[^@]+\.[^@.]+", re.I)


def has_parts(kind: str, text: str) -> bool:
    """The parts that a datum of the kind cannot do without, whatever its notation."""
    if kind == "email":
        return bool(_AT.fullmatch(text))
    if kind == "ip":
        return bool(_IP.fullmatch(text)) and valid(kind, text)
    digits, letters = sum("0" <= c <= "9" for c in text), sum(c.isalpha() for c in text)
    if kind == "secret":
        return digits > 0 and letters > 0 and digits + letters >= 16 and not any(c.isspace() for c in text)
    return not letters and (13 <= digits <= 19 if kind == "card" else 9 <= digits <= 15)


def digest(spans: list[Span]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b in spans)


def in_order(spans: list[Span]) -> list[Span]:
    return sorted(spans, key=lambda x: (ALL_KINDS.index(x[0]), x[1], x[2]))


def find(texts: list[str], field: Field) -> tuple[list[list[Span]], list[list[Span]]]:
    """Base spans, and all spans, of each text."""
    base = [base_spans(x) if _SEED_WORD.search(x) else [] for x in texts]
    more = added_spans(texts, base, field)
    return base, [in_order([*a, *b]) for a, b in zip(base, more, strict=True)]


_OUT = f"doc_id long, {', '.join(f'n_{k} long' for k in ALL_KINDS)}, n_spans long, n_added long, base_sha256 string, spans string"


def _report(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        field = shared.value
        for batch in slices(batches):
            texts = batch.column("text")
            hot = pc.match_substring_regex(texts, r"(?i)[0-9@]|[(\[]at[)\]]").to_numpy(zero_copy_only=False)
            some = np.flatnonzero(hot)
            base, every = find(texts.take(pa.array(some)).to_pylist(), field)
            n = batch.num_rows
            counts = np.zeros((n, len(ALL_KINDS)), np.int64)
            added = np.zeros(n, np.int64)
            hashes, spans = [hashlib.sha256(b"").hexdigest()] * n, [""] * n
            for i, b, e in zip(some.tolist(), base, every, strict=True):
                for kind, _, _ in e:
                    counts[i, ALL_KINDS.index(kind)] += 1
                added[i] = len(e) - len(b)
                hashes[i], spans[i] = hashlib.sha256(digest(b).encode()).hexdigest(), digest(e)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *(pa.array(counts[:, k]) for k in range(len(ALL_KINDS))), pa.array(counts.sum(1)), pa.array(added), pa.array(hashes), pa.array(spans)], ["doc_id", *(f"n_{k}" for k in ALL_KINDS), "n_spans", "n_added", "base_sha256", "spans"])

    return run


def report(docs: DataFrame) -> DataFrame:
    """One row per row of docs: counts of all spans by kind, of all and of those added, digest of the base spans, all spans.

    Null and empty texts hold none; repeated rows are reported as often as they occur, null ids as null; other columns
    are not read.
    """
    field = docs.sparkSession.sparkContext.broadcast(train(docs))
    return ids_and_texts(docs).mapInArrow(_report(field), _OUT)


def redact(text: str, spans: list[Span]) -> str:
    """The text with each span (the longest of those that overlap, then the first) replaced by its kind."""
    chosen: list[Span] = []
    for span in sorted(spans, key=lambda x: (x[1] - x[2], x[1], ALL_KINDS.index(x[0]))):
        if not any(s < span[2] and span[1] < e for _, s, e in chosen):
            chosen.append(span)
    out, end = [], 0
    for kind, a, b in sorted(chosen, key=lambda x: x[1]):
        out += [text[end:a], f"<{kind.upper()}>"]
        end = b
    return "".join([*out, text[end:]])


def _redacted(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        field = shared.value
        for batch in slices(batches):
            at = batch.schema.get_field_index("text")
            texts = batch.column(at).to_pylist()
            some = [i for i, x in enumerate(texts) if x and _SEED_WORD.search(x)]
            _, every = find([texts[i] for i in some], field)
            for i, spans in zip(some, every, strict=True):
                texts[i] = redact(texts[i], spans) if spans else texts[i]
            yield batch.set_column(at, "text", pa.array(texts, batch.schema.field(at).type))

    return run


def redacted(docs: DataFrame) -> DataFrame:
    """docs with the personal data in ``text`` replaced; null texts stay null, all other columns as they are."""
    field = docs.sparkSession.sparkContext.broadcast(train(docs))
    return docs.mapInArrow(_redacted(field), docs.schema)
