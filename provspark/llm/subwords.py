"""Public subword tokenizers over whole texts, each distinct word encoded once per worker.

White space never joins two words into one subword, so a text's ids are its words' ids in a row.  Words of plain
letters go straight to the library's merge model; any other word goes through the library's whole pipeline.
"""

from __future__ import annotations

import os
import re
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from .common import Words

#: Words kept by a worker before it starts afresh.
CACHE_WORDS = 400_000

_PLAIN = re.compile(r"([a-zß-öø-ÿ]+)([.,]*)").fullmatch


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def _byte_characters() -> dict[int, str]:
    """Byte-level alphabet: printable Latin-1 bytes stand for themselves, the others follow from 256 on."""
    kept = {*range(33, 127), *range(161, 173), *range(174, 256)}
    others = (b for b in range(256) if b not in kept)
    return {b: chr(b) for b in kept} | {b: chr(256 + i) for i, b in enumerate(others)}


class WordEncoder:
    """Ids of words as little-endian 16-bit strings; ``ids(words)`` gives those of whole texts."""

    def __init__(self, path: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.wide = self.library.get_vocab_size() > 1 << 16
        self.kind = np.dtype("<u4" if self.wide else "<u2")
        self.alphabet = _byte_characters()
        self.words: dict[str, bytes] = {}

    def _pack(self, ids: list[int]) -> bytes:
        return np.array(ids, self.kind).tobytes()

    def _run(self, letters: str) -> bytes:
        found = self.words.get(letters)
        if found is None:
            coded = letters if letters.isascii() else letters.encode().decode("latin1").translate(self.alphabet)
            found = self.words[letters] = self._pack([x.id for x in self.library.model.tokenize(coded)])
        return found

    def _encode(self, word: str) -> bytes:
        plain = _PLAIN(word)
        if plain:
            return self._run(plain[1]) + (self._run(plain[2]) if plain[2] else b"")
        return self._pack(self.library.encode(word, add_special_tokens=False).ids)

    def ids(self, words: Words) -> tuple[np.ndarray, np.ndarray]:
        """All ids of the slice, and the number of ids of each text."""
        out, each = self.ids_by_word(words)
        return out, np.diff(np.concatenate([[0], np.cumsum(each)])[words.starts])

    def coded(self, words: list[str], kept: int = CACHE_WORDS) -> tuple[np.ndarray, np.ndarray]:
        """The ids of distinct words in a row, and the number of ids of each."""
        if len(self.words) > kept:
            self.words.clear()
        known, coded = self.words, []
        for word in words:
            ids = known.get(word)
            if ids is None:
                ids = known[word] = self._encode(word)
            coded.append(ids)
        return np.frombuffer(b"".join(coded), self.kind), np.fromiter(map(len, coded), np.int64, len(coded)) // self.kind.itemsize

    def ids_by_word(self, words: Words) -> tuple[np.ndarray, np.ndarray]:
        """All ids of the slice, and the number of ids of each word."""
        flat, lengths = self.coded(words.values.to_pylist())
        return spread(flat, np.cumsum(lengths) - lengths, lengths, words.codes)


def spread(flat: np.ndarray, begins: np.ndarray, lengths: np.ndarray, codes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The ids of the words ``codes``, and the number of ids of each; word i has ``lengths[i]`` from ``flat[begins[i]]`` on."""
    each = lengths[codes]
    ends = np.cumsum(each)
    total = int(ends[-1]) if len(ends) else 0
    return flat[np.repeat(begins[codes] - (ends - each), each) + np.arange(total)], each


@lru_cache(maxsize=2)
def encoder(path: str) -> WordEncoder:
    return WordEncoder(path)


def encode_texts(texts: pa.Array, path: str) -> tuple[np.ndarray, np.ndarray]:
    """Ids and counts of whole texts.  Upper-case letters matter only inside special tokens, so a slice with
    such a mark keeps its case."""
    marked = bool(pc.any(pc.match_substring(texts, "<|")).as_py())
    return encoder(path).ids(Words(texts, lower=not marked))
