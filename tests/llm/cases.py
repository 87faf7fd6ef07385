"""A small table with the cases that every operator has to handle."""

from __future__ import annotations

import random

SCHEMA = "doc_id long, text string, lang string, source string"
_SYLLABLES = {"en": "the and ing ton wh er st".split(), "de": "der sch ung ich ein keit zu".split()}


def prose(rng: random.Random, lang: str, n: int) -> str:
    return " ".join("".join(rng.choice(_SYLLABLES[lang]) for _ in range(rng.randint(1, 4))) for _ in range(n))


def documents() -> list[tuple]:
    """Null, empty, blank, signs only, personal data, copies, near copies, a long text, null sources and languages."""
    rng = random.Random(4)
    rows = [(1, None, None, None), (2, "", "en", "s1"), (3, "Write to jo.doe@mail.example.org or +49 (170) 123-4567, 4111 1111 1111 1111 at 10.0.0.1", None, "s1"), (5, " \t\n 12 # % ", "de", None)]
    base = prose(rng, "en", 120)
    near = base.split()
    near[60] = "Other"
    rows += [(10, base, "en", "s1"), (11, base, "en", "s2"), (12, " ".join(near), "en", "s2"), (13, base.upper(), "en", "s2")]
    rows += [(20, "one two three", "en", "s3"), (21, "one two  three", "en", "s3"), (22, "a b c d e f g h " * 40, "en", "s3"), (23, "line\nline\nother\nline", "en", "s3")]
    rows += [(24, prose(rng, "en", 6000), "en", "s3"), (25, "éß中\U0001f600 <|endoftext|> 'S İx café", "de", "s4")]
    for i in range(30, 110):
        lang = "en" if i % 2 else "de"
        text = prose(rng, lang, rng.randint(12, 90))
        if i % 5 == 0:
            text += " vorgle " + prose(rng, lang, 3)
        rows.append((i, text, lang, f"s{i % 5}"))
    return rows
