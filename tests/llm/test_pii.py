import hashlib
import random
import re

import numpy as np
import pytest

from provspark.llm import pii

from . import cases as make


class Groups:
    """Labels a word of four digits as the begin of a phone number, all others as its rest."""

    def decode(self, sequences):
        begin, rest = pii.LABELS.index("B-phone"), pii.LABELS.index("I-phone")
        return [[begin if "digits=4" in x else rest for x in sequence] for sequence in sequences]


def test_numbers_across_long_runs_are_found_whole():
    number, n = "0049 170 1234567", 200
    text = " ".join([number] * n)
    found = pii.added_spans([text], [[]], Groups())[0]
    assert found == [("phone", i * (len(number) + 1), i * (len(number) + 1) + len(number)) for i in range(n)]


def test_training_takes_all_runs_with_equal_chance(monkeypatch):
    monkeypatch.setattr(pii, "TRAIN_SEQUENCES", 300)
    texts = [" ".join(f"word 10.0.{i % 200}.{j}" for j in range(200)) for i in range(20)]
    sequences, labels = pii.training_table(iter(texts), most=0)
    assert len(sequences) == len(labels) == 300 and any(x == [0] for x in labels)


# the contract's patterns, as it states them
CONTRACT = {
    "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+",
    "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)",
    "card": r"[0-9]([\x20-]?[0-9])+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}


def contract_spans(text):
    out = []
    for kind, pattern in CONTRACT.items():
        for m in re.finditer(pattern, text):
            digits = [int(c) for c in m[0] if c in "0123456789"]
            luhn = sum(sum(divmod(2 * d, 10)) if i % 2 else d for i, d in enumerate(reversed(digits))) % 10 == 0
            good = {"email": True, "ip": all(int(x) <= 255 for x in m[0].split(".")) if kind == "ip" else False, "card": 13 <= len(digits) <= 19 and luhn, "phone": 9 <= len(digits) <= 15}[kind]
            if good:
                out.append(f"{kind}:{m.start()}:{m.end()}")
    return ",".join(out)


def odd_texts():
    rng = random.Random(3)
    signs = ["@", ".", "-", " ", "+", "(", ")", "1", "23", "4111 1111 1111 1111", "a", "b.c", "255", "10.0.0.1", "0", "+49 170 1234567", "x@y.example.org", "%", "_", "é", "é@b.de"]
    return ["".join(rng.choice(signs) for _ in range(rng.randint(0, 40))) for _ in range(3000)]


def test_base_spans_are_those_of_the_contract(spark):
    texts = odd_texts() + [t or "" for _, t, *_ in make.documents()]
    for text in texts:
        assert pii.digest(pii.base_spans(text)) == contract_spans(text), text
    some = spark.createDataFrame(list(enumerate(texts[:300])), "doc_id long, text string")
    for r in pii.report(some).collect():
        assert r["base_sha256"] == hashlib.sha256(contract_spans(texts[r["doc_id"]]).encode()).hexdigest()


def planted(rng):
    """(text, spans planted that no base pattern finds, as kind and datum)."""
    digits = lambda n: "".join(rng.choice("0123456789") for _ in range(n))
    word = lambda: make.prose(rng, "en", 3)
    text, wanted = word(), []
    for _ in range(rng.randint(0, 3)):
        kind = rng.choice(["card", "secret", "email", "phone", "none"])
        if kind == "card":
            datum = digits(16)
            if pii.luhn(datum):
                continue
        elif kind == "secret":
            datum = "".join(rng.choice("0123456789abcdef") for _ in range(40))
        elif kind == "email":
            datum = f"jo.{digits(2)}[at]mail{digits(1)}.example.com"
        elif kind == "phone":
            datum = f"(0{digits(2)}) {digits(3)}-{digits(4)}"
        else:
            datum = rng.choice(["2021-03-04", "12.5.1999", "v3.2", "$12.50", "17%", "1984", "4.0", "12:30", "3rd"])
        lead = "token = " if kind == "secret" else ""
        text += f" {lead}{datum} {word()}"
        wanted += [(kind, datum)] if kind != "none" else []
    return text, wanted


def test_added_spans_of_a_planted_table(spark):
    rng = random.Random(8)
    made = [planted(rng) for _ in range(400)]
    base = [(1000 + i, f"{make.prose(rng, 'en', 4)} jo.{i}@mail.example.org {make.prose(rng, 'en', 2)} +1 ({i:03d}) 555-{i:04d} end 10.0.0.{i % 250} and 4111 1111 1111 1111 so") for i in range(150)]
    docs = spark.createDataFrame([*((i, t) for i, (t, _) in enumerate(made)), *base], "doc_id long, text string")
    hit, found, wanted = 0, 0, 0
    for r in pii.report(docs).where("doc_id < 1000").collect():
        text, gold = made[r["doc_id"]]
        plain = set(filter(None, contract_spans(text).split(",")))
        own = {(x.split(":")[0], text[int(x.split(":")[1]) : int(x.split(":")[2])]) for x in r["spans"].split(",") if x and x not in plain}
        hit, found, wanted = hit + len(own & set(gold)), found + len(own), wanted + len(set(gold))
        assert r["n_added"] >= len(own) and r["n_spans"] == len(list(filter(None, r["spans"].split(","))))
    assert hit >= 0.95 * found and hit >= 0.9 * wanted


def test_odd_rows(spark):
    rows = [(1, None, "x"), (None, "a@b.de", "y"), (5, "a@b.de", "z"), (5, "a@b.de", "z"), (6, "1 " * 30_000, "w")]
    got = pii.report(spark.createDataFrame(rows, "doc_id long, text string, spans string")).collect()
    assert len(got) == 5 and sorted(r["n_email"] for r in got) == [0, 0, 1, 1, 1]


def test_redaction_takes_the_longest():
    assert pii.redact("x 10.0.0.1 y", [("ip", 2, 10), ("phone", 2, 6)]) == "x <IP> y"


def test_no_examples_no_labels():
    field = pii.Field()
    assert field.decode([[["bias"]], [["bias"], ["bias"]]]) == [[0], [0, 0]]
    assert np.array(field.weights).size == 0


@pytest.mark.parametrize("text, kind, good", [("9807915762804490", "card", True), ("1234", "card", False), ("a[at]b.de", "email", True), ("ab", "email", False), ("0170/1234567", "phone", True), ("d41d8cd98f00b204e9800998ecf8427e", "secret", True), ("deadbeef", "secret", False)])
def test_parts(text, kind, good):
    assert pii.has_parts(kind, text) == good
