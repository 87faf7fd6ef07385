"""Stages of the corpus pipeline on odd tables: null and shared ids, nulls everywhere, empty tables, helper names."""

import random

import pytest

from . import cases as make

pytest.importorskip("corpus_pipeline")
SCHEMA = "doc_id long, text string, source string, n_chars int, _copies int, _copy int, _row string, _document string, n_words string, key string, size int"


def rows():
    rng = random.Random(9)
    texts = [make.prose(rng, "en", 40) for _ in range(12)]
    out = [(i, t, f"s{i % 3}") for i, t in enumerate(texts)]
    out += [(20, texts[0], "s0"), (20, texts[0], "s0"), (None, texts[1], "s1"), (None, make.prose(rng, "en", 50), None), (None, make.prose(rng, "en", 50), None)]
    out += [(30, None, "s1"), (31, "", None), (30, " ", "s1"), (40, make.prose(rng, "en", 30_000), "s2")]
    return [(d, t, s, None if t is None else len(t), 7, 8, "r", "d", "w", "k", 9) for d, t, s in out]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(rows(), SCHEMA).repartition(3)


def stage(name):
    import corpus_pipeline

    return dict(corpus_pipeline.STAGES)[name]


def key(r):
    return tuple((x is None, x) for x in r)


@pytest.mark.parametrize("name", ["quality_rules", "near_duplicates", "personal_data", "source_mixing"])
def test_columns_stay_and_empty_tables_pass(spark, docs, name):
    nothing = spark.createDataFrame([], SCHEMA)
    assert stage(name)(spark, docs, "").columns == docs.columns
    got = stage(name)(spark, nothing, "")
    assert got.columns == docs.columns and got.count() == 0


def test_quality_rules(spark, docs):
    got = stage("quality_rules")(spark, docs, "").collect()
    wanted = [r for r in rows() if r[1] and r[1].strip()]
    assert sorted(map(tuple, got), key=key) == sorted(wanted, key=key)


def test_near_duplicates_keep_one_of_repeated_rows_and_rows_without_an_id(spark, docs):
    got = sorted(map(tuple, stage("near_duplicates")(spark, docs, "").collect()), key=key)
    wanted, seen = [], set()
    for r in sorted(rows(), key=lambda r: (r[0] is None, r[0] or 0)):
        if not (r[1] or "").strip() or r[1] not in seen:
            wanted.append(r)
            seen.add(r[1])
    assert got == sorted(wanted, key=key)


def test_mixing_takes_rows_without_an_id(spark, docs):
    from provspark.llm import mixing

    got = stage("source_mixing")(spark, docs, "").collect()
    goals = {r["key"]: (r["target"], r["source_size"]) for r in mixing.copies(docs).collect()}
    for name in {r[2] for r in rows()}:
        own = sum(len((r["text"] or "").split()) for r in got if r["source"] == name)
        longest = max(len((r[1] or "").split()) for r in rows() if r[2] == name)
        assert abs(own - goals["" if name is None else f"={name}"][0]) <= longest
    assert any(r["doc_id"] is None for r in got)
    times = {}
    for r in got:
        times[tuple(r)] = times.get(tuple(r), 0) + 1
    assert all(n <= 3 * rows().count(r) for r, n in times.items())


def test_targets_by_the_rule(docs):
    """Weights 5, 2, 1 in turn by code point, null last; nothing above three times its source."""
    from provspark.llm import mixing

    sizes = {}
    for r in rows():
        sizes[r[2]] = sizes.get(r[2], 0) + len((r[1] or "").split())
    order = sorted(sizes, key=lambda x: (x is None, x or ""))
    weight = {x: (5, 2, 1)[i % 3] for i, x in enumerate(order)}
    capped: set = set()
    while True:
        free = [x for x in order if x not in capped]
        room = sum(sizes.values()) - sum(3 * sizes[x] for x in capped)
        goal = {x: 3 * sizes[x] if x in capped else room * weight[x] / sum(weight[y] for y in free) for x in order}
        over = {x for x in free if goal[x] > 3 * sizes[x]}
        if not over:
            break
        capped |= over
    got = {r["key"]: r["target"] for r in mixing.copies(docs).collect()}
    assert got == pytest.approx({"" if x is None else f"={x}": t for x, t in goal.items()})


def test_personal_data_counts_characters_again(spark):
    docs = spark.createDataFrame([(1, "mail to a.b@c.example.org", 25), (2, None, None)], "doc_id long, text string, n_chars int")
    got = {r["doc_id"]: r for r in stage("personal_data")(spark, docs, "").collect()}
    assert got[1]["text"] == "mail to <EMAIL>" and got[1]["n_chars"] == 15 and got[2]["n_chars"] is None


def test_last_stage_packs_every_row(spark, docs):
    from provspark.llm import packing
    from provspark.llm.subwords import default_path

    got = packing.pack(docs, default_path(), 256).collect()
    assert len([r for r in got if r["piece"] == 0]) == len(rows()) and sum(r["doc_id"] is None and r["piece"] == 0 for r in got) == 3
