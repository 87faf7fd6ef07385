import pytest

from provspark import queries
from provspark.plans.baselines import formula_fixpoint
from provspark.queries import QUERIES


def test_page_links_over_paths_of_many_pages(spark, tmp_path):
    hrefs = {i: ["/hot", f"/own{i}"] for i in range(7)} | {10: ["/pair"], 11: ["/pair", "/next"], 12: ["/next"], 13: ["/alone"]}
    rows = [(i, " ".join(f'<a href="http://h{i}.org{x}">' for x in paths)) for i, paths in hrefs.items()]
    spark.createDataFrame(rows, "page_id long, html string").write.parquet(f"{tmp_path}/pages.parquet")
    got = {r["page_id"]: r["component"] for r in QUERIES["page_link_reach"](spark, str(tmp_path)).collect()}
    assert got == {**dict.fromkeys(range(7), 0), 10: 10, 11: 10, 12: 10, 13: 13}


def test_all_scenes_take_part(spark, monkeypatch):
    asked = []
    monkeypatch.setattr(queries.graphs, "scenes", lambda *given, **named: asked.append((given[2:], named)) or 1 / 0)
    queries.w.forget()
    for name in ("vqa_exact", "vqa_error_hist", "vqa_answers", "vqa_attributes"):
        with pytest.raises(ZeroDivisionError):
            QUERIES[name](spark, "none")
    assert asked == [((), {})] * 4


def test_unanswered_facts_are_no_errors(spark):
    rows = [(0.5, 0.45, "ok"), (0.5, None, "ok"), (None, 0.3, "node_cap"), (None, None, "node_cap")]
    got = queries.error_buckets(spark.createDataFrame(rows, "exact double, approx double, status string"))
    assert {r["bucket"]: r["n"] for r in got.collect()} == {1: 1, 9: 1, -1: 2}


def test_bounds_above_the_exact_value_are_refused(spark):
    rows = spark.createDataFrame([(0.5, 0.6, "ok")], "exact double, approx double, status string")
    with pytest.raises(Exception, match="above the exact"):
        queries.error_buckets(rows).collect()


def test_unknown_fixpoint_modes_are_refused(spark):
    with pytest.raises(ValueError, match="sideways"):
        formula_fixpoint(queries.w.reach_example(spark), "sideways")


def test_the_ontology_has_127_rules_in_few_shapes(spark):
    from provspark.plans.compile import shapes
    from provspark.workloads import onto

    own = onto.ontology_rules(spark, "/root/testdata/sf0.001")
    plans = shapes(own)
    assert len(own) == 127 == sum(len(p.ids) for p in plans) and len(plans) < 50


def test_generated_queries_have_one_to_four_atoms_that_hang_together():
    from provspark.rules import Program, rules
    from provspark.workloads import onto
    from provspark.workloads.generate import generate_queries

    made = generate_queries(Program(rules(onto.CORE)), 50)
    for q in made:
        seen = set(q.body[0].variables)
        for atom in q.body[1:]:
            assert seen & set(atom.variables)
            seen |= set(atom.variables)
        assert 1 <= len(q.body) <= 4 and set(q.head.variables) <= seen
