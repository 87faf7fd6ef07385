import pytest

from provspark.rules import Atom, Program, Query, RuleError, Var, adorned, parse, rules, with_rule_probability


def test_parse_rules_facts_and_comments():
    own, given = parse("0.4::e(a, 'B c').  % a fact\np(X,Y) :- e(X,Y). 0.7::p(X,3) :- p(X,Y), e(Y,2.5).")
    assert given[0].pi == 0.4 and given[0].atom == Atom("e", ("a", "B c"))
    assert own[0].body[0].args == (Var("X"), Var("Y")) and own[1].prob == 0.7
    assert own[1].head.args == (Var("X"), 3)


@pytest.mark.parametrize("text", ["p(X,Y) :- e(X).", "p(X) :- ", "p(X :- e(X).", "p(X)."])
def test_bad_rules_are_refused(text):
    with pytest.raises(RuleError):
        parse(text)


def test_arity_and_unknown_predicates():
    from provspark.rules import check_program

    with pytest.raises(RuleError):
        check_program(Program(rules("p(X) :- p(X,X).")))
    with pytest.raises(RuleError):
        check_program(Program(rules("p(X) :- nothing(X).")))


def test_rule_probability_adds_a_coin():
    rule, coin = with_rule_probability(rules("0.3::p(X) :- e(X).")[0])
    assert rule.body[-1] == coin == Atom("rule_on", ("r1",)) and rule.prob is None
    _, coin = with_rule_probability(rules("p(X) :- e(X).")[0], "grounding")
    assert coin.args == ("r1", Var("X"))


def test_rewriting_carries_bindings():
    program = Program(rules("reach(X,Y) :- edge(X,Y). reach(X,Y) :- reach(X,Z), edge(Z,Y)."), {"edge": None})
    out, demand, seed = adorned(program, Query.parse("q(Y) :- reach(1,Y)."))
    assert seed == "need_seed"
    assert {r.head.pred for r in out} == {"q", "reach__bf"}
    assert {r.head.pred for r in demand} == {"need_reach__bf"}
