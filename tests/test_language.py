import pytest

from rpqframe.functions import conditions as C
from rpqframe.functions.paths import LAST
from rpqframe.operators.automata import compile_dfa, is_unambiguous
from rpqframe.plans.lang import parse
from rpqframe.plans.regex import ParseError, first_labels, lengths, normalize, parse_regex, uniform_len
from rpqframe.plans.workload import SHAPES, abstract_queries, seed_label, templates
from rpqframe.sources.tables import EDGES


def test_precedence():
    assert str(parse_regex("a|b.c+")) == "(a|(b.c+))" and str(parse_regex("!a.b?")) == "(!a.b?)"


@pytest.mark.parametrize("bad", ["a|", "(a", "a)", "!", "a b", "+a", ""])
def test_bad_patterns(bad):
    with pytest.raises(ParseError):
        parse_regex(bad)


def test_query_parts():
    q = parse('MATCH TRAIL p = (x)-[(likes.hasCreator)*]-(y) WHERE x.id = 7 AND NOT (y.name = "a" OR label(edge(2)) = "b") RETURN p, y.name AS n, length() LIMIT 5')
    assert q.tau == "trail" and q.limit == 5 and [a for a, _ in q.returns] == ["p", "n", "length()"]
    assert C.conjuncts(q.where)[0] == C.Cmp(C.node(1), "=", 7)
    assert parse("MATCH p = (a)-[k]->(b) RETURN b").tau == "walk"
    assert parse("MATCH WALK p = (x)-[k]->(y) RETURN nProp(len()+1, name)").returns[0][1] == C.prop("node", LAST, "name")


@pytest.mark.parametrize("bad", ["MATCH p = (x)-[a]->(y)", "MATCH TRAIL (x)-[a]->(y) RETURN p", "MATCH p = (x)-[a]->(y) WHERE x.n RETURN p", "MATCH p = (x)-[a]->(y) RETURN p LIMIT", "MATCH p = (x)-[a]->(y) WHERE node(0) = 1 RETURN p"])
def test_bad_queries(bad):
    with pytest.raises((ParseError, ValueError)):
        parse(bad)


def test_static_facts():
    assert lengths(parse_regex("a+.b?")) == (1, None) and uniform_len(parse_regex("a.b|c.d")) == 2
    assert first_labels(parse_regex("a?.b")) == ["a", "b"]
    for a, b in (("(a?)+", "a*"), ("(a*)?", "a*"), ("(a+)*", "a*"), ("a??", "a?"), ("(a*)*", "a*"), ("(a+)?", "a*")):
        assert normalize(parse_regex(a)) == parse_regex(b)


def test_ambiguity():
    alphabet = list(EDGES)
    assert not is_unambiguous(parse_regex("(knows|knows.knows)+"), alphabet) and not is_unambiguous(parse_regex("knows|knows"), alphabet)
    assert all(is_unambiguous(parse_regex(t), alphabet) for s in abstract_queries() for t in templates(s))


def test_workload_size():
    assert len(SHAPES) == 26 and sum(len(templates(s)) for s in abstract_queries()) == 142
    assert all(seed_label(t) in EDGES for s in abstract_queries() for t in templates(s))


def test_dfa_of_the_running_example():
    d = compile_dfa(parse_regex("(likes.hasCreator)+"), ["likes", "hasCreator", "knows"])
    assert len(d.moves) == 3 and d.states() == 3 and len(d.finals) == 1
