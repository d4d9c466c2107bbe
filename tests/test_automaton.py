import itertools
import random

import pytest

from waypoint.plans.automaton import determinised, minimised, parse, position_automaton, prepared, reversed_automaton, single_final, thompson_automaton

EXPRESSIONS = ["a*/a*", "(a|b)*/a/(a|b)", "a?", "(a/b)*", "a{2,3}/b?", "a|b/c?", "(a|a/b)*", "a+/b*/c", "()", "a{2,}"]
WORDS = [w for n in range(6) for w in itertools.product("abc", repeat=n)]


@pytest.mark.parametrize("text", EXPRESSIONS)
def test_constructions_agree(text):
    a, b = position_automaton(parse(text)), thompson_automaton(parse(text))
    d, m = determinised(a), minimised(a)
    one, empty = single_final(a)
    back = reversed_automaton(a)
    assert d.is_deterministic() and d.is_unambiguous() and m.n <= d.n and len(one.finals) <= 1
    for w in WORDS:
        want = a.accepts(w)
        assert want == b.accepts(w) == d.accepts(w) == m.accepts(w)
        assert want == (one.accepts(w) or (empty and not w))
        assert want == back.accepts(tuple("^" + x for x in reversed(w)))


def test_ambiguity():
    assert not position_automaton(parse("a*/a*")).is_unambiguous()
    assert position_automaton(parse("a*/b*")).is_unambiguous()
    with pytest.raises(ValueError):
        prepared("a*/a*", ambiguity="error")


def test_wildcards_and_errors():
    assert prepared("!(a|b)", {"a", "b", "c"}).labels == {"c"}
    assert prepared(".", {"a", "b"}).labels == {"a", "b"}
    for bad in ("a/", "(a", "a)", "|", "a{"):
        with pytest.raises(ValueError):
            parse(bad)
    random.seed(0)
