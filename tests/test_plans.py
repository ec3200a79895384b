import random
import re

import pytest

from wfpath.plans import rpq, safety, spec
from wfpath.plans.spec import BadSpec, Spec
from wfpath.sources.runs import CARRIERS, EXAMPLE


def test_example_specification():
    assert EXAMPLE.size == 15 and EXAMPLE.cycles[0].slots == ((2, 2),)
    assert (EXAMPLE.colour(2, 1), EXAMPLE.colour(2, 3), EXAMPLE.colour(1, 1)) == ("red", "blue", None)


@pytest.mark.parametrize("rules, fine", [
    ([("S", "a S b"), ("S", "a")], True),
    ([("S", "a S b"), ("S", "c S d"), ("S", "a")], False),
    ([("S", "a {S S} b"), ("S", "a")], False),
    ([("S", "a T b"), ("T", "c S d"), ("T", "e")], True),
    ([("S", "a {T U} b"), ("T", "c S d"), ("U", "c S d"), ("T", "e"), ("U", "e"), ("S", "f")], False),
    ([("S", "a {T U} b"), ("T", "c T d"), ("T", "e"), ("U", "c U d"), ("U", "e")], True),
])
def test_strict_linearity(rules, fine):
    assert Spec.chain("S", rules).is_strictly_linear() == fine


def test_bad_specifications():
    for rules in ([("S", ["a", "b"], [(1, 2), (2, 1)])], [("S", ["a", "b"], [])], [("S", [], [])], [("T", ["a"], [])]):
        with pytest.raises(BadSpec):
            Spec.build("S", rules)


def test_published_statistics():
    assert tuple(spec.deep_like().statistics.values()) == spec.DEEP
    assert tuple(spec.branchy_like().statistics.values()) == spec.BRANCHY
    assert spec.branchy_like().is_strictly_linear() and spec.deep_like().is_strictly_linear()
    for size in (400, 1200):
        made = spec.random_spec(size, cycle_len=2, seed=size)
        assert made.is_strictly_linear() and abs(made.size - size) < 40


def _pattern(x, name):
    match x.kind:
        case "eps":
            return "(?:)"
        case "any":
            return "."
        case "tag":
            return name.get(x.tag, "(?!)")
        case "cat":
            return "".join(f"(?:{_pattern(p, name)})" for p in x.parts)
        case "alt":
            return "|".join(f"(?:{_pattern(p, name)})" for p in x.parts)
    return f"(?:{_pattern(x.parts[0], name)})" + {"star": "*", "plus": "+"}[x.kind]


def test_automata_against_regular_expressions():
    tags, rng = ("x", "y", "z"), random.Random(4)
    name = {t: t for t in tags}
    for seed in range(120):
        q = rpq.random_rpq(tags, seed, 1 + seed % 5)
        dfa, other = rpq.compile_(q, tags), rpq.compile_(rpq.rewrite(q), tags)
        assert rpq.equivalent(dfa, other) and dfa == other, q
        pattern = re.compile(_pattern(q, name))
        for _ in range(40):
            word = [rng.choice(tags) for _ in range(rng.randint(0, 6))]
            assert rpq.accepts(dfa, word) == bool(pattern.fullmatch("".join(word))), (q, word)
        assert rpq.parse(str(q)) == q or rpq.equivalent(rpq.compile_(rpq.parse(str(q)), tags), dfa)


def test_parsing():
    assert rpq.parse("a.(b|c)+ _* 'x y'?") == rpq.cat(rpq.tag("a"), rpq.plus(rpq.alt(rpq.tag("b"), rpq.tag("c"))), rpq.reach(), rpq.alt(rpq.tag("x y"), rpq.EPS))
    for bad in ("a|", "(a", "a)", "*", ""):
        with pytest.raises(ValueError):
            rpq.parse(bad)
    assert rpq.is_deterministic(rpq.parse("a.(b|c)*")) and not rpq.is_deterministic(rpq.parse("(a|b)*.a"))
    assert rpq.compile_(rpq.tag("nowhere"), ("a",)).n == 1


def test_alternation_of_safe_queries_can_be_unsafe():
    g = Spec.build("S", [
        ("S", ["i", "M", "o", "z", "e"], [(1, 2, "i"), (2, 3, "r"), (2, 4, "s"), (3, 5, "o"), (4, 5, "z")]),
        ("M", ["p", "a", "b", "q"], [(1, 2, "x"), (1, 3, "y"), (2, 4, "u"), (3, 4, "w")]),
        ("M", ["p", "a", "b", "q"], [(1, 2, "x"), (1, 3, "y"), (2, 4, "w"), (3, 4, "u")]),
    ])
    one, two = rpq.parse("x._.r"), rpq.parse("_.u.s")
    assert safety.is_safe(g, one) and safety.is_safe(g, two) and not safety.is_safe(g, rpq.alt(one, two))


def test_witness():
    with pytest.raises(safety.UnsafeQuery) as e:
        safety.compile_rpq(EXAMPLE, "e")
    assert e.value.witness.module == "A"
    assert safety.is_safe(CARRIERS["events"].spec, "_*") and not safety.is_safe(CARRIERS["orders"].spec, "_*.pick._*")
