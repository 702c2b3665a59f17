import re
from itertools import product

import pytest

from walkengine.lang.automata import (
    Nfa, close_spontaneous, compile_pattern, determinize, equivalent, inductive_nfa, minimize, position_nfa, reverse, trim_states,
)
from walkengine.lang.patterns import EMPTY, parse_pattern

WORDS = ["".join(w) for n in range(6) for w in product("ab", repeat=n)]
PATTERNS = {"a*": "a*", "(a|b)* a (a|b)": "(a|b)*a(a|b)", "a? (b a)+": "a?(ba)+", "()": "", "a{2,3} b*": "a{2,3}b*", "(a|())(b|a b)*": "(a|)(b|ab)*", "a{2,}": "a{2,}"}


@pytest.mark.parametrize("text", PATTERNS)
def test_constructions_accept_the_pattern_s_words(text):
    ast, expected = parse_pattern(text), re.compile(PATTERNS[text])
    forms = [inductive_nfa(ast), position_nfa(ast)]
    forms += [close_spontaneous(forms[0]), trim_states(close_spontaneous(forms[0])), determinize(forms[0]), minimize(forms[0]), reverse(reverse(forms[0]))]
    for nfa in forms:
        assert [w for w in WORDS if nfa.accepts(w)] == [w for w in WORDS if expected.fullmatch(w)]
    assert equivalent(forms[0], forms[1])
    assert len(inductive_nfa(ast).moves) <= ast.size() and inductive_nfa(ast).n <= 4 * ast.size()
    assert position_nfa(ast).n <= ast.size() + 1


def test_any_and_other_labels_need_an_alphabet():
    nfa = compile_pattern(". !a", ("a", "b"))
    assert nfa.accepts("ab") and nfa.accepts("bb") and not nfa.accepts("ba")


@pytest.mark.parametrize("text", ["(", "a)", "*", "a |* b", "{2}", "a ! *"])
def test_bad_patterns_are_refused(text):
    with pytest.raises(ValueError):
        parse_pattern(text)


def test_sizes_and_properties():
    assert parse_pattern("") == EMPTY
    assert compile_pattern("h* s (h|s)*").is_unambiguous()
    second = Nfa.of(2, [(0, "h", 0), (0, "s", 0), (0, "s", 1), (1, "h", 1), (1, "s", 1)], [0], [1])
    assert not second.is_unambiguous() and not second.is_deterministic() and minimize(second).is_deterministic()
    assert minimize(second).n == 2
