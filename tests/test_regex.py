import itertools
import re

import pytest

from pathsieve.plans.regex import automaton, determinize, drop_epsilon, glushkov, is_ambiguous, min_hops_to_accept, minimize, parse_regex, thompson

LABELS = "abc"
EXPRESSIONS = ["a+ b", "a* b?", "(a | b c)+", "a{2,3} c", ". b .", "[^a]{2}", "(a | a a)+ b", "x:(a b?)* y:c", "a{0,2}", "a{2,}", "(a | b)* c (a | b)"]


def as_python(text):
    text = re.sub(r"\w+:", "", text)
    return re.compile(text.replace(" ", "").replace(".", "[abc]") + r"\Z")


@pytest.mark.parametrize("text", EXPRESSIONS)
def test_languages_equal_those_of_re(text):
    tree = parse_regex(text)
    plain = parse_regex(re.sub(r"\w+:", "", text))
    built = [glushkov(tree, LABELS), drop_epsilon(*thompson(tree, LABELS)), automaton(text, LABELS), minimize(determinize(glushkov(plain, LABELS)))]
    for n in range(6):
        for word in itertools.product(LABELS, repeat=n):
            expected = bool(as_python(text).match("".join(word)))
            assert [x.accepts(word) for x in built] == [expected] * len(built), (text, word)


def test_sizes_and_tags():
    assert automaton("dom:Domestic+ fgn:Foreign").rows() == [(0, 1, "Domestic"), (1, 1, "Domestic"), (1, 2, "Foreign")]
    q1 = automaton("normal:(click|view|purchase)+ fishy:(error|signup)+")
    assert len(q1.rows()) == 10 and q1.tags == {1: "normal", 2: "fishy"} and q1.accepting == {2}
    assert min_hops_to_accept(q1) == {2: 0, 1: 1, 0: 2}


def test_ambiguity():
    text = "(a | a a)+ b"
    assert is_ambiguous(glushkov(parse_regex(text))) and not is_ambiguous(automaton(text))
    mixed = automaton("x:a y:a | x:a z:a b?")  # tags would be mixed: every place stays
    assert is_ambiguous(mixed)


@pytest.mark.parametrize("text", ["a |", "(a", "a)", "+a", "a{3,1}", "a %"])
def test_errors(text):
    if text == "a |":
        assert parse_regex(text).kind == "alt"  # an empty branch
    else:
        with pytest.raises(ValueError):
            parse_regex(text)
