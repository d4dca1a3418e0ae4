import pytest

from rulemat.engine.reasoner import infer_types
from rulemat.lang import RuleError, check_program, parse_program
from rulemat.lang.syntax import SyntaxFault


def test_text_round_trip():
    text = '@a m(x, median(t)) <- near(x, y), temp(y, t) group x.\n@b s(x, d) <- m(x, k), temp(x, t), !off(x), d := ((t - k) * 2), d > 5000, t != -1.5.\n@c f(1, "a").'
    p = parse_program(text)
    assert p.text().splitlines() == [line.replace(" <- .", ".") for line in text.splitlines()]
    assert parse_program(p.text()).rules == p.rules


def test_keyword_dialect():
    p = parse_program("r8: p2(X, Z) :- p3(X, Y) and p2(Y, Z). h(?x, ?m) :- AGGREGATE(p(?x, ?y) and COMP(?y, >=, 3)) ON ?x WITH MED(?y) AS ?m . k(?x, ?v) :- p(?x, ?y), BIND(?y + 1 AS ?v), not q(?x).")
    r8, h, k = p
    assert r8.id == "r8" and [a.pred for a in r8.positives] == ["p3", "p2"]
    assert (h.agg.fn, h.agg.var, h.agg.result, h.agg.group) == ("median", "y", "m", ("x",))
    assert k.binds[0].var == "v" and k.negatives[0].pred == "q"


def test_equal_up_to_names():
    a, b = parse_program("@a p(x, z) <- q(x, y), r(y, z)."), parse_program("@b p(u, w) <- q(u, v), r(v, w).")
    c = parse_program("@c p(u, w) <- q(u, v), r(w, v).")
    shape = lambda p: next(iter(p)).shape()
    assert shape(a) == shape(b) != shape(c)


@pytest.mark.parametrize(
    "text",
    ["p(x, y) <- q(x).", "p(x) <- q(x), !r(x, y).", "p(x) <- q(x), y > 3.", "p(y) <- q(x), y := z + 1.", "p(x).", "p(x) <- q(x). p(x, y) <- r(x, y).", "@a p(x, count(y)) <- q(x, y) group x. @b p(x, y) <- q(x, y).", "p(x, count(z)) <- q(x, y) group x."],
)
def test_rejected(text):
    with pytest.raises(RuleError):
        check_program(parse_program(text))


@pytest.mark.parametrize("text", ["p(x <- q(x).", "p(x) <- q(x) r(x).", "p(sum(x), count(y)) <- q(x, y).", "@a p(x) <- q(x). @a p(x) <- r(x)."])
def test_unreadable(text):
    with pytest.raises(SyntaxFault):
        parse_program(text)


def test_types():
    t = infer_types(parse_program("a(x, t) <- e(x, t). b(x, d) <- a(x, t), d := t / 2. c(x, count(t)) <- a(x, t) group x. a(y, t) <- a(x, t), f(x, y)."), {"e": ["int", "bigint"], "f": ["bigint", "bigint"]})
    assert t["a"] == ["bigint", "bigint"] and t["b"] == ["bigint", "double"] and t["c"] == ["bigint", "bigint"]
    with pytest.raises(RuleError):
        infer_types(parse_program("a(x) <- e(x). a(x) <- f(x)."), {"e": ["bigint"], "f": ["string"]})
