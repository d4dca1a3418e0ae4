"""Syntax tree and parser.

Surface syntax::

    @r5 medTemp(x, median(t)) <- near(x, y), temp(y, t) group x.
    @r6 suspect(x, d) <- medTemp(x, m), temp(x, t), !broken(x), d := t - m, d > 5000.
    edge(1, 2).

Names in term positions are variables, ``_`` is a wildcard; numbers and quoted strings are
constants.  The keyword dialect is read as well: ``label: h(X) :- p(X, Y) and not q(Y)``,
``BIND(expr AS ?v)``, ``COMP(a, >, b)`` and
``h(?x, ?m) :- AGGREGATE(p(?x, ?y)) ON ?x WITH MED(?y) AS ?m``.
"""

from __future__ import annotations

import re
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field, replace


@dataclass(frozen=True)
class Var:
    name: str

    def __str__(self) -> str:
        return self.name


@dataclass(frozen=True)
class Const:
    value: object

    def __str__(self) -> str:
        return '"' + str(self.value).replace("\\", "\\\\").replace('"', '\\"') + '"' if isinstance(self.value, str) else str(self.value).lower() if isinstance(self.value, bool) else repr(self.value)


Term = Var | Const


@dataclass(frozen=True)
class Atom:
    pred: str
    args: tuple[Term, ...]

    def vars(self) -> list[str]:
        return list(dict.fromkeys(a.name for a in self.args if isinstance(a, Var) and a.name != "_"))

    def __str__(self) -> str:
        return f"{self.pred}({', '.join(map(str, self.args))})"


@dataclass(frozen=True)
class Expr:
    """Arithmetic: an operator with operands, a function call, or a term."""

    op: str
    args: tuple[Expr | Term, ...]

    def vars(self) -> list[str]:
        out: list[str] = []
        for a in self.args:
            out += a.vars() if isinstance(a, Expr) else [a.name] if isinstance(a, Var) else []
        return list(dict.fromkeys(out))

    def __str__(self) -> str:
        if self.op == "term":
            return str(self.args[0])
        if self.op == "neg":
            return f"-({self.args[0]})"
        if self.op in "+-*/%":
            return f"({self.args[0]} {self.op} {self.args[1]})"
        return f"{self.op}({', '.join(map(str, self.args))})"


@dataclass(frozen=True)
class Bind:
    var: str
    expr: Expr

    def __str__(self) -> str:
        return f"{self.var} := {self.expr}"


@dataclass(frozen=True)
class Compare:
    left: Term
    op: str
    right: Term

    def vars(self) -> list[str]:
        return [t.name for t in (self.left, self.right) if isinstance(t, Var)]

    def __str__(self) -> str:
        return f"{self.left} {self.op} {self.right}"


@dataclass(frozen=True)
class Aggregate:
    fn: str
    var: str
    result: str
    group: tuple[str, ...]


@dataclass(frozen=True)
class Rule:
    id: str
    head: Atom
    positives: tuple[Atom, ...] = ()
    negatives: tuple[Atom, ...] = ()
    binds: tuple[Bind, ...] = ()
    comps: tuple[Compare, ...] = ()
    agg: Aggregate | None = None

    def body_preds(self) -> set[str]:
        return {a.pred for a in (*self.positives, *self.negatives)}

    def text(self) -> str:
        if not self.positives:
            return str(self.head)
        body = [*map(str, self.positives), *(f"!{a}" for a in self.negatives), *map(str, self.binds), *map(str, self.comps)]
        head = str(self.head)
        tail = ""
        if self.agg:
            shown = [f"{self.agg.fn}({self.agg.var})" if isinstance(a, Var) and a.name == self.agg.result else str(a) for a in self.head.args]
            head, tail = f"{self.head.pred}({', '.join(shown)})", " group " + ", ".join(self.agg.group) if self.agg.group else ""
        return f"{head} <- {', '.join(body)}{tail}"

    def shape(self) -> str:
        """Text with variables numbered by first use: equal for rules that differ in names."""
        names: dict[str, str] = {}

        def number(m: re.Match[str]) -> str:
            w = m[0]
            if w == "_" or w in ("group", *AGGREGATES.values()) or self.text()[m.end() : m.end() + 1] == "(":
                return w
            return names.setdefault(w, f"v{len(names)}")

        return re.sub(r'"(?:\\.|[^"\\])*"|[A-Za-z_]\w*', lambda m: m[0] if m[0][0] == '"' else number(m), self.text())


# The aggregate operators.
AGGREGATES = {"max": "max", "min": "min", "avg": "avg", "count": "count", "sum": "sum", "med": "median", "median": "median"}
COMPARATORS = (">=", "<=", "!=", ">", "<", "=")


class SyntaxFault(ValueError):
    """A rule text that cannot be read."""


_TOKEN = re.compile(r"""\s*(?:(?P<skip>%[^\n]*|\#[^\n]*)|(?P<str>"(?:\\.|[^"\\])*")|(?P<num>\d+(?:\.\d+)?(?:[eE][+-]?\d+)?)|(?P<name>\??[A-Za-z_]\w*)|(?P<op><-|:-|:=|>=|<=|!=|[-+*/%(),.!@:<>=&]))""")


def _tokens(text: str) -> list[tuple[str, str]]:
    out, at = [], 0
    text = text.rstrip()
    while at < len(text):
        m = _TOKEN.match(text, at)
        if not m or m.end() == at:
            raise SyntaxFault(f"cannot read {text[at : at + 30]!r}")
        at = m.end()
        if m.lastgroup != "skip":
            out.append((m.lastgroup, m[m.lastgroup]))
    return out


class _Reader:
    def __init__(self, text: str):
        self.toks, self.at, self.fresh = _tokens(text), 0, 0

    def peek(self, k: int = 0) -> tuple[str, str]:
        return self.toks[self.at + k] if self.at + k < len(self.toks) else ("end", "")

    def take(self, *want: str) -> str:
        kind, value = self.peek()
        if want and value not in want and kind not in want:
            raise SyntaxFault(f"expected {' or '.join(want)}, found {value or 'the end'!r}")
        self.at += 1
        return value

    def maybe(self, *want: str) -> bool:
        if self.peek()[1] in want:
            self.at += 1
            return True
        return False

    def is_word(self, word: str, k: int = 0) -> bool:
        kind, value = self.peek(k)
        return kind == "name" and value.lower() == word

    # terms and expressions

    def term(self) -> Term:
        kind, value = self.peek()
        if kind == "op" and value == "-":
            self.take()
            return Const(-self.number())
        if kind == "num":
            return Const(self.number())
        if kind == "str":
            self.take()
            return Const(re.sub(r"\\(.)", r"\1", value[1:-1]))
        if kind != "name":
            raise SyntaxFault(f"expected a term, found {value or 'the end'!r}")
        self.take()
        return Const(value == "true") if value in ("true", "false") else Var(value.lstrip("?"))

    def number(self) -> int | float:
        v = self.take("num")
        return float(v) if re.search(r"[.eE]", v) else int(v)

    def expr(self) -> Expr:
        out = self.product()
        while self.peek()[1] in ("+", "-"):
            out = Expr(self.take(), (out, self.product()))
        return out

    def product(self) -> Expr:
        out = self.factor()
        while self.peek()[1] in ("*", "/", "%"):
            out = Expr(self.take(), (out, self.factor()))
        return out

    def factor(self) -> Expr:
        if self.maybe("-"):
            return Expr("neg", (self.factor(),))
        if self.maybe("("):
            out = self.expr()
            self.take(")")
            return out
        if self.peek()[0] == "name" and self.peek(1)[1] == "(":
            fn = self.take()
            self.take("(")
            args = [self.expr()]
            while self.maybe(","):
                args.append(self.expr())
            self.take(")")
            return Expr(fn, tuple(args))
        return Expr("term", (self.term(),))

    def atom(self) -> Atom:
        pred = self.take("name")
        self.take("(")
        args = [self.term()]
        while self.maybe(","):
            args.append(self.term())
        self.take(")")
        return Atom(pred, tuple(args))

    # bodies and rules

    def literals(self, stop: tuple[str, ...]) -> dict[str, list]:
        parts: dict[str, list] = {"positives": [], "negatives": [], "binds": [], "comps": []}
        while True:
            if self.maybe("!"):
                parts["negatives"].append(self.atom())
            elif self.is_word("not"):
                self.take()
                parts["negatives"].append(self.atom())
            elif self.is_word("bind") and self.peek(1)[1] == "(":
                self.take()
                self.take("(")
                e = self.expr()
                if not self.is_word("as"):
                    raise SyntaxFault("expected AS in BIND")
                self.take()
                parts["binds"].append(Bind(self.take("name").lstrip("?"), e))
                self.take(")")
            elif self.is_word("comp") and self.peek(1)[1] == "(":
                self.take()
                self.take("(")
                left = self.term()
                self.take(",")
                op = self.take(*COMPARATORS)
                self.take(",")
                parts["comps"].append(Compare(left, op, self.term()))
                self.take(")")
            elif self.peek()[0] == "name" and self.peek(1)[1] == ":=":
                v = self.take().lstrip("?")
                self.take(":=")
                parts["binds"].append(Bind(v, self.expr()))
            elif self.peek()[0] == "name" and self.peek(1)[1] == "(":
                parts["positives"].append(self.atom())
            else:
                left = self.term()
                op = self.take(*COMPARATORS)
                parts["comps"].append(Compare(left, op, self.term()))
            if self.maybe(",", "&") or (self.is_word("and") and self.take()):
                continue
            if self.peek()[1] not in stop and not any(self.is_word(w) for w in stop) and self.peek()[0] != "end":
                raise SyntaxFault(f"unexpected {self.peek()[1]!r}")
            return parts

    def head(self) -> tuple[Atom, tuple[str, str, str] | None]:
        pred = self.take("name")
        self.take("(")
        args, agg = [], None
        while True:
            if self.peek()[0] == "name" and self.peek(1)[1] == "(":
                fn = self.take().lower()
                if fn not in AGGREGATES or agg:
                    raise SyntaxFault(f"{fn} is no aggregate, or a second one")
                self.take("(")
                v = self.take("name").lstrip("?")
                self.take(")")
                self.fresh += 1
                agg = (AGGREGATES[fn], v, f"agg{self.fresh}_")
                args.append(Var(agg[2]))
            else:
                args.append(self.term())
            if not self.maybe(","):
                break
        self.take(")")
        return Atom(pred, tuple(args)), agg

    def names(self) -> tuple[str, ...]:
        out = [self.take("name").lstrip("?")]
        while self.maybe(","):
            out.append(self.take("name").lstrip("?"))
        return tuple(out)

    def rule(self, fallback: str) -> Rule:
        label = fallback
        if self.maybe("@"):
            label = self.take("name")
        elif self.peek()[0] == "name" and self.peek(1)[1] == ":":
            label = self.take()
            self.take(":")
        head, agg = self.head()
        if not self.maybe("<-", ":-"):
            self.maybe(".")
            return Rule(label, head)
        if self.is_word("aggregate") and self.peek(1)[1] == "(":
            self.take()
            self.take("(")
            parts = self.literals((")",))
            self.take(")")
            group: tuple[str, ...] = ()
            if self.is_word("on"):
                self.take()
                group = self.names()
            if not self.is_word("with"):
                raise SyntaxFault("expected WITH")
            self.take()
            fn = self.take("name").lower()
            if fn not in AGGREGATES:
                raise SyntaxFault(f"{fn} is no aggregate")
            self.take("(")
            v = self.take("name").lstrip("?")
            self.take(")")
            if not self.is_word("as"):
                raise SyntaxFault("expected AS")
            self.take()
            result = self.take("name").lstrip("?")
            self.maybe(".")
            return Rule(label, head, **{k: tuple(x) for k, x in parts.items()}, agg=Aggregate(AGGREGATES[fn], v, result, group))
        parts = self.literals((".", "group"))
        if agg:
            group = tuple(a.name for a in head.args if isinstance(a, Var) and a.name != agg[2])
            if self.is_word("group"):
                self.take()
                group = self.names()
            made = Aggregate(*agg, group)
        else:
            made = None
        self.maybe(".")
        return Rule(label, head, **{k: tuple(x) for k, x in parts.items()}, agg=made)


@dataclass
class Program:
    """A finite set of rules, by identifier."""

    rules: dict[str, Rule] = field(default_factory=dict)

    def __iter__(self) -> Iterator[Rule]:
        return iter(self.rules.values())

    def __len__(self) -> int:
        return len(self.rules)

    def without(self, ids: Iterable[str]) -> Program:
        gone = set(ids)
        return Program({k: r for k, r in self.rules.items() if k not in gone})

    def only(self, ids: Iterable[str]) -> Program:
        keep = set(ids)
        return Program({k: r for k, r in self.rules.items() if k in keep})

    def plus(self, rules: Iterable[Rule]) -> Program:
        return Program(self.rules | {r.id: r for r in rules})

    def preds(self) -> set[str]:
        return {p for r in self for p in (r.head.pred, *r.body_preds())}

    def heads(self) -> set[str]:
        return {r.head.pred for r in self}

    def text(self) -> str:
        return "\n".join(f"@{r.id} {r.text()}." for r in self)


def parse_rules(text: str, prefix: str = "r", start: int = 1) -> list[Rule]:
    reader, out, k = _Reader(text), [], start
    used: set[str] = set()
    while reader.peek()[0] != "end":
        rule = reader.rule("")
        if not rule.id:
            while f"{prefix}{k}" in used:
                k += 1
            rule = replace(rule, id=f"{prefix}{k}")
        if rule.id in used:
            raise SyntaxFault(f"rule {rule.id} is given twice")
        used.add(rule.id)
        out.append(rule)
    return out


def parse_program(text: str) -> Program:
    """Rules of a text; ground facts in it are rules without a body."""
    return Program({r.id: r for r in parse_rules(text)})


def parse_atoms(text: str) -> dict[str, list]:
    """The parts of a conjunctive goal such as ``near(3, y), temp(y, t), t > 0``."""
    reader = _Reader(text)
    return reader.literals((".",))
