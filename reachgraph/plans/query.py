"""Queries: text, patterns with property paths, and the query graph they make."""

from __future__ import annotations

import itertools
import re
from dataclasses import dataclass, field


@dataclass(frozen=True)
class Var:
    name: str

    def __str__(self) -> str:
        return f"?{self.name}"


@dataclass(frozen=True)
class Const:
    """A name such as ``nation/3``, or a quoted literal."""

    text: str
    literal: bool = False

    def __str__(self) -> str:
        return f'"{self.text}"' if self.literal else self.text


Term = Var | Const


@dataclass(frozen=True)
class Step:
    """One property of a path; ``mark`` is empty, ``*``, ``+`` or ``?``."""

    prop: str | Var
    mark: str = ""
    inverse: bool = False


@dataclass(frozen=True)
class Pattern:
    s: Term
    path: tuple[Step, ...]
    o: Term


@dataclass(frozen=True)
class Query:
    patterns: tuple[Pattern, ...]
    select: tuple[str, ...] = ()  # empty: all variables
    distinct: bool = False

    def variables(self) -> list[str]:
        seen: dict[str, None] = {}
        for p in self.patterns:
            for t in (p.s, *(s.prop for s in p.path), p.o):
                if isinstance(t, Var) and not t.name.startswith("_"):
                    seen[t.name] = None
        return list(seen)


class QueryError(ValueError):
    """The text is not a query of the language."""


_TOKEN = re.compile(r"""\s+|(?P<var>\?[A-Za-z_]\w*)|(?P<lit>"(?:[^"\\]|\\.)*"|'(?:[^'\\]|\\.)*')|(?P<name>[A-Za-z_][\w:\-]*(?:/\d+)?|<[^>\s]*>)|(?P<op>[{}.^*+?/|();=<>!])""")
_LEFT_OUT = {"filter", "union", "optional", "minus", "group", "order", "having", "graph", "service", "bind", "values", "limit", "offset", "construct", "ask", "describe"}


def _tokens(text: str) -> list[tuple[str, str]]:
    out, at = [], 0
    while at < len(text):
        m = _TOKEN.match(text, at)
        if not m:
            raise QueryError(f"unexpected {text[at:at + 10]!r}")
        at = m.end()
        if m.lastgroup:
            out.append((m.lastgroup, m[0]))
    return out


class _Parser:
    def __init__(self, text: str) -> None:
        self.tokens, self.at = _tokens(text), 0

    def peek(self) -> tuple[str, str]:
        return self.tokens[self.at] if self.at < len(self.tokens) else ("end", "")

    def take(self, what: str | None = None) -> tuple[str, str]:
        kind, text = self.peek()
        if kind == "name" and text.lower() in _LEFT_OUT:
            raise QueryError(f"{text.upper()} is not part of the language; use DataFrame operations on the result")
        if what and text.lower() != what:
            raise QueryError(f"{what!r} expected, not {text or 'the end'!r}")
        self.at += 1
        return kind, text

    def query(self) -> Query:
        self.take("select")
        distinct = self.peek()[1].lower() == "distinct"
        if distinct:
            self.take()
        select: list[str] = []
        if self.peek()[1] == "*":
            self.take()
        else:
            while self.peek()[0] == "var":
                select.append(self.take()[1][1:])
            if not select:
                raise QueryError("a SELECT list or * is needed")
        self.take("where")
        self.take("{")
        patterns = []
        while self.peek()[1] != "}":
            patterns.append(Pattern(self.term(), self.path(), self.term()))
            if self.peek()[1] == ".":
                self.take()
            elif self.peek()[1] != "}":
                raise QueryError(f"'.' expected, not {self.peek()[1] or 'the end'!r}")
        self.take("}")
        if self.peek()[0] != "end":
            self.take()
            raise QueryError(f"unexpected {self.tokens[self.at - 1][1]!r} after the query")
        query = Query(tuple(patterns), tuple(select), distinct)
        if not patterns:
            raise QueryError("no pattern")
        if missing := set(select) - set(query.variables()):
            raise QueryError(f"unknown variables {sorted(missing)}")
        return query

    def term(self) -> Term:
        kind, text = self.take()
        if kind == "var":
            return Var(text[1:])
        if kind == "lit":
            return Const(re.sub(r"\\(.)", r"\1", text[1:-1]), True)
        if kind == "name":
            return Const(_bare(text))
        raise QueryError(f"a variable, a name or a literal expected, not {text or 'the end'!r}")

    def path(self) -> tuple[Step, ...]:
        steps = [self.step()]
        while self.peek()[1] == "/":
            self.take()
            steps.append(self.step())
        return tuple(steps)

    def step(self) -> Step:
        inverse = self.peek()[1] == "^"
        if inverse:
            self.take()
        if self.peek()[1] == "(":
            return Step(self.group(), self.take()[1] if self.peek()[1] in ("*", "+", "?") else "", inverse)
        kind, text = self.take()
        if kind == "var":
            return Step(Var(text[1:]), "", inverse)
        if kind != "name":
            raise QueryError(f"a property expected, not {text or 'the end'!r}")
        mark = self.take()[1] if self.peek()[1] in ("*", "+") or self._optional() else ""
        return Step(_bare(text), mark, inverse)

    def group(self) -> str:
        """Alternatives of sequences of properties in brackets, such as (p|q/r), as one property of that name."""
        self.take("(")
        text = "("
        while True:
            kind, name = self.take()
            if kind != "name":
                raise QueryError(f"a property expected, not {name or 'the end'!r}")
            text += _bare(name)
            _, sign = self.take()
            if sign not in ("|", "/", ")"):
                raise QueryError(f"'|', '/' or ')' expected, not {sign or 'the end'!r}")
            text += sign
            if sign == ")":
                return text

    def _optional(self) -> bool:
        return self.peek()[1] == "?"


def _bare(name: str) -> str:
    return re.sub(r"^[A-Za-z_][\w\-]*:", "", name.strip("<>"))


def parse(text: str) -> Query:
    """The query that a text says; QueryError if it says none."""
    return _Parser(text).query()


def normalise(query: Query) -> Query:
    """Paths of several steps become patterns of one step each, joined by fresh variables; inverse steps swap their ends."""
    fresh = itertools.count()
    out = []
    for p in query.patterns:
        s = p.s
        for i, step in enumerate(p.path):
            o = p.o if i == len(p.path) - 1 else Var(f"_{next(fresh)}")
            if isinstance(step.prop, Var) and step.mark:
                raise QueryError("a variable property has no mark")
            a, b = (o, s) if step.inverse else (s, o)
            out.append(Pattern(a, (Step(step.prop, step.mark),), b))
            s = o
    return Query(tuple(out), query.select or tuple(query.variables()), query.distinct)


@dataclass(frozen=True)
class Vertex:
    """A relation of the query: a plain pattern, a constant, or the vertices of properties for a variable bound by no pattern."""

    kind: str  # plain, constant, unbound
    label: str
    pattern: Pattern | None = None
    term: Term | None = None
    props: tuple[str, ...] = ()

    def variables(self) -> frozenset[str]:
        if self.pattern:
            p = self.pattern
            return frozenset(t.name for t in (p.s, p.path[0].prop, p.o) if isinstance(t, Var))
        return frozenset((column(self.term),))


@dataclass(frozen=True)
class Solid:
    """Equal values of a shared variable."""

    a: int
    b: int
    var: str


@dataclass(frozen=True)
class Dashed:
    """A reachability predicate between the columns of two vertices; ``number`` is that of its pattern."""

    a: int
    b: int
    x: str
    y: str
    prop: str
    mark: str
    number: int


def column(term: Term) -> str:
    """Column that holds the binding of a variable, or a constant."""
    return term.name if isinstance(term, Var) else "const:" + str(term)


@dataclass
class QueryGraph:
    vertices: list[Vertex] = field(default_factory=list)
    solid: list[Solid] = field(default_factory=list)
    dashed: list[Dashed] = field(default_factory=list)

    @classmethod
    def of(cls, query: Query) -> QueryGraph:
        query = normalise(query)
        g = cls()
        plain = [p for p in query.patterns if not p.path[0].mark]
        paths = [(i, p) for i, p in enumerate(query.patterns) if p.path[0].mark]
        for p in plain:
            g.vertices.append(Vertex("plain", f"R{len(g.vertices) + 1}", p))
        bound = frozenset().union(*(v.variables() for v in g.vertices)) if g.vertices else frozenset()
        extra: dict[str, int] = {}
        for _, p in paths:
            for t in (p.s, p.o):
                key = column(t)
                if key in extra or isinstance(t, Var) and t.name in bound:
                    continue
                props = tuple(dict.fromkeys(q.path[0].prop for _, q in paths if t in (q.s, q.o)))
                extra[key] = len(g.vertices)
                kind = "unbound" if isinstance(t, Var) else "constant"
                g.vertices.append(Vertex(kind, f"R{len(g.vertices) + 1}", None, t, props))
        for (i, a), (j, b) in itertools.combinations(enumerate(g.vertices), 2):
            for v in sorted(a.variables() & b.variables()):
                g.solid.append(Solid(i, j, v))
        for number, p in paths:
            x, y = column(p.s), column(p.o)
            at = lambda c: [i for i, v in enumerate(g.vertices) if c in v.variables()]
            for i in at(x):
                for j in at(y):
                    g.dashed.append(Dashed(i, j, x, y, p.path[0].prop, p.path[0].mark, number))
        return g
