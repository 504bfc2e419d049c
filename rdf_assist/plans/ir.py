"""Queries as values: terms, patterns, filters and modifiers."""

from __future__ import annotations

from dataclasses import dataclass, field, replace


@dataclass(frozen=True)
class Term:
    """kind: var, iri or literal."""

    kind: str
    value: str
    lang: str | None = None
    dtype: str | None = None

    def __str__(self) -> str:
        return f"?{self.value}" if self.kind == "var" else f'"{self.value}"' if self.kind == "literal" else self.value


def var(name: str) -> Term:
    return Term("var", name.lstrip("?"))


def iri(value: str) -> Term:
    return Term("iri", value)


def lit(value: str, lang: str | None = None) -> Term:
    return Term("literal", value, lang)


@dataclass(frozen=True)
class Pattern:
    s: Term
    p: Term
    o: Term

    def variables(self) -> list[str]:
        return list(dict.fromkeys(t.value for t in (self.s, self.p, self.o) if t.kind == "var"))


@dataclass(frozen=True)
class Filter:
    """op: = != < <= > >= contains starts regex lang minlen maxlen, on a variable."""

    variable: str
    op: str
    value: str | float


@dataclass(frozen=True)
class Aggregate:
    """function: count, sum, avg, min or max of a variable (None for rows), as a name."""

    function: str
    variable: str | None
    name: str
    distinct: bool = False


@dataclass(frozen=True)
class Body:
    """What stands between braces: patterns, filters and nested groups."""

    patterns: tuple[Pattern, ...] = ()
    filters: tuple[Filter, ...] = ()
    groups: tuple[Group, ...] = ()

    def variables(self) -> list[str]:
        """What an answer of the body may bind."""
        inner = [v for g in self.groups if g.kind in ("optional", "union") for part in g.parts for v in part.variables()]
        return list(dict.fromkeys([v for p in self.patterns for v in p.variables()] + inner))

    def problems(self) -> list[str]:
        known = set(self.variables())
        out = [f"a filter on ?{f.variable}, which its group does not bind" for f in self.filters if f.variable not in known]
        out += ["an empty group"] * (not self.patterns and not self.groups)
        return out + [x for g in self.groups for part in g.parts for x in part.problems()]


@dataclass(frozen=True)
class Group:
    """A nested group: kind optional, union (with its alternatives), minus or absent."""

    kind: str
    parts: tuple[Body, ...]


@dataclass(frozen=True)
class SelectQuery:
    patterns: tuple[Pattern, ...]
    variables: tuple[str, ...] = ()
    distinct: bool = False
    filters: tuple[Filter, ...] = ()
    groups: tuple[Group, ...] = ()
    aggregates: tuple[Aggregate, ...] = ()
    group_by: tuple[str, ...] = ()
    having: tuple[Filter, ...] = ()
    order_by: tuple[tuple[str, bool], ...] = ()  # (variable, descending)
    limit: int | None = None
    offset: int = 0
    hide: tuple[str, ...] = field(default=())

    def all_variables(self) -> list[str]:
        return self.body().variables()

    def body(self) -> Body:
        return Body(self.patterns, self.filters, self.groups)

    def with_pattern(self, i: int, pattern: Pattern) -> SelectQuery:
        """The query with one triple edited."""
        return replace(self, patterns=(*self.patterns[:i], pattern, *self.patterns[i + 1 :]))

    def with_term(self, i: int, position: str, term: Term) -> SelectQuery:
        return self.with_pattern(i, replace(self.patterns[i], **{position: term}))

    def constants(self) -> list[tuple[int, str, Term]]:
        return [(i, pos, t) for i, p in enumerate(self.patterns) for pos in "spo" if (t := getattr(p, pos)).kind != "var"]

    def literals(self) -> list[str]:
        return list(dict.fromkeys(t.value for _, _, t in self.constants() if t.kind == "literal"))


def text_of(q: SelectQuery) -> str:
    """A query of plain patterns as text that parse() reads."""

    def term(t: Term) -> str:
        if t.kind == "literal":
            plain = t.value.replace("\\", "\\\\").replace('"', '\\"')
            return t.value if t.dtype in ("integer", "double") else f'"{plain}"'
        return f"?{t.value}" if t.kind == "var" else f"<{t.value}>"

    names = " ".join(f"?{v}" for v in q.variables) or "*"
    return f"SELECT {'DISTINCT ' if q.distinct else ''}{names} WHERE {{ {' . '.join(' '.join(map(term, (p.s, p.p, p.o))) for p in q.patterns)} }}"


def validate(q: SelectQuery) -> list[str]:
    """What keeps a query from running; empty if nothing does."""
    out = []
    if not q.patterns and not q.groups:
        out.append("the query has no pattern")
    for i, p in enumerate(q.patterns):
        for pos in "spo":
            t = getattr(p, pos)
            if t is None or not t.value:
                out.append(f"pattern {i + 1}: {pos} is empty")
        if p.s.kind == "literal":
            out.append(f"pattern {i + 1}: a literal cannot be a subject")
        if p.p.kind == "literal":
            out.append(f"pattern {i + 1}: a literal cannot be a predicate")
    out += [x for g in q.groups for part in g.parts for x in part.problems()]
    known = set(q.all_variables())
    made = {a.name for a in q.aggregates}
    out += [f"unknown variable ?{v}" for v in dict.fromkeys([*q.variables, *q.group_by, *(f.variable for f in q.filters)]) if v not in known | made]
    out += [f"unknown variable ?{v}" for v, _ in q.order_by if v not in known | made]
    return out
