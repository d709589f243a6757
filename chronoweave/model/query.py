"""Pattern queries: quad patterns over nodes and instants, order clauses, and a small text form.

Text form: patterns and clauses separated by ``;``. A pattern is ``s p o @t`` where ``?x`` is a node variable,
``@t`` a time variable, ``@'1998-06-15'`` or ``@5`` a constant instant and anything else a constant term. A clause is
``@t1 <= @t2``, ``@t < @u``, ``@t = @u``, ``@t <= @u + 3`` or has a constant instant on either side.
"""

from __future__ import annotations

import re
from dataclasses import dataclass, field, replace
from datetime import datetime


@dataclass(frozen=True)
class Var:
    name: str


@dataclass(frozen=True)
class TimeVar:
    name: str


@dataclass(frozen=True)
class Const:
    value: object


Term = Var | Const
Instant = TimeVar | Const


@dataclass(frozen=True)
class QuadPattern:
    s: Term
    p: Term
    o: Term
    t: Instant

    @property
    def terms(self) -> tuple[tuple[str, Term], ...]:
        return (("s", self.s), ("p", self.p), ("o", self.o))

    @property
    def variables(self) -> list[str]:
        return list(dict.fromkeys(x.name for _, x in self.terms if isinstance(x, Var)))


@dataclass(frozen=True)
class OrderClause:
    """``left <= right + offset``; ``strict`` asks for ``<``. The offset is in time units (microseconds, or whole numbers)."""

    left: Instant
    right: Instant
    offset: int = 0
    strict: bool = False


@dataclass(frozen=True)
class PatternQuery:
    patterns: tuple[QuadPattern, ...]
    clauses: tuple[OrderClause, ...] = ()
    unsatisfiable: bool = field(default=False, compare=False)

    def __post_init__(self) -> None:
        if not self.patterns:
            raise ValueError("a pattern query needs at least one pattern")

    @property
    def nodes(self) -> list[str]:
        return list(dict.fromkeys(v for p in self.patterns for v in p.variables))

    @property
    def times(self) -> list[str]:
        used = [p.t for p in self.patterns] + [x for c in self.clauses for x in (c.left, c.right)]
        return list(dict.fromkeys(x.name for x in used if isinstance(x, TimeVar)))

    def with_clauses(self, *more: OrderClause) -> PatternQuery:
        return replace(self, clauses=(*self.clauses, *more))

    def with_time(self, t: Instant) -> PatternQuery:
        """The same triples, all at ``t``."""
        return PatternQuery(tuple(replace(p, t=t) for p in self.patterns))


def _instant(word: str) -> Instant:
    body = word[1:] if word.startswith("@") else word
    if body.startswith("'"):
        return Const(datetime.fromisoformat(body.strip("'")))
    if re.fullmatch(r"-?\d+", body):
        return Const(int(body))
    return TimeVar(body)


def _term(word: str) -> Term:
    return Var(word[1:]) if word.startswith("?") else Const(word)


def parse(text: str) -> PatternQuery:
    patterns, clauses = [], []
    for part in filter(None, (x.strip() for x in text.split(";"))):
        if m := re.fullmatch(r"(@\S+?|@'[^']*')\s*(<=|<|=)\s*(@'[^']*'|@\S+)(?:\s*\+\s*(\d+))?", part):
            a, b, shift = _instant(m[1]), _instant(m[3]), int(m[4] or 0)
            clauses.append(OrderClause(a, b, shift, m[2] == "<"))
            if m[2] == "=":
                clauses.append(OrderClause(b, a, shift))
            continue
        words = re.findall(r"@'[^']*'|\S+", part)
        if len(words) not in (3, 4):
            raise ValueError(f"not a pattern or clause: {part!r}")
        patterns.append(QuadPattern(*map(_term, words[:3]), _instant(words[3] if len(words) == 4 else "@t")))
    return PatternQuery(tuple(patterns), tuple(clauses))
