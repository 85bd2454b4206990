"""Predicates over declared attributes: a small tree that compiles to a Column and to SQL text."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

OPERATORS = ("=", "!=", "<", "<=", ">", ">=", "in", "between", "is null", "match")
_INVERSE = {"=": "!=", "!=": "=", "<": ">=", ">=": "<", ">": "<=", "<=": ">"}


class Predicate:
    def __and__(self, other: Predicate) -> Predicate:
        return And((self, other))

    def __or__(self, other: Predicate) -> Predicate:
        return Or((self, other))

    def __invert__(self) -> Predicate:
        return self.negated()

    def to_column(self) -> Column:
        raise NotImplementedError

    def to_sql(self) -> str:
        raise NotImplementedError

    def negated(self) -> Predicate:
        raise NotImplementedError


def _quoted(value) -> str:
    return "'" + value.replace("'", "''") + "'" if isinstance(value, str) else str(value)


@dataclass(frozen=True)
class Leaf(Predicate):
    """One comparison. A null value never qualifies, except under ``is null``."""

    column: str
    op: str
    value: object = None

    def __post_init__(self):
        if self.op not in OPERATORS and self.op not in ("not in", "is not null", "not match", "not between"):
            raise ValueError(f"unknown operator {self.op}")

    def to_column(self) -> Column:
        c = F.col(self.column)
        test = {
            "=": lambda v: c == v,
            "!=": lambda v: c != v,
            "<": lambda v: c < v,
            "<=": lambda v: c <= v,
            ">": lambda v: c > v,
            ">=": lambda v: c >= v,
            "in": lambda v: c.isin(*v),
            "not in": lambda v: ~c.isin(*v),
            "between": lambda v: c.between(*v),
            "not between": lambda v: ~c.between(*v),
            "is null": lambda v: c.isNull(),
            "is not null": lambda v: c.isNotNull(),
            "match": lambda v: F.array_contains(c, v),
            "not match": lambda v: ~F.array_contains(c, v),
        }[self.op](self.value)
        return F.coalesce(test, F.lit(False))

    def to_sql(self) -> str:
        if self.op in ("is null", "is not null"):
            return f"{self.column} {self.op.upper()}"
        if self.op.endswith("match"):
            return f"{'NOT ' if self.op[0] == 'n' else ''}list_contains({self.column}, {_quoted(self.value)})"
        if self.op.endswith("in"):
            return f"{self.column} {self.op.upper()} ({', '.join(map(_quoted, self.value))})"
        if self.op.endswith("between"):
            return f"{self.column} {self.op.upper()} {_quoted(self.value[0])} AND {_quoted(self.value[1])}"
        return f"{self.column} {self.op} {_quoted(self.value)}"

    def negated(self) -> Predicate:
        if self.op in _INVERSE:
            return Leaf(self.column, _INVERSE[self.op], self.value)
        other = {"is null": "is not null", "is not null": "is null"}.get(self.op)
        return Leaf(self.column, other or (self.op[4:] if self.op.startswith("not ") else f"not {self.op}"), self.value)


@dataclass(frozen=True)
class And(Predicate):
    parts: tuple

    def to_column(self) -> Column:
        out = self.parts[0].to_column()
        for p in self.parts[1:]:
            out = out & p.to_column()
        return out

    def to_sql(self) -> str:
        return "(" + " AND ".join(p.to_sql() for p in self.parts) + ")"

    def negated(self) -> Predicate:
        return Or(tuple(p.negated() for p in self.parts))


@dataclass(frozen=True)
class Or(Predicate):
    parts: tuple

    def to_column(self) -> Column:
        out = self.parts[0].to_column()
        for p in self.parts[1:]:
            out = out | p.to_column()
        return out

    def to_sql(self) -> str:
        return "(" + " OR ".join(p.to_sql() for p in self.parts) + ")"

    def negated(self) -> Predicate:
        return And(tuple(p.negated() for p in self.parts))


def match_all(column: str, words: list[str]) -> Predicate:
    leaves = tuple(Leaf(column, "match", w) for w in words)
    return leaves[0] if len(leaves) == 1 else And(leaves)


def match_any(column: str, words: list[str]) -> Predicate:
    leaves = tuple(Leaf(column, "match", w) for w in words)
    return leaves[0] if len(leaves) == 1 else Or(leaves)
