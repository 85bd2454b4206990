"""Results of two engines, made comparable."""

from __future__ import annotations


def as_rows(columns, rows):
    """Rows as sorted tuples of text, columns in order of name."""
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    return sorted(tuple(repr(r[i] + 0.0) if isinstance(r[i], float) else str(r[i]) for i in order) for r in rows)
