"""Exact linear algebra over a field: vectors are tuples of field elements, subspaces are lists of vectors."""

from __future__ import annotations

from linform.functions.fields import Q

Vector = tuple


def rref(rows: list[Vector], field=Q) -> tuple[list[Vector], list[int]]:
    """Reduced rows without zero rows, and their pivot columns."""
    rows, pivots, top = [list(r) for r in rows], [], 0
    width = len(rows[0]) if rows else 0
    for col in range(width):
        at = next((i for i in range(top, len(rows)) if rows[i][col]), None)
        if at is None:
            continue
        rows[top], rows[at] = rows[at], rows[top]
        scale = field.inv(rows[top][col])
        rows[top] = [field.mul(scale, x) for x in rows[top]]
        for i, row in enumerate(rows):
            if i != top and row[col]:
                minus = field.neg(row[col])
                rows[i] = [field.add(x, field.mul(minus, y)) for x, y in zip(row, rows[top], strict=True)]
        pivots.append(col)
        top += 1
    return [tuple(r) for r in rows[:top]], pivots


def rank(rows: list[Vector], field=Q) -> int:
    return len(rref(rows, field)[0])


def space_key(rows: list[Vector], field=Q) -> tuple:
    """Equal for lists with the same span."""
    return tuple(rref(list(rows), field)[0])


def null_basis(rows: list[Vector], width: int, field=Q) -> list[Vector]:
    """Vectors orthogonal to all rows."""
    reduced, pivots = rref(rows, field) if rows else ([], [])
    out = []
    for free in range(width):
        if free not in pivots:
            v = [field.of(0)] * width
            v[free] = field.of(1)
            for row, p in zip(reduced, pivots, strict=True):
                v[p] = field.neg(row[free])
            out.append(tuple(v))
    return out


def contains(space: list[Vector], vectors: list[Vector], field=Q) -> bool:
    return rank([*space, *vectors], field) == rank(list(space), field)


def intersect(a: list[Vector], b: list[Vector], width: int, field=Q) -> list[Vector]:
    """A basis of the common subspace: what is orthogonal to both complements."""
    return null_basis([*null_basis(list(a), width, field), *null_basis(list(b), width, field)], width, field)


def independent(vectors: list[Vector], field=Q) -> list[int]:
    """Positions of the vectors that are not in the span of those before."""
    out, kept = [], []
    for i, v in enumerate(vectors):
        if rank([*kept, v], field) > len(kept):
            kept.append(v)
            out.append(i)
    return out


def coordinates(v: Vector, basis: list[Vector], field=Q) -> tuple | None:
    """Coefficients of v over independent vectors; None outside their span."""
    if not basis:
        return () if not any(v) else None
    rows = [tuple([*(b[i] for b in basis), v[i]]) for i in range(len(v))]
    reduced, pivots = rref(rows, field)
    if len(basis) in pivots:
        return None
    out = [field.of(0)] * len(basis)
    for row, p in zip(reduced, pivots, strict=True):
        out[p] = row[-1]
    return tuple(out)


def dependencies(vectors: list[Vector], field=Q) -> list[Vector]:
    """Coefficient vectors of all linear relations among the vectors (a basis of them)."""
    if not vectors:
        return []
    width = len(vectors[0])
    return null_basis([tuple(v[i] for v in vectors) for i in range(width)], len(vectors), field)


def combine(coefficients, vectors: list[Vector], width: int, field=Q) -> Vector:
    out = [field.of(0)] * width
    for c, v in zip(coefficients, vectors, strict=True):
        out = [field.add(x, field.mul(c, y)) for x, y in zip(out, v, strict=True)]
    return tuple(out)


def scale(v: Vector, by, field=Q) -> Vector:
    return tuple(field.mul(by, x) for x in v)
