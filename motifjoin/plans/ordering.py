"""Attribute orders: any permutation is right, some are cheaper or needed."""

from __future__ import annotations

from collections.abc import Mapping

from motifjoin.plans.query import JoinQuery


def attribute_order(query: JoinQuery, strategy: str = "given", lead: int | None = None, fanout: Mapping[str, float] | None = None) -> tuple[str, ...]:
    """An order of the query's attributes.

    ``given``: the query's own; ``edge_seed``: the same, but its first two attributes
    share an atom; ``lead``: the attributes of atom ``lead`` first; ``connected``: next
    comes the attribute with the most atoms that touch bound ones, ties by smaller
    ``fanout`` (average extensions), then by the given order.
    """
    given = query.order or query.attrs
    if strategy == "given":
        return tuple(given)
    if strategy == "lead":
        first = tuple(dict.fromkeys(query.atoms[lead or 0].attrs))
        return _grow(query, first, given, fanout)
    if strategy == "edge_seed":
        pair = next(tuple(a for a in given if a in atom.attrs)[:2] for atom in sorted(query.atoms, key=lambda t: sorted(given.index(x) for x in t.attrs)) if len(set(atom.attrs)) > 1)
        return pair + tuple(a for a in given if a not in pair)
    if strategy == "connected":
        return _grow(query, (), given, fanout)
    raise ValueError(f"no strategy {strategy}")


def _grow(query: JoinQuery, first: tuple[str, ...], given: tuple[str, ...], fanout: Mapping[str, float] | None) -> tuple[str, ...]:
    out = list(first)
    while len(out) < len(given):
        touching = lambda a: sum(a in t.attrs and any(b in out for b in t.attrs) for t in query.atoms)
        out.append(min((a for a in given if a not in out), key=lambda a: (-touching(a), (fanout or {}).get(a, 0.0), given.index(a))))
    return tuple(out)
