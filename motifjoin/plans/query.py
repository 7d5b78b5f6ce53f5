"""Join queries: atoms over relations, parsed from text and bound to DataFrames."""

from __future__ import annotations

import re
from collections.abc import Mapping, Sequence
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

_INTEGRAL = (T.ByteType, T.ShortType, T.IntegerType, T.LongType)


@dataclass(frozen=True)
class Atom:
    """A relation and the attributes that its columns are bound to, in column order."""

    relation: str
    attrs: tuple[str, ...]


@dataclass(frozen=True)
class JoinQuery:
    """A full conjunctive query; ``filters`` compare two attributes: (left, operator, right)."""

    name: str
    atoms: tuple[Atom, ...]
    filters: tuple[tuple[str, str, str], ...] = ()
    order: tuple[str, ...] | None = None

    @property
    def attrs(self) -> tuple[str, ...]:
        """Attributes in the order in which the atoms first name them."""
        return tuple(dict.fromkeys(a for atom in self.atoms for a in atom.attrs))

    @property
    def graph_like(self) -> bool:
        """Whether all atoms are copies of one binary relation."""
        return len({a.relation for a in self.atoms}) == 1 and all(len(a.attrs) == 2 for a in self.atoms)

    def connected(self) -> bool:
        seen, todo = set(), [self.attrs[0]]
        while todo:
            a = todo.pop()
            if a not in seen:
                seen.add(a)
                todo += [b for atom in self.atoms if a in atom.attrs for b in atom.attrs]
        return seen == set(self.attrs)

    def injective(self) -> JoinQuery:
        """The same with all attributes pairwise different."""
        pairs = [(a, "<>", b) for i, a in enumerate(self.attrs) for b in self.attrs[i + 1 :]]
        return replace(self, filters=(*self.filters, *pairs))

    def bind(self, relations: Mapping[str, DataFrame], distinct: bool = True) -> dict[str, DataFrame]:
        """Relations ready to be joined: set semantics (unless the reader drops duplicates), no nulls, integer columns as long.

        Checks arities, that every attribute has one type, and that filters name attributes.
        """
        out: dict[str, DataFrame] = {}
        kinds: dict[str, T.DataType] = {}
        for atom in self.atoms:
            if atom.relation not in relations:
                raise KeyError(f"no relation {atom.relation}")
            df = relations[atom.relation]
            if len(df.columns) != len(atom.attrs):
                raise ValueError(f"{atom.relation} has {len(df.columns)} columns, the atom names {len(atom.attrs)}")
            if atom.relation not in out:
                out[atom.relation] = clean(df, distinct)
            for attr, f in zip(atom.attrs, out[atom.relation].schema.fields):
                if kinds.setdefault(attr, f.dataType) != f.dataType:
                    raise TypeError(f"{attr} is bound to {kinds[attr].simpleString()} and {f.dataType.simpleString()}")
        for left, op, right in self.filters:
            if left not in kinds or right not in kinds or op not in ("<", "<=", "<>", ">", ">=", "="):
                raise ValueError(f"filter {left} {op} {right} does not compare two attributes")
        return out


def clean(df: DataFrame, distinct: bool = True) -> DataFrame:
    """Columns c0.., integers as long, rows with nulls dropped, duplicates dropped unless the reader drops them."""
    cols = []
    for k, f in enumerate(df.schema.fields):
        if isinstance(f.dataType, T.MapType):
            raise TypeError(f"{f.name}: maps cannot be joined on")
        col = F.col(f"`{f.name}`")
        cols.append((col.cast("long") if isinstance(f.dataType, _INTEGRAL) else col).alias(f"c{k}"))
    rows = df.select(*cols).na.drop()
    return rows.dropDuplicates() if distinct else rows


_ATOM = re.compile(r"\s*(\w+)\s*\(\s*([\w\s,]*?)\s*\)\s*")
_FILTER = re.compile(r"\s*(\w+)\s*(<=|>=|<>|!=|<|>|=)\s*(\w+)\s*")


def parse_query(text: str) -> JoinQuery:
    """``name(a, b, c) := e(a, b), e(b, c), a < c``; the head gives name and output order."""
    head, mark, body = text.partition(":=")
    if not mark or not (m := _ATOM.fullmatch(head)):
        raise ValueError("expected name(attributes) := atoms and filters")
    name, order = m[1], tuple(x.strip() for x in m[2].split(",") if x.strip())
    atoms, filters, at = [], [], 0
    while at < len(body):
        if m := _ATOM.match(body, at):
            atoms.append(Atom(m[1], tuple(x.strip() for x in m[2].split(","))))
        elif m := _FILTER.match(body, at):
            filters.append((m[1], m[2].replace("!=", "<>"), m[3]))
        else:
            raise ValueError(f"cannot read {body[at:]!r}")
        at = m.end()
        if at < len(body):
            if body[at] != ",":
                raise ValueError(f"expected a comma before {body[at:]!r}")
            at += 1
    query = JoinQuery(name, tuple(atoms), tuple(filters), order or None)
    if not atoms or order and set(order) != set(query.attrs):
        raise ValueError("the head must name every attribute of the atoms, once")
    return query


def pattern(name: str, edges: Sequence[str], relation: str = "e") -> JoinQuery:
    """A graph pattern from edges like ``12``: an edge from a1 to a2."""
    return JoinQuery(name, tuple(Atom(relation, (f"a{e[0]}", f"a{e[1]}")) for e in edges), order=tuple(f"a{k}" for k in sorted({c for e in edges for c in e})))


#: The edges of the studied patterns.
PATTERNS: dict[str, JoinQuery] = {
    name: pattern(name, edges.split())
    for name, edges in {
        "triangle": "12 13 23",
        "cyclic_triangle": "12 23 31",
        "four_clique": "12 13 14 23 24 34",
        "diamond": "12 23 41 43",
        "house": "12 13 14 23 24 34 25 35",
        "five_clique": "12 13 14 15 23 24 25 34 35 45",
    }.items()
}
