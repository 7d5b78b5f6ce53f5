"""From a query and an order to stages: which index every attribute is extended by."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

from motifjoin.plans.ordering import attribute_order
from motifjoin.plans.query import JoinQuery


@dataclass(frozen=True)
class AtomUse:
    """An atom's part in a stage: its index from bound positions to the new one."""

    atom: int
    relation: str
    key_attrs: tuple[str, ...]
    key_pos: tuple[int, ...]
    ext_pos: int
    version: str = "new"

    @property
    def index_id(self) -> tuple[str, str, tuple[int, ...], int]:
        return self.relation, self.version, self.key_pos, self.ext_pos


@dataclass(frozen=True)
class Stage:
    """Binds ``attr`` in prefixes over ``bound``; ``filters`` become checkable here."""

    attr: str
    bound: tuple[str, ...]
    uses: tuple[AtomUse, ...]
    filters: tuple[tuple[str, str, str], ...]


@dataclass(frozen=True)
class DeltaRule:
    """Changes of one atom joined with new versions of the atoms before it and old ones after."""

    lead: int
    order: tuple[str, ...]
    versions: tuple[str, ...]


def compile_stages(query: JoinQuery, order: Sequence[str], start: int = 0, *, unbound: str = "auto", versions: Sequence[str] | None = None, seed_atoms: Sequence[int] = ()) -> list[Stage]:
    """Stages that bind ``order[start:]``.

    Every atom that holds the new attribute and a bound one takes part, with its
    projection on what is bound so far. Atoms without a bound attribute are left out of
    graph patterns and take part otherwise (``unbound`` = never, always or auto); they are
    needed where relations differ in size, and where nothing else proposes. ``seed_atoms``
    are wholly applied already.
    """
    out = []
    with_unbound = unbound == "always" or unbound == "auto" and not query.graph_like
    for j in range(start, len(order)):
        attr, bound = order[j], tuple(order[:j])
        uses, spare = [], []
        for i, atom in enumerate(query.atoms):
            if attr not in atom.attrs or i in seed_atoms:
                continue
            ext = atom.attrs.index(attr)
            pos = tuple(p for p, a in enumerate(atom.attrs) if a in bound)
            use = AtomUse(i, atom.relation, tuple(atom.attrs[p] for p in pos), pos, ext, versions[i] if versions else "new")
            (uses if pos or atom.attrs.count(attr) > 1 else spare).append(use)
        if with_unbound or not uses:
            uses += spare
        if not uses:
            raise ValueError(f"{attr} is in no atom")
        seen = dict.fromkeys((u.index_id, u.key_attrs) for u in uses)
        uses = [next(u for u in uses if (u.index_id, u.key_attrs) == s) for s in seen]
        filters = tuple(f for f in query.filters if attr in (f[0], f[2]) and {f[0], f[2]} <= {*bound, attr})
        out.append(Stage(attr, bound, tuple(uses), filters))
    return out


def delta_rules(query: JoinQuery) -> list[DeltaRule]:
    """One rule per atom; orders start with the changed atom's attributes."""
    n = len(query.atoms)
    return [DeltaRule(i, attribute_order(query, "lead", i), tuple("new" if j < i else "delta" if j == i else "old" for j in range(n))) for i in range(n)]


def describe(stages: Sequence[Stage]) -> str:
    """The stages as text: what proposes, what filters."""
    lines = []
    for s in stages:
        uses = ", ".join(f"{u.relation}.{u.version}[{','.join(u.key_attrs)}]->{s.attr}" for u in s.uses)
        lines.append(f"{s.attr}: smallest of {uses}" + "".join(f"; {a} {op} {b}" for a, op, b in s.filters))
    return "\n".join(lines)
