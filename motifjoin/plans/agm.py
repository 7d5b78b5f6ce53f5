"""The largest possible output of a join: minimum fractional edge cover, exactly."""

from __future__ import annotations

import math
from collections.abc import Mapping
from dataclasses import dataclass
from fractions import Fraction

from motifjoin.plans.query import JoinQuery


@dataclass(frozen=True)
class AgmBound:
    """``cover`` holds the weight of every atom; the bound is the product of sizes to these powers."""

    cover: tuple[Fraction, ...]
    log_value: float

    @property
    def value(self) -> float:
        return math.exp(self.log_value)

    @property
    def exponent(self) -> Fraction:
        """The power of a common relation size."""
        return sum(self.cover, Fraction(0))


def fractional_cover(edges: list[frozenset[str]], costs: list[Fraction]) -> tuple[Fraction, ...]:
    """Cheapest weights that cover every attribute at least once.

    Solved as its dual, packing attribute weights under the costs, by a simplex in
    fractions: costs are not negative, so it starts feasible; Bland's rule ends it.
    The cover is what the slacks cost in the final row.
    """
    attrs = sorted(set().union(*edges))
    m, n = len(attrs), len(edges)
    rows = [[Fraction(a in e) for a in attrs] + [Fraction(i == k) for k in range(n)] + [costs[i]] for i, e in enumerate(edges)]
    goal = [Fraction(-1)] * m + [Fraction(0)] * (n + 1)
    basis = [m + i for i in range(n)]
    while (enter := next((j for j in range(m + n) if goal[j] < 0), None)) is not None:
        options = [(row[-1] / row[enter], basis[i], i) for i, row in enumerate(rows) if row[enter] > 0]
        if not options:
            raise ValueError("an attribute is in no atom")
        leave = min(options)[2]
        scale = rows[leave][enter]
        rows[leave] = [x / scale for x in rows[leave]]
        for i, row in enumerate(rows):
            if i != leave and row[enter]:
                rows[i] = [x - row[enter] * y for x, y in zip(row, rows[leave])]
        goal = [x - goal[enter] * y for x, y in zip(goal, rows[leave])]
        basis[leave] = enter
    return tuple(goal[m : m + n])


def agm_bound(query: JoinQuery, sizes: Mapping[str, int]) -> AgmBound:
    """The bound for relation sizes; an empty relation makes it zero."""
    edges = [frozenset(a.attrs) for a in query.atoms]
    if any(sizes[a.relation] <= 0 for a in query.atoms):
        return AgmBound(tuple(Fraction(0) for _ in edges), -math.inf)
    logs = [math.log(sizes[a.relation]) for a in query.atoms]
    same = len(set(logs)) == 1
    cover = fractional_cover(edges, [Fraction(1) if same else Fraction(x).limit_denominator(10**9) for x in logs])
    return AgmBound(cover, sum(float(w) * x for w, x in zip(cover, logs)))
