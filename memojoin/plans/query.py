"""Full conjunctive queries: atoms over named relations, with variables and constants, and no projection."""

from __future__ import annotations

import re
from dataclasses import dataclass, field


@dataclass(frozen=True)
class Const:
    value: object


@dataclass(frozen=True)
class Atom:
    """A relation applied to terms: variable names, or constants. A variable may repeat."""

    relation: str
    terms: tuple

    def __init__(self, relation: str, terms):
        object.__setattr__(self, "relation", relation)
        object.__setattr__(self, "terms", tuple(terms))

    @property
    def variables(self) -> tuple[str, ...]:
        return tuple(dict.fromkeys(t for t in self.terms if isinstance(t, str)))


@dataclass(frozen=True)
class ConjunctiveQuery:
    """Atoms; selections on single variables; comparisons between variables (SQL text over variable names)."""

    atoms: tuple[Atom, ...]
    selections: tuple[tuple[str, str], ...] = ()
    comparisons: tuple[str, ...] = field(default=())

    def __init__(self, atoms, selections=(), comparisons=()):
        object.__setattr__(self, "atoms", tuple(atoms))
        object.__setattr__(self, "selections", tuple(selections))
        object.__setattr__(self, "comparisons", tuple(comparisons))

    @property
    def variables(self) -> tuple[str, ...]:
        return tuple(dict.fromkeys(v for a in self.atoms for v in a.variables))

    def where(self, variable: str, condition: str) -> ConjunctiveQuery:
        """Add a selection, written over the variable's name; every atom with the variable gets it."""
        return ConjunctiveQuery(self.atoms, (*self.selections, (variable, condition)), self.comparisons)

    def having(self, comparison: str) -> ConjunctiveQuery:
        """Add a comparison between variables."""
        return ConjunctiveQuery(self.atoms, self.selections, (*self.comparisons, comparison))

    def compared(self, comparison: str) -> frozenset[str]:
        """The variables that a comparison names."""
        return frozenset(re.findall(r"[A-Za-z_]\w*", comparison)) & frozenset(self.variables)


def parse_cq(text: str) -> ConjunctiveQuery:
    """Read `E(a, b), F(b, 7), G(b, 'x')`: bare words are variables, numbers and quoted text constants."""
    atoms, rest = [], text.strip()
    while rest:
        m = re.match(r"\s*([A-Za-z_]\w*)\s*\(((?:[^()']|'(?:[^']|'')*')*)\)\s*(?:,|$)", rest)
        if not m:
            raise ValueError(f"cannot read an atom at: {rest[:40]}")
        terms = []
        for t in re.findall(r"'(?:[^']|'')*'|[^,\s]+", m[2]):
            if t[0] == "'":
                terms.append(Const(t[1:-1].replace("''", "'")))
            elif re.fullmatch(r"-?\d+", t):
                terms.append(Const(int(t)))
            elif re.fullmatch(r"[A-Za-z_]\w*", t):
                terms.append(t)
            else:
                raise ValueError(f"cannot read the term {t}")
        atoms.append(Atom(m[1], terms))
        rest = rest[m.end() :]
    if not atoms:
        raise ValueError("a query needs an atom")
    return ConjunctiveQuery(atoms)


def residual(query: ConjunctiveQuery, assigned: dict[str, object]) -> ConjunctiveQuery:
    """The query that is left once some variables have values."""
    return ConjunctiveQuery([Atom(a.relation, [Const(assigned[t]) if isinstance(t, str) and t in assigned else t for t in a.terms]) for a in query.atoms], [s for s in query.selections if s[0] not in assigned], query.comparisons)
