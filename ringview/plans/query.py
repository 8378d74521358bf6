"""Natural-join group-by queries over rings."""

from __future__ import annotations

import re
from dataclasses import dataclass, field, replace

from ringview.functions.rings import IntRing, ProductRing, Ring


@dataclass(frozen=True)
class FD:
    """Functional dependency lhs -> rhs."""

    lhs: frozenset[str]
    rhs: frozenset[str]

    @classmethod
    def parse(cls, text: str) -> FD:
        a, b = text.split("->")
        return cls(frozenset(a.replace(",", " ").split()), frozenset(b.replace(",", " ").split()))


@dataclass(frozen=True)
class NaturalJoinQuery:
    """Relations by name with their variables (join variables share names), the variables of the result, the ring."""

    relations: dict[str, tuple[str, ...]]
    free: tuple[str, ...] = ()
    ring: Ring = field(default_factory=IntRing)
    fds: tuple[FD, ...] = ()
    static: frozenset[str] = frozenset()

    @property
    def variables(self) -> tuple[str, ...]:
        return tuple(dict.fromkeys(v for s in self.relations.values() for v in s))

    @property
    def join_variables(self) -> tuple[str, ...]:
        return tuple(v for v in self.variables if sum(v in s for s in self.relations.values()) > 1)

    def of(self, variable: str) -> frozenset[str]:
        """Relations with a variable."""
        return frozenset(r for r, s in self.relations.items() if variable in s)

    def without(self, *relations: str) -> NaturalJoinQuery:
        rest = {r: s for r, s in self.relations.items() if r not in relations}
        have = {v for s in rest.values() for v in s}
        return replace(self, relations=rest, free=tuple(f for f in self.free if f in have))

    @classmethod
    def from_sql(cls, sql: str, schemas: dict[str, tuple[str, ...]], **how) -> NaturalJoinQuery:
        """SELECT [keys,] SUM(1 | x * y ...) [AS name], ... FROM r NATURAL JOIN s ... [GROUP BY keys]."""
        m = re.fullmatch(r"\s*select\s+(.*?)\s+from\s+(.*?)(?:\s+group\s+by\s+(.*?))?\s*;?\s*", sql, re.I | re.S)
        if not m:
            raise ValueError("expected SELECT ... FROM a NATURAL JOIN b ... [GROUP BY ...]")
        names = [x.strip() for x in re.split(r"\s+natural\s+join\s+", m[2], flags=re.I)]
        if missing := [n for n in names if n not in schemas]:
            raise ValueError(f"unknown relations {missing}")
        free = tuple(x.strip() for x in m[3].split(",")) if m[3] else ()
        sums, plain = [], []
        for item in re.split(r",(?![^(]*\))", m[1]):
            if s := re.fullmatch(r"\s*(?:sum\s*\((.*?)\)|count\s*\(\s*\*\s*\))(?:\s+as\s+(\w+))?\s*", item, re.I | re.S):
                factors = [x.strip() for x in (s[1] or "1").split("*") if x.strip() != "1"]
                sums.append((s[2] or f"sum{len(sums) + 1}", IntRing(*factors)))
            else:
                plain.append(item.strip())
        if set(plain) - set(free):
            raise ValueError(f"{set(plain) - set(free)} must be grouped by")
        relations = {n: schemas[n] for n in names}
        known = {v for s in relations.values() for v in s}
        if unknown := {v for _, r in sums for v in r.lifts} | set(free) - known:
            unknown -= known
            if unknown:
                raise ValueError(f"unknown variables {sorted(unknown)}")
        ring = how.pop("ring", None) or (sums[0][1] if len(sums) == 1 else ProductRing(tuple(sums)))
        return cls(relations, free, ring, **how)
