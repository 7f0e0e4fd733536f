"""Atoms, terms and schemes: positive formulas in disjunctive normal form over field agreements.

An atom pairs an indexing function with a mapping of field sets. With several fields on a side, the
atom is the disjunction over all field pairs; as keys that is the union of the keys of a side's
fields, so an atom costs |F1| + |F2| key sets, not |F1| * |F2| comparisons.
"""

from __future__ import annotations

import itertools
import json
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

from dnfblock.functions.indexing import REGISTRY, let

SEPARATOR = "\x1f"


@dataclass(frozen=True, order=True)
class Atom:
    """A specific blocking predicate: ``gbp`` over a mapping of left fields to right fields."""

    gbp: str
    left: tuple[str, ...]
    right: tuple[str, ...]

    @staticmethod
    def simple(gbp: str, f1: str, f2: str | None = None) -> Atom:
        return Atom(gbp, (f1,), (f2 or f1,))

    @staticmethod
    def complex(gbp: str, left, right) -> Atom:
        return Atom(gbp, tuple(left), tuple(right))

    def fields(self, side: int) -> tuple[str, ...]:
        return self.right if side else self.left

    def keys(self, side: int, column=F.col) -> Column:
        """Keys of a record on ``side``: the union over the atom's fields."""
        sets = [REGISTRY[self.gbp].of_values(column(f)) for f in self.fields(side)]
        return reduce(F.array_union, sets)

    def covers(self, left=F.col, right=F.col, combine: str = "or") -> Column:
        """Whether a pair agrees; ``combine='and'`` asks every field pair to agree."""
        if combine == "or":
            return F.coalesce(F.arrays_overlap(self.keys(0, left), self.keys(1, right)), F.lit(False))
        parts = [Atom.simple(self.gbp, a, b).covers(left, right) for a, b in itertools.product(self.left, self.right)]
        return reduce(lambda x, y: x & y, parts)

    def expand(self) -> list[Atom]:
        """The 1:1 atoms whose disjunction this atom is."""
        return [Atom.simple(self.gbp, a, b) for a, b in itertools.product(self.left, self.right)]


Term = tuple[Atom, ...]


@dataclass(frozen=True)
class Scheme:
    """A disjunction of terms; a term is a conjunction of atoms."""

    terms: tuple[Term, ...]

    @staticmethod
    def of(*terms) -> Scheme:
        return Scheme(tuple((t,) if isinstance(t, Atom) else tuple(t) for t in terms))

    @property
    def k(self) -> int:
        """Atoms of the longest term."""
        return max(map(len, self.terms), default=0)

    @property
    def is_disjunctive(self) -> bool:
        return self.k <= 1

    def fields(self, side: int) -> tuple[str, ...]:
        return tuple(dict.fromkeys(f for t in self.terms for a in t for f in a.fields(side)))

    def expand(self) -> Scheme:
        """Complex atoms distributed: a scheme of 1:1 atoms that covers the same pairs."""
        return Scheme(tuple(dict.fromkeys(c for t in self.terms for c in itertools.product(*(a.expand() for a in t)))))

    def covers(self, left=F.col, right=F.col) -> Column:
        parts = [reduce(lambda x, y: x & y, [a.covers(left, right) for a in t]) for t in self.terms]
        return reduce(lambda x, y: x | y, parts, F.lit(False))

    def term_keys(self, i: int, side: int, column=F.col) -> Column:
        """Keys of term ``i``; for a conjunction the combinations of its atoms' keys."""
        sets = [a.keys(side, column) for a in self.terms[i]]

        def pair(xs: Column, ys: Column) -> Column:
            both = F.struct(xs.alias("x"), ys.alias("y"))
            return let(both, lambda b: F.flatten(F.transform(b["x"], lambda x: F.transform(b["y"], lambda y: F.concat(x, F.lit(SEPARATOR), y)))))

        return reduce(pair, sets)

    def to_json(self) -> str:
        return json.dumps([[{"gbp": a.gbp, "left": a.left, "right": a.right} for a in t] for t in self.terms])

    @staticmethod
    def from_json(text: str) -> Scheme:
        return Scheme(tuple(tuple(Atom(a["gbp"], tuple(a["left"]), tuple(a["right"])) for a in t) for t in json.loads(text)))

    def __str__(self) -> str:
        show = lambda a: f"{a.gbp}({'+'.join(a.left)}~{'+'.join(a.right)})"
        return " | ".join(" & ".join(map(show, t)) for t in self.terms) or "nothing"
