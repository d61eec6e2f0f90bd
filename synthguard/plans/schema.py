"""Declared schemas of micro data: attributes with finite known domains, and the model built on them."""

from __future__ import annotations

import json
from dataclasses import dataclass, field
from math import prod


@dataclass(frozen=True)
class Attribute:
    """An attribute whose values are stored as 0..card-1; bucket_of tells each value's bucket where it is a parent."""

    name: str
    kind: str  # numeric or categorical
    card: int
    bucket_of: tuple[int, ...]
    labels: tuple[str, ...] = ()
    low: int = 0  # the value that is stored as 0, for numeric attributes

    @property
    def buckets(self) -> int:
        return max(self.bucket_of) + 1


def numeric(name: str, card: int, width: int = 1, low: int = 0) -> Attribute:
    return Attribute(name, "numeric", card, tuple(v // width for v in range(card)), (), low)


def categorical(name: str, labels, groups=None) -> Attribute:
    labels = tuple(map(str, labels))
    return Attribute(name, "categorical", len(labels), tuple(groups) if groups else tuple(range(len(labels))), labels)


@dataclass(frozen=True)
class Schema:
    name: str
    attributes: tuple[Attribute, ...]
    by_name: dict = field(default_factory=dict, compare=False, hash=False)

    def __post_init__(self):
        self.by_name.update({a.name: i for i, a in enumerate(self.attributes)})

    def __len__(self) -> int:
        return len(self.attributes)

    @property
    def names(self) -> list[str]:
        return [a.name for a in self.attributes]

    def index(self, name: str) -> int:
        return self.by_name[name]

    def possible_records(self) -> int:
        return prod(a.card for a in self.attributes)

    def to_json(self) -> str:
        return json.dumps({"name": self.name, "attributes": [{k: getattr(a, k) for k in ("name", "kind", "card", "bucket_of", "labels", "low")} for a in self.attributes]})

    @staticmethod
    def from_json(text: str) -> Schema:
        x = json.loads(text)
        return Schema(x["name"], tuple(Attribute(a["name"], a["kind"], a["card"], tuple(a["bucket_of"]), tuple(a["labels"]), a["low"]) for a in x["attributes"]))


@dataclass(frozen=True)
class Graph:
    """Parents of each attribute (by index), and a topological order of all attributes."""

    parents: tuple[tuple[int, ...], ...]
    order: tuple[int, ...]

    def __post_init__(self):
        seen: set[int] = set()
        for a in self.order:
            if not seen.issuperset(self.parents[a]):
                raise ValueError("the order puts a child before its parent")
            seen.add(a)
        if len(seen) != len(self.parents):
            raise ValueError("the order misses an attribute")

    @property
    def edges(self) -> list[tuple[int, int]]:
        """(child, parent)."""
        return [(c, p) for c, ps in enumerate(self.parents) for p in ps]


def topological(parents: list[tuple[int, ...]]) -> tuple[int, ...]:
    """Kahn's order, the smallest free index first."""
    order: list[int] = []
    while len(order) < len(parents):
        free = [i for i, p in enumerate(parents) if i not in order and set(p) <= set(order)]
        if not free:
            raise ValueError("the graph has a cycle")
        order.append(free[0])
    return tuple(order)


@dataclass(frozen=True)
class DeniabilityParams:
    k: int = 50
    gamma: float = 4.0
    eps0: float = 1.0
    max_plausible: int | None = None
    max_check: int | None = None

    def __post_init__(self):
        if self.k < 1 or self.gamma <= 1 or self.eps0 <= 0:
            raise ValueError("k must be 1 or more, gamma above 1, eps0 above 0")
        if self.max_plausible is not None and self.max_plausible < self.k:
            raise ValueError("with max_plausible below k no candidate can pass")
