"""Metapath queries: walks over types with predicates at positions."""

from __future__ import annotations

import re
from dataclasses import dataclass

#: Constraints of a span: (position counted from its start, canonical predicate), in order.
Key = tuple[tuple[int, str], ...]


@dataclass(frozen=True)
class PathQuery:
    """types[i] are the walk's node types, edges[i] the name of the relation of step i or None, constraints pairs (position, predicate)."""

    types: tuple[str, ...]
    edges: tuple[str | None, ...]
    constraints: tuple[tuple[int, str], ...] = ()

    def __len__(self) -> int:
        return len(self.types)

    @property
    def symbols(self) -> tuple[str, ...]:
        """One symbol per position; a named relation is part of the symbol it leads to."""
        return (self.types[0], *(t if e is None else f"[{e}]{t}" for t, e in zip(self.types[1:], self.edges, strict=True)))

    @property
    def path(self) -> str:
        return "-".join(self.symbols)

    def span(self, i: int, j: int) -> tuple[str, ...]:
        """The symbols of positions i..j; the first one without its relation."""
        return (self.types[i], *self.symbols[i + 1 : j + 1])

    def key(self, i: int, j: int) -> Key:
        """The canonical predicates at positions i..j, counted from i."""
        return tuple((p - i, c) for p, c in sorted(self.constraints) if i <= p <= j)

    def reversible(self, i: int, j: int) -> bool:
        """May a span be walked backward: no relation of it has a name, hence a direction."""
        return not any(self.edges[i:j])

    def reversed_span(self, i: int, j: int) -> tuple[tuple[str, ...], Key]:
        """The reverse of a span and its constraints."""
        return tuple(reversed(self.span(i, j))), tuple(sorted((j - p, c) for p, c in self.constraints if i <= p <= j))

    def at(self, position: int) -> list[str]:
        return [c for p, c in self.constraints if p == position]


def normalised(predicate: str, node_type: str = "", keys: tuple[str, ...] = ()) -> str:
    """A predicate's canonical text: no white space beside comparisons and commas, single spaces elsewhere, quoted text as it is.

    An equality on the type's letter, its key column or id is one on id.
    """
    parts = re.split(r"('(?:[^']|'')*')", predicate.strip())
    for i in range(0, len(parts), 2):
        parts[i] = re.sub(r"\s*(<=|>=|<>|!=|=|<|>|,)\s*", r"\1", re.sub(r"\s+", " ", parts[i]))
    text = "".join(parts)
    left, eq, right = text.partition("=")
    if eq and left in {node_type, "id", *keys} and re.fullmatch(r"-?\d+", right):
        return f"id = {int(right)}"
    return text


def key_text(key: Key) -> str:
    """A key for display."""
    return " & ".join(f"{p}:{c}" for p, c in key)


_STEP = re.compile(r"\s*(?:-\s*(?:\[(?P<edge>\w+)\]\s*->?\s*)?)?(?P<type>[A-Za-z]\w*)")
_TYPED = re.compile(r"^([A-Za-z]\w*)(?:@(\d+))?\.(.+)$")


def parse_path(text: str, net=None, constraints: dict[int, str] | None = None) -> PathQuery:
    """C-O-P, with O-[next]->O for a named relation, and {predicates} at the end.

    Predicates are separated by semicolons: T.predicate holds at all positions of type T, T@i.predicate at
    position i. With a network, steps and types are checked against it.
    """
    body, _, rest = text.partition("{")
    types: list[str] = []
    edges: list[str | None] = []
    at = 0
    while at < len(body.rstrip()):
        m = _STEP.match(body, at)
        if not m:
            raise ValueError(f"cannot read {text!r} from {body[at:]!r}")
        if types:
            edges.append(m["edge"])
        types.append(m["type"])
        at = m.end()
    if len(types) < 2:
        raise ValueError("a metapath has two types at least")
    canonical = lambda p, c: (p, normalised(c, types[p], net.key_names(types[p]) if net is not None and types[p] in net.nodes else ()) if 0 <= p < len(types) else c)
    found = [canonical(p, c) for p, c in (constraints or {}).items()]
    for part in filter(None, (p.strip() for p in rest.rstrip().rstrip("}").split(";"))):
        m = _TYPED.match(part)
        if not m or m[1] not in types:
            raise ValueError(f"predicate {part!r} names no type of the path")
        where = [int(m[2])] if m[2] else [i for i, t in enumerate(types) if t == m[1]]
        found += [canonical(i, m[3]) for i in where]
    if any(not 0 <= p < len(types) for p, _ in found):
        raise ValueError("a constraint is at no position of the path")
    q = PathQuery(tuple(types), tuple(edges), tuple(sorted(found)))
    if net is not None:
        for i, e in enumerate(q.edges):
            net.edge(q.types[i], q.types[i + 1], e)
    return q
