"""Plan records: what the optimiser decides and the operators lower to DataFrames."""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass

from motifloom.plans.pattern import QueryGraph


def relation(q: QueryGraph, a: int, b: int, symmetry: bool) -> str | None:
    """How the images of two query vertices must compare: '<', '>', '!=' or None where nothing is left to check."""
    if symmetry and (a, b) in q.symmetry_order:
        return "<"
    if symmetry and (b, a) in q.symmetry_order:
        return ">"
    if q.has_edge(a, b):
        return None
    la, lb = q.label(a), q.label(b)
    return None if la is not None and lb is not None and la != lb else "!="


def use_symmetry(q: QueryGraph, choice: str = "auto") -> bool:
    """auto: order constraints apply to unlabelled patterns only."""
    return choice == "on" or (choice == "auto" and not q.labelled)


@dataclass(frozen=True)
class Round:
    """One step of vertex growth: place target next to the vertices in back."""

    target: int
    back: tuple[int, ...]
    keep_array: bool
    #: Triangle-index groups: (visited vertex, vertices resolved during the visit).
    groups: tuple[tuple[int, tuple[int, ...]], ...] = ()


@dataclass(frozen=True)
class GrowthPlan:
    order: tuple[int, ...]
    rounds: tuple[Round, ...]

    @property
    def arrays(self) -> tuple[int, ...]:
        return tuple(r.target for r in self.rounds if r.keep_array)

    def explain(self) -> str:
        return "\n".join(f"round {i + 2}: place v{r.target} next to {', '.join(f'v{b}' for b in r.back)}{' as array' if r.keep_array else ''}{f' groups {r.groups}' if r.groups else ''}" for i, r in enumerate(self.rounds))

    def to_json(self) -> str:
        return json.dumps(asdict(self))


@dataclass(frozen=True)
class UnitNode:
    """A join unit: kind edge, star, wedge or clique; root of a star; edges it covers."""

    kind: str
    vertices: tuple[int, ...]
    edges: tuple[tuple[int, int], ...]
    root: int = 0
    #: Vertices kept as arrays.
    arrays: tuple[int, ...] = ()

    @property
    def leaves(self) -> tuple[UnitNode, ...]:
        return (self,)

    def explain(self, depth: int = 0) -> str:
        shape = f"root v{self.root}" if self.root else "all pairs"
        return "  " * depth + f"{self.kind} {' '.join(f'v{v}' for v in self.vertices)} ({shape})" + (f" arrays {self.arrays}" if self.arrays else "")


@dataclass(frozen=True)
class JoinNode:
    left: JoinNode | UnitNode
    right: JoinNode | UnitNode

    @property
    def vertices(self) -> tuple[int, ...]:
        return tuple(sorted({*self.left.vertices, *self.right.vertices}))

    @property
    def edges(self) -> tuple[tuple[int, int], ...]:
        return tuple(sorted({*self.left.edges, *self.right.edges}))

    @property
    def key(self) -> tuple[int, ...]:
        return tuple(sorted({*self.left.vertices} & {*self.right.vertices}))

    @property
    def leaves(self) -> tuple[UnitNode, ...]:
        return (*self.left.leaves, *self.right.leaves)

    @property
    def joins(self) -> int:
        return len(self.leaves) - 1

    def explain(self, depth: int = 0) -> str:
        return "\n".join(["  " * depth + f"join on {' '.join(f'v{v}' for v in self.key)}", self.left.explain(depth + 1), self.right.explain(depth + 1)])


def joins_of(node: JoinNode | UnitNode) -> list[JoinNode]:
    return [] if isinstance(node, UnitNode) else [*joins_of(node.left), *joins_of(node.right), node]
