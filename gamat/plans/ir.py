"""Engine-neutral plans: what a matrix operation does, before any engine is chosen."""

from __future__ import annotations

from dataclasses import dataclass, fields, replace

from ..types import GraphMatrix, VertexState


@dataclass(frozen=True)
class PlanNode:
    def children(self) -> list[PlanNode]:
        out = []
        for f in fields(self):
            v = getattr(self, f.name)
            out += [v] if isinstance(v, PlanNode) else [x for x in v if isinstance(x, PlanNode)] if isinstance(v, tuple) else []
        return out

    def label(self) -> str:
        shown = {f.name: getattr(self, f.name) for f in fields(self)}
        shown = {k: v for k, v in shown.items() if isinstance(v, (int, float, str, bool))}
        return type(self).__name__ + (f"({', '.join(f'{k}={v}' for k, v in shown.items())})" if shown else "")

    def text(self, depth: int = 0) -> str:
        return "\n".join(["  " * depth + self.label(), *[c.text(depth + 1) for c in self.children()]])


@dataclass(frozen=True)
class Load(PlanNode):
    """A converted graph. summed: parallel edges are already added up."""

    name: str
    graph: GraphMatrix
    summed: bool = True


@dataclass(frozen=True)
class State(PlanNode):
    name: str
    state: VertexState


@dataclass(frozen=True)
class Transpose(PlanNode):
    child: PlanNode


@dataclass(frozen=True)
class Scale(PlanNode):
    child: PlanNode
    factor: float


@dataclass(frozen=True)
class Expand(PlanNode):
    """Mirror a stored triangle (kind: sym or herm), or add a unit diagonal (kind: unit)."""

    child: PlanNode
    kind: str


@dataclass(frozen=True)
class Sum(PlanNode):
    """Parallel edges added up."""

    child: PlanNode


@dataclass(frozen=True)
class Gather(PlanNode):
    matrix: PlanNode
    state: PlanNode


@dataclass(frozen=True)
class Combine(PlanNode):
    """Fold of what was gathered, per vertex."""

    child: PlanNode
    fold: str = "sum"


@dataclass(frozen=True)
class Finalize(PlanNode):
    child: PlanNode
    name: str = "identity"


@dataclass(frozen=True)
class MergeEdges(PlanNode):
    """Fold of the edges of several graphs."""

    parts: tuple[PlanNode, ...]


@dataclass(frozen=True)
class Contract(PlanNode):
    """Product of a series of matrices; mode: tree, paths, dp or sequential."""

    parts: tuple[PlanNode, ...]
    mode: str = "tree"


@dataclass(frozen=True)
class Iterate(PlanNode):
    """The superstep on `matrix`, `times` times, from `state`."""

    matrix: PlanNode
    state: PlanNode
    times: int


@dataclass(frozen=True)
class Reorder(PlanNode):
    child: PlanNode
    method: str = "lpa"


def mv(matrix: PlanNode, state: PlanNode) -> PlanNode:
    return Combine(Gather(matrix, state))


def with_children(node: PlanNode, new: list[PlanNode]) -> PlanNode:
    left, changed = list(new), {}
    for f in fields(node):
        v = getattr(node, f.name)
        if isinstance(v, PlanNode):
            changed[f.name] = left.pop(0)
        elif isinstance(v, tuple) and v and isinstance(v[0], PlanNode):
            changed[f.name] = tuple(left.pop(0) for _ in v)
    return replace(node, **changed)
