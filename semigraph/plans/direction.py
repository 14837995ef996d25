"""When to push and when to pull: the published switching rules as policies over driver-known counts."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass
class State:
    direction: str
    frontier: int
    previous: int
    unvisited: int
    n: int
    nnz: int
    frontier_edges: int | None = None  # exact counts, where a policy asks for them
    unvisited_edges: int | None = None

    @property
    def mean(self) -> float:
        return self.nnz / self.n if self.n else 0.0

    def edges(self) -> float:
        return self.frontier_edges if self.frontier_edges is not None else self.mean * self.frontier

    def edges_left(self) -> float:
        return self.unvisited_edges if self.unvisited_edges is not None else self.mean * self.unvisited


@dataclass(frozen=True)
class AlwaysPush:
    def choose(self, s: State) -> str:
        return "push"


@dataclass(frozen=True)
class AlwaysPull:
    def choose(self, s: State) -> str:
        return "pull"


@dataclass(frozen=True)
class ReferencePolicy:
    """Pull while the estimated edges of the frontier pass a share of all edges."""

    share: float = 10

    def choose(self, s: State) -> str:
        return "pull" if s.mean * s.frontier > s.nnz / self.share else "push"


@dataclass(frozen=True)
class EdgeFractionPolicy:
    share: float = 20
    exact = True

    def choose(self, s: State) -> str:
        return "pull" if s.edges() > s.nnz / self.share else "push"


@dataclass(frozen=True)
class UnvisitedEdgePolicy:
    """Into pull when a growing frontier passes a share of the unvisited edges; back when a shrinking one is small."""

    up: float = 14
    down: float = 24
    exact = True

    def choose(self, s: State) -> str:
        if s.direction == "push":
            return "pull" if s.edges() > s.edges_left() / self.up and s.frontier > s.previous else "push"
        return "push" if s.frontier < s.n / self.down and s.frontier < s.previous else "pull"


@dataclass(frozen=True)
class TwoThresholdPolicy:
    up: float = 1000
    down: float = 5

    def choose(self, s: State) -> str:
        edges, left = s.mean * s.frontier, s.mean * s.unvisited
        if s.direction == "push":
            return "pull" if edges > left / self.up else "push"
        return "push" if edges < left / self.down else "pull"


@dataclass(frozen=True)
class BytesPolicy:
    """Compares the bytes that each direction moves: a broadcast frontier and its products, or the dense vector."""

    executors: int = 8
    entry: int = 16

    def choose(self, s: State) -> str:
        push = s.frontier * self.entry * self.executors + s.mean * s.frontier * self.entry
        pull = s.n * self.entry + s.mean * s.unvisited / 8
        return "push" if push <= pull else "pull"


POLICIES = {"reference": ReferencePolicy(), "edge_fraction": EdgeFractionPolicy(), "unvisited_edges": UnvisitedEdgePolicy(), "two_thresholds": TwoThresholdPolicy(), "push": AlwaysPush(), "pull": AlwaysPull(), "bytes": BytesPolicy()}
