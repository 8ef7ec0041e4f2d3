"""Direction rules: small driver-side state machines over a level's counts."""

from __future__ import annotations

from dataclasses import dataclass, field

PUSH, PULL = "push", "pull"


@dataclass
class Level:
    """What a rule may look at; counts that a rule does not ask for stay None."""

    nnz_f: int
    m: int
    nnz_u: int | None = None
    out_edges_f: int | None = None
    in_edges_u: int | None = None
    parents_checked: int | None = None


@dataclass
class RatioRule:
    """r = nnz(f) / M: rising above alpha pulls, falling below beta pushes, all else keeps the direction."""

    alpha: float = 0.01
    beta: float = 0.01
    needs: tuple[str, ...] = ()
    direction: str = PUSH
    last: float = 0.0

    def next(self, level: Level) -> str:
        r = level.nnz_f / level.m if level.m else 0.0
        if r > self.last and r > self.alpha:
            self.direction = PULL
        elif r < self.last and r < self.beta:
            self.direction = PUSH
        self.last = r
        return self.direction


@dataclass
class EdgeRule:
    """Edge-exact form: out-edges(f) / in-edges(unvisited) above alpha pulls; nnz(f) / M below beta pushes back."""

    alpha: float = 0.01
    beta: float = 0.01
    needs: tuple[str, ...] = ("out_edges_f", "in_edges_u")
    direction: str = PUSH

    def next(self, level: Level) -> str:
        if self.direction == PUSH and level.out_edges_f > self.alpha * level.in_edges_u:
            self.direction = PULL
        elif self.direction == PULL and level.nnz_f / level.m < self.beta:
            self.direction = PUSH
        return self.direction


@dataclass
class BestOfBoth:
    """The cheaper of gathered edges and checked parents; ties push."""

    needs: tuple[str, ...] = ("out_edges_f", "parents_checked")

    def next(self, level: Level) -> str:
        return PULL if level.parents_checked < level.out_edges_f else PUSH


@dataclass
class PushOnly:
    needs: tuple[str, ...] = ()

    def next(self, level: Level) -> str:
        return PUSH


@dataclass
class PullOnly:
    needs: tuple[str, ...] = ()

    def next(self, level: Level) -> str:
        return PULL


@dataclass
class Schedule:
    """A fixed list of directions; the last one stays."""

    steps: list[str]
    needs: tuple[str, ...] = ()
    at: int = field(default=0)

    def next(self, level: Level) -> str:
        step = self.steps[min(self.at, len(self.steps) - 1)]
        self.at += 1
        return step


@dataclass
class TwoPhase:
    """Push until the ratio first passes alpha, then pull for good."""

    alpha: float = 0.01
    needs: tuple[str, ...] = ()
    pulled: bool = False

    def next(self, level: Level) -> str:
        self.pulled = self.pulled or level.nnz_f > self.alpha * level.m
        return PULL if self.pulled else PUSH


@dataclass
class BytesRule:
    """Spark's costs: a pull reads the open rows and sends no output; a push shuffles the gathered edges."""

    shuffle_weight: float = 3.0
    needs: tuple[str, ...] = ("out_edges_f", "in_edges_u")

    def next(self, level: Level) -> str:
        return PULL if level.in_edges_u < self.shuffle_weight * level.out_edges_f else PUSH
