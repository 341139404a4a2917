"""Settings of the migration heuristic."""

from __future__ import annotations

from dataclasses import dataclass, replace


@dataclass(frozen=True)
class MigrationConfig:
    """``k`` partitions; every choice the heuristic leaves open is a field.

    s: chance that a willing vertex acts. slack: capacity over the mean load; caps:
    capacities by partition instead. count_self: a vertex counts itself as a
    neighbour. candidate_rule: majority or any. tie_break: hash or lowest.
    admission: gain or hash. quota_remainder: drop or rotate. deferred: a move is
    announced now and takes place one iteration later. patience: quiet iterations
    that end a run must exceed it.
    """

    k: int = 9
    s: float = 0.5
    slack: float = 1.10
    caps: tuple[int, ...] | None = None
    count_self: bool = False
    candidate_rule: str = "majority"
    tie_break: str = "hash"
    admission: str = "gain"
    quota_remainder: str = "rotate"
    use_quota: bool = True
    deferred: bool = False
    adaptive: bool = True
    newcomer: str = "hash"
    patience: int = 30
    max_iter: int = 200
    seed: int = 0

    def but(self, **changes) -> MigrationConfig:
        return replace(self, **changes)
