"""Settings of a training run, checked when made."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class FleetConfig:
    """A fleet of ``quorum + spares`` workers over ``shards`` parameter servers."""

    quorum: int
    spares: int = 0
    shards: int = 1

    def __post_init__(self) -> None:
        if self.quorum < 1 or self.spares < 0 or self.shards < 1:
            raise ValueError("a fleet needs a quorum of 1 at least, no negative spares and a shard")
        if self.spares >= self.workers:
            raise ValueError("spares must be fewer than workers")

    @property
    def workers(self) -> int:
        return self.quorum + self.spares


@dataclass(frozen=True)
class TrainConfig:
    """One run.  What the reference leaves open (batch size, decay constants, convergence tolerance) is set here."""

    fleet: FleetConfig
    steps: int = 5
    eval_every: int = 1  # steps between checkpoints, where a run is given a folder for them
    ema_decay: float = 0.9
    close: str = "quorum"  # quorum, deadline or either
    deadline: float | None = None
    quorum_scope: str = "global"  # or shard
    straggler: str = "fresh"  # or busy
    merge_hosts: int = 1

    def __post_init__(self) -> None:
        if self.close not in ("quorum", "deadline", "either"):
            raise ValueError(f"unknown way to close a step: {self.close}")
        if self.close != "quorum" and not (self.deadline and self.deadline > 0):
            raise ValueError("a deadline must be positive")
        if self.quorum_scope not in ("global", "shard") or self.straggler not in ("fresh", "busy"):
            raise ValueError("unknown quorum scope or straggler model")
