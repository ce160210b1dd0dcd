"""Settings shared by all methods."""

from __future__ import annotations

from dataclasses import dataclass, replace


@dataclass(frozen=True)
class Params:
    """tg: largest gap between neighbours. fth: relative frequency threshold (two-phase selector). k: most multi-node episodes.

    min_freq_base: the threshold counts from the `current` or the `original` number of events. stop_rule: path growth ends when
    no extension has a better score (`score_improves`) or only when none reaches the gain floor (`frequency_floor`).
    max_candidates, max_size, max_rounds: optional cuts. min_gain: a round that gains no more ends the loop.
    overlap_mode: `penalise` shared events or `ignore` them. engine: `table` works in DataFrames throughout; `kernel` solves a
    sequence of at most `kernel_events` events in one task (`selection.alone` tells of fewer); `auto` picks by the number of events, with equal results.
    """

    tg: int = 5
    fth: float | None = None
    k: int | None = None
    min_freq_base: str = "current"
    stop_rule: str = "score_improves"
    max_candidates: int | None = None
    max_size: int | None = None
    max_rounds: int | None = None
    min_gain: int = 0
    overlap_mode: str = "penalise"
    engine: str = "auto"
    kernel_events: int = 4_000_000
    block_ticks: int = 1 << 16

    def __post_init__(self):
        if self.tg < 1 or (self.k is not None and self.k < 0):
            raise ValueError("tg must be 1 or more and k 0 or more")
        for name, value, options in (("stop_rule", self.stop_rule, ("score_improves", "frequency_floor")), ("min_freq_base", self.min_freq_base, ("current", "original")), ("overlap_mode", self.overlap_mode, ("penalise", "ignore")), ("engine", self.engine, ("auto", "kernel", "table"))):
            if value not in options:
                raise ValueError(f"{name} must be one of {options}")

    def but(self, **changes) -> Params:
        return replace(self, **changes)
