"""Schemas, and the episode as a plain value."""

from __future__ import annotations

from dataclasses import dataclass
from itertools import accumulate

EVENTS = "seq_id long, etype int, t long"
ALPHABET = "etype int, symbol string, n long"
EPISODES = "ep_id string, size int, types array<int>, gaps array<int>, offsets array<int>"
OCCURRENCES = "ep_id string, start_t long"
SELECTED = "round int, rank int, size int, types array<int>, gaps array<int>, score long, starts array<long>"
ENCODED = "row_no int, size int, types array<int>, gaps array<int>, n_occ long, starts array<long>"


@dataclass(frozen=True)
class Episode:
    types: tuple[int, ...]
    gaps: tuple[int, ...] = ()

    def __post_init__(self):
        if len(self.gaps) != len(self.types) - 1 or any(g < 1 for g in self.gaps):
            raise ValueError("an episode of n types has n - 1 positive gaps")
        if len(set(self.types)) != len(self.types):
            raise ValueError("an episode's types must differ")

    @property
    def size(self) -> int:
        return len(self.types)

    @property
    def offsets(self) -> tuple[int, ...]:
        return tuple(accumulate(self.gaps, initial=0))

    @property
    def key(self) -> str:
        return "".join(f"{e}" if not i else f"+{g}>{e}" for i, (e, g) in enumerate(zip(self.types, (0, *self.gaps), strict=True)))

    def row(self) -> tuple:
        return self.key, self.size, list(self.types), list(self.gaps), list(self.offsets)


def score(size: int, freq: int) -> int:
    """Units saved at least by writing freq occurrences as starts instead of single events."""
    return freq * size - (2 * size + freq + 1)


def floor_met(size: int, freq: int, gap: int, tg: int) -> bool:
    """Whether an extension of an episode of this size reaches the gain floor; at the floor itself the gap must be under tg."""
    have, need = freq * size, 2 * (size + 1) + 1
    return have > need or (have == need and gap < tg)
