"""Parameters of a subtrajectory join."""

from __future__ import annotations

from dataclasses import dataclass
from datetime import timedelta

HOUR = 3_600_000_000


def micros(value: int | timedelta) -> int:
    """A duration as microseconds; day-time intervals are timedeltas in PySpark."""
    return value // timedelta(microseconds=1) if isinstance(value, timedelta) else int(value)


@dataclass(frozen=True)
class JoinParams:
    """Spatial radius, time tolerance and least duration (microseconds), distance, least points of a piece."""

    eps_sp: float
    eps_t_us: int | timedelta
    delta_t_us: int | timedelta = 0
    metric: str = "euclid"
    min_points: int = 2

    def __post_init__(self):
        object.__setattr__(self, "eps_t_us", micros(self.eps_t_us))
        object.__setattr__(self, "delta_t_us", micros(self.delta_t_us))
        if self.eps_sp < 0 or self.eps_t_us < 0 or self.delta_t_us < 0 or self.min_points < 1:
            raise ValueError(f"negative tolerance or no points: {self}")

    @property
    def lifespan_floor_us(self) -> int:
        """Least common lifespan of a match; negative when the duration test is vacuous."""
        return self.delta_t_us - 2 * self.eps_t_us

    @property
    def inner_window_us(self) -> int:
        return max(0, self.lifespan_floor_us)


SET_A = JoinParams(10.0, 2 * HOUR, 5 * HOUR)
SET_B = JoinParams(20.0, 6 * HOUR, 13 * HOUR)
SET_C = JoinParams(20.0, 6 * HOUR, 0)
SET_D = JoinParams(10.0, 2 * HOUR, 2 * HOUR)
