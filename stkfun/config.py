"""Study windows, distance grids and job parameters."""

from __future__ import annotations

import warnings
from dataclasses import dataclass, field
from datetime import UTC, datetime

HOUR = 3_600_000_000
DAY = 24 * HOUR
#: Ticks (µs) of each unit; a month is the mean one.
UNITS = {"us": 1, "s": 1_000_000, "min": 60_000_000, "h": HOUR, "d": DAY, "week": 7 * DAY, "month": int(30.436875 * DAY)}


def micros(day: str) -> int:
    return int(datetime.fromisoformat(day).replace(tzinfo=UTC).timestamp()) * 1_000_000


@dataclass(frozen=True)
class StudyWindow:
    """A rectangle or a ring of vertices, and a half-open period in µs."""

    x0: float
    x1: float
    y0: float
    y1: float
    t_start: int = 0
    t_end: int = 0
    ring: tuple[tuple[float, float], ...] = ()

    @classmethod
    def from_rect(cls, x0, x1, y0, y1, start: str, end: str) -> StudyWindow:
        return cls(float(x0), float(x1), float(y0), float(y1), micros(start), micros(end))

    @classmethod
    def from_ring(cls, ring, start: str, end: str) -> StudyWindow:
        xs, ys = [p[0] for p in ring], [p[1] for p in ring]
        return cls(min(xs), max(xs), min(ys), max(ys), micros(start), micros(end), tuple((float(x), float(y)) for x, y in ring))

    @classmethod
    def from_mbr(cls, points) -> StudyWindow:
        """The bounding box of a point set (one aggregate job)."""
        from pyspark.sql import functions as F

        r = points.agg(F.min("x"), F.max("x"), F.min("y"), F.max("y"), F.min("t0"), F.max("t0")).first()
        return cls(r[0], r[1], r[2], r[3], r[4], r[5] + 1)

    @classmethod
    def from_zone(cls, zone_rings: dict[int, list], zone: int, start: str, end: str) -> StudyWindow:
        return cls.from_ring(zone_rings[zone], start, end)

    def with_ring(self, ring) -> StudyWindow:
        return StudyWindow(self.x0, self.x1, self.y0, self.y1, self.t_start, self.t_end, tuple(map(tuple, ring)))

    @property
    def area(self) -> float:
        if not self.ring:
            return (self.x1 - self.x0) * (self.y1 - self.y0)
        r = self.ring
        return abs(sum(a[0] * b[1] - b[0] * a[1] for a, b in zip(r, r[1:] + r[:1]))) / 2

    @property
    def short_side(self) -> float:
        return min(self.x1 - self.x0, self.y1 - self.y0)

    @property
    def period(self) -> int:
        return self.t_end - self.t_start

    @property
    def hours(self) -> float:
        return self.period / HOUR

    @property
    def vertices(self) -> int:
        return len(self.ring) or 4


@dataclass(frozen=True)
class DistanceGrid:
    """Spatial steps of ``s_step`` up to ``s_max``, temporal steps (µs) up to ``t_max``."""

    s_step: float
    s_steps: int
    t_step: int
    t_steps: int

    @property
    def s_max(self) -> float:
        return self.s_step * self.s_steps

    @property
    def t_max(self) -> int:
        return self.t_step * self.t_steps

    @classmethod
    def of(cls, s_max: float, s_step: float, t_max: int, t_step: int) -> DistanceGrid:
        return cls(s_step, round(s_max / s_step), t_step, round(t_max / t_step))

    @classmethod
    def from_fraction(cls, window: StudyWindow, fraction: float, steps: int = 8) -> DistanceGrid:
        return cls(window.short_side * fraction / steps, steps, int(window.period * fraction) // steps, steps)

    @classmethod
    def suggest(cls, window: StudyWindow, n: int, steps: int = 8, neighbours: float = 100.0) -> DistanceGrid:
        """Thresholds that a uniform set of n points would fill with about so many
        neighbours, at most a quarter of the short side and of the period."""
        fraction, volume = 1 / 4, window.area * window.period
        for halvings in range(2, 12):
            fraction = 2.0**-halvings
            inside = n * 3.141592653589793 * (window.short_side * fraction) ** 2 * 2 * window.period * fraction / volume
            if inside <= neighbours:
                break
        return cls.from_fraction(window, fraction, steps)

    def validate(self, window: StudyWindow, on_violation: str = "error") -> DistanceGrid:
        """At most a quarter of the short side and of the period; at least one step."""
        wrong = []
        if self.s_steps < 1 or self.t_steps < 1:
            wrong.append("a grid needs at least one step")
        if self.s_max > window.short_side / 4 * (1 + 1e-9):
            wrong.append("s_max is above a quarter of the window's short side")
        if self.t_max > window.period / 4:
            wrong.append("t_max is above a quarter of the period")
        if wrong and on_violation == "error":
            raise ValueError("; ".join(wrong))
        for w in wrong:
            warnings.warn(w, stacklevel=2)
        return self


@dataclass(frozen=True)
class KJob:
    """All parameters of one run."""

    points: str
    window: StudyWindow
    grid: DistanceGrid
    correction: str = "isotropic"
    simulation: str = "permutation"
    m: int = 0
    seed: int = 42
    #: Fields of the strategy plan that replace the planner's choice.
    options: dict = field(default_factory=dict)

    def validate(self) -> KJob:
        if self.correction not in ("isotropic", "none", "border", "translation"):
            raise ValueError(f"unknown correction {self.correction}")
        if self.simulation not in ("permutation", "bootstrap", "cstr"):
            raise ValueError(f"unknown simulation {self.simulation}")
        if self.m < 0:
            raise ValueError("m is negative")
        self.grid.validate(self.window)
        return self


W_EVENTS = StudyWindow.from_rect(0, 600, 0, 100, "2024-01-01", "2024-01-31")
W_ORDERS = StudyWindow.from_rect(0, 100, 0, 100, "1995-01-01", "2001-08-02")
W_LINES = StudyWindow.from_rect(0, 51, -1, 11, "1995-01-01", "2001-11-05")
W_EMBED = StudyWindow(-1.0, 1.0, -1.0, 1.0)

G_SMALL = DistanceGrid(1.0, 5, 4 * HOUR, 5)
G20 = DistanceGrid(0.25, 20, HOUR, 20)
G10 = DistanceGrid(0.5, 10, 2 * HOUR, 10)
G_ORDERS = DistanceGrid(0.5, 8, 10 * DAY, 12)
G_LINES = DistanceGrid(1.0, 1, DAY, 30)
G_OVERALL = DistanceGrid(100 / 240, 10, int(22.5 * HOUR) // 10, 10)
