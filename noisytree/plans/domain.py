"""Public domains of point sets. A domain is declared, never computed from data."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class Axis:
    name: str
    lo: float
    hi: float

    def __post_init__(self):
        if not self.lo < self.hi:
            raise ValueError(f"axis {self.name}: [{self.lo}, {self.hi}) is empty")

    @property
    def width(self) -> float:
        return self.hi - self.lo


@dataclass(frozen=True)
class Domain:
    axes: tuple[Axis, ...]

    @property
    def d(self) -> int:
        return len(self.axes)

    @property
    def names(self) -> list[str]:
        return [a.name for a in self.axes]

    @property
    def box(self) -> list[str]:
        """Names of the columns of a box: low and high end by axis."""
        return [f"{a.name}{e}" for a in self.axes for e in (0, 1)]


def plane(x0: float, x1: float, y0: float, y1: float) -> Domain:
    return Domain((Axis("x", x0, x1), Axis("y", y0, y1)))


LI = plane(0.0, 105_000.0, 0.0, 2_560.0)
EV = plane(0.0, 30.0, 0.0, 640.0)
OR = plane(0.0, 500_000.0, 0.0, 2_560.0)
CUST = plane(-1_000.0, 10_000.0, 0.0, 25.0)
EMB = Domain(tuple(Axis(n, -1.0, 1.0) for n in "xyz"))
LEN = Domain((Axis("x", 0.0, 131_072.0),))
PRICE = Domain((Axis("x", 0.0, 105_000.0),))
VAL = Domain((Axis("x", 0.0, 640.0),))
UNI = Domain((Axis("x", 0.0, float(1 << 26)),))
UNIT = plane(0.0, 1.0, 0.0, 1.0)
DOMAINS = {"LI": LI, "EV": EV, "OR": OR, "CUST": CUST, "SUPP": CUST, "EMB": EMB, "LEN": LEN, "PRICE": PRICE, "VAL": VAL, "UNI": UNI, "UNIT": UNIT}
