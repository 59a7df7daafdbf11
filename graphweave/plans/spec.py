"""What to aggregate, and how: a checked specification and the choice of a physical form."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

OPERANDS = ("src", "dst", "edge")
STRATEGIES = ("long", "wide", "summarizer", "arrow", "baseline")


@dataclass(frozen=True)
class AggSpec:
    """reduce over in-edges of (lhs binary rhs); operands are vectors of the source, the destination or the edge."""

    binary: str | Callable = "copy_lhs"
    reduce: str | Callable = "sum"
    lhs: str = "src"
    rhs: str | None = None
    empty: float | None = 0.0
    keep_isolated: bool = True

    def __post_init__(self) -> None:
        if self.lhs not in OPERANDS or self.rhs not in (*OPERANDS, None):
            raise ValueError(f"operands are {OPERANDS}")
        if self.binary != "copy_lhs" and self.rhs is None:
            raise ValueError("this combination needs a right operand")

    @property
    def operands(self) -> tuple[str, ...]:
        """The operands that are read; the plan joins no others."""
        if self.binary == "copy_lhs":
            return (self.lhs,)
        if self.binary == "copy_rhs":
            return (self.rhs,)
        return (self.lhs, self.rhs)


def choose(spec: AggSpec, width: int, groups: int | None = None) -> str:
    """long rows only where few groups meet narrow vectors, else one aggregate column per dimension.

    Above 100 columns whole-stage code generation falls back, so wide vectors go to the vector summarizer where
    the reduction allows it.
    """
    if callable(spec.reduce):
        return "long"
    if groups is not None and groups * width <= 1_000_000 and width > 16:
        return "long"
    if width > 100 and spec.reduce in ("sum", "max", "min", "mean"):
        return "summarizer"
    return "wide"
