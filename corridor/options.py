"""What a stored file fixes: tolerance and its split, block and chunk lengths, code variants."""

from __future__ import annotations

from dataclasses import dataclass

MODES = ("supports", "inputs", "feasible")
ENDS = ("nearest", "mid", "low", "high")
STEP_FACTORS = {"2eq": 2.0, "eq": 1.0, "eq/2": 0.5}


@dataclass(frozen=True)
class Options:
    """eps is shared between the grid (lam * eps) and the line ((1 - lam) * eps); lengths of time are in frames."""

    eps: float = 1.0
    lam: float = 0.5
    step: str = "2eq"
    mode: str = "supports"
    end: str = "nearest"
    connect: bool = True
    test: str = "divide"
    block: int = 2048
    chunk: int = 1024
    width: int = 512  # series in a bucket
    zigzag: str = "dense"
    layout: str = "split"  # of a chunk: split with reversed displacements, forward, or interleaved pairs
    value_bytes: int = 8

    def __post_init__(self) -> None:
        if not self.eps > 0:
            raise ValueError("eps must be positive")
        if not 0 < self.lam <= 1:
            raise ValueError("lam must lie in (0, 1]")
        if self.mode not in MODES or self.end not in ENDS or self.step not in STEP_FACTORS or self.test not in ("divide", "cross"):
            raise ValueError("unknown variant")
        if min(self.block, self.chunk, self.width) < 1:
            raise ValueError("lengths must be positive")

    @property
    def grid(self) -> float:
        """Distance of grid points."""
        return STEP_FACTORS[self.step] * self.lam * self.eps

    @property
    def slack(self) -> float:
        """Half width of the corridor in grid units."""
        return (1 - self.lam) * self.eps / self.grid

    @property
    def bound(self) -> float:
        """What no error exceeds, by mode."""
        return (1 - self.lam) * self.eps + (self.grid if self.mode == "inputs" else self.grid / 2)
