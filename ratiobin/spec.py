"""User-controllable parameters of the codec."""

from __future__ import annotations

from dataclasses import dataclass

STRATEGIES = ("topk", "equal", "log", "kmeans", "optimal")


@dataclass(frozen=True)
class CodecSpec:
    """error_bound: largest allowed distance of a ratio from its centre.  bits: index length, None to choose it by size.

    bound: 'ratio', or 'value' to hold the error against the current value as well.  bits_scope: 'step', or 'group' to let
    every run of group_points positions have its own centres and index length.  centres_scope: 'step', or 'series' for one set
    of centres and one index length for all steps.  cache: intermediate steps on 'disk' (the shared folder, survives lost
    executors) or in 'memory' where they fit.  With 4-byte elements centres and exact values are stored as such.
    """

    error_bound: float = 0.001
    bits: int | None = None
    strategy: str = "topk"
    candidates: tuple[int, ...] = tuple(range(1, 17))
    block_bytes: int = 1 << 20
    level: int = 6
    elem_bytes: int = 8
    anchor: str = "min"
    zero_prev: str = "exact"
    reference: str = "original"
    objective: str = "size"
    anchor_every: int | None = None
    round_block: bool = False
    bound: str = "ratio"
    bits_scope: str = "step"
    group_points: int = 1 << 16
    centres_scope: str = "step"
    cache: str = "disk"

    def __post_init__(self):
        if not self.error_bound > 0:
            raise ValueError("error_bound must be positive")
        if self.strategy not in STRATEGIES:
            raise ValueError(f"strategy is one of {STRATEGIES}")
        if self.bits is not None and not 1 <= self.bits <= 16:
            raise ValueError("bits lies in 1..16")
        if not self.candidates or min(self.candidates) < 1 or max(self.candidates) > 16:
            raise ValueError("candidates lie in 1..16")
        if self.elem_bytes not in (4, 8):
            raise ValueError("elements have 4 or 8 bytes")
        if self.group_points < 1:
            raise ValueError("group_points must be positive")
        choices = {
            "anchor": ("min", "zero"), "zero_prev": ("exact", "unchanged"), "reference": ("original", "reconstructed"), "objective": ("size", "entropy", "measured"),
            "bound": ("ratio", "value"), "bits_scope": ("step", "group"), "centres_scope": ("step", "series"), "cache": ("disk", "memory"),
        }
        for name, allowed in choices.items():
            if getattr(self, name) not in allowed:
                raise ValueError(f"{name} is one of {allowed}")

    @property
    def width(self) -> float:
        return 2 * self.error_bound
