"""Split schedules: which bit of which axis each halving settles."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class SplitSchedule:
    """``steps[l]`` = (axis, bit): the halving that takes level l to l + 1."""

    bits: tuple[int, ...]
    steps: tuple[tuple[int, int], ...]

    def __post_init__(self):
        for axis, b in enumerate(self.bits):
            if [bit for a, bit in self.steps if a == axis] != list(range(b - 1, -1, -1)):
                raise ValueError(f"axis {axis} must be halved {b} times, high bit first")

    @property
    def q(self) -> int:
        return len(self.steps)

    @classmethod
    def of_axes(cls, bits, axes) -> SplitSchedule:
        left, steps = list(bits), []
        for a in axes:
            left[a] -= 1
            steps.append((a, left[a]))
        return cls(tuple(bits), tuple(steps))

    @classmethod
    def round_robin(cls, bits, order=None) -> SplitSchedule:
        """Cyclic order; an axis without bits left drops out."""
        order = list(order or range(len(bits)))
        return cls.of_axes(bits, [a for r in range(max(bits, default=0)) for a in order if bits[a] > r])

    @classmethod
    def axis_major(cls, bits, order=None) -> SplitSchedule:
        """All halvings of one axis before the next."""
        return cls.of_axes(bits, [a for a in (order or range(len(bits))) for _ in range(bits[a])])

    @classmethod
    def align_low(cls, bits) -> SplitSchedule:
        """Cyclic with low bits aligned: short axes start late."""
        top = max(bits, default=0)
        return cls.of_axes(bits, [a for r in range(top) for a in range(len(bits)) if bits[a] >= top - r])

    @classmethod
    def longest_side(cls, bits) -> SplitSchedule:
        left, axes = list(bits), []
        for _ in range(sum(bits)):
            axes.append(max(range(len(bits)), key=lambda a: (left[a], -a)))
            left[axes[-1]] -= 1
        return cls.of_axes(bits, axes)

    @classmethod
    def explicit(cls, bits, axes) -> SplitSchedule:
        return cls.of_axes(bits, axes)

    def used(self, level: int) -> tuple[int, ...]:
        """Halvings of each axis within the first ``level`` steps."""
        return tuple(sum(a == axis for a, _ in self.steps[:level]) for axis in range(len(self.bits)))

    def level_of_precision(self, r: int) -> int:
        """Level at which every axis has been halved r times, or as often as it can."""
        want = [min(r, b) for b in self.bits]
        return next(lv for lv in range(self.q + 1) if all(u >= w for u, w in zip(self.used(lv), want, strict=True)))

    def round_of(self, level: int) -> int:
        return max(self.used(level), default=0)

    def rows(self) -> list[tuple[int, int, int]]:
        return [(level, axis, bit) for level, (axis, bit) in enumerate(self.steps)]
