"""Thresholds of the forest algorithms; fixed once from the original input."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class Budget:
    """``light_cap`` (tau): a side with at most so many nodes is light.  ``full_cap``: a view of that size stops.

    ``memory_words`` bounds the state of the core: shrinking goes on while
    live nodes * guess^3 exceeds it.
    """

    light_cap: int = 256
    memory_words: int = 1 << 40
    lcl_cap: int = 64

    @property
    def full_cap(self) -> int:
        return 2 * self.light_cap**2

    @classmethod
    def from_delta(cls, n: int, delta: float, **more) -> Budget:
        """The literal thresholds n^(delta/8) and n^(delta/2); tiny at realistic n."""
        return cls(light_cap=max(1, int(n ** (delta / 8))), lcl_cap=max(1, int(n ** (delta / 2))), **more)

    @classmethod
    def from_rows(cls, light_cap: int = 256, **more) -> Budget:
        return cls(light_cap=light_cap, **more)
