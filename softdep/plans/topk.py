"""The list of the k best candidates under a total order."""

from __future__ import annotations

from bisect import insort


def rank_key(rho: float, lhs: tuple[int, ...], rhs: int) -> tuple:
    """Smaller is better: rho, at most 1, to 12 significant digits; then the size and positions of the left side; then the right."""
    return (float(f"{min(rho, 1.0):.11e}"), len(lhs), lhs, rhs)


class BoundedTopK:
    """threshold is -1 until k entries are held, so that nothing is pruned before."""

    def __init__(self, k: int):
        if k < 1:
            raise ValueError("k must be at least 1")
        self.k, self.entries, self.operations = k, [], 0

    def offer(self, rho: float, lhs: tuple[int, ...], rhs: int) -> bool:
        key = rank_key(rho, lhs, rhs)
        if len(self.entries) == self.k and key >= self.entries[-1]:
            return False
        insort(self.entries, key)
        del self.entries[self.k :]
        self.operations += 1
        return True

    @property
    def threshold(self) -> float:
        return max(0.0, 1 - self.entries[-1][0]) if len(self.entries) == self.k else -1.0

    def result(self) -> list[tuple[int, tuple[int, ...], int, float]]:
        """(rank, lhs, rhs, mu_plus) in order."""
        return [(i + 1, lhs, rhs, max(0.0, 1 - rho)) for i, (rho, _, lhs, rhs) in enumerate(self.entries)]
