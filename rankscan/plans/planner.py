"""Plan choices that depend on sizes known before a job starts."""

from __future__ import annotations


def choose_search(n: int, w_max: int, exhaustive_cells: int = 200_000) -> str:
    """The whole plane while it is small (a vectorised scan is then cheaper than restarts), restarts above."""
    return "exhaustive" if n * w_max <= exhaustive_cells else "powell"
