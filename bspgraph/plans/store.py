"""The state between supersteps, where only what changed is written."""

from __future__ import annotations

from pyspark.sql import DataFrame

from .checkpoints import drop, pack

#: Deltas that lie on the base before they are folded into it.
MOST_DELTAS = 3


class Store:
    """A base table of all vertices and deltas of the rows that ran since.

    All have the graph's layout.  A delta is folded with those before it when
    they are many, or together hold half as many rows as the base; so a row that
    runs is written a few times, whatever the size of the graph.
    """

    def __init__(self, base: DataFrame, num_vertices: int, owned: bool):
        self.base, self._size, self._owned = base, num_vertices, owned
        self._deltas: list[tuple[DataFrame, int]] = []

    def over(self, rows: DataFrame) -> DataFrame:
        """``rows`` of the base with the newest value and status of each."""
        for delta, _ in self._deltas:
            newer = delta.selectExpr("pid", "id", "value AS newer_value", "halted AS newer_halted", "true AS is_newer")
            rows = rows.join(newer, ["id", "pid"], "left")
            newest = {c: f"CASE WHEN is_newer THEN newer_{c} ELSE {c} END AS {c}" for c in ("value", "halted")}
            rows = rows.selectExpr(*[newest.get(c, f"`{c}`") for c in rows.columns if c not in ("newer_value", "newer_halted", "is_newer")])
        return rows

    @property
    def current(self) -> DataFrame:
        return self.over(self.base)

    def replace(self, base: DataFrame, made: DataFrame) -> None:
        """A new base, columns of the frame ``made`` that ``pack`` returned."""
        old = [f for f, _ in self._deltas] + ([self._made] if self._owned else [])
        self.base, self._made, self._owned, self._deltas = base, made, True, []
        drop(*old)

    def add(self, made: DataFrame, rows: int) -> None:
        """Rows that ran, as a frame that ``pack`` returned.  The deltas before it
        are folded first: their mail is delivered, so their files can go."""
        waiting = sum(n for _, n in self._deltas) + rows
        if len(self._deltas) >= MOST_DELTAS or 2 * waiting > self._size:
            self.fold()
        self._deltas.append((made, rows))

    def fold(self) -> None:
        """Write base and deltas as one; the deltas' files go."""
        if self._deltas:
            base, _ = pack(self.current.select(self.base.columns))
            self.replace(base, base)
