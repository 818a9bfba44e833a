"""How two messages for one vertex become one.

A combiner has a partial form for messages that leave one partition and a final
form for partials that meet at the receiver.  Both are aggregates, so Spark
combines on the sending side before the shuffle and needs no locks.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

Fold = Callable[[Column, Column], Column]


@dataclass(frozen=True)
class Combiner:
    name: str
    partial: Callable[[Column], Column]
    final: Callable[[Column], Column]
    #: The same on a queue, for mailboxes that were not combined.
    fold: Callable[[Column], Column]

    @staticmethod
    def sum() -> Combiner:
        return Combiner("sum", F.sum, F.sum, lambda q: _reduce(q, lambda a, b: a + b))

    @staticmethod
    def min() -> Combiner:
        return Combiner("min", F.min, F.min, F.array_min)

    @staticmethod
    def max() -> Combiner:
        return Combiner("max", F.max, F.max, F.array_max)

    @staticmethod
    def avg() -> Combiner:
        """A mean is carried as sum and count: means of means would be wrong."""
        partial = lambda m: F.struct(F.sum(m).alias("s"), F.count(m).alias("n"))
        final = lambda p: F.sum(p["s"]) / F.sum(p["n"])
        return Combiner("avg", partial, final, lambda q: _reduce(q, lambda a, b: a + b) / F.size(q))

    @staticmethod
    def custom(fold: Fold) -> Combiner:
        """Any associative and commutative operation on two messages."""
        partial = lambda m: _reduce(F.collect_list(m), fold)
        return Combiner("custom", partial, partial, lambda q: _reduce(q, fold))


def _reduce(queue: Column, fold: Fold) -> Column:
    """Fold of an array without a zero element."""
    return F.when(F.size(queue) > 0, F.aggregate(F.slice(queue, F.lit(2), F.greatest(F.size(queue) - 1, F.lit(0))), F.get(queue, F.lit(0)), fold))


def combine_arrow(rows, key: str, value: str, fold: Callable, partitions: int):
    """Two-phase combination of (key, value) rows by a Python function on two
    values, for operations that expressions cannot state."""
    import pyarrow as pa

    from ..shipping import ship

    ship(rows.sparkSession)
    rows = rows.select(key, value)
    schema = rows.schema

    def phase(batches):
        held: dict = {}
        for batch in batches:
            for k, v in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                held[k] = fold(held[k], v) if k in held else v
        names = [f.name for f in schema]
        yield pa.RecordBatch.from_pydict({names[0]: list(held), names[1]: list(held.values())}) if held else pa.RecordBatch.from_pydict({n: [] for n in names})

    return rows.mapInArrow(phase, schema).repartition(partitions, key).mapInArrow(phase, schema)
