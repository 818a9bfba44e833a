"""What a user writes: one vertex in one superstep."""

from __future__ import annotations

import inspect
from abc import ABC, abstractmethod
from collections.abc import Callable
from dataclasses import dataclass
from typing import TYPE_CHECKING

from pyspark.sql import Column
from pyspark.sql import functions as F

from .functions.combiners import Combiner

if TYPE_CHECKING:
    import pandas as pd


#: What the engine puts before the names of attributes, so they cannot clash.
ATTRIBUTE = "attribute_"


@dataclass(frozen=True)
class StepView:
    """Facts of the superstep; constants in its plan."""

    number: int
    num_vertices: int

    @property
    def is_first(self) -> bool:
        return self.number == 0


class VertexView:
    """The vertex at hand: its own data and mail, never another vertex's."""

    def __init__(self, queued: bool, combiner: Combiner | None):
        self._queued, self._combiner = queued, combiner
        self.id = F.col("id")
        self.value = F.col("value")
        self.out_degree = F.col("out_degree")

    @property
    def messages(self) -> Column:
        """The mailbox as an array; empty without mail."""
        if self._queued:
            return F.coalesce(F.col("msg.msg"), F.array())
        return F.when(F.col("msg").isNotNull(), F.array("msg")).otherwise(F.array())

    @property
    def message(self) -> Column:
        """The mailbox combined into one message; null without mail."""
        if not self._queued:
            return F.col("msg")
        return self._combiner.fold(F.col("msg.msg"))

    def attr(self, name: str) -> Column:
        return F.col(ATTRIBUTE + name)

    def apply(self, fn: Callable[..., pd.Series], returns: str, *columns: Column) -> Column:
        """A Python function on whole batches (Arrow) of this vertex's columns,
        for what expressions cannot say."""
        return F.pandas_udf(fn, returns)(*columns)


@dataclass(frozen=True)
class Turn:
    """What a vertex does: its new value, one payload for all out-neighbours
    (where ``when`` holds), payloads for single ones (an array of structs with
    ``to`` and ``msg``), and whether it halts until mail wakes it."""

    value: Column
    broadcast: Column | None = None
    when: Column | None = None
    sends: Column | None = None
    halt: Column | bool = True


class VertexProgram(ABC):
    """A value type, a message type, a combiner and ``compute``."""

    value_type = "double"
    message_type = "double"
    combiner: Combiner | None = None

    @abstractmethod
    def compute(self, me: VertexView, step: StepView) -> Turn:
        """Columns for one superstep; called once per superstep, on the driver."""

    def on_edge(self, payload: Column, weight: Column | None) -> Column:
        """The message a payload becomes on an edge."""
        return payload


def halts_every_step(program: VertexProgram, num_vertices: int = 1) -> bool:
    """Whether every turn halts by a literal; shown on steps 0 and 1."""
    view = VertexView(False, program.combiner)
    return all(program.compute(view, StepView(t, num_vertices)).halt is True for t in (0, 1))


def broadcasts_only(program: VertexProgram, num_vertices: int = 1) -> bool:
    view = VertexView(False, program.combiner)
    return all(program.compute(view, StepView(t, num_vertices)).sends is None for t in (0, 1))


def user_lines(program: type | VertexProgram) -> int:
    """Lines of user code without blanks, comments and documentation."""
    kind = program if inspect.isclass(program) else type(program)
    source = inspect.getsource(kind)
    if kind.__doc__:
        source = source.replace(kind.__doc__, "")
    lines = [x.strip() for x in source.splitlines()]
    return sum(bool(x) and not x.startswith("#") and x != '""""""' for x in lines)
