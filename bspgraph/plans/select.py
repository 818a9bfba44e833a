"""Which vertices run in a superstep.

All three forms return the state with the mail ``msg`` and the flag ``run``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame


def first(state: DataFrame, message_type: str) -> DataFrame:
    """The first superstep: everyone runs, nobody has mail."""
    return state.selectExpr("*", f"CAST(NULL AS {message_type}) AS msg", "true AS run")


def scan(state: DataFrame, inbox: DataFrame) -> DataFrame:
    """Every vertex is tested: awake, or woken by mail."""
    joined = state.join(inbox, ["id", "pid"], "left")
    return joined.selectExpr("*", "NOT halted OR msg IS NOT NULL AS run")


def bypass(state: DataFrame, inbox: DataFrame) -> DataFrame:
    """Exactly the receivers run, without a test of their status, and only they
    are rows of the result: the inbox is the list.  Mail is keyed by receiver, so
    it has no duplicates."""
    return inbox.join(state, ["id", "pid"]).selectExpr("*", "true AS run")


def receivers(state: DataFrame, inbox: DataFrame) -> DataFrame:
    """The same among all rows, for when most vertices have mail."""
    return state.join(inbox, ["id", "pid"], "left").selectExpr("*", "msg IS NOT NULL AS run")


def everyone(state: DataFrame, inbox: DataFrame) -> DataFrame:
    """No selection at all."""
    return state.join(inbox, ["id", "pid"], "left").selectExpr("*", "true AS run")


def rebalanced(chosen: DataFrame, partitions: int) -> DataFrame:
    """The vertices that run, with all they need, dealt evenly over the workers."""
    return chosen.repartition(partitions)
