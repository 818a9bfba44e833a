"""Engine choices that never touch a program."""

from __future__ import annotations

from dataclasses import dataclass

SELECTIONS = ("scan", "bypass", "none")
EXCHANGES = ("push", "pull", "pull_addressed", "auto")


class EngineError(ValueError):
    """A program and an option that do not go together."""


class SystematicHaltError(EngineError):
    """Bypass was asked for a program whose vertices do not halt every step."""


class PullNotApplicable(EngineError):
    """Pull was asked for a program that sends to single neighbours."""


class NotSupported(EngineError):
    """A baseline lacks the feature an application needs."""


@dataclass(frozen=True)
class Options:
    """``selection`` finds the vertices to run: ``scan`` tests all of them,
    ``bypass`` takes the receivers of the last step, ``none`` runs all.  With
    bypass and combined, pushed mail, a step of at most ``lookup_most`` messages
    looks its rows up by key (0: never).  ``rebalance_active`` deals the vertices
    that run evenly over the workers, whatever their partitions, for two shuffles
    of their rows; ``measure_balance`` has the ledger say how evenly they lie.
    ``exchange`` moves messages; ``auto`` pulls when the senders' out-edges are
    above ``switch_threshold`` of all edges.  Without ``combine`` mailboxes are
    queues, cut at ``mailbox_limit`` messages by sender id if it is set."""

    selection: str = "scan"
    exchange: str = "push"
    combine: bool = True
    mailbox_limit: int | None = None
    switch_threshold: float = 0.05
    rebalance_active: bool = False
    measure_balance: bool = False
    lookup_most: int = 256
    max_supersteps: int = 100_000
    force_bypass: bool = False

    def __post_init__(self):
        if self.selection not in SELECTIONS or self.exchange not in EXCHANGES:
            raise EngineError(f"unknown selection {self.selection!r} or exchange {self.exchange!r}")
        if self.mailbox_limit is not None and self.combine:
            raise EngineError("a mailbox limit is for queued mailboxes")
