"""Options of the analysis, and query forms before and after a refactoring."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class Options:
    """Choices where a method can be read in more than one way.

    join_rule: ``linked`` (any dependency), ``cross_container``, ``key_equality``.  walk: ``all_paths`` (exclusive branches do
    not reach each other) or ``linear``.  kill: whether an assignment ends what a variable held.  aliases: whether
    the forward pass follows assignments.  learn_from_writes: whether payloads of inserts and updates show fields.
    merge_scope: ``container`` or ``global``.  co_use: ``statement``, ``block`` or ``any``.  naming: ``prefixed`` or ``plain``.
    max_rounds: rounds after which a walk that still finds something ends with an error; none: it goes on until nothing is new.
    """

    join_rule: str = "cross_container"
    walk: str = "all_paths"
    kill: bool = False
    aliases: bool = True
    learn_from_writes: bool = False
    merge_scope: str = "container"
    co_use: str = "block"
    reset_per_join: bool = True
    naming: str = "prefixed"
    strategy: str = "kernel"
    max_rounds: int | None = None


def paper_options() -> Options:
    """The reading that keeps to the procedures as they are printed."""
    return Options(join_rule="linked", walk="linear", aliases=False, co_use="statement", reset_per_join=False, naming="plain")
