"""Vertex programs: four small functions over Columns that the loop turns into joins and aggregates."""

from __future__ import annotations

from collections.abc import Callable, Mapping
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .algebra import Fold, require_commutative

ANY_MESSAGE, ALL = "any_message", "all"


@dataclass(frozen=True)
class VertexProgram:
    """One computation v.state = f(v.state, in-edge states, source states).

    * ``result`` and ``outgoing``: first values, over vertex columns; ``active``: who emits first.
    * ``emit(outgoing, edge)``: payload sent along an out-edge; ``edge`` names an edge column.
    * ``emit_where``: SQL over edge columns for the out-edges that carry messages.
    * ``fold``: how payloads to one vertex merge into its accumulator.
    * ``settle(result, acc)``: the new result; ``next_outgoing(result)`` what it emits next.
    * ``rearm(old, new)``: whether the vertex emits again; ``retire``: whether emitting stops it otherwise.
    * ``wake``: settle vertices that got a message, or all of them (acc is null without messages).
    * ``edge_update``: new values of edge columns, computed as a message passes.
    * ``reads_result``: false if ``settle`` looks at the accumulator only.
    * ``needs_target``: the message function reads the target's result, which proxies don't hold.
    """

    name: str
    result: Column
    outgoing: Callable[[Column], Column]
    emit: Callable[[Column, Callable[[str], Column]], Column]
    fold: Fold
    settle: Callable[[Column, Column], Column]
    active: Column = field(default_factory=lambda: F.lit(True))
    rearm: Callable[[Column, Column], Column] = lambda old, new: F.lit(True)
    wake: str = ANY_MESSAGE
    retire: bool = False
    emit_where: str | None = None
    edge_update: Mapping[str, Callable[[Column, Callable[[str], Column]], Column]] = field(default_factory=dict)
    needs_target: Callable[[Column, Column], Column] | None = None
    attributes: tuple[str, ...] = ()
    reads_result: bool = True

    def validate(self, state: DataFrame | None = None) -> None:
        """Check the contract: a declared commutative fold, a known wake rule, and state columns apart.

        ``outgoing`` and the accumulator are separate columns by construction, so neither can alias the
        other; ``result`` may hold the same values as either.
        """
        require_commutative(self.fold)
        if self.wake not in (ANY_MESSAGE, ALL):
            raise ValueError(f"unknown wake rule {self.wake}")
        taken = {"id", "result", "outgoing", "acc", "can_emit"} & set(self.attributes)
        if taken:
            raise ValueError(f"attributes clash with state columns: {sorted(taken)}")
        if state is not None and {"id", "result", "outgoing", "can_emit"} - set(state.columns):
            raise ValueError("state lacks columns")


def seed(vertices: DataFrame, program: VertexProgram) -> DataFrame:
    """First state: (id, attributes, result, outgoing, can_emit)."""
    first = vertices.select("id", *program.attributes, program.result.alias("result"), program.active.alias("can_emit"))
    return first.select("id", *program.attributes, "result", program.outgoing(F.col("result")).alias("outgoing"), "can_emit")
