"""A vertex program: column expressions that every execution model interprets alike."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, functions as F

#: Aggregates that may run before the exchange: commutative and associative.
COMBINERS = {"sum": F.sum, "min": F.min, "max": F.max, "bool_or": F.bool_or}


@dataclass(frozen=True)
class VertexProgram:
    """One problem.

    ``state``: column names and types of a vertex's state. ``payload``: message
    columns, made from the sender's state and the edge's ``w``. ``combine``: the
    aggregate of each message column. ``update``: new state from old state and
    combined messages (null where none came). ``sends``: which states may send.
    ``changed``: whether a vertex improved. ``activation``: who sends next:
    'improved' vertices, 'messaged' ones (those that got a message), or 'all'.
    """

    name: str
    state: dict[str, str]
    payload: dict[str, Callable[[], Column]]
    combine: dict[str, str]
    update: dict[str, Callable[[], Column]]
    sends: Callable[[], Column]
    changed: Callable[[], Column]
    activation: str = "all"
    options: dict = field(default_factory=dict)

    def __post_init__(self):
        if self.activation not in ("all", "improved", "messaged"):
            raise ValueError("activation is 'all', 'improved' or 'messaged'")
        if set(self.combine) != set(self.payload) or set(self.update) != set(self.state):
            raise ValueError("each message column needs a combiner, each state column an update")
        if bad := {c for c in self.combine.values() if c not in COMBINERS}:
            raise ValueError(f"not commutative and associative, so no combiner: {sorted(bad)}")

    # -- pieces that the engines put together

    def messages(self, joined: DataFrame, *more: Column) -> DataFrame:
        """Messages of rows that hold the sender's state, ``dst`` and ``w``."""
        return joined.select("dst", *[make().alias(c) for c, make in self.payload.items()], *more)

    def combined(self, messages: DataFrame, by: str = "dst") -> DataFrame:
        return messages.groupBy(by).agg(*[COMBINERS[how](c).alias(c) for c, how in self.combine.items()], F.count("*").alias("_n"))

    def stepped(self, joined: DataFrame, keep: tuple[str, ...] = ()) -> DataFrame:
        """New state of rows that hold the old state and the combined messages; who sends next; what came."""
        got = F.coalesce(F.col("_n"), F.lit(0))
        better = F.coalesce(self.changed(), F.lit(False))
        active = {"all": F.lit(True), "improved": better, "messaged": got > 0}[self.activation]
        return joined.select("id", *[make().cast(self.state[c]).alias(c) for c, make in self.update.items()], active.alias("_active"), better.alias("_improved"), got.cast("long").alias("_got"), *keep)

    def fresh(self, state: DataFrame, keep: tuple[str, ...] = ()) -> DataFrame:
        """State before the first round; an ``_active`` column says who sends at first (all, where there is none)."""
        active = F.col("_active") if "_active" in state.columns else F.lit(True)
        return state.select("id", *[F.col(c).cast(k).alias(c) for c, k in self.state.items()], active.alias("_active"), F.lit(False).alias("_improved"), F.lit(0).cast("long").alias("_got"), *keep)

    def sending(self):
        return F.col("_active") & self.sends()
