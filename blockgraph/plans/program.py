"""What a user writes to run an algorithm: four hooks, each of which returns a Column."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column
from pyspark.sql import functions as F

_FOLDS = {"sum": F.sum, "min": F.min, "max": F.max, "bit_or": F.bit_or}


@dataclass
class VertexProgram:
    """A vertex has value columns (``init``); along each edge goes ``message``; messages to a vertex are folded by ``combine``;
    ``finish`` makes the new values from the old ones and the fold (null where no message came).

    names: value columns, with Columns over ``id`` and ``outdeg`` as initial values. message: Columns over the value columns of the
    source and ``w``, one for each accumulator. combine: how each accumulator is folded. finish: Columns over id, outdeg, the
    value columns and the accumulators (named acc0, acc1 ...). changed: optional, whether a vertex changed, over old_<name> and
    <name>, for stopping."""

    init: dict[str, Column]
    message: list[Column]
    combine: list[str]
    finish: dict[str, Column]
    changed: Column | None = None
    needs_degree: bool = False
    needs_weight: bool = False
    extra: dict = field(default_factory=dict)

    @property
    def accumulators(self) -> list[str]:
        return [f"acc{i}" for i in range(len(self.combine))]

    def fold(self, names: list[str]) -> list[Column]:
        return [_FOLDS[c](n).alias(a) for c, n, a in zip(self.combine, names, self.accumulators, strict=True)]

    def both(self, a: list[Column], b: list[Column]) -> list[Column]:
        """The fold of two partial folds, either of which may be null."""
        out = []
        for c, x, y in zip(self.combine, a, b, strict=True):
            if c == "sum":
                out.append(F.when(x.isNull(), y).when(y.isNull(), x).otherwise(x + y))
            elif c == "bit_or":
                out.append(F.when(x.isNull(), y).when(y.isNull(), x).otherwise(x.bitwiseOR(y)))
            else:
                out.append((F.least if c == "min" else F.greatest)(x, y))
        return out
