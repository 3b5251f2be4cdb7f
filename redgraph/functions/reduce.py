"""Reduction operators: their algebra, their Spark aggregate and their NumPy kernel.

An operator says whether it commutes, associates, can be repeated without effect (idempotent) and moves
values in one direction (ordered).  All decisions on combining, early local updates and fused
rounds read these four facts only.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class ReduceOp:
    """``agg`` folds a group, ``merge`` folds two columns, ``at`` scatters in NumPy, ``worst`` is its identity there."""

    name: str
    commutative: bool
    associative: bool
    idempotent: bool
    ordered: bool
    agg: Callable[[Column], Column] | None = None
    merge: Callable[[Column, Column], Column] | None = None
    at: Callable | None = None
    worst: int | None = None

    @property
    def monotone(self) -> bool:
        """Ordered and safe to repeat; a sum of positives is ordered but not safe."""
        return self.ordered and self.idempotent

    @property
    def fusible(self) -> bool:
        return self.commutative and self.associative and self.monotone


MIN = ReduceOp("min", True, True, True, True, F.min, F.least, np.minimum.at, np.iinfo(np.int64).max)
MAX = ReduceOp("max", True, True, True, True, F.max, F.greatest, np.maximum.at, np.iinfo(np.int64).min)
OR = ReduceOp("or", True, True, True, True, F.max, F.greatest, np.maximum.at, np.iinfo(np.int64).min)
SUM = ReduceOp("sum", True, True, False, True, F.sum, lambda a, b: a + b, np.add.at, 0)
LAST = ReduceOp("last", False, True, True, False)
OPS = {op.name: op for op in (MIN, MAX, OR, SUM, LAST)}


def user_op(name: str, zero, merge: Callable[[Column, Column], Column], *, commutative: bool = True, associative: bool = True, idempotent: bool = False, ordered: bool = False) -> ReduceOp:
    """An operator of the user's: a start value and a binary expression, folded over the values of a group."""
    return ReduceOp(name, commutative, associative, idempotent, ordered, lambda c: F.aggregate(F.collect_list(c), F.lit(zero), merge), merge)


def ordered_fold(rows: DataFrame, key: str, seq: str, value: str, zero: Column, step: Callable[[Column, Column], Column]) -> DataFrame:
    """Fold a non-commutative operator in the order of ``seq``: every entry is kept until the fold.

    Groups are as large as the number of updates to one target; use it where that is bounded.
    """
    entries = F.array_sort(F.collect_list(F.struct(F.col(seq), F.col(value))))
    return rows.groupBy(key).agg(F.aggregate(entries, zero, lambda acc, x: step(acc, x[value])).alias(value))
