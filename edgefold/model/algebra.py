"""Folds: how messages to one vertex merge, and what that allows a plan to do."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Fold:
    """A merge of payloads. ``aggregate`` builds the built-in aggregate over a payload column;
    ``merge`` folds an array of payloads in one place, for plans without pre-merging."""

    name: str
    aggregate: Callable[[Column], Column]
    merge: Callable[[Column], Column]
    commutative: bool = True
    associative: bool = True
    idempotent: bool = False


def _reduce_array(step: Callable[[Column, Column], Column]) -> Callable[[Column], Column]:
    return lambda xs: F.reduce(F.slice(xs, 2, F.greatest(F.size(xs) - 1, F.lit(0))), F.get(xs, F.lit(0)), step)


SUM = Fold("sum", F.sum, _reduce_array(lambda a, b: a + b))
COUNT = Fold("count", lambda c: F.count(c), lambda xs: F.size(xs).cast("long"))
MIN = Fold("min", F.min, F.array_min, idempotent=True)
MAX = Fold("max", F.max, F.array_max, idempotent=True)
ANY_OR = Fold("any", F.bool_or, lambda xs: F.exists(xs, lambda x: x), idempotent=True)
#: Smallest struct: the first field decides, later ones break ties.
MIN_BY = Fold("min_by", F.min, F.array_min, idempotent=True)
#: All payloads, in no order; allowed for any function of the whole group, but nothing merges early.
COLLECT = Fold("collect", F.collect_list, lambda xs: xs, associative=False)


def top_k(k: int) -> Fold:
    """The ``k`` largest payloads."""
    best = lambda xs: F.slice(F.sort_array(xs, asc=False), 1, k)
    return Fold(f"top{k}", lambda c: best(F.collect_list(c)), best)


def require_commutative(fold: Fold) -> None:
    if not fold.commutative:
        raise ValueError(f"fold {fold.name} is not commutative: messages arrive in no order")


def allow_premerge(fold: Fold) -> bool:
    """Whether partial merging at the sender, and so in-proxies, keep the result."""
    return fold.commutative and fold.associative
