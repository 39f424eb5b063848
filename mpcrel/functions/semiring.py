"""Commutative semirings as pairs of Column expressions over named annotation columns."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Semiring:
    """names: annotation columns; plus: the scan operation of each; times: combines two annotations; one: the neutral element."""

    label: str
    names: tuple[str, ...]
    plus: tuple[str, ...]
    times: Callable[[list[Column], list[Column]], list[Column]]
    one: tuple[int, ...]

    def ones(self) -> dict[str, Column]:
        return {n: F.lit(v).cast("long") for n, v in zip(self.names, self.one)}


def _each(op: Callable[[Column, Column], Column]):
    return lambda a, b: [op(x, y) for x, y in zip(a, b)]


SUM_PRODUCT = Semiring("sum-product", ("__ann",), ("sum",), _each(lambda x, y: x * y), (1,))
COUNT = Semiring("count", ("__ann",), ("sum",), _each(lambda x, y: x * y), (1,))
BOOLEAN = Semiring("boolean", ("__ann",), ("max",), _each(F.least), (1,))
MAX_PLUS = Semiring("max-plus", ("__ann",), ("max",), _each(lambda x, y: x + y), (0,))
MIN_PLUS = Semiring("min-plus", ("__ann",), ("min",), _each(lambda x, y: x + y), (0,))
MAX_TIMES = Semiring("max-times", ("__ann",), ("max",), _each(lambda x, y: x * y), (1,))  # for values of at least 0
#: (count, sum): the sum adds up over joined rows, so averages of sums and differences across relations are one pass.
MOMENT1 = Semiring("count and sum", ("__ann_cnt", "__ann"), ("sum", "sum"), lambda a, b: [a[0] * b[0], a[0] * b[1] + b[0] * a[1]], (1, 0))
ALL = (SUM_PRODUCT, COUNT, BOOLEAN, MAX_PLUS, MIN_PLUS, MAX_TIMES, MOMENT1)
