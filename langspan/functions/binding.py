"""Names for intermediate values inside one column expression."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` of a value that is computed once for the row.

    Lambdas of array functions evaluate what they capture again for every element; a bound name is only looked up.
    """
    return F.get(F.transform(F.array(value), body), F.lit(0))
